"""The two indexes, how often a query reads them, and a trace of single accesses on small stores."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.operators.evaluate import Evaluator
from treefacts.operators.store import Store, first_index, positions, second_index
from treefacts.plans import specialise as sp
from treefacts.plans.path import And, Step, Test, parse

__all__ = ["access_counts", "first_index", "positions", "second_index", "trace"]

SMALL = 1_000


def access_counts(store: Store, path: str) -> DataFrame:
    """pred, n: facts that each test of the last step's conjunction reads. The first test reads its predicate by the first index, the
    next ones the groups of records that are still there by the second."""
    tree = parse(path)
    step = tree.steps[-1]
    parts = step.condition.parts if isinstance(step.condition, And) else (step.condition,)
    evaluator = Evaluator(store)
    context = sp.resolve(store.rules, tree)[-1]
    depth = store.rules.by_chain[next(iter(context.chains))].depth
    found, out = None, None
    for test in parts:
        name = test.path.steps[0]
        pred = model.attribute(name.tags[0]) if name.axis == "attribute" else name.tags[0]
        own = store.facts.where((F.col("pred") == pred) & F.col("chain").isin(sorted(context.chains)))
        if found is not None:
            own = own.join(found.select("doc_id", F.col("okey").alias("gkey")), ["doc_id", "gkey"], "left_semi")
        one = own.agg(F.lit(pred).alias("pred"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
        keys_ = evaluator.satisfying(test, depth, context.chains)
        found = keys_ if found is None else found.join(keys_, ["doc_id", "okey"], "left_semi")
    return out


@dataclass(frozen=True)
class Access:
    index: str
    pred: str
    pos: int
    hit: bool


def trace(store: Store, path: str) -> list[Access]:
    """Each access, fact by fact, of a path whose last two steps are a record with a conjunction of child or attribute
    equalities, and an output step; depth first, as a resolution engine would. Stores of at most SMALL facts."""
    facts = positions(store.facts).orderBy("pos").limit(SMALL + 1).collect()
    if len(facts) > SMALL:
        raise ValueError(f"over {SMALL} facts")
    tree = parse(path)
    at = next(k for k, s in enumerate(tree.steps) if s.condition is not None)
    chains = sp.resolve(store.rules, tree)[at].chains
    condition, out = tree.steps[at].condition, tree.steps[at + 1]
    tests = condition.parts if isinstance(condition, And) else (condition,)
    log: list[Access] = []

    def name(step: Step) -> str:
        return model.attribute(step.tags[0]) if step.axis == "attribute" else step.tags[0]

    def holds(fact, test: Test) -> bool:
        return test.op is None or (fact.value_num if isinstance(test.literal, float) else fact.value) == test.literal

    def remaining(doc: int, gkey: str, gpos: int, rest: tuple[Test, ...]) -> bool:
        if not rest:
            return True
        pred, good = name(rest[0].path.steps[0]), False
        for f in facts[gpos:]:
            if f.gpos != gpos:
                break
            if f.pred == pred:
                hit = holds(f, rest[0])
                log.append(Access("second", pred, f.pos, hit))
                if hit and remaining(doc, gkey, gpos, rest[1:]):
                    good = True
                    break
        return good

    def output(doc: int, record: str, gpos: int) -> None:
        pred = name(out)
        inner = [s for s in store.rules.shapes if s.tag == pred and s.parent_chain in chains]
        if not inner:
            for f in facts[gpos:]:
                if f.gpos != gpos:
                    break
                if f.pred == pred:
                    log.append(Access("second", pred, f.pos, True))
            return
        for shape in inner:
            whole = [store.rules.by_chain[c] for c in sorted(sp.descendants(store.rules, frozenset((shape.chain,))), key=lambda c: store.rules.by_chain[c].depth)]
            known: dict[str, int] = {}
            for s in whole:
                for call in s.preds:
                    if any(x.tag == call and x.parent_chain == s.chain for x in whole):
                        continue
                    group = next((g for g in known if keys.decode(g)[: s.depth] and len(g) == s.depth * keys.WIDTH), None)
                    if group is not None:
                        start = known[group]
                        for f in facts[start:]:
                            if f.gpos != start:
                                break
                            if f.pred == call:
                                log.append(Access("second", call, f.pos, True))
                        continue
                    for f in facts:
                        if f.pred == call and f.chain == s.chain and f.doc_id == doc:
                            hit = f.gkey.startswith(record)
                            log.append(Access("first", call, f.pos, hit))
                            if hit:
                                known[f.gkey] = f.gpos

    first = name(tests[0].path.steps[0])
    for f in facts:
        if f.pred == first and f.chain in chains:
            hit = holds(f, tests[0])
            log.append(Access("first", first, f.pos, hit))
            if hit and remaining(f.doc_id, f.gkey, f.gpos, tests[1:]):
                output(f.doc_id, f.gkey, f.gpos)
    return log
