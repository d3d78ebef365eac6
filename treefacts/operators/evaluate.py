"""Evaluation of paths over facts.

Top-down: a path is lowered to scans of the named predicates, restricted to the chains that the rules leave, and to a
chain of semi-joins on record keys: the first test finds record keys, later tests and the output are looked up under them.
Where no condition stands, no keys are built at all. Other engines answer the same paths for comparison: grouped tests
(bottom-up), and whole records before any test (unspecialised).
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.operators.store import Store
from treefacts.plans import specialise as sp
from treefacts.plans.path import And, Condition, Not, Or, Path, Step, Test, parse
from treefacts.plans.specialise import Context


@dataclass(frozen=True)
class Options:
    order: str = "text"  #: of tests: text, document or cost
    engine: str = "topdown"  #: topdown or bottomup
    value_test: str = "leaf"  #: leaf, own_text (direct text runs too) or string_value (all text below)
    text_mode: str = "leaf"  #: text() also returns the value of a leaf; strict: text runs only
    goal_scope: str = "chain"  #: type: the type number instead of the chain, which may let other records in
    conjunction: str = "exists"  #: unify: two constants for one predicate contradict each other


KEYS = ["doc_id", "okey"]


@dataclass(frozen=True)
class Branch:
    at: Context
    held: tuple[int, DataFrame] | None


def union_all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _chains(column: str, chains) -> Column:
    return F.col(column).isin(sorted(chains))


class Evaluator:
    def __init__(self, store: Store, options: Options = Options()):
        self.store, self.rules, self.options = store, store.rules, options
        self._counts: dict[str, int] | None = None

    # scans

    def records(self, chains) -> DataFrame:
        return self.store.records.where(_chains("chain", chains))

    def facts(self, preds) -> DataFrame:
        """Facts of (chain, predicate) pairs."""
        names = sorted({p for _, p in preds})
        own = self.store.facts.where(F.col("pred").isin(names))
        if self.options.goal_scope == "type":
            return own.where(F.col("typ").isin(sorted({self.rules.by_chain[c].child_typ for c, _ in preds})))
        by_pred = defaultdict(set)
        for c, p in preds:
            by_pred[p].add(c)
        if len({frozenset(x) for x in by_pred.values()}) == 1:
            return own.where(_chains("chain", next(iter(by_pred.values()))))
        return own.where(reduce(Column.__or__, [(F.col("pred") == p) & _chains("chain", c) for p, c in sorted(by_pred.items())]))

    def depth(self, chain: int) -> int:
        return self.rules.by_chain[chain].depth if chain else 0

    def by_depth(self, chains) -> dict[int, set[int]]:
        out = defaultdict(set)
        for c in chains:
            out[self.depth(c)].add(c)
        return out

    # contexts: branches of chains and predicates, each with the records (doc_id, okey) of one depth at or above them
    # that the last condition left, or None where there was none

    def restrict(self, df: DataFrame, column: str, held: tuple[int, DataFrame] | None) -> DataFrame:
        """Rows whose key lies in or below the records held."""
        if held is None:
            return df
        d, records = held
        cut = df.withColumn("_cut", keys.cut(F.col(column), d)).where(F.length(column) >= d * keys.WIDTH)
        return cut.join(records.select("doc_id", F.col("okey").alias("_cut")), ["doc_id", "_cut"], "left_semi").drop("_cut")

    def run(self, steps: tuple[Step, ...], start: Context) -> list[Branch]:
        branches = [Branch(start, None)]
        for step in steps:
            branches = [new for b in branches for new in self.after(step, b)]
        return branches

    def after(self, step: Step, b: Branch) -> list[Branch]:
        at = sp.advance(self.rules, b.at, step)
        if step.axis == "text":
            if self.options.text_mode == "strict":
                at = Context(preds=frozenset(p for p in at.preds if p[1] == model.TEXT))
        if not at:
            return []
        if step.axis == "parent":
            out = []
            for d, records in self.parents(b).items():
                own = Context(frozenset(c for c in at.chains if self.depth(c) == d))
                out += self.tested(step, Branch(own, (d, records)))
            return out
        return self.tested(step, Branch(at, b.held))

    def tested(self, step: Step, b: Branch) -> list[Branch]:
        """Branches of one depth each that satisfy the step's condition."""
        if step.condition is None:
            return [b]
        out = []
        possible = {c for c in b.at.chains if sp.possible(self.rules, c, step.condition)}
        told = {c for c in possible if sp.certain(self.rules, c, step.condition)} if self.options.engine == "topdown" else set()
        if told:  # nothing to test
            out.append(Branch(Context(frozenset(told)), b.held))
        for d, own in sorted(self.by_depth(possible - told).items()):
            condition = sp.untold(self.rules, own, step.condition) if self.options.engine == "topdown" else step.condition
            found = self.restrict(self.satisfying(condition, d, own), "okey", b.held)
            out.append(Branch(Context(frozenset(own)), (d, found)))
        if b.at.preds and isinstance(step.condition, Not):  # leaves have nothing to test
            out.append(Branch(Context(preds=b.at.preds), b.held))
        return out

    def parents(self, b: Branch) -> dict[int, DataFrame]:
        """Records, by depth, that have a node of the branch as a child."""
        parts = defaultdict(list)
        if b.at.chains:
            inner = self.restrict(self.records(b.at.chains), "okey", b.held).select("doc_id", keys.parent(F.col("okey")).alias("okey"), "chain")
            for d, own in self.by_depth(b.at.chains).items():
                if d > 1:
                    parts[d - 1].append(inner.where(_chains("chain", own)).select(*KEYS))
        if b.at.preds:
            facts = self.restrict(self.facts(b.at.preds), "gkey", b.held).select("doc_id", F.col("gkey").alias("okey"), "chain")
            for d, own in self.by_depth({c for c, _ in b.at.preds}).items():
                parts[d].append(facts.where(_chains("chain", own)).select(*KEYS))
        return {d: union_all(p).distinct() for d, p in parts.items()}

    # conditions

    def witnesses(self, test: Test, d: int, chains) -> tuple[DataFrame | None, DataFrame | None]:
        """Facts and records that a test finds from records of chains at depth d."""
        facts, inner = [], []
        for b in self.run(test.path.steps, Context(frozenset(chains))):
            preds = b.at.preds
            if b.at.chains and test.op is None:
                inner.append(self.restrict(self.records(b.at.chains), "okey", b.held))
            elif b.at.chains and self.options.value_test == "own_text":
                preds = preds | {(c, model.TEXT) for c in b.at.chains if model.TEXT in self.rules.by_chain[c].child_tags}
            elif b.at.chains and self.options.value_test == "string_value":
                inner += [self.restrict(x, "okey", b.held) for x in self.whole_values(b.at.chains, test)]
            if preds:
                own = self.restrict(self.facts(preds), "gkey", b.held)
                facts.append(own if test.op is None else own.where(self.compare(test)))
        return union_all(facts) if facts else None, union_all(inner) if inner else None

    def whole_values(self, chains, test: Test) -> list[DataFrame]:
        """Records of chains whose whole text below satisfies a test."""
        below = sp.descendants(self.rules, frozenset(chains))
        every = {(c, t) for c in below for t in self.rules.by_chain[c].child_tags}
        parts = []
        for depth, own in self.by_depth(chains).items():
            texts = self.facts(every).withColumn("_top", keys.cut(F.col("okey"), depth)).where(F.length("okey") > depth * keys.WIDTH)
            whole = texts.groupBy("doc_id", F.col("_top").alias("okey")).agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("okey", "value"))), lambda x: x["value"]), "").alias("value"))
            valued = whole.withColumn("value_num", F.trim("value").try_cast("double")).where(self.compare(test))
            parts.append(self.records(own).join(valued.select(*KEYS), KEYS, "left_semi"))
        return parts

    def test_keys(self, test: Test, d: int, chains) -> DataFrame:
        """Records (doc_id, okey) at depth d that satisfy a test; not distinct."""
        facts, inner = self.witnesses(test, d, chains)
        parts = [x.select("doc_id", keys.cut(F.col(c), d).alias("okey")) for x, c in ((facts, "gkey"), (inner, "okey")) if x is not None]
        return union_all(parts) if parts else self.records([]).select(*KEYS)

    @staticmethod
    def compare(test: Test) -> Column:
        """A numeric literal is held against numbers, a text against text."""
        if test.op in ("contains", "starts-with"):
            value = F.col("value")
            return (value.contains if test.op == "contains" else value.startswith)(str(test.literal))
        value = F.col("value_num" if isinstance(test.literal, float) else "value")
        literal = F.lit(test.literal)
        return {"=": value == literal, "!=": value != literal, "<": value < literal, ">": value > literal, "<=": value <= literal, ">=": value >= literal}[test.op]

    def ordered(self, parts: tuple[Condition, ...]) -> tuple[Condition, ...]:
        """The parts of a conjunction in the order in which they are evaluated."""
        if self.options.order == "text":
            return parts

        def name(p: Condition) -> str:
            first = sp.tests_of(p)[0].path.steps[0]
            return (model.attribute(first.tags[0]) if first.axis == "attribute" else first.tags[0]) if first.tags else "*"

        if self.options.order == "document":
            return tuple(sorted(parts, key=lambda p: (name(p).startswith("@"), name(p))))
        if self._counts is None:
            self._counts = {r.pred: r["count"] for r in self.store.facts.groupBy("pred").count().collect()}
        return tuple(sorted(parts, key=lambda p: self._counts.get(name(p), 1 << 60) / (100 if any(t.op == "=" for t in sp.tests_of(p)) else 1)))

    def satisfying(self, condition: Condition, d: int, chains) -> DataFrame:
        """Records (doc_id, okey, distinct) of chains at depth d that satisfy a condition."""
        if self.options.engine == "bottomup":
            return self.grouped(condition, d, chains)
        if isinstance(condition, Test):
            return self.test_keys(condition, d, chains).distinct()
        if isinstance(condition, Or):
            return union_all([self.satisfying(p, d, chains) for p in condition.parts]).distinct()
        if isinstance(condition, Not):
            return self.records(chains).select(*KEYS).join(self.satisfying(condition.part, d, chains), KEYS, "left_anti")
        if self.options.conjunction == "unify" and self.contradicts(condition):
            return self.records([]).select(*KEYS)
        first, *rest = self.ordered(condition.parts)
        found = self.satisfying(first, d, chains)
        for p in rest:
            if isinstance(p, Not):
                found = found.join(self.satisfying(p.part, d, chains), KEYS, "left_anti")
            else:
                found = found.join(self.satisfying(p, d, chains), KEYS, "left_semi")
        return found

    @staticmethod
    def contradicts(condition: And) -> bool:
        seen: dict[Path, object] = {}
        for t in sp.tests_of(condition):
            if t.op == "=" and seen.setdefault(t.path, t.literal) != t.literal:
                return True
        return False

    def grouped(self, condition: Condition, d: int, chains) -> DataFrame:
        """All tests at once, grouped by record, then the condition as a formula over flags: no key finds another."""
        tests = sp.tests_of(condition)
        parts = [self.test_keys(t, d, chains).withColumn("_test", F.lit(i)) for i, t in enumerate(tests)]
        parts.append(self.records(chains).select(*KEYS).withColumn("_test", F.lit(-1)))
        flags = union_all(parts).groupBy(*KEYS).agg(*[F.max(F.col("_test") == i).alias(f"_t{i}") for i in range(len(tests))])
        place = iter(range(len(tests)))

        def formula(c: Condition) -> Column:
            if isinstance(c, Test):
                return F.col(f"_t{next(place)}")
            if isinstance(c, Not):
                return ~formula(c.part)
            return reduce(Column.__and__ if isinstance(c, And) else Column.__or__, [formula(p) for p in c.parts])

        return flags.where(formula(condition)).select(*KEYS)

    # answers

    def answers(self, path: Path) -> DataFrame:
        """doc_id, okey, tag, kind, value, value_num of the nodes that a path returns; each once."""
        columns = ["doc_id", "okey", "tag", "kind", "value", "value_num"]
        parts = []
        branches = self.run(path.steps, sp.ROOT)
        for b in branches:
            if b.at.chains:
                inner = self.restrict(self.records(b.at.chains), "okey", b.held)
                parts.append(inner.select("doc_id", "okey", "tag", F.lit(model.INNER).alias("kind"), F.lit(None).cast("string").alias("value"), F.lit(None).cast("double").alias("value_num")))
            if b.at.preds:
                facts = self.restrict(self.facts(b.at.preds), "gkey", b.held)
                parts.append(facts.select("doc_id", "okey", F.col("pred").alias("tag"), "kind", "value", "value_num"))
        if not parts:
            return self.store.facts.where(F.lit(False)).select("doc_id", "okey", F.col("pred").alias("tag"), "kind", "value", "value_num")
        found = union_all(parts).select(*columns)
        return found.distinct() if len(branches) > 1 else found


def query(store: Store, path: str | Path, **options) -> DataFrame:
    path = parse(path) if isinstance(path, str) else path
    return Evaluator(store, Options(**options)).answers(path)


def scanned(store: Store, path: str) -> set[str]:
    """Predicates that the plan of a path reads."""
    evaluator, out = Evaluator(store), set()
    real = evaluator.facts
    evaluator.facts = lambda preds: (out.update(p for _, p in preds), real(preds))[1]
    evaluator.answers(parse(path))
    return out


def count(store: Store, path: str, **options) -> DataFrame:
    return query(store, path, **options).agg(F.count("*").alias("n"))


def unspecialised(store: Store, path: str) -> DataFrame:
    """The path without specialisation: every record that stands at the first conditional step is built whole, from all
    predicates, before its conditions are tested; then the rest of the path is read off the built records.

    For paths whose conditional step tests children or attributes of the record, and whose output is a child or the record.
    """
    tree = parse(path)
    rules = store.rules
    at = next((k for k, s in enumerate(tree.steps) if s.condition is not None), None)
    contexts = sp.resolve(rules, Path(tuple(Step(s.axis, s.tags, None, s.deep) for s in tree.steps)))
    at = len(tree.steps) - 2 if at is None else at
    chains = contexts[at].chains
    depths = {rules.by_chain[c].depth for c in chains}
    if len(depths) != 1:
        raise ValueError("records of one level, please")
    d = depths.pop()
    whole = store.facts.withColumn("_top", keys.cut(F.col("gkey"), d)).where(F.length("gkey") >= d * keys.WIDTH)
    built = whole.groupBy("doc_id", F.col("_top").alias("okey")).agg(F.sort_array(F.collect_list(F.struct(F.col("okey").alias("at"), "pred", "kind", "value", "value_num", "gkey"))).alias("parts"))
    built = built.join(store.records.where(_chains("chain", chains)).select(*KEYS, "tag"), KEYS)

    def formula(c: Condition) -> Column:
        if isinstance(c, Not):
            return ~formula(c.part)
        if isinstance(c, And | Or):
            return reduce(Column.__and__ if isinstance(c, And) else Column.__or__, [formula(p) for p in c.parts])
        step = c.path.steps[0]
        if len(c.path.steps) > 1 or step.axis not in ("child", "attribute") or step.tags is None:
            raise ValueError("tests of children and attributes only")
        names = [model.attribute(t) if step.axis == "attribute" else t for t in step.tags]

        def holds(x: Column) -> Column:
            good = x["pred"].isin(names) & (x["gkey"] == F.col("okey"))
            if c.op is None:
                return good
            value = x["value_num"] if isinstance(c.literal, float) else x["value"]
            return good & {"=": value == F.lit(c.literal), "<": value < F.lit(c.literal), ">": value > F.lit(c.literal), "!=": value != F.lit(c.literal), "<=": value <= F.lit(c.literal), ">=": value >= F.lit(c.literal)}[c.op]

        return F.exists("parts", holds)

    condition = tree.steps[at].condition
    kept = built if condition is None else built.where(formula(condition))
    after = tree.steps[at + 1 :]
    if not after:
        return kept.select("doc_id", "okey", "tag", F.lit(model.INNER).alias("kind"), F.lit(None).cast("string").alias("value"), F.lit(None).cast("double").alias("value_num"))
    step = after[0]
    names = [model.attribute(t) if step.axis == "attribute" else t for t in step.tags]
    out = kept.select("doc_id", F.col("okey").alias("_top"), F.explode("parts").alias("p")).where(F.col("p.pred").isin(names) & (F.col("p.gkey") == F.col("_top")))
    return out.select("doc_id", F.col("p.at").alias("okey"), F.col("p.pred").alias("tag"), "p.kind", "p.value", "p.value_num")


def derivation_counts(store: Store, path: str) -> DataFrame:
    """doc_id, okey, n: how many ways each answer record can be derived whole, without making them: sums over the
    children of a predicate, products over predicates, from the deepest level up."""
    tree = parse(path)
    evaluator = Evaluator(store)
    at = sp.resolve(store.rules, tree)[-1]
    wanted = evaluator.answers(tree).where(F.col("kind") == model.INNER).select("doc_id", "okey")
    below = sp.descendants(store.rules, at.chains)
    depths = {store.rules.by_chain[c].depth for c in at.chains}
    if len(depths) != 1:
        raise ValueError("answers of one level, please")
    top = depths.pop()
    deepest = max(store.rules.by_chain[c].depth for c in below)
    facts = store.facts.where(_chains("chain", below)).select("doc_id", "pred", "gkey", keys.depth(F.col("gkey")).alias("d"), F.lit(1.0).alias("n"))
    made: DataFrame | None = None
    for d in range(deepest, top - 1, -1):
        own = facts.where(F.col("d") == d).select("doc_id", "gkey", "pred", "n")
        if made is not None:
            up = made.join(store.records.select("doc_id", "okey", "tag"), ["doc_id", "okey"]).select("doc_id", keys.parent(F.col("okey")).alias("gkey"), F.col("tag").alias("pred"), "n")
            own = own.unionByName(up)
        sums = own.groupBy("doc_id", "gkey", "pred").agg(F.sum("n").alias("n"))
        made = sums.groupBy("doc_id", F.col("gkey").alias("okey")).agg(F.product("n").alias("n"))
    return made.join(wanted, ["doc_id", "okey"], "left_semi")


def derivations(store: Store, path: str, limit: int | None = None) -> DataFrame:
    """One row for each combination of children of the answer records, for records of leaves and attributes; all of them
    unless a limit is given."""
    tree = parse(path)
    evaluator = Evaluator(store)
    wanted = evaluator.answers(tree).where(F.col("kind") == model.INNER).select("doc_id", "okey")
    out = []
    for c in sorted(sp.resolve(store.rules, tree)[-1].chains):
        shape = store.rules.by_chain[c]
        rows = evaluator.records([c]).join(wanted, ["doc_id", "okey"], "left_semi").select("doc_id", F.col("okey").alias("gkey"))
        for p in shape.preds:
            one = store.facts.where((F.col("pred") == p) & (F.col("chain") == c)).select("doc_id", "gkey", F.struct(F.lit(p).alias("pred"), "value", "okey").alias(f"_{p}"))
            rows = rows.join(one, ["doc_id", "gkey"])
        out.append(rows.select("doc_id", F.col("gkey").alias("okey"), F.array(*[F.col(f"`_{p}`") for p in shape.preds]).alias("terms")))
    every = union_all(out)
    return every if limit is None else every.limit(limit)


def access_plan(store: Store, path: str) -> list[dict]:
    """For each sub-goal in order: its predicate, and whether the group is known by then (second index) or not (first
    index, with the record keys cut to the depth that is known)."""
    tree = parse(path)
    contexts = sp.resolve(store.rules, tree)
    plan, known = [], set()
    for step, context in zip(tree.steps, contexts, strict=True):
        for test in sp.tests_of(step.condition):
            for c in sorted(context.chains):
                end = sp.resolve(store.rules, test.path, Context(frozenset((c,))))[-1]
                for chain, pred in sorted(end.preds):
                    entry = {"pred": pred, "index": "second" if chain in known else "first", "bound": bool(known), "cut": store.rules.by_chain[c].depth}
                    if entry not in plan:
                        plan.append(entry)
                    known.add(chain)
    for chain in sorted(contexts[-1].chains):
        for c in sorted(sp.descendants(store.rules, frozenset((chain,)))):
            for pred in store.rules.by_chain[c].preds:
                plan.append({"pred": pred, "index": "second" if c in known else "first", "bound": bool(known), "cut": store.rules.by_chain[chain].depth})
                known.add(c)
    for chain, pred in sorted(contexts[-1].preds):
        plan.append({"pred": pred, "index": "second" if chain in known else "first", "bound": bool(known), "cut": store.rules.by_chain[chain].depth})
        known.add(chain)
    return plan
