"""Forms of answers, and joins and sets of them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.operators import rebuild
from treefacts.operators.evaluate import KEYS, Evaluator, Options, query, union_all
from treefacts.operators.store import Store
from treefacts.plans import specialise as sp
from treefacts.plans.path import And, Path, Test, parse
from treefacts.session import materialise


def forest(store: Store, path: str, **options) -> DataFrame:
    """doc_id, okey, xml: each answer as a tree of its own."""
    found = query(store, path, **options)
    at = sp.resolve(store.rules, parse(path))[-1]
    parts = []
    depths = sorted({store.rules.by_chain[c].depth for c in at.chains})
    roots = found.where(F.col("kind") == model.INNER).select("doc_id", F.col("okey").alias("top"))
    for d in depths:
        own = sorted(c for c in at.chains if store.rules.by_chain[c].depth == d)
        below = sorted(sp.descendants(store.rules, frozenset(own)))
        here = roots.where(F.length("top") == d * keys.WIDTH)
        under = lambda df: df.where(F.col("chain").isin(below)).withColumn("top", keys.cut(F.col("okey"), d)).join(here, ["doc_id", "top"], "left_semi")  # noqa: B023, E731
        made = rebuild.tokens(store, under(store.facts).drop("top"), under(store.records).drop("top"))
        made = made.withColumn("okey", keys.cut(F.col("key"), d))
        parts.append(rebuild.fold(made, "doc_id", "okey").withColumnRenamed("text", "xml"))
    value = rebuild.escaped(F.col("value"))
    leaves = found.where(F.col("kind") != model.INNER)
    parts.append(leaves.select("doc_id", "okey", F.when(F.col("kind") == model.LEAF, F.concat(F.lit("<"), "tag", F.lit(">"), value, F.lit("</"), "tag", F.lit(">"))).otherwise(value).alias("xml")))
    return union_all(parts)


def branch(store: Store, path: str, keep_attributes: bool = False, **options) -> DataFrame:
    """The part of the documents that the path is about: answers whole, what made conditions true (whole too), and what lies
    above. Attributes of what lies above stay only where they are answers or witnesses, unless keep_attributes."""
    tree = parse(path)
    evaluator = Evaluator(store, Options(**options))
    columns = ["doc_id", "okey", "tag", "kind", "value", "value_num"]
    found = evaluator.answers(tree).select(*columns)
    parts, tops = [found], [found.where(F.col("kind") == model.INNER)]
    contexts = sp.resolve(store.rules, tree)
    depths = {store.rules.by_chain[c].depth for c in contexts[-1].chains}
    for k, (step, context) in enumerate(zip(tree.steps, contexts, strict=True)):
        if step.condition is None:
            continue
        # records of this step that lead to an answer, and the witnesses of their tests
        rest = tree.steps[k + 1 :]
        condition = And((step.condition, Test(Path(rest)))) if rest else step.condition
        held = materialise(evaluator.answers(Path((*tree.steps[:k], replace(step, condition=condition)))).where(F.col("kind") == model.INNER).select(*KEYS), "branch-records")
        for d, chains in evaluator.by_depth(context.chains).items():
            above = held.where(F.length("okey") == d * keys.WIDTH).select(*KEYS)
            for test in sp.tests_of(step.condition):
                facts, inner = evaluator.witnesses(test, d, chains)
                for df in (facts, inner):
                    if df is None:
                        continue
                    is_inner = df is inner
                    if is_inner:
                        df = df.withColumns({"kind": F.lit(model.INNER), "value": F.lit(None).cast("string"), "value_num": F.lit(None).cast("double")})
                        end = sp.resolve(store.rules, test.path, sp.Context(frozenset(chains)))[-1]
                        depths |= {store.rules.by_chain[c].depth for c in end.chains}
                    else:
                        df = df.withColumn("tag", F.col("pred"))
                    df = df.withColumn("_top", keys.cut(F.col("okey"), d))
                    seen = df.join(above.withColumnRenamed("okey", "_top"), ["doc_id", "_top"], "left_semi").select(*columns)
                    parts.append(seen)
                    if is_inner:
                        tops.append(seen)
    # read several times below
    whole = materialise(union_all(parts).distinct(), "branch")
    every_top = materialise(union_all(tops).distinct(), "branch-tops") if len(tops) > 1 else whole.where(F.col("kind") == model.INNER)
    named = whole.select("doc_id", F.explode(F.transform(F.sequence(F.lit(1), keys.depth(F.col("okey"))), lambda i: F.substring(F.col("okey"), F.lit(1), i * keys.WIDTH))).alias("okey")).distinct()
    above = store.records.join(named, ["doc_id", "okey"], "left_semi").select("doc_id", "okey", "tag", F.lit(model.INNER).alias("kind"), F.lit(None).cast("string").alias("value"), F.lit(None).cast("double").alias("value_num"))
    out = [whole, above]
    if keep_attributes:
        atts = store.facts.where(F.col("kind") == model.ATTRIBUTE).join(named, ["doc_id", "okey"], "left_semi")
        out.append(atts.select("doc_id", "okey", F.col("pred").alias("tag"), "kind", "value", "value_num"))
    for d in sorted(depths):
        here = every_top.where(F.length("okey") == d * keys.WIDTH).select("doc_id", F.col("okey").alias("_top"))
        for df in (store.facts.withColumnRenamed("pred", "tag"), store.records.withColumns({"kind": F.lit(model.INNER), "value": F.lit(None).cast("string"), "value_num": F.lit(None).cast("double")})):
            below = df.where(F.length("okey") >= d * keys.WIDTH).withColumn("_top", keys.cut(F.col("okey"), d)).join(here, ["doc_id", "_top"], "left_semi")
            out.append(below.select(*columns))
    return union_all([x.select(*columns) for x in out]).distinct()


def as_records(store: Store, tag: str, preds: list[str]) -> DataFrame:
    """doc_id, okey and one column for each predicate (first value; null where it is missing) of the records of a tag."""
    chains = sorted(s.chain for s in store.rules.shapes if s.tag == tag)
    facts = store.facts.where(F.col("pred").isin(preds) & F.col("chain").isin(chains))
    firsts = [F.min(F.when(F.col("pred") == p, F.struct("okey", "value"))).getField("value").alias(p) for p in preds]
    wide = facts.groupBy("doc_id", F.col("gkey").alias("okey")).agg(*firsts)
    return store.records.where(F.col("chain").isin(chains)).select("doc_id", "okey").join(wide, ["doc_id", "okey"], "left")


def join_children(store: Store, left: str, right: str, depth: int, how: str = "inner") -> DataFrame:
    """Values of two paths that lie below the same record of a depth."""
    a = query(store, left).select("doc_id", keys.cut(F.col("okey"), depth).alias("okey"), F.col("value").alias("left_value"), F.col("value_num").alias("left_num"))
    b = query(store, right).select("doc_id", keys.cut(F.col("okey"), depth).alias("okey"), F.col("value").alias("right_value"), F.col("value_num").alias("right_num"))
    return a.join(b, ["doc_id", "okey"], how)


def join_descendants(ancestors: DataFrame, nodes: DataFrame, depth: int | None = None) -> DataFrame:
    """nodes with the ancestors (doc_id, okey) that they lie below: an equality join on cut keys, one for each depth."""
    if depth is not None:
        cut = nodes.where(F.length("okey") > depth * keys.WIDTH).withColumn("ancestor", keys.cut(F.col("okey"), depth))
    else:
        cut = nodes.withColumn("ancestor", F.explode(F.transform(F.sequence(F.lit(1), keys.depth(F.col("okey")) - 1), lambda i: F.substring(F.col("okey"), F.lit(1), i * keys.WIDTH))))
    return cut.join(ancestors.select("doc_id", F.col("okey").alias("ancestor")), ["doc_id", "ancestor"])


def range_join(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of rows of a key in which right's time is within seconds after left's: an equality join on time buckets."""
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    a = left.select(F.col(key).alias("_k"), F.col(time).alias("_from")).withColumn("_b", F.explode(F.array(bucket("_from"), bucket("_from") + 1)))
    b = right.withColumnRenamed(key, "_k").withColumn("_b", bucket(time))
    return a.join(b, ["_k", "_b"]).where((F.col(time) > F.col("_from")) & (F.col(time) <= F.col("_from") + F.expr(f"interval {seconds} seconds")))


def asof(left: DataFrame, right: DataFrame, key: str, time: str) -> DataFrame:
    """left with before: the last earlier time of right under the same key; one window over both, no join."""
    both = left.withColumn("_right", F.lit(None).cast("timestamp_ntz")).withColumn("_side", F.lit(0)).unionByName(right.withColumns({"_right": F.col(time), "_side": F.lit(1)}), allowMissingColumns=True)
    before = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("before", F.last("_right", ignorenulls=True).over(before)).where("_side = 0").drop("_right", "_side")


def combine(how: str, a: DataFrame, b: DataFrame) -> DataFrame:
    """union, intersect or minus of answers as sets of nodes."""
    a, b = (x.select("doc_id", "okey", "tag", "kind") for x in (a, b))
    return {"union": lambda: a.unionByName(b).distinct(), "intersect": lambda: a.intersect(b), "minus": lambda: a.subtract(b)}[how]()


def to_json(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "okey", F.to_json(F.struct("tag", "kind", "value")).alias("json"))


def exists(store: Store, path: str | Path) -> bool:
    """Whether a path has an answer; ends with the first."""
    return not query(store, path).limit(1).isEmpty()
