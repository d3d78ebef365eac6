"""Counts over stores by level, tag and kind, sibling windows, and the SQL surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treefacts.functions import keys
from treefacts.operators.store import Store


def levels(store: Store) -> DataFrame:
    return store.facts.select(keys.depth(F.col("okey")).alias("depth"), "pred", "kind")


def grouped(store: Store, how: str) -> DataFrame:
    """Facts counted by depth, predicate and kind, with the subtotals of a rollup or cube."""
    df = levels(store)
    return (df.rollup if how == "rollup" else df.cube)("depth", "pred", "kind").agg(F.count("*").alias("n"))


def grouping_sets(store: Store) -> DataFrame:
    return levels(store).groupingSets([["depth"], ["pred"], ["depth", "pred"]], "depth", "pred").agg(F.count("*").alias("n"))


def shape_histogram(store: Store) -> DataFrame:
    spark = store.facts.sparkSession
    return spark.createDataFrame([(s.tag, s.depth, list(s.preds), s.n_nodes) for s in store.rules.shapes], "tag string, depth int, preds array<string>, n long")


def siblings(facts: DataFrame) -> DataFrame:
    """facts with place (among siblings), before (predicate of the sibling before) and same_before (earlier siblings of
    the same predicate)."""
    record = Window.partitionBy("doc_id", "gkey").orderBy("okey")
    same = Window.partitionBy("doc_id", "gkey", "pred").orderBy("okey").rowsBetween(Window.unboundedPreceding, -1)
    return facts.withColumns({"place": F.row_number().over(record), "before": F.lag("pred").over(record), "same_before": F.count("*").over(same)})


def register_views(store: Store, name: str) -> None:
    """Views name_facts, name_records and name_rules for SQL."""
    store.facts.createOrReplaceTempView(f"{name}_facts")
    store.records.createOrReplaceTempView(f"{name}_records")
    shape_histogram(store).createOrReplaceTempView(f"{name}_rules")
