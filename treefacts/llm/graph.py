"""Connected components of a table of links, by least labels and pointer jumping, over written tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefacts.llm import common


def components(links: DataFrame) -> DataFrame:
    """(id, component) of every id in links (a, b); component is the least id reachable."""
    both = common.materialise(links.select("a", "b").union(links.select("b", "a")).where("a <> b").distinct(), "links")
    labels = common.materialise(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("label")).withColumnRenamed("a", "id"), "labels")
    while True:
        near = both.join(labels.select("id", "label"), F.col("b") == F.col("id")).groupBy("a").agg(F.min("label").alias("near"))
        lower = labels.select("id", "label").join(near, F.col("id") == F.col("a")).select("id", F.col("label").alias("was"), F.least("label", "near").alias("label"))
        jump = lower.join(labels.select(F.col("id").alias("via"), F.col("label").alias("further")), F.col("label") == F.col("via"), "left")
        after = common.materialise(jump.select("id", "was", F.least("label", F.coalesce("further", "label")).alias("label")), "labels")
        done = after.where("label < was").isEmpty()
        common.discard(labels)
        labels = after
        if done:
            common.discard(both)
            out = labels.select("id", F.col("label").alias("component"))
            out._treefacts_folder = labels._treefacts_folder
            return out
