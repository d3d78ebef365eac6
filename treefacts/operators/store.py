"""Facts and records of trees, and the store that keeps them.

The first index is the partitioning of facts by predicate; the second is their order by record group inside each file.

A store on disk is a row of batches, each a folder of facts, of records and, written last, of all rules so far. Readers
take the batches up to the newest rules, so a batch that isn't finished, or was broken off, is not seen; the next append writes
over it. One writer at a time.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefacts import model
from treefacts.functions import keys, values
from treefacts.operators.shapes import Rules, Shape, added_types, rules
from treefacts.session import new_folder
from treefacts.sources.publish import global_rank


def extract(nodes: DataFrame, found: Rules) -> DataFrame:
    """FACTS of nodes: one for each leaf, text run and attribute. The dictionary gives the types; it is small and literal."""
    types = F.create_map(*[F.lit(x) for s in found.shapes for x in (s.chain, s.child_typ)]) if found.shapes and len(found.shapes) <= 500 else None
    own = nodes.where(F.col("kind") != model.INNER).select("doc_id", F.col("tag").alias("pred"), "kind", "value", "okey", keys.parent(F.col("okey")).alias("gkey"), "chain")
    atts = nodes.where((F.col("kind") == model.INNER) & (F.size("att_names") > 0)).select("doc_id", F.explode("atts").alias("name", "value"), "okey", "chain")
    atts = atts.select("doc_id", F.concat(F.lit("@"), "name").alias("pred"), F.lit(model.ATTRIBUTE).alias("kind"), "value", "okey", F.col("okey").alias("gkey"), "chain")
    facts = own.unionByName(atts)
    if types is not None:
        facts = facts.withColumn("typ", types[F.col("chain")])
    elif found.shapes:
        spark = nodes.sparkSession
        facts = facts.join(F.broadcast(spark.createDataFrame([(s.chain, s.child_typ) for s in found.shapes], "chain long, typ int")), "chain", "left")
    else:
        facts = facts.withColumn("typ", F.lit(None).cast("int"))
    facts = facts.withColumns({"value_num": values.number(F.col("value")), "value_list": values.number_list(F.col("value"))})
    return facts.select(*model.FACTS.names)


def records_of(nodes: DataFrame) -> DataFrame:
    return nodes.where(F.col("kind") == model.INNER).select(*model.RECORDS.names)


SIBLINGS = 3  #: hexadecimal digits of a sibling's number that stay together: blocks of 4,096


@dataclass
class Store:
    """Rules are held by the planner; facts and records are tables."""

    rules: Rules
    facts: DataFrame
    records: DataFrame

    @classmethod
    def from_nodes(cls, nodes: DataFrame, mode: str = "classes") -> Store:
        found = rules(nodes, mode)
        return cls(found, extract(nodes, found), records_of(nodes))

    def write(self, path: str, layout: str = "indexed") -> None:
        """indexed: a folder for each predicate, sorted by group; flat: no index at all."""
        self._write(path, 0, self.rules, layout)

    def _write(self, path: str, batch: int, every: Rules, layout: str = "indexed") -> None:
        """Facts and records of this store as a batch, then every rule so far."""
        folder = lambda name: f"{path}/{name}/batch={batch}"
        if layout == "flat":
            self.facts.write.mode("overwrite").parquet(folder("facts"))
        else:
            # by document, record of the second level and block of records below it, so no document or record is one task's
            dealt = self.facts.repartition("pred", "doc_id", keys.cut(F.col("gkey"), 2), F.substring("gkey", 2 * keys.WIDTH + 1, keys.WIDTH - SIBLINGS))
            dealt.sortWithinPartitions("pred", "doc_id", "gkey", "okey").write.mode("overwrite").partitionBy("pred").parquet(folder("facts"))
        self.records.sortWithinPartitions("doc_id", "okey").write.mode("overwrite").parquet(folder("records"))
        spark = self.facts.sparkSession
        spark.createDataFrame([(json.dumps([asdict(s) for s in every.shapes]),)], "shapes string").coalesce(1).write.mode("overwrite").text(folder("rules"))

    @staticmethod
    def _newest(spark: SparkSession, path: str) -> tuple[int, Rules]:
        newest = spark.read.text(f"{path}/rules").orderBy(F.desc("batch")).first()
        shapes = [Shape(**{**x, "child_tags": tuple(x["child_tags"]), "att_names": tuple(x["att_names"]), "first": tuple(x["first"])}) for x in json.loads(newest.value)]
        return newest.batch, Rules(shapes)

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> Store:
        batch, every = cls._newest(spark, path)
        table = lambda name, schema: spark.read.schema(T.StructType([*schema.fields, T.StructField("batch", T.IntegerType())])).parquet(f"{path}/{name}").where(F.col("batch") <= batch).select(*schema.names)
        return cls(every, table("facts", model.FACTS), table("records", model.RECORDS))

    def saved(self, name: str = "store", layout: str = "indexed") -> Store:
        """The store after a round trip through the shared folder."""
        spark = self.facts.sparkSession
        folder = new_folder(spark, name)
        self.write(folder, layout)
        return Store.open(spark, folder)

    @classmethod
    def append(cls, nodes: DataFrame, path: str) -> None:
        """Adds documents to a written store as a new batch; types of old shapes stay, new shapes are added to the newest rules."""
        batch, old = cls._newest(nodes.sparkSession, path)
        new = [s for s in rules(nodes).shapes if s.chain not in old.by_chain]
        every = Rules([*old.shapes, *added_types(old.shapes, new)])
        cls(every, extract(nodes, every), records_of(nodes))._write(path, batch + 1, every)

    def stats(self) -> DataFrame:
        """Facts, distinct values (approximate) and extremes of each predicate."""
        return self.facts.groupBy("pred").agg(F.count("*").alias("n"), F.approx_count_distinct("value").alias("values"), F.min("value_num").alias("low"), F.max("value_num").alias("high"))


def translate(nodes: DataFrame, mode: str = "classes") -> Store:
    """Rules and facts of trees, in one pass over the nodes after the shapes are known."""
    return Store.from_nodes(nodes, mode)


def positions(facts: DataFrame, layout: str = "group") -> DataFrame:
    """Facts with pos (place in the file) and gpos (place where their group begins), from 0. layout group: clustered by
    record; document: pure document order."""
    order = ["doc_id", "gkey", "okey", "pred"] if layout == "group" else ["doc_id", "okey", "pred"]
    ranked = global_rank(facts, order, "pos").withColumn("pos", F.col("pos") - 1)
    return ranked.withColumn("gpos", F.min("pos").over(Window.partitionBy("doc_id", "gkey")))


def first_index(placed: DataFrame) -> DataFrame:
    """Predicate to positions."""
    return placed.select("pred", "pos", "gpos")


def second_index(placed: DataFrame) -> DataFrame:
    """Position to the position of its group."""
    return placed.select("pos", "gpos")
