"""Documents and answers as text again.

Tokens (openings with their attributes, texts, closings) carry keys by which they sort into document order; each renders on
its own, so a document of any size is a sorted table of tokens, and small answers are folded by key in the JVM.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treefacts import model
from treefacts.functions import keys
from treefacts.operators.store import Store


def escaped(value: Column) -> Column:
    return F.replace(F.replace(F.replace(value, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))


def quoted(value: Column) -> Column:
    return F.replace(escaped(value), F.lit('"'), F.lit("&quot;"))


def tokens(store: Store, facts: DataFrame | None = None, records: DataFrame | None = None) -> DataFrame:
    """doc_id, key, place, token: what (key, place) sorts into the text of the documents."""
    facts, records = store.facts if facts is None else facts, store.records if records is None else records
    opening = records.select("doc_id", F.col("okey").alias("key"), F.lit(0).alias("place"), F.concat(F.lit("<"), "tag").alias("token"))
    closing = records.select("doc_id", F.concat("okey", F.lit("g")).alias("key"), F.lit(9).alias("place"), F.concat(F.lit("</"), "tag", F.lit(">")).alias("token"))
    atts = facts.where(F.col("kind") == model.ATTRIBUTE)
    attribute = atts.select("doc_id", F.col("okey").alias("key"), F.lit(1).alias("place"), F.concat(F.lit(" "), F.substring("pred", 2, 1 << 20), F.lit('="'), quoted(F.col("value")), F.lit('"')).alias("token"))
    end = records.select("doc_id", F.col("okey").alias("key"), F.lit(2).alias("place"), F.lit(">").alias("token"))
    value = escaped(F.col("value"))
    text = F.when(F.col("kind") == model.RUN, value).otherwise(F.concat(F.lit("<"), "pred", F.lit(">"), value, F.lit("</"), "pred", F.lit(">")))
    leaves = facts.where(F.col("kind") != model.ATTRIBUTE).select("doc_id", F.col("okey").alias("key"), F.lit(3).alias("place"), text.alias("token"))
    # an opening and its end are one token: attributes, by name, stand between
    head = opening.unionByName(attribute).unionByName(end)
    joined = head.groupBy("doc_id", "key").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("place", "token"))), lambda x: x["token"]), "").alias("token")).select("doc_id", "key", F.lit(0).alias("place"), "token")
    return joined.unionByName(leaves).unionByName(closing)


def document(store: Store) -> DataFrame:
    """doc_id, xml: each document as one text; for documents of a row's size."""
    return fold(tokens(store), "doc_id").select("doc_id", F.col("text").alias("xml"))


def fold(made: DataFrame, *by: str) -> DataFrame:
    ordered = F.array_sort(F.collect_list(F.struct("key", "place", "token")))
    return made.groupBy(*by).agg(F.array_join(F.transform(ordered, lambda x: x["token"]), "").alias("text"))


def write_document(store: Store, path: str, wrapper: str | None = None) -> None:
    """A document of any size as text files, in order by file name; tokens are never brought together."""
    n = int(store.facts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    made = tokens(store)
    if wrapper:
        spark = made.sparkSession
        ends = spark.createDataFrame([(-(1 << 62), "", 0, f"<{wrapper}>"), ((1 << 62), "", 0, f"</{wrapper}>")], made.schema)
        made = made.unionByName(ends)
    made.repartitionByRange(n, "doc_id", "key", "place").sortWithinPartitions("doc_id", "key", "place").select(F.col("token").alias("value")).write.text(path)
