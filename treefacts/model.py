"""Schemas of the engine's tables, and the reserved predicate names."""

from __future__ import annotations

from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, MapType, StringType, StructField, StructType

TEXT = "#text"  #: predicate of a text run; no tag contains #
INNER, LEAF, RUN, ATTRIBUTE = "inner", "leaf", "text", "att"

#: Sources make nodes. child_tags, att_names and chain are those of an inner node; a leaf or text has its parent's chain.
NODES = StructType([
    StructField("doc_id", LongType()), StructField("okey", StringType()), StructField("tag", StringType()), StructField("kind", StringType()),
    StructField("atts", MapType(StringType(), StringType())), StructField("value", StringType()),
    StructField("child_tags", ArrayType(StringType())), StructField("att_names", ArrayType(StringType())),
    StructField("chain", LongType()), StructField("parent_chain", LongType()),
])

FACTS = StructType([
    StructField("doc_id", LongType()), StructField("pred", StringType()), StructField("kind", StringType()), StructField("value", StringType()),
    StructField("value_num", DoubleType()), StructField("value_list", ArrayType(DoubleType())), StructField("okey", StringType()),
    StructField("gkey", StringType()), StructField("typ", IntegerType()), StructField("chain", LongType()),
])

RECORDS = StructType([
    StructField("doc_id", LongType()), StructField("okey", StringType()), StructField("tag", StringType()), StructField("chain", LongType()),
])


def attribute(name: str) -> str:
    return f"@{name}"
