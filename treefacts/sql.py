"""The SQL surface: a table function that parses trees, and path queries as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from treefacts.operators.evaluate import query
from treefacts.operators.profile import register_views
from treefacts.operators.store import Store


class TreeParse:
    """Nodes of one XML text: key, tag, kind and value; none for null."""

    def eval(self, xml: str):
        from treefacts.sources.markup import parse_xml, rows_of

        root = parse_xml(xml) if xml is not None else None
        if root is not None:
            for row in rows_of(0, root):
                yield row[1], row[2], row[3], row[5]


def register(spark: SparkSession) -> None:
    """Makes tree_parse(xml) known to SQL."""
    spark.udtf.register("tree_parse", udtf(TreeParse, returnType="okey string, tag string, kind string, value string"))


def path_view(store: Store, path: str, name: str, **options) -> DataFrame:
    """Answers of a path as a view, beside the views of its store."""
    register_views(store, name)
    found = query(store, path, **options)
    found.createOrReplaceTempView(f"{name}_answers")
    return found
