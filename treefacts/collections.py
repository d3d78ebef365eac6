"""The given tables as trees, K1 to K9, each translated once for a session and kept in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefacts.operators.store import Store
from treefacts.session import table
from treefacts.sources import markup
from treefacts.sources.publish import Level, publish

_stores: dict[tuple[str, str, str], Store] = {}


def orders_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, items = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    c = F.col
    item = Level(
        items, "item", [], ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"], ["l_orderkey"],
        {"flag": c("l_returnflag"), "linestatus": c("l_linestatus")},
        [("partkey", c("l_partkey")), ("suppkey", c("l_suppkey")), ("quantity", c("l_quantity")), ("price", c("l_extendedprice")), ("discount", c("l_discount")), ("tax", c("l_tax")), ("shipdate", c("l_shipdate"))],
    )
    order = Level(
        orders, "order", ["o_orderkey"], ["o_orderkey"], [],
        {"status": c("o_orderstatus"), "priority": F.when(c("o_orderpriority") != "4-NOT SPECIFIED", c("o_orderpriority"))},
        [("orderkey", c("o_orderkey")), ("custkey", c("o_custkey")), ("total", c("o_totalprice")), ("orderdate", c("o_orderdate"))], below=[item],
    )
    return publish("orders", [order])


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, c = lambda n: table(spark, sf_dir, n), F.col
    people = [
        Level(t("supplier"), "supplier", [], ["s_suppkey"], ["s_nationkey"], {}, [("name", c("s_name")), ("acctbal", c("s_acctbal"))]),
        Level(t("customer"), "customer", [], ["c_custkey"], ["c_nationkey"], {"segment": c("c_mktsegment")}, [("name", c("c_name")), ("acctbal", c("c_acctbal"))]),
    ]
    nation = Level(t("nation"), "nation", ["n_nationkey"], ["n_nationkey"], ["n_regionkey"], {"name": c("n_name")}, [], below=people)
    return publish("regions", [Level(t("region"), "region", ["r_regionkey"], ["r_regionkey"], [], {"name": c("r_name")}, [], below=[nation])])


def parts_tree(spark: SparkSession, sf_dir: str, first: int | None = None) -> DataFrame:
    parts, c = table(spark, sf_dir, "part"), F.col
    if first is not None:  # the ladder of document sizes
        parts = parts.orderBy("p_partkey").limit(first)
    return publish("parts", [Level(parts, "part", ["p_partkey"], ["p_partkey"], [], {"brand": c("p_brand")}, [("name", c("p_name")), ("type", c("p_type")), ("size", c("p_size")), ("price", c("p_retailprice"))])])


def docs_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("l_id"), "quality", "toxic")
    docs, c = table(spark, sf_dir, "documents"), F.col
    docs = docs.join(labels, docs.doc_id == labels.l_id, "left")
    return publish("documents", [Level(docs, "document", ["doc_id"], ["doc_id"], [], {"lang": c("lang"), "source": c("source")}, [("chars", c("n_chars")), ("quality", c("quality")), ("toxic", c("toxic"))], text=c("text"))])


def chat_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations")
    said = Level(turns.select(F.col("conv_id").alias("t_conv"), "turn", "role", "text"), F.col("role"), [], ["turn"], ["t_conv"], {}, [(F.col("role"), F.col("text"))], is_leaf=True)
    convs = turns.select("conv_id").distinct()
    return publish("conversations", [Level(convs, "conversation", ["conv_id"], ["conv_id"], [], {"id": F.col("conv_id")}, [], below=[said])])


def event_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    events, c = table(spark, sf_dir, "events"), F.col
    k = F.get_json_object("props", "$.k")
    event = Level(events.withColumnRenamed("user_id", "e_user"), c("event_type"), [], ["ts", "event_id"], ["e_user"], {"ts": c("ts")}, [("value", c("value")), ("k", k)])
    return publish("users", [Level(events.select("user_id").distinct(), "user", ["user_id"], ["user_id"], [], {"id": c("user_id")}, [], below=[event])])


def page_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return markup.from_html(table(spark, sf_dir, "pages"))


def vector_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors, c = table(spark, sf_dir, "embeddings"), F.col
    return publish("vectors", [Level(vectors, "vector", ["vec_id"], ["vec_id"], [], {"label": c("label")}, [("values", c("embedding"))])])


def item_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return publish("items", [Level(table(spark, sf_dir, "benchmark"), "item", ["item_id"], ["item_id"], [], {}, [("item", F.col("text"))], is_leaf=True)])


TREES = {"K1": orders_tree, "K2": geo_tree, "K3": parts_tree, "K4": docs_tree, "K5": chat_tree, "K6": event_tree, "K7": page_tree, "K8": vector_tree, "K9": item_tree}


def store(spark: SparkSession, sf_dir: str, name: str) -> Store:
    """The store of a collection: translated when first asked for, then read from its files."""
    key = spark.sparkContext.applicationId, sf_dir, name
    if key not in _stores:
        nodes = TREES[name](spark, sf_dir)
        if name == "K7":
            from treefacts.session import materialise

            nodes = materialise(nodes, "page-nodes")  # parsed once, read for shapes and for facts
        _stores[key] = Store.from_nodes(nodes).saved(name)
    return _stores[key]
