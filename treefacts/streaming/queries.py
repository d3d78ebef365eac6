"""Streaming queries over the given tables and their SQL."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefacts.operators.shapes import rules
from treefacts.plans.path import parse
from treefacts.plans.specialise import resolve
from treefacts.session import materialise, new_folder, table
from treefacts.sources import markup
from treefacts.streaming import hits


def _events(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events")
    return hits.event_stream(spark, hits.event_files(spark, events), events.schema)


def ntz(column: str):
    return F.col(column).cast("timestamp_ntz").alias(column)


def st_tumbling(spark: SparkSession, d: str) -> DataFrame:
    """Hits of each kind of event by hour; complete, so that the open windows count too."""
    found = hits.run_once(hits.window_counts(_events(spark, d), "tumbling", "1 hour"), "complete")
    return found.select(ntz("start"), "event_type", "n")


def st_sliding(spark: SparkSession, d: str) -> DataFrame:
    found = hits.run_once(hits.window_counts(_events(spark, d), "sliding", "2 hours", "1 hour"), "complete")
    return found.select(ntz("start"), "event_type", "n")


def st_session(spark: SparkSession, d: str) -> DataFrame:
    found = hits.run_once(hits.window_counts(_events(spark, d), "session", "6 hours", watermark="400 days"), "complete")
    return found.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def st_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Every event arrives twice; one of each stays."""
    events = table(spark, d, "events")
    folder = hits.event_files(spark, events.unionByName(events))
    stream = hits.event_stream(spark, folder, events.schema).withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"])
    return hits.run_once(stream.select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


def st_late(spark: SparkSession, d: str) -> DataFrame:
    """The first day's events arrive again after all others: they are behind the watermark and must not count."""
    events = table(spark, d, "events")
    folder = new_folder(spark, "late-events")
    events.coalesce(1).write.parquet(folder)
    start = events.agg(F.min("ts")).first()[0]
    stream = hits.event_stream(spark, folder, events.schema)
    hits.run_once(hits.window_counts(stream, "tumbling", "1 day", watermark="1 hour"), "append")
    late = events.where(F.col("ts") < F.lit(start) + F.expr("interval 1 day"))
    out, state = new_folder(spark, "late-out"), new_folder(spark, "late-state")

    def run() -> None:
        counts = hits.window_counts(hits.event_stream(spark, folder, events.schema), "tumbling", "1 day", watermark="1 hour")
        counts.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()

    run()
    late.coalesce(1).write.mode("append").parquet(folder)
    run()
    return spark.read.parquet(out).select(ntz("start"), "event_type", "n")


def _chat_text(spark: SparkSession, d: str) -> DataFrame:
    turns = table(spark, d, "conversations").where(F.col("role").isin("system", "user", "assistant"))
    one = F.concat(F.lit("<"), "role", F.lit(">"), F.replace(F.replace("text", F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit("</"), "role", F.lit(">"))
    made = turns.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", one.alias("x")))), lambda x: x["x"]), "").alias("inner"))
    return made.select(F.col("conv_id").alias("doc_id"), F.concat(F.lit('<conversation id="'), "conv_id", F.lit('">'), "inner", F.lit("</conversation>")).alias("xml"))


def _node_stream(spark: SparkSession, d: str) -> DataFrame:
    folder = new_folder(spark, "chat-files")
    texts = materialise(_chat_text(spark, d), "chat-text")
    texts.repartition(3, "doc_id").write.parquet(folder)
    return markup.from_xml_text(spark.readStream.schema(texts.schema).option("maxFilesPerTrigger", 1).parquet(folder))


def st_shapes(spark: SparkSession, d: str) -> DataFrame:
    """The dictionary that grows with the stream, at its end."""
    path = new_folder(spark, "shapes")
    hits.grow_shapes(_node_stream(spark, d), path)
    jvm, sc = spark.sparkContext._jvm, spark.sparkContext
    folder = jvm.org.apache.hadoop.fs.Path(path)
    names = [f.getPath().getName() for f in folder.getFileSystem(sc._jsc.hadoopConfiguration()).listStatus(folder)]
    last = max(int(n[1:]) for n in names if re.fullmatch(r"v\d+", n))
    return spark.read.parquet(f"{path}/v{last}").select(F.array_join("child_tags", ",").alias("roles"), F.col("n_nodes").alias("n"))


def st_join(spark: SparkSession, d: str) -> DataFrame:
    """Hits of users of a static table: a stream-static join."""
    users = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    stream = _events(spark, d).join(users, "user_id").select("event_id", "c_mktsegment")
    return hits.run_once(stream).groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n"))


def st_translate(spark: SparkSession, d: str) -> DataFrame:
    """Facts of a stream of documents, types by the rules of what came before it."""
    nodes = materialise(markup.from_xml_text(_chat_text(spark, d)), "chat-nodes")
    found = hits.run_once(hits.translate(_node_stream(spark, d), rules(nodes)))
    return found.where("typ is not null").groupBy("pred").agg(F.count("*").alias("n"))


def st_standing(spark: SparkSession, d: str) -> DataFrame:
    """A standing path over a stream of documents: what assistants said, after a user or a system."""
    nodes = materialise(markup.from_xml_text(_chat_text(spark, d)), "chat-nodes")
    known = rules(nodes)
    chains = sorted(c for c, p in resolve(known, parse("/conversation[user]/assistant"))[-1].preds if p == "assistant")
    found = hits.run_once(hits.standing(hits.translate(_node_stream(spark, d), known), chains, "assistant"))
    return found.groupBy("doc_id").agg(F.count("*").alias("n"))


QUERIES = {
    "st_translate": (st_translate, "select role as pred, count(*) as n from conversations group by 1 union all select '@id', count(distinct conv_id) from conversations"),
    "st_standing": (st_standing, "select conv_id as doc_id, count(*) as n from conversations c where role = 'assistant' and exists (select 1 from conversations u where u.conv_id = c.conv_id and u.role = 'user') group by 1"),
    "st_tumbling": (st_tumbling, "select date_trunc('hour', ts) as start, event_type, count(*) as n from events group by 1, 2"),
    "st_sliding": (st_sliding, "select start, event_type, count(*) as n from (select date_trunc('hour', ts) as start, event_type from events union all select date_trunc('hour', ts) - interval 1 hour, event_type from events) group by 1, 2"),
    "st_session": (st_session, "with g as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hour then 0 else 1 end as fresh from events) select user_id, cast(sum(fresh) as bigint) as sessions, count(*) as n from g group by 1"),
    "st_dedup": (st_dedup, "select event_type, count(*) as n from events group by 1"),
    "st_late": (st_late, "select date_trunc('day', ts) as start, event_type, count(*) as n from events where date_trunc('day', ts) + interval 1 day <= (select max(ts) - interval 1 hour from events) group by 1, 2"),
    "st_shapes": (st_shapes, "select roles, count(*) as n from (select string_agg(distinct role, ',' order by role) as roles from conversations group by conv_id) group by 1"),
    "st_join": (st_join, "select c_mktsegment as segment, count(*) as n from events join customer on user_id = c_custkey group by 1"),
}
