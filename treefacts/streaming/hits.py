"""Streams of documents and events: translation, growing shapes, standing paths, and windows over path hits.

A document is one row, so numbering, shapes and chains need no state. What needs state is counted under a watermark.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefacts.functions import keys
from treefacts.operators.store import extract
from treefacts.operators.shapes import Rules, dictionary
from treefacts.session import new_folder


def run_once(stream: DataFrame, mode: str = "append", name: str = "stream") -> DataFrame:
    """Runs a stream over what there is, into files (append) or batches that replace each other (complete), and reads that."""
    spark = stream.sparkSession
    out, state = new_folder(spark, name), new_folder(spark, f"{name}-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("checkpointLocation", state).option("path", out).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    else:
        stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def event_files(spark: SparkSession, events: DataFrame, files: int = 4) -> str:
    """Events as files in time order, for a stream to find."""
    folder = new_folder(spark, "events")
    events.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(folder)
    return folder


def event_stream(spark: SparkSession, folder: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def window_counts(stream: DataFrame, kind: str, size: str, slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """Hits in tumbling or sliding windows, or in sessions of a user."""
    marked = stream.withWatermark("ts", watermark)
    if kind == "session":
        return marked.groupBy(F.session_window("ts", size).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return marked.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def translate(nodes: DataFrame, rules: Rules) -> DataFrame:
    """Facts of a stream of nodes; types of shapes that the rules don't know stay null until they are read with new rules."""
    return extract(nodes, rules)


def grow_shapes(nodes: DataFrame, path: str) -> None:
    """Keeps the dictionary of a stream of nodes at path: each batch is merged by chain, the first appearance stays. A batch that
    is run again writes the same folder."""
    spark = nodes.sparkSession

    def merge(batch: DataFrame, batch_id: int) -> None:
        new = dictionary(batch)
        before = f"{path}/v{batch_id - 1}"
        if batch_id:
            new = new.unionByName(spark.read.parquet(before))
            new = new.groupBy("chain", "parent_chain", "depth", "tag", "child_tags", "att_names").agg(F.min("first").alias("first"), F.sum("n_nodes").alias("n_nodes"))
        new.write.mode("overwrite").parquet(f"{path}/v{batch_id}")

    nodes.writeStream.foreachBatch(merge).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()


def standing(stream: DataFrame, chains: list[int], pred: str) -> DataFrame:
    """Facts of a stream that a standing path of one predicate returns."""
    return stream.where((F.col("pred") == pred) & F.col("chain").isin(chains)).select("doc_id", keys.dotted(F.col("okey")).alias("node"), "pred", "value")
