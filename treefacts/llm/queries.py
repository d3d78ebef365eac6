"""Queries of the operators over the given tables, with production parameters, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefacts.llm import common, decontaminate, html_text, jaccard, langid, lines, mixing, quality, tokens, toxicity, warc


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.measure(common.read(spark, sf_dir, "documents"))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents").select("doc_id", "source")
    names = {f"mix_{x}": x for x in ("position", "block", "slot", "release", "deadline", "phase")}
    return mixing.mix(docs).withColumnsRenamed(names)


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "benchmark"))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.dedup(common.read(spark, sf_dir, "documents"))


def op8_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join(common.read(spark, sf_dir, "documents"), words=3, percent=90)


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = warc.round_trip(common.read(spark, sf_dir, "pages"))
    return found.select(warc.page_id_of("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", warc.page_id_of("refers_to").alias("refers_to"))


def op7_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(common.read(spark, sf_dir, "pages"))


def op6_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents")
    fold = langid.fold("doc_id", 5)
    held_out = F.coalesce(fold == 0, F.lit(False))
    found = langid.identify(docs, docs.where(fold != 0))
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents")
    return tokens.round_trip(docs, [F.col("doc_id"), F.xxhash64("text")]).select("doc_id", "start", "n_tokens", "ids_crc32")


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "labels")
    fold = langid.fold("doc_id", 3)
    found = toxicity.score(docs, labels.where(fold != 1))
    held_out = F.coalesce(fold == 1, F.lit(False))
    return found.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality": op1_quality,
        "op2_mixing": op2_mixing,
        "op3_decontaminate": op3_decontaminate,
        "op4_warc": op4_warc,
        "op5_line_dedup": op5_line_dedup,
        "op6_langid": op6_langid,
        "op7_html_text": op7_html_text,
        "op8_jaccard": op8_jaccard,
        "op9_token_files": op9_token_files,
        "op10_toxicity": op10_toxicity,
    }


WARC_SQL = f"""with p as (select page_id, cast(strlen(coalesce(html, '')) as bigint) as payload_bytes, sha256(coalesce(html, '')) as payload_digest from pages),
f as (select payload_digest, min(page_id) as first_id from p where payload_bytes >= {warc.LEAST_BYTES} group by 1),
r as (select p.*, case when payload_bytes >= {warc.LEAST_BYTES} and page_id > first_id then first_id end as refers_to from p left join f on p.payload_digest = f.payload_digest)
select page_id, payload_bytes, payload_digest, case when refers_to is null then 'response' else 'revisit' end as record_type, refers_to from r"""


def oracle_sql() -> dict[str, str]:
    return {"op4_warc": WARC_SQL}
