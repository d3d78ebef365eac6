"""Line dedup by a suffix array over line ids, built by distributed prefix doubling.

Lines are trimmed and blank ones left out before the others of a document are numbered, so runs go across blank lines. Each
line is named by a fingerprint. Level 0 ranks the places of lines by it; level k + 1 sorts
the distinct pairs of ranks of a place and of the one 2^k lines on, so a rank at level k is the place's order among all
runs of 2^k lines. Places whose run occurs once drop out, as no longer run of theirs can repeat. Places of equal rank at
level k are a longest-common-prefix interval of at least 2^k lines; two ranks that overlap name the intervals of the
lengths between.

A maximal repeated run of min_lines lines or more is the union of its runs of exactly min_lines; a shorter one is deleted
if it has min_words words. So the doubling may end at min_lines: a place that isn't the first of its interval is a later copy,
and its lines go. suffix_array() doubles to the end and gives the order of all suffixes that begin with a repeated line.

Null text: no lines, text stays null. Empty text: stays. Blank lines stay, also between lines that go. Ties in the order of documents: rows
of one id are taken by a fingerprint of the text, equal rows in any order. A null id comes first. Work is by line, never by group of equal lines; one
document's lines are together in a task, as its text is.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treefacts.llm import common

MIN_LINES = 3
MIN_WORDS = 50
WORD = "[^\\x20\\x09-\\x0D]+"
BLANK = " \t\r\x0b\x0c"


def numbered(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc (a number of the row that follows id and text; unique), id, text."""
    rows = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text"))
    rows = rows.withColumn("print", F.xxhash64("text"))
    dealt = rows.repartitionByRange("id", "print").sortWithinPartitions("id", "print")
    return common.materialise(dealt.drop("print").withColumn("doc", F.monotonically_increasing_id()), "numbered")


def line_places(docs: DataFrame) -> DataFrame:
    """doc, line (from 0, of those that aren't blank), print of each line that isn't blank."""
    whole = F.trim("text", F.lit(BLANK + "\n"))  # so that blank lines are all between others
    split = docs.where(F.col("text").isNotNull()).select("doc", F.posexplode(F.split(whole, f"\n[{BLANK}\n]*")).alias("line", "text"))
    return split.withColumn("text", F.trim(F.translate("text", "\t\r\x0b\x0c", "    "))).where("text <> ''").select("doc", "line", F.xxhash64("text").alias("rank"))


def original(text: Column) -> Column:
    """For each line that isn't blank, its number among all lines."""
    numbers = F.transform(F.split(text, "\n"), lambda x, i: F.when(F.trim(x, F.lit(BLANK)) != "", i))
    return F.filter(numbers, lambda i: i.isNotNull())


def repeated(rows: DataFrame, keys: list[str]) -> DataFrame:
    return rows.groupBy(*keys).agg(F.count("*").alias("n"), F.min(F.struct("doc", "line")).alias("first")).where("n > 1")


def ahead(rows: DataFrame, lines: int) -> DataFrame:
    """rows with the rank of the place so many lines on, as next; without those that have none."""
    there = Window.partitionBy("doc").orderBy("line").rangeBetween(lines, lines)
    return common.materialise(rows.select("doc", "line", "rank", F.max("rank").over(there).alias("next")).where("next is not null"), "pairs")


def levels(places: DataFrame, lines: int | None = None) -> list[DataFrame]:
    """For each level k: doc, line, rank of the places whose run of 2^k lines occurs more than once, while 2^k <= lines
    (to the end if lines is None)."""
    several = common.materialise(repeated(places, ["rank"]).select("rank"), "repeated-lines")
    current = common.materialise(places.join(several, "rank").select("doc", "line", "rank"), "level")
    out = []
    while not current.isEmpty():
        out.append(current)
        step = 1 << (len(out) - 1)
        if lines is not None and 2 * step > lines:
            break
        pairs = ahead(current, step)
        # sorted over ranges, so the numbers given out follow the order of the pairs
        distinct = repeated(pairs, ["rank", "next"]).repartitionByRange("rank", "next").sortWithinPartitions("rank", "next")
        ranks = common.materialise(distinct.select("rank", "next", F.monotonically_increasing_id().alias("new")), "ranks")
        current = common.materialise(pairs.join(ranks, ["rank", "next"]).select("doc", "line", F.col("new").alias("rank")), "level")
    return out


def suffix_array(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, line and ranks (one for each level that the suffix reaches) of each suffix that begins with a repeated line;
    suffixes sort by ranks, compared from the first level on as far as both go."""
    rows = numbered(docs, id_col, text_col)
    found = [x.withColumn("level", F.lit(k)) for k, x in enumerate(levels(line_places(rows)))]
    if not found:
        return rows.select(F.col("id").alias(id_col), F.lit(0).alias("line"), F.array().cast("array<long>").alias("ranks")).limit(0)
    every = found[0]
    for x in found[1:]:
        every = every.union(x)
    ranks = every.groupBy("doc", "line").agg(F.transform(F.sort_array(F.collect_list(F.struct("level", "rank"))), lambda x: x["rank"]).alias("ranks"))
    lines_of = rows.select("doc", "id", original(F.col("text")).alias("lines"))
    return ranks.join(lines_of, "doc").select(F.col("id").alias(id_col), F.get("lines", F.col("line")).alias("line"), "ranks")


def later_copies(found: list[DataFrame], min_lines: int) -> DataFrame | None:
    """doc, line, length: runs of at most min_lines lines that have occurred before."""
    out = None
    for length in range(1, min_lines + 1):
        k = length.bit_length() - 1
        if k >= len(found):
            break
        rows, keys = (found[k], ["rank"]) if length == 1 << k else (ahead(found[k], length - (1 << k)), ["rank", "next"])
        first = common.materialise(repeated(rows, keys).select(*keys, "first"), "first-places")
        later = rows.join(first, keys).where(F.struct("doc", "line") > F.col("first")).select("doc", "line", F.lit(length).alias("length"))
        out = later if out is None else out.union(later)
    return out


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_lines: int = MIN_LINES, min_words: int = MIN_WORDS) -> DataFrame:
    """id, n_lines (with blank ones), n_removed and text (without later copies of repeated runs) of each row of docs."""
    rows = numbered(docs, id_col, text_col)
    runs = later_copies(levels(line_places(rows), min_lines), min_lines)
    if runs is None:
        runs = rows.select("doc", F.lit(0).alias("line"), F.lit(0).alias("length")).limit(0)
    by_doc = runs.groupBy("doc").agg(F.collect_list(F.struct("line", "length")).alias("runs"))
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import re

        word = re.compile(WORD)
        for batch in batches:
            n_lines, n_removed, texts = [], [], []
            for text, own in zip(batch.column(1), batch.column(2).to_pylist(), strict=True):
                text = text.as_py()
                lines = [] if text is None else text.split("\n")
                gone = set()
                places = [i for i, x in enumerate(lines) if x.strip(BLANK)] if own else []
                for r in own or []:
                    there = places[r["line"] : r["line"] + r["length"]]
                    if r["length"] >= min_lines or sum(len(word.findall(lines[i])) for i in there) >= min_words:
                        gone.update(there)
                n_lines.append(len(lines))
                n_removed.append(len(gone))
                texts.append(text if not gone else "\n".join(x for i, x in enumerate(lines) if i not in gone))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_lines, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(texts, pa.string())], names=["id", "n_lines", "n_removed", "text"])

    joined = rows.join(by_doc, "doc", "left").select("id", "text", "runs")
    return joined.mapInArrow(run, f"id {kind}, n_lines long, n_removed long, text string").withColumnsRenamed({"id": id_col, "text": text_col})
