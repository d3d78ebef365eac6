"""Mixing sources to target weights by proportionate fair scheduling.

The documents of a source, in a hashed order, form blocks of block_docs. With target weight w (an exact fraction of the
sum of all), block i of a source (from 1) is released at floor((i - 1) / w) and due at ceil(i / w); in every slot the released
block that is due first goes out (ties: by name). So after every slot each source has had its due number of blocks, to
less than one, however long the mix is: weights are never rounded. When a source has no blocks left, a new phase begins, in
which the rest share the slots by their weights. No document is lost or taken twice; the last block of a source may be short.

The slots of all blocks are worked out by the driver and broadcast, 8 bytes a block. That is bounded: a block has BLOCK_DOCS
documents, or more where there would be over MOST_BLOCKS blocks (then a MOST_BLOCKS-th of all documents).

A null source is a source of its own. Null ids and repeated rows are documents like others, ordered by their other columns;
equal rows in any order. No documents: an empty result. Over max_sources sources are an error.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator, Mapping
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefacts.llm import common

BLOCK_DOCS = 32
MOST_BLOCKS = 1 << 20
MAX_SOURCES = 1_000
EXPONENT = 0.5  #: a source without a given weight gets its number of documents to this power
BUCKET_DOCS = 256
NO_SOURCE = "\x00no source"


def windows(weight: Fraction, i: int) -> tuple[int, int]:
    """Release and deadline of block i (from 1) of a source with this share of the slots."""
    p, q = weight.numerator, weight.denominator
    return (i - 1) * q // p, -(-i * q // p)


@dataclass
class Phase:
    start: int  #: first slot
    weights: dict[str, Fraction]  #: shares of the slots, 1 in all
    first: dict[str, int]  #: blocks that each source has had before


def schedule_slots(blocks: Mapping[str, int], weights: Mapping[str, float]) -> tuple[list[Phase], dict[str, np.ndarray]]:
    """Phases, and the slot of each block of each source, by earliest deadline first."""
    left = {s: n for s, n in sorted(blocks.items()) if n}
    exact = {s: Fraction(weights[s]) for s in left}
    if any(w <= 0 for w in exact.values()):
        raise ValueError("weights are over 0")
    out, had = {s: np.zeros(n, np.int64) for s, n in left.items()}, dict.fromkeys(left, 0)
    found, slot = [], 0
    while left:
        total = sum(exact[s] for s in left)
        phase = Phase(slot, {s: exact[s] / total for s in left}, {s: had[s] for s in left})
        found.append(phase)
        waiting = [(0, s, 1) for s in left]  # by release
        heapq.heapify(waiting)
        ready: list[tuple[int, str, int]] = []
        while True:
            while waiting and waiting[0][0] <= slot - phase.start:
                _, s, i = heapq.heappop(waiting)
                heapq.heappush(ready, (windows(phase.weights[s], i)[1], s, i))
            _, s, i = heapq.heappop(ready)
            out[s][had[s]] = slot
            had[s] += 1
            left[s] -= 1
            slot += 1
            if not left[s]:
                del left[s]
                break
            heapq.heappush(waiting, (windows(phase.weights[s], i + 1)[0], s, i + 1))
    return found, out


class Schedule:
    def __init__(self, docs: Mapping[str, int], weights: Mapping[str, float], block_docs: int):
        self.block_docs = block_docs
        self.phases, self.slots = schedule_slots({s: -(-n // block_docs) for s, n in docs.items()}, weights)
        short = sorted((int(own[-1]), len(own) * block_docs - docs[s]) for s, own in self.slots.items())
        self.short_slots = np.array([x for x, _ in short], np.int64)
        self.missing = np.concatenate(([0], np.cumsum([n for _, n in short]))).astype(np.int64)

    def place(self, source: str, block: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Slot, phase, release and deadline of blocks (from 0) of a source."""
        own = [k for k, p in enumerate(self.phases) if source in p.first]
        at = np.searchsorted([self.phases[k].first[source] for k in own], block, side="right") - 1
        each, back = np.unique(block, return_inverse=True)
        spans = []
        for b, j in zip(each.tolist(), at[np.unique(block, return_index=True)[1]].tolist(), strict=True):
            p = self.phases[own[j]]
            release, due = windows(p.weights[source], b - p.first[source] + 1)
            spans.append((p.start + release, p.start + due))
        spans_ = np.array(spans, np.int64).reshape(-1, 2)[back]
        return self.slots[source][block], np.array(own, np.int64)[at], spans_[:, 0], spans_[:, 1]

    def position(self, slot: np.ndarray, inside: np.ndarray) -> np.ndarray:
        """Place of a document in the whole mix."""
        return slot * self.block_docs + inside - self.missing[np.searchsorted(self.short_slots, slot)]


def mix(docs: DataFrame, weights: Mapping[str, float] | None = None, id_col: str = "doc_id", source_col: str = "source", block_docs: int | None = None, max_sources: int = MAX_SOURCES) -> DataFrame:
    """docs with mix_position (0 on, without gaps), mix_block (of its source, from 0), mix_slot, mix_release, mix_deadline
    and mix_phase; columns of these names in docs are replaced."""
    added = ("mix_position", "mix_block", "mix_slot", "mix_release", "mix_deadline", "mix_phase")
    docs = docs.drop(*added)
    source = F.coalesce(F.col(source_col).cast("string"), F.lit(NO_SOURCE))
    common.ship(docs.sparkSession)
    found = docs.groupBy(source.alias("s")).agg(F.count("*").alias("n"), F.count(F.col(id_col)).alias("with_id")).limit(max_sources + 1).collect()
    counts, null_ids = {r.s: r.n for r in found}, any(r.with_id < r.n for r in found)
    if len(counts) > max_sources:
        raise ValueError(f"over {max_sources} sources")
    target = {s: float((weights or {}).get(s, n**EXPONENT)) for s, n in counts.items()}
    block_docs = block_docs or max(BLOCK_DOCS, -(-sum(counts.values()) // MOST_BLOCKS))
    sent = docs.sparkSession.sparkContext.broadcast(Schedule(counts, target, block_docs))

    # ranks inside a source: hashed order in buckets, whose sizes add up to where each begins
    total = sum(counts.values())
    bits = max(4, min(20, (max(1, total // BUCKET_DOCS)).bit_length()))
    rest = F.xxhash64(*[F.col(f"`{f.name}`") for f in docs.schema.fields if isinstance(f.dataType, T.AtomicType)])
    hashed = F.xxhash64(F.col(id_col), F.lit("mix"))
    if null_ids:  # rows without an id are spread by what else they hold
        hashed = F.when(F.col(id_col).isNull(), rest).otherwise(hashed)
    keyed = docs.withColumns({"_mix_source": source, "_mix_key": hashed, "_mix_bucket": F.shiftrightunsigned(hashed, 64 - bits)})
    sizes = docs.groupBy(source.alias("_mix_source"), F.shiftrightunsigned(hashed, 64 - bits).alias("_mix_bucket")).count()
    before = Window.partitionBy("_mix_source").orderBy("_mix_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("_mix_source", "_mix_bucket", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_mix_start"))
    inside = Window.partitionBy("_mix_source", "_mix_bucket").orderBy("_mix_key", F.col(id_col), rest)
    ranked = keyed.withColumn("_mix_row", F.row_number().over(inside) - 1).join(starts, ["_mix_source", "_mix_bucket"])
    ranked = ranked.select(*[F.col(f"`{c}`") for c in docs.columns], F.col("_mix_source"), (F.col("_mix_start") + F.col("_mix_row")).alias("_mix_rank"))
    schema = T.StructType([*docs.schema.fields, *[T.StructField(c, T.LongType()) for c in added]])
    n = len(docs.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schedule = sent.value
        for batch in batches:
            rank = batch.column(n + 1).to_numpy(zero_copy_only=False).astype(np.int64)
            block, out = rank // block_docs, np.zeros((4, len(rank)), np.int64)
            names = batch.column(n).dictionary_encode()
            code = names.indices.to_numpy(zero_copy_only=False)
            for k, name in enumerate(names.dictionary.to_pylist()):
                mask = code == k
                out[:, mask] = schedule.place(name, block[mask])
            slot, phase, release, due = out
            position = schedule.position(slot, rank % block_docs)
            yield pa.RecordBatch.from_arrays([*batch.columns[:n], *map(pa.array, (position, block, slot, release, due, phase))], names=schema.names)

    return ranked.mapInArrow(run, schema)


def in_order(docs: DataFrame, weights: Mapping[str, float] | None = None, **options) -> DataFrame:
    """The rows and columns of docs in mixed order: written, the files by name and the rows in each follow it."""
    mixed = mix(docs, weights, **options)
    n = docs.sparkSession.conf.get("spark.sql.shuffle.partitions")
    return mixed.repartitionByRange(int(n), "mix_position").sortWithinPartitions("mix_position").select(*[F.col(f"`{c}`") for c in docs.columns])
