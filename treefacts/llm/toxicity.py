"""Toxicity by nearest labelled examples.

Texts are TF-IDF vectors of length 1. Terms are all words of the labelled sample, and all beginnings of words together with
how often they occur at least (so that inflected forms add up). A term's weight is its idf times its relevance: how far the
share of label 1 among its rows is from that among all, times how sure that is: 1 less the evidence that the
largest of so many terms reaches by chance over its own (rows times the divergence of the two shares, in nats). A term below that
weighs nothing; no number of terms is fixed.

An inverted index over the examples keeps, for each term and each block of examples, the largest
weight; blocks are visited from the highest bound down and the search ends when no block can hold a nearer example, so
the k nearest by cosine are exact. Their votes, weighted by similarity, are smoothed towards the rate among examples
without a term of weight, and calibrated: isotonic regression of the labels of up to CALIBRATION examples on the votes
of their nearest others.

The examples are a bounded sample of about train_rows labelled rows by hash of the id. A text without terms of weight
(empty and null ones too) gets the rate among examples without any. Ties go to the example with the smaller id. Repeated
rows are scored each on its own; equal texts of one label make one example; rows without a label or an id make none.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefacts.llm import common

TRAIN_ROWS = 8_000
CALIBRATION = 2_000  #: examples that scores are calibrated on at most, the first by hash
NEAREST = 15
BLOCK = 64
SMOOTHING = 0.25
SURE = 3.0  #: nats of evidence beyond the logarithm of the number of terms
BEGINNINGS, LEVELS = (3, 4, 5), (1, 2, 3, 4, 6, 8)  #: letters of a beginning, and how often a text has it at least
CACHE_WORDS = 200_000
WORDS = re.compile(r"[^\W\d_]{2,}")


def words(text: str | None) -> list[str]:
    return WORDS.findall(text.lower()) if text else []


def beginnings(word: str) -> list[str]:
    return [word[:n] + "*" for n in BEGINNINGS if len(word) > n]


def terms(text: str | None) -> Counter:
    """How often a text has each term; a beginning at a level counts once."""
    out = Counter(words(text))
    often: Counter = Counter()
    for w, n in out.items():
        for b in beginnings(w):
            often[b] += n
    out.update(f"{b}{level}" for b, n in often.items() for level in LEVELS if n >= level)
    return out


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Points of the non-decreasing step function nearest to y over x, by pooling neighbours."""
    order = np.argsort(x, kind="stable")
    pools: list[list[float]] = []  # of sum of x, sum of y, number
    for a, b in zip(x[order].tolist(), y[order].tolist(), strict=True):
        pools.append([a, b, 1])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [u + v for u, v in zip(pools[-1], last, strict=True)]
    return np.array([p[0] / p[2] for p in pools]), np.array([(p[1] + 0.05) / (p[2] + 0.1) for p in pools])


class Index:
    """Examples by (id, label, counts of terms); vocabulary: weights of terms."""

    def __init__(self, vocabulary: dict[str, float], examples: list[tuple[int, int, dict[str, int]]]):
        self.place = {t: i for i, t in enumerate(vocabulary)}
        self.weight = np.array(list(vocabulary.values()) or [0.0])
        examples = [(i, y, {t: n for t, n in c.items() if t in self.place}) for i, y, c in examples]
        full = sorted((e for e in examples if e[2]), key=lambda e: e[0])
        bare = [e[1] for e in examples if not e[2]]
        labels = [e[1] for e in examples]
        self.rate = (sum(labels) + 0.5) / (len(labels) + 1)
        self.bare_rate = (sum(bare) + 0.5 * self.rate) / (len(bare) + 0.5) if labels else 0.0
        self.ids = np.array([e[0] for e in full], np.int64)
        self.labels = np.array([e[1] for e in full], np.float64)
        n_blocks = -(-len(full) // BLOCK)
        postings: list[dict[int, list[tuple[int, float]]]] = [{} for _ in self.place]  # by term, by block
        self.highest = np.zeros((len(self.place), max(n_blocks, 1)))
        self.vectors = [self.vector({self.place[t]: n for t, n in e[2].items()}) for e in full]
        for i, vector in enumerate(self.vectors):
            for t, w in vector:
                postings[t].setdefault(i // BLOCK, []).append((i % BLOCK, w))
                self.highest[t, i // BLOCK] = max(self.highest[t, i // BLOCK], w)
        self.packed = [{b: (np.array([p for p, _ in x]), np.array([w for _, w in x])) for b, x in own.items()} for own in postings]
        self.steps = np.zeros(0), np.zeros(0)
        self.memory: dict[tuple, tuple[float, list[tuple[int, float, int]]]] = {}
        self.known: dict[str, tuple[int | None, tuple[str, ...]]] = {}
        self.levels: dict[str, list[tuple[int, int]]] = {}  # of a beginning: levels with weight, and their places
        for t, i in self.place.items():
            head, star, level = t.partition("*")
            if star:
                self.levels.setdefault(head + star, []).append((int(level), i))

    def vector(self, counts: dict[int, int]) -> list[tuple[int, float]]:
        raw = sorted((t, (1 + np.log(n)) * self.weight[t]) for t, n in counts.items())
        size = np.sqrt(sum(w * w for _, w in raw))
        return [(t, float(w / size)) for t, w in raw if size > 0]

    def nearest(self, vector: list[tuple[int, float]], k: int = NEAREST) -> list[tuple[float, int]]:
        """(cosine, place) of the k nearest examples with a cosine over 0, nearest first, then by id."""
        if not vector:
            return []
        places, weights = np.array([t for t, _ in vector]), np.array([w for _, w in vector])
        bounds = weights @ self.highest[places]
        found: list[tuple[float, int]] = []
        for b in np.argsort(-bounds, kind="stable").tolist():
            if bounds[b] <= 0 or (len(found) >= k and bounds[b] + 1e-12 < -found[k - 1][0]):
                break
            scores = np.zeros(BLOCK)
            for t, w in vector:
                if (own := self.packed[t].get(b)) is not None:
                    scores[own[0]] += w * own[1]
            found += [(-round(float(scores[i]), 12), b * BLOCK + int(i)) for i in np.flatnonzero(scores)]
            found = sorted(found)[:k]
        return [(-s, i) for s, i in found]

    def votes(self, near: list[tuple[float, int]]) -> float:
        return (sum(s * self.labels[i] for s, i in near) + SMOOTHING * self.bare_rate) / (sum(s for s, _ in near) + SMOOTHING)

    def calibrate(self) -> None:
        """Fits the steps from votes to shares of label 1, each example judged by its nearest others."""
        own = sorted(range(len(self.ids)), key=lambda i: (int(self.ids[i]) * 0x9E3779B97F4A7C15) % (1 << 64))[:CALIBRATION]
        votes = np.array([self.votes([x for x in self.nearest(self.vectors[i], NEAREST + 1) if x[1] != i][:NEAREST]) for i in own])
        if len(own):
            self.steps = isotonic(votes, self.labels[own])

    def calibrated(self, votes: float) -> float:
        return float(np.interp(votes, *self.steps)) if len(self.steps[0]) else votes

    def counts(self, text: str | None) -> Counter:
        """terms() of the vocabulary, by place."""
        out, often = Counter(), Counter()
        for w, n in Counter(words(text)).items():
            got = self.known.get(w)
            if got is None:
                if len(self.known) > CACHE_WORDS:
                    self.known.clear()
                got = self.known[w] = self.place.get(w), tuple(b for b in beginnings(w) if b in self.levels)
            if got[0] is not None:
                out[got[0]] += n
            for b in got[1]:
                often[b] += n
        for b, n in often.items():
            for level, place in self.levels[b]:
                if n >= level:
                    out[place] += 1
        return out

    def score(self, text: str | None) -> tuple[float, list[tuple[int, float, int]]]:
        counts = self.counts(text)
        key = tuple(sorted(counts.items()))
        if not key:
            return self.bare_rate, []
        if key not in self.memory:
            if len(self.memory) > 20_000:
                self.memory.clear()
            near = self.nearest(self.vector(counts))
            self.memory[key] = self.calibrated(self.votes(near)), [(int(self.ids[i]), s, int(self.labels[i])) for s, i in near[:3]]
        return self.memory[key]


def fit(labelled: DataFrame, id_col: str, text_col: str, label_col: str) -> tuple[dict[str, float], list[tuple[int, int, dict[str, int]]]]:
    """Weights of terms, and examples with the counts of these; labelled is a sample of bounded size."""
    rows = labelled.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), F.col(label_col).cast("int").alias("label"))
    rows = common.materialise(rows.groupBy("text", "label").agg(F.min("id").alias("id")), "examples")
    totals = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum("label"), F.lit(0)).alias("positive")).first()
    n, rate = int(totals.n), (totals.positive + 0.5) / (totals.n + 1)
    if not n:
        return {}, []

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, positive = Counter(), Counter()
        for batch in batches:
            for text, label in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                own = terms(text.as_py()).keys()
                df.update(own)
                if label:
                    positive.update(own)
        yield pa.RecordBatch.from_arrays([pa.array(list(df), pa.string()), pa.array(list(df.values()), pa.int64()), pa.array([positive[t] for t in df], pa.int64())], names=["term", "df", "a"])

    found = rows.select("text", "label").mapInArrow(seen, "term string, df long, a long").groupBy("term").agg(F.sum("df").alias("df"), F.sum("a").alias("a"))
    found = common.materialise(found, "terms")
    chance = float(np.log(max(1, found.count()))) + SURE
    share = F.col("a") / F.col("df")
    part = lambda x, y: F.when(x > 0, x * F.log(x / y)).otherwise(0.0)
    evidence = F.col("df") * (part(share, F.lit(rate)) + part(1 - share, F.lit(1 - rate)))
    best = found.select("term", "df", share.alias("share"), F.round(evidence, 9).alias("evidence")).where(F.col("evidence") > chance).collect()
    weight = {r.term: float((np.log((1 + n) / (1 + r.df)) + 1) * (1 - chance / r.evidence) * abs(r.share - rate) / max(rate, 1 - rate)) for r in sorted(best, key=lambda r: r.term)}
    sent = rows.sparkSession.sparkContext.broadcast(set(weight))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = [{t: n for t, n in terms(x.as_py()).items() if t in sent.value} for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([list(c) for c in counts], pa.list_(pa.string())), pa.array([list(c.values()) for c in counts], pa.list_(pa.int32()))], names=["id", "label", "terms", "counts"])

    got = rows.select("id", "text", "label").mapInArrow(counted, "id long, label int, terms array<string>, counts array<int>").collect()
    common.discard(rows, found)
    return weight, [(r.id, r.label, dict(zip(r.terms, r.counts, strict=True))) for r in got]


def bounded(labels: DataFrame, id_col: str, train_rows: int) -> DataFrame:
    """About train_rows of the rows, by hash of the id; all, if there are no more."""
    n = labels.count()
    return labels.where(F.pmod(F.xxhash64(F.col(id_col)), F.lit(1 << 30)) < int((1 << 30) * min(1.0, train_rows / max(n, 1))))


def score(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train_rows: int = TRAIN_ROWS) -> DataFrame:
    """id, score (0 to 1), evidence (nearest examples) of each row of docs; labels: id and label of the rows to learn from."""
    common.ship(docs.sparkSession)
    chosen = bounded(labels.where(F.col(label_col).isNotNull()).select(id_col, label_col), id_col, train_rows)
    labelled = docs.select(id_col, text_col).join(F.broadcast(chosen), id_col)  # about train_rows rows, whatever the input
    index = Index(*fit(labelled, id_col, text_col, label_col))
    index.calibrate()
    sent = docs.sparkSession.sparkContext.broadcast(index)
    evidence = T.ArrayType(T.StructType([T.StructField("id", T.LongType()), T.StructField("similarity", T.DoubleType()), T.StructField("label", T.IntegerType())]))
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("score", T.DoubleType()), T.StructField("evidence", evidence)])
    kind = pa.list_(pa.struct([("id", pa.int64()), ("similarity", pa.float64()), ("label", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = sent.value
        for batch in batches:
            got = [index.score(x.as_py()) for x in batch.column(1)]
            found = [[{"id": i, "similarity": s, "label": y} for i, s, y in e] for _, e in got]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s for s, _ in got], pa.float64()), pa.array(found, kind)], names=[id_col, "score", "evidence"])

    return docs.select(docs[id_col], docs[text_col]).mapInArrow(run, schema)
