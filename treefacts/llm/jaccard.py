"""n-gram Jaccard self-join by token-combination prefixes, as classes of linked documents.

A document's tokens are its distinct k-word shingles, as 64-bit fingerprints. All documents share one order of tokens:
those in more than a given share of documents last, otherwise by fingerprint. A prefix has e + t tokens (e: how many of its
n tokens a partner may lack; t: 2 and n / STRETCH more). If two documents link, they share at least t tokens of the prefix
that ends first in the order, so documents with fewer keys that others hold drop out. Tokens are of two classes by how
many prefixes hold them. Rare ones index alone: pairs count their shared keys against a bound. Frequent ones are combined
with more tokens: holders of a frequent token are held against one pivot, and only pairs that also share rare tokens of
what they differ in from the pivot go on (see Join.by_differences).

Equal sets are one class from the start. Large groups of near copies never become pairs: first each document is held
against one pivot of its keys; the links found make components, and only keys that still hold several
components go on, first by one representative each, at last by all their documents of different components. So every
link either is verified or joins documents that verified links join already, and the classes are those of all links.

Sets are held as fingerprints throughout (two of the whole set and its size for equal sets), so "all links" is up to a
collision: among 10^12 distinct shingles the chance that a given pair of a document's 10^3 shingles collides is below 10^-13.

Prefix tokens travel as binary chunks, one for each bucket of tokens and batch, not as rows; sets are compared in numpy.
A bucket holds about BUCKET_TOKENS entries; tokens of the frequent class spread over the buckets by batch.

Null, empty and wordless texts: an empty set, linked with nothing. Null ids: linked with nothing, component null. Equal ids: one
document for each text, all in one component if they have words. Ids that aren't whole numbers go the same way. The texts are
read whole; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treefacts.llm import common, graph, textcore

RARE = 12  #: prefixes that a rare token may be in
HOT_SHARE = 2e-4  #: tokens of more documents than this share (and RARE) come last in the order
STRETCH = 20  #: one more token of a prefix for so many of the set
BROADCAST_ROWS = 1_000_000  #: ids that are broadcast at most; of more a table of bits is, or they are joined
FILTER_WORDS = 1 << 20  #: rows of that table, of 64 bits each
ROUND_BYTES, ROUND_SHARE = 1 << 29, 4  #: sets of pairs that are held at once: so many bytes, or this part of all sets
SPREAD_ROUNDS = 1
BUCKET_TOKENS, MOST_BUCKETS = 1 << 16, 1 << 17
LEAST_LOCAL = 4  #: documents of a partition that hold a token before it counts as a possibly frequent one
KEPT_TOKENS = 1 << 20  #: of a partition that are counted before those met once are dropped
COMPARE_TOKENS = 1 << 19  #: of pairs of sets that are compared at once
ENTRY = np.dtype([("token", np.int64), ("id", np.int64), ("n", np.int32)])
WHOLE = ("tinyint", "smallint", "int", "bigint")


@dataclass(frozen=True)
class Rule:
    """Two sets link when 100 * shared >= percent * union."""

    words: int = 5
    percent: int = 80

    def may_lack(self, n: np.ndarray) -> np.ndarray:
        """How many of n tokens a partner may lack."""
        return (100 - self.percent) * n // 100

    def prefix(self, n: np.ndarray) -> np.ndarray:
        """How long the prefix of a set of n tokens is; a set of one token needs none."""
        return np.where(n > 1, np.minimum(n, self.may_lack(n) + 2 + n // STRETCH), 0)

    def prefix_of(self, n: Column) -> Column:
        return F.least(n, F.floor(F.lit(100 - self.percent) * n / 100) + 2 + F.floor(n / STRETCH))

    def least_keys(self, n: Column) -> Column:
        """How many prefix tokens a set of n shares at least with any partner: t of the smallest partner there may be."""
        return F.least(n, 2 + F.floor(F.lit(self.percent) * n / (100 * STRETCH)))

    def shared_at_least(self, a: Column, b: Column) -> Column:
        return F.ceil(self.percent * (a + b) / F.lit(100 + self.percent) - F.lit(1e-9))

    def sizes_fit(self, a: Column, b: Column) -> Column:
        return F.lit(100) * F.least(a, b) >= F.lit(self.percent) * F.greatest(a, b)


def heads(sorted_texts: np.ndarray, sizes: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Mask of the first length[i] of the sizes[i] places of each text."""
    starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    return np.arange(len(sorted_texts)) - starts[sorted_texts] < length[sorted_texts]


def chunks(values: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """Runs of the given sizes of values as binary."""
    offsets = np.zeros(len(sizes) + 1, np.int32)
    np.cumsum(sizes * values.dtype.itemsize, out=offsets[1:])
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(values))])


def values_of(column: pa.Array, kind: type | np.dtype = np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """All values of a binary column, and how many each row has."""
    _, offsets, data = column.buffers()
    ends = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw.view(kind), np.diff(ends) // np.dtype(kind).itemsize


def sketch(docs: DataFrame, id_col: str, text_col: str, rule: Rule) -> DataFrame:
    """id, n (set size), print1, print2 (of the whole set) of each row; and for each partition one row of n = -1 with the
    tokens (often) that many of its documents have, and in how many (often_n)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["id", "n", "print1", "print2", "often", "often_n"]
        kind, n_docs, seen, n_seen = None, 0, [], 0
        tokens_seen, counts_seen = np.zeros(0, np.uint64), np.zeros(0, np.int64)

        def counted(least: int) -> tuple[np.ndarray, np.ndarray]:
            every = np.concatenate([np.zeros(0, np.uint64), *seen])
            seen.clear()
            every.sort()
            first = np.flatnonzero(np.concatenate((every[:1] == every[:1], every[1:] != every[:-1])))
            sums = np.diff(np.append(first, len(every)))
            every = every[first]
            old = np.searchsorted(every, tokens_seen)
            there = is_in(every, tokens_seen)
            sums[old[there]] += counts_seen[there]
            good = sums >= least
            every, sums = np.concatenate((every[good], tokens_seen[~there])), np.concatenate((sums[good], counts_seen[~there]))
            order = np.argsort(every)
            return every[order][sums[order] >= least], sums[order][sums[order] >= least]

        for batch in batches:
            kind = batch.column(0).type
            for block in textcore.blocks(batch.column(1)):
                text, tokens = textcore.shingles(block, rule.words)
                n = np.bincount(text, minlength=block.n).astype(np.int64)
                edges = np.concatenate(([0], np.cumsum(n)))
                sums = []
                for salt in (np.uint64(0), np.uint64(0x632BE59BD9B4E019)):
                    total = np.zeros(len(tokens) + 1, np.uint64)
                    np.cumsum(textcore.mix(tokens ^ salt), out=total[1:])
                    sums.append((total[edges[1:]] - total[edges[:-1]]).view(np.int64))
                seen.append(tokens)
                n_docs, n_seen = n_docs + block.n, n_seen + len(seen[-1])
                if n_seen > KEPT_TOKENS:
                    (tokens_seen, counts_seen), n_seen = counted(2), 0
                none = pa.nulls(block.n, pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(block.first, block.n), pa.array(n), pa.array(sums[0]), pa.array(sums[1]), none, none], names=names)
        often, often_n = counted(max(LEAST_LOCAL, int(HOT_SHARE * n_docs)))
        if kind is not None and len(often):
            lists = [pa.ListArray.from_arrays(pa.array([0, len(often)], pa.int32()), pa.array(x)) for x in (often.view(np.int64), often_n)]
            yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), *(pa.array([x], pa.int64()) for x in (-1, 0, 0)), *lists], names=names)

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).mapInArrow(run, f"id {kind}, n long, print1 long, print2 long, often array<long>, often_n array<long>")


def is_in(sorted_values: np.ndarray, x: np.ndarray) -> np.ndarray:
    if not len(sorted_values):
        return np.zeros(len(x), bool)
    return sorted_values[np.minimum(np.searchsorted(sorted_values, x), len(sorted_values) - 1)] == x


def token_lists(docs: DataFrame, rule: Rule, hot: np.ndarray | None) -> DataFrame:
    """id and tokens (binary) of docs (id, text): the prefix in the common order, or with hot None the whole set."""
    sent = None if hot is None else docs.sparkSession.sparkContext.broadcast(hot)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in textcore.blocks(batch.column(1)):
                text, tokens = textcore.shingles(block, rule.words)
                n = np.bincount(text, minlength=block.n).astype(np.int64)
                if sent is not None:
                    order = np.argsort(text * 2 + is_in(sent.value, tokens), kind="stable")
                    text, tokens = text[order], tokens[order]
                    mask = heads(text, n, rule.prefix(n))
                    text, tokens = text[mask], tokens[mask]
                found = chunks(tokens, np.bincount(text, minlength=block.n))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(block.first, block.n), found], names=["id", "tokens"])

    kind = docs.schema["id"].dataType.simpleString()
    return docs.mapInArrow(run, f"id {kind}, tokens binary")


def shared_entries(lists: DataFrame, hot: np.ndarray, n_tokens: int) -> DataFrame:
    """token, id, n, holders of the tokens that several rows of lists (id, n, tokens) hold; a frequent token has RARE + 1
    holders at least, whether counted or not."""
    bits = max(1, min(MOST_BUCKETS, n_tokens // BUCKET_TOKENS)).bit_length()
    sent = lists.sparkSession.sparkContext.broadcast(hot)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, batch in enumerate(batches):
            tokens, sizes = values_of(batch.column(2))
            owner = np.repeat(np.arange(len(sizes)), sizes)
            rows = np.empty(len(tokens), ENTRY)
            rows["token"], rows["id"], rows["n"] = tokens.view(np.int64), batch.column(0).to_numpy()[owner], batch.column(1).to_numpy()[owner]
            often = is_in(sent.value, tokens)
            bucket = np.where(often, (owner + number) % (1 << bits), (tokens >> np.uint64(64 - bits)).astype(np.int64)) * 2 + often
            order = np.argsort(bucket, kind="stable")
            counts = np.bincount(bucket, minlength=2 << bits)
            full = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array(full), chunks(rows[order], counts[full])], names=["bucket", "rows"])

    def table(rows: np.ndarray, holders: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(rows["token"])), pa.array(np.ascontiguousarray(rows["id"])), pa.array(rows["n"].astype(np.int64)), pa.array(holders)], names=["token", "id", "n", "holders"])

    def several(parts: list[np.ndarray]) -> pa.RecordBatch:
        rows = np.concatenate(parts)
        rows = rows[np.argsort(rows["token"])]
        token = rows["token"]
        edges = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1], [True])))
        holders = np.repeat(np.diff(edges), np.diff(edges))
        return table(rows[holders > 1], holders[holders > 1].astype(np.int64))

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts = None, []
        for batch in batches:
            for bucket, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                rows = np.frombuffer(raw.as_buffer(), ENTRY)
                if bucket & 1:
                    yield table(rows, np.full(len(rows), RARE + 1, np.int64))
                    continue
                if bucket != at and parts:
                    yield several(parts)
                    parts = []
                at = bucket
                parts.append(rows.copy())
        if parts:
            yield several(parts)

    dealt = lists.select("id", "n", "tokens").mapInArrow(deal, "bucket long, rows binary").repartition("bucket").sortWithinPartitions("bucket")
    return dealt.mapInArrow(gather, "token long, id long, n long, holders long")


def shared_counts(a: np.ndarray, na: np.ndarray, b: np.ndarray, nb: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each pair of sets how many values they share; and masks of the values of a and of b that aren't shared."""
    row = np.concatenate((np.repeat(np.arange(len(na)), na), np.repeat(np.arange(len(nb)), nb)))
    every = np.concatenate((a, b))
    order = np.lexsort((every, row))
    same = (row[order][1:] == row[order][:-1]) & (every[order][1:] == every[order][:-1])
    hit = order[1:][same]
    alone = np.ones(len(every), bool)
    alone[hit] = alone[order[:-1][same]] = False
    return np.bincount(row[hit], minlength=len(na)), alone[: len(a)], alone[len(a) :]


def slices(na: np.ndarray, nb: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about COMPARE_TOKENS values, a row at least."""
    ends, i = np.cumsum(na + nb), 0
    while i < len(na):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + COMPARE_TOKENS, side="right")))
        yield i, j
        i = j


def of_ids(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of docs (id, text) whose id is in ids, where these are many with a few others; texts are never shuffled."""
    if ids.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        return docs.join(F.broadcast(ids), "id", "left_semi")
    place = F.pmod(F.xxhash64("id"), F.lit(64 * FILTER_WORDS))
    placed = lambda df: df.withColumns({"_word": F.shiftright(place, 6), "_bit": F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(63).cast("int"))})
    words = placed(ids).groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    return placed(docs).join(F.broadcast(words), "_word").where(F.col("_bits").bitwiseAND(F.col("_bit")) != 0).select(*docs.columns)


class Join:
    """Over a table whose ids are whole numbers, each id once or null."""

    def __init__(self, docs: DataFrame, id_col: str, text_col: str, rule: Rule):
        common.ship(docs.sparkSession)
        self.rule, self.spark = rule, docs.sparkSession
        docs = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].alias("text"))
        self.texts = docs.where("id is not null")
        self.sketch = common.materialise(sketch(docs, "id", "text", rule), "sketch")
        self.base = self.sketch.where("n >= 0").select("id", "n", "print1", "print2")
        # of the documents of one set the smallest id stands for all
        self.sets = common.materialise(self.base.where("n > 0 and id is not null").groupBy("print1", "print2", "n").agg(F.min("id").alias("rep")), "sets")
        self.component: DataFrame | None = None

    def hot_tokens(self) -> np.ndarray:
        """Tokens of over HOT_SHARE of the documents, as far as partitions have met them often: at most as many as the mean
        size of a set over HOT_SHARE (so 12 MB for sets of 300), whatever the number of documents. They only change the
        order, so it is no matter if one is missed."""
        least = max(RARE, int(HOT_SHARE * self.base.count()))
        found = self.sketch.where("n < 0").select(F.explode(F.arrays_zip("often", "often_n")).alias("x")).groupBy("x.often").agg(F.sum("x.often_n").alias("n")).where(F.col("n") > least)
        tokens = found.select("often").toArrow().column(0).to_numpy()
        return np.sort(tokens.astype(np.int64).view(np.uint64))

    def prefixes(self) -> DataFrame:
        """token, id, n, holders: of tokens that several representatives have in their prefixes."""
        hot = self.hot = self.hot_tokens()
        reps = self.sets.where("n > 1").select(F.col("rep").alias("id"), "n")
        n_tokens = reps.agg(F.sum(self.rule.prefix_of(F.col("n")))).first()[0] or 0
        return common.materialise(shared_entries(token_lists(self.texts, self.rule, hot).join(reps, "id"), hot, n_tokens), "shared-prefixes")

    def both_sets(self, pairs: DataFrame, a: str, b: str) -> tuple[DataFrame, DataFrame]:
        """pairs with the sets (sa, sb) of two ids, and the written sets."""
        ids = pairs.select(F.col(a).alias("id")).union(pairs.select(F.col(b).alias("id"))).distinct()
        sets = common.materialise(token_lists(of_ids(self.texts, ids), self.rule, None), "pair-sets")
        left, right = sets.select(F.col("id").alias(a), F.col("tokens").alias("sa")), sets.select(F.col("id").alias(b), F.col("tokens").alias("sb"))
        return pairs.join(left, a).join(right, b).select(*pairs.columns, "sa", "sb"), sets

    def rounds(self, pairs: DataFrame, a: str = "a", b: str = "b") -> list[DataFrame]:
        """pairs of ids in parts whose sets take ROUND_BYTES or 1 / ROUND_SHARE of all sets; all pairs of one document, of the end
        that has more documents, are in one part."""
        sizes = self.sets.select("rep", "n")
        of_end = lambda end: sizes.select(F.col("rep").alias(end), F.col("n").alias(f"_n{end}"))
        found = pairs.join(of_end(a), a).join(of_end(b), b).agg(F.sum(F.col(f"_n{a}") + F.col(f"_n{b}")), F.approx_count_distinct(a), F.approx_count_distinct(b)).first()
        held = max(ROUND_BYTES, 8 * (self.sets.agg(F.sum("n")).first()[0] or 0) // ROUND_SHARE)
        n = -(-8 * (found[0] or 0) // held)
        part = F.pmod(F.xxhash64(a if found[1] > found[2] else b), F.lit(n))
        return [pairs.where(part == k) for k in range(n)] if n > 1 else [pairs]

    def verify(self, pairs: DataFrame) -> DataFrame:
        """Links among pairs (a, b): those whose whole sets are close enough."""
        percent = self.rule.percent

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                (sa, na), (sb, nb) = values_of(batch.column(2)), values_of(batch.column(3))
                ea, eb = np.concatenate(([0], np.cumsum(na))), np.concatenate(([0], np.cumsum(nb)))
                good = [np.zeros(0, bool)]
                for i, j in slices(na, nb):
                    shared, _, _ = shared_counts(sa[ea[i] : ea[j]], na[i:j], sb[eb[i] : eb[j]], nb[i:j])
                    both = na[i:j] + nb[i:j]
                    good.append((both > 0) & (100 * shared >= percent * (both - shared)))
                yield batch.select([0, 1]).filter(pa.array(np.concatenate(good)))

        pairs = common.materialise(pairs.select("a", "b").distinct(), "pairs")
        common.free(self.spark)
        parts = []
        for some in self.rounds(pairs):
            joined, sets = self.both_sets(some, "a", "b")
            parts.append(common.materialise(joined.mapInArrow(run, "a long, b long"), "new-links"))
            common.discard(sets)
            common.free(self.spark)
        common.discard(pairs)
        if len(parts) == 1:
            return parts[0]
        links = common.materialise(reduce(DataFrame.union, parts), "new-links")
        common.discard(*parts)
        return links

    def add(self, pairs: DataFrame) -> bool:
        """Verifies pairs and joins components; whether there were links."""
        new = self.verify(pairs)
        if new.isEmpty():
            return False
        # the components so far stand for their links
        known = new if self.component is None else new.union(self.component.select(F.col("id").alias("a"), F.col("component").alias("b")))
        self.component, old = graph.components(known), self.component
        common.discard(new, old)
        return True

    def mixed(self, rows: DataFrame) -> DataFrame:
        """Rows of keys that hold several components still, of documents with enough of them."""
        own = rows.drop("component")
        if self.component is None:
            own = own.withColumn("component", F.col("id"))
        else:
            own = own.join(self.component, "id", "left").withColumn("component", F.coalesce("component", "id"))
        several = own.groupBy("token").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high").select("token")
        keyed = own.join(several, "token", "left_semi").withColumn("keys", F.count("*").over(Window.partitionBy("id")))
        out = common.materialise(keyed.where(F.col("keys") >= self.rule.least_keys(F.col("n"))).drop("keys"), "mixed-prefixes")
        common.discard(rows)
        return out

    def least_shared(self, na: Column, nb: Column) -> Column:
        """How many tokens two prefixes share at least if the sets link: of the prefix that ends first in the order, all but what
        lies behind it are in the other."""
        return self.rule.shared_at_least(na, nb) + F.least(self.rule.prefix_of(na) - na, self.rule.prefix_of(nb) - nb)

    def pivots(self, rows: DataFrame, highest: bool) -> DataFrame:
        """For each document the pivot that it shares most keys with; a key's pivot is its lowest or highest document. Few
        shared keys are left for the last round."""
        pick = F.max if highest else F.min
        pivot = rows.groupBy("token").agg(pick(F.struct("id", "n", "component")).alias("pivot"))
        near = rows.join(pivot, "token").where("component <> pivot.component").where(self.rule.sizes_fit(F.col("n"), F.col("pivot.n")))
        counts = near.groupBy("id", F.col("pivot.id").alias("to")).agg(F.count("*").alias("shared"), F.first("n").alias("n"), F.first("pivot.n").alias("m"))
        best = counts.where(F.col("shared") * 3 >= self.least_shared(F.col("n"), F.col("m"))).groupBy("id").agg(F.max(F.struct("shared", "to")).alias("best"))
        return best.select(F.least("id", "best.to").alias("a"), F.greatest("id", "best.to").alias("b"))

    @staticmethod
    def representatives(rows: DataFrame) -> DataFrame:
        """The rows of one document for each key and component."""
        one = rows.groupBy("token", "component").agg(F.min(F.struct("id", "n")).alias("one"))
        return one.select("token", "component", "one.id", "one.n")

    def remaining(self, rows: DataFrame) -> DataFrame:
        """All pairs of different components that may link and share a rare token, or only frequent ones.

        A pair that shares a rare token is found by it, whatever else it shares; of the others both have frequent tokens
        enough for all that they share.
        """
        frequent = rows.where(F.col("holders") > RARE)
        numbers = frequent.groupBy("id").agg(F.count("*").alias("frequent"))
        enough = frequent.withColumn("frequent", F.count("*").over(Window.partitionBy("id"))).where(F.col("frequent") >= self.rule.least_keys(F.col("n")))
        rare = rows.where(F.col("holders") <= RARE).join(numbers, "id", "left").select("token", "id", "n", "component", F.coalesce("frequent", F.lit(0)).alias("frequent"))
        x, y = rare.alias("x"), rare.alias("y")
        near = x.join(y, F.col("x.token") == F.col("y.token")).where("x.id < y.id and x.component <> y.component").where(self.rule.sizes_fit(F.col("x.n"), F.col("y.n")))
        shared = near.groupBy(F.col("x.id").alias("a"), F.col("y.id").alias("b")).agg(F.count("*").alias("shared"), F.first("x.n").alias("na"), F.first("y.n").alias("nb"), F.first(F.least("x.frequent", "y.frequent")).alias("more"))
        by_rare = shared.where(F.col("shared") + F.col("more") >= self.least_shared(F.col("na"), F.col("nb"))).select("a", "b")
        return by_rare.union(self.by_differences(enough))

    def by_differences(self, frequent: DataFrame) -> DataFrame:
        """Pairs that share frequent tokens, by how their sets differ from a pivot's.

        Each holder of a token is held against the token's pivot. Two sets a and b link if they differ in at most D tokens, D
        in proportion to their sizes. If their differences from the pivot have da and db tokens, of which s are common, they differ
        in da + db - 2 s. Where s may be 0, both link with the pivot; other pairs share (da + db - D) / 2 of their
        differences, so prefixes of these in the common order meet. Of two sets at least one doesn't link with the pivot.
        Only these prefixes become rows.

        Sets that are far from their pivot all lack the same of its tokens, which says nothing. But what two sets have beside the
        pivot's tokens differs in at most D, too: a set with more than D such tokens (far) shares some of them with each
        partner, so it is found by prefixes of these alone.

        Of its frequent tokens a document needs only the first in the order of how many hold them: all but as many as it
        shares with any partner, less one.
        """
        pivot = frequent.groupBy("token").agg(F.min("id").alias("pivot"), F.count("*").alias("held_by"))
        first = F.row_number().over(Window.partitionBy("id").orderBy("held_by", "token"))
        chosen = frequent.join(pivot, "token").withColumn("first", first).where(F.col("first") <= F.col("frequent") - self.rule.least_keys(F.col("n")) + 1)
        held = common.materialise(chosen.select("id", "n", "component", "pivot").distinct(), "pivot-pairs")
        percent, sent = self.rule.percent, self.spark.sparkContext.broadcast(self.hot)
        c = (100 - percent) / (100 + percent)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            names = ["id", "n", "component", "pivot", "inside", "d", "place", "early", "token", "own", "far"]
            for batch in batches:
                (sa, na), (sb, nb) = values_of(batch.column(4)), values_of(batch.column(5))
                ea, eb = np.concatenate(([0], np.cumsum(na))), np.concatenate(([0], np.cumsum(nb)))
                for i, j in slices(na, nb):
                    mine, theirs = sa[ea[i] : ea[j]], sb[eb[i] : eb[j]]
                    shared, alone_a, alone_b = shared_counts(mine, na[i:j], theirs, nb[i:j])
                    inside = 100 * shared >= percent * (na[i:j] + nb[i:j] - shared)
                    row = np.concatenate((np.repeat(np.arange(j - i), na[i:j])[alone_a], np.repeat(np.arange(j - i), nb[i:j])[alone_b]))
                    values = np.concatenate((mine[alone_a], theirs[alone_b]))
                    order = np.lexsort((values, is_in(sent.value, values), row))
                    row, values = row[order], values[order]
                    d = np.bincount(row, minlength=j - i)
                    place = np.arange(len(row)) - (np.cumsum(d) - d)[row] + 1
                    most = np.floor(c * batch.column(1).to_numpy()[i:j] * (1 + 100 / percent) + 1e-6).astype(np.int64)  # D with any partner
                    long = d - np.maximum(1, d - most) + 1
                    short = d - np.maximum(np.maximum(1, d - most), np.ceil(d * (1 - c) / 2 - 1e-6).astype(np.int64)) + 1  # for partners that don't link with the pivot
                    # what is beside the pivot's tokens: its prefixes are rows of their own
                    beside = np.concatenate((np.ones(alone_a.sum(), bool), np.zeros(alone_b.sum(), bool)))[order]
                    e = na[i:j] - shared
                    far = e > most
                    row_e, values_e = row[beside], values[beside]
                    place_e = np.arange(len(row_e)) - (np.cumsum(e) - e)[row_e] + 1
                    kept_e = place_e <= most[row_e] + 1
                    kept = (place <= np.where(inside, short, long)[row]) & ~far[row]
                    linked = np.flatnonzero(inside)  # one row of place 0 says that the document links with the pivot
                    every = np.concatenate((row[kept], row_e[kept_e], linked))
                    own = np.repeat([False, True, False], [kept.sum(), kept_e.sum(), len(linked)])
                    place = np.concatenate((place[kept], place_e[kept_e], np.zeros(len(linked), np.int64)))
                    token = np.concatenate((values[kept].view(np.int64), values_e[kept_e].view(np.int64), np.zeros(len(linked), np.int64)))
                    first = [x.take(pa.array(every + i)) for x in batch.columns[:4]]
                    yield pa.RecordBatch.from_arrays([*first, pa.array(inside[every]), pa.array(np.where(own, e[every], d[every])), pa.array(place), pa.array(place <= short[every]), pa.array(token), pa.array(own), pa.array(far[every])], names=names)

        parts = []
        for some in self.rounds(held, "id", "pivot"):
            both, sets = self.both_sets(some, "id", "pivot")
            parts.append(common.materialise(both.mapInArrow(run, "id long, n long, component long, pivot long, inside boolean, d long, place long, early boolean, token long, own boolean, far boolean"), "difference-keys"))
            common.discard(sets)
            common.free(self.spark)
        common.discard(held)
        found = reduce(DataFrame.union, parts)

        same = (F.col("x.pivot") == F.col("y.pivot")) & (F.col("x.token") == F.col("y.token")) & (F.col("x.component") != F.col("y.component"))
        whole, beside = found.where("place > 0 and not own"), found.where("own")
        near = whole.where("early").alias("x").join(whole.where("not inside").alias("y"), same).where("x.inside or (y.early and x.id < y.id)")
        near = near.union(beside.where("far").alias("x").join(beside.alias("y"), same).where("not y.far or x.id < y.id")).toDF(*[f"{side}_{c}" for side in "xy" for c in found.columns])
        # at the first token that they share, what is left behind it bounds all that they share
        needed = (F.col("x_d") + F.col("y_d") - F.floor(c * (F.col("x_n") + F.col("y_n")) + 1e-6)) / 2
        near = near.where(F.least(F.col("x_d") - F.col("x_place"), F.col("y_d") - F.col("y_place")) + 1 >= needed - 1e-6)
        near = near.where(self.rule.sizes_fit(F.col("x_n"), F.col("y_n"))).select(F.least("x_id", "y_id").alias("a"), F.greatest("x_id", "y_id").alias("b"))
        linked = found.where("place = 0 and id <> pivot").select(F.least("id", "pivot").alias("a"), F.greatest("id", "pivot").alias("b"))
        return near.union(linked)

    def link(self) -> None:
        rows = self.mixed(self.prefixes())
        self.add(self.pivots(rows, False))
        for step in range(SPREAD_ROUNDS):
            rows = self.mixed(rows)
            if rows.isEmpty():
                return
            if not self.add(self.pivots(self.representatives(rows) if step else rows, step != 1)):
                break
        rows = self.mixed(rows)
        self.add(self.remaining(rows))
        common.discard(rows)

    def classes(self) -> DataFrame:
        """id, n_shingles, component_id of each row."""
        self.link()
        sets = self.sets
        if self.component is not None:
            sets = sets.join(self.component.withColumnRenamed("id", "rep"), "rep", "left").withColumn("rep", F.coalesce("component", "rep")).drop("component")
        sets = common.materialise(sets, "set-components")
        found = self.base.join(sets, ["print1", "print2", "n"], "left")
        return found.select("id", F.col("n").alias("n_shingles"), F.when(F.col("id").isNull(), F.col("id")).otherwise(F.coalesce("rep", "id")).alias("component_id"))


def vertices(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, text, vertex of each row: a number for each id and text, null where the id is."""
    rows = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text"))
    return rows.withColumn("vertex", F.when(F.col("id").isNotNull(), F.xxhash64("id", "text")))


def vertex_classes(rows: DataFrame, rule: Rule) -> DataFrame:
    """vertex, n_shingles, component_id (a vertex) of each vertex of rows."""
    each = rows.where("vertex is not null").groupBy("vertex").agg(F.first("text").alias("text"))
    return common.materialise(Join(each, "vertex", "text", rule).classes(), "vertex-classes").withColumnRenamed("id", "vertex")


def one_row_ids(docs: DataFrame, id_col: str) -> bool:
    """Whether ids are whole numbers, each of one row."""
    if docs.schema[id_col].dataType.simpleString() not in WHOLE:
        return False
    return docs.where(docs[id_col].isNotNull()).groupBy(docs[id_col]).count().where("count > 1").isEmpty()


def join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """id, n_shingles (set size) and component_id (smallest id that links reach, its own included) of each row of docs."""
    rule = Rule(words, percent)
    kind = docs.schema[id_col].dataType
    if one_row_ids(docs, id_col):
        found = Join(docs, id_col, text_col, rule).classes()
        return found.select(F.col("id").cast(kind).alias(id_col), "n_shingles", F.col("component_id").cast(kind).alias("component_id"))
    # ids that stand for several rows: each text of an id is a vertex, and those of one id that have words are linked
    rows = vertices(docs, id_col, text_col)
    found = vertex_classes(rows, rule)
    own = common.materialise(rows.select("id", "vertex").join(found, "vertex", "left"), "row-classes")
    full = own.where("n_shingles > 0")
    least = full.groupBy("id").agg(F.min("vertex").alias("b"))
    label = graph.components(full.select(F.col("vertex").alias("a"), F.col("component_id").alias("b")).union(full.join(least, "id").select("vertex", "b")))
    own = common.materialise(own.join(label.withColumnRenamed("id", "vertex"), "vertex", "left").withColumn("component", F.coalesce("component", "vertex")), "row-components")
    lowest = own.where("n_shingles > 0").groupBy("component").agg(F.min("id").alias("component_id"))
    empty = rows.where("vertex is null").select(F.col("id"), "text")
    sizes = sketch(empty, "id", "text", rule).where("n >= 0").select("id", F.col("n").alias("n_shingles"), F.col("id").alias("component_id"))
    named = own.drop("component_id").where("vertex is not null").join(lowest, "component", "left")
    return named.select("id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("id")).alias("component_id")).unionByName(sizes).withColumnRenamed("id", id_col)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """One row of each group of docs, that of the smallest id (of rows that share it: one of any text that the group has); rows
    without an id or words all stay. Rows that share an id but link with nothing of each other are groups of their own."""
    if one_row_ids(docs, id_col):
        found = common.materialise(join(docs, id_col, text_col, words, percent), "classes")
        gone = found.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias("gone_id"))
        few = gone.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
        return docs.join(F.broadcast(gone) if few else gone, docs[id_col] == F.col("gone_id"), "left_anti")
    rows = vertices(docs, id_col, text_col)
    found = vertex_classes(rows, Rule(words, percent)).where("n_shingles > 0")
    placed = found.join(rows.where("vertex is not null").groupBy("vertex").agg(F.min("id").alias("id")), "vertex")
    best = placed.groupBy("component_id").agg(F.min(F.struct("id", "vertex")).alias("best")).select(F.col("best.vertex").alias("_kept"))
    marked = docs.withColumn("_vertex", F.when(docs[id_col].isNotNull(), F.xxhash64(docs[id_col], docs[text_col])))
    wordy = common.materialise(found.select(F.col("vertex").alias("_wordy")), "vertices-with-words")
    one = marked.join(best, F.col("_vertex") == F.col("_kept"), "left_semi").dropDuplicates(["_vertex"])
    rest = marked.join(wordy, F.col("_vertex") == F.col("_wordy"), "left_anti")
    return one.unionByName(rest).drop("_vertex")
