"""Benchmark decontamination by q-gram lemma filtering.

Each window of WINDOW characters of an item counts, at every offset (bytes of UTF-8, lower-cased in A-Z, runs of white
space as one space); a shorter item is one window. A window of w characters may differ from a passage by e = rate * w
edits; then they share at least w - q + 1 - q e q-grams, on 2 e + 1 neighbouring diagonals. Shared q-grams of whole texts
and whole items are taken in bands of twice as many diagonals that overlap by half, so one band has them all. Windows are
never listed: places of shared q-grams give those that reach the bound, and an edit breaks q-grams of at most q places
in a row, which drops more. A run of shared q-grams as long as a window is an exact copy; what is left is verified by
alignments inside the band, many windows at once. Shared q-grams are held HITS at a time, however often texts and items
repeat themselves (see Index.tiles).

The items are broadcast in parts of at most PART_BYTES; more parts mean more passes over the texts. Null or empty texts
and items match nothing, nor do items of fewer than q characters. Repeated rows match each on its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefacts.llm import textcore

Q = 10
WINDOW = 100
RATE = 0.08
PART_BYTES = 8_000_000
FILTER_BITS = 22
BATCH = 2048
HITS = 1 << 21  #: places of texts with places of items that share a q-gram, held at once
SPACE = np.uint8(32)


def normal(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes lower-cased in A-Z with runs of white space as one space, and where texts begin then."""
    white = textcore.WHITE[data]
    keep = np.ones(len(data), bool)
    keep[1:] = ~(white[1:] & white[:-1])
    starts = offsets[:-1][offsets[:-1] < len(data)]
    keep[starts] = True
    kept = np.zeros(len(data) + 1, np.int64)
    np.cumsum(keep, out=kept[1:])
    out = textcore.LOWER[np.where(white, SPACE, data)][keep]
    return out, kept[offsets]


def normal_text(text: str | None) -> bytes:
    raw = np.frombuffer((text or "").encode("utf-8", "replace"), np.uint8)
    return normal(raw, np.array([0, len(raw)]))[0].tobytes().strip()


def aligned(patterns: np.ndarray, data: np.ndarray, start: np.ndarray, end: np.ndarray, low: np.ndarray, width: int, budget: int) -> np.ndarray:
    """For each row of patterns, least edits against any part of data[start:end] over the diagonals (data less pattern
    place) from low on, so many; budget + 1 if over the budget."""
    size, far = patterns.shape[1], budget + 1
    at = low[:, None] + np.arange(size + width + 1)
    text = data[np.clip(at, 0, len(data) - 1)]
    inside = (at >= start[:, None]) & (at <= end[:, None])
    slope = np.arange(width, dtype=np.int16)
    out, left = np.full(len(patterns), far), np.arange(len(patterns))
    row = np.where(inside[:, :width], 0, far).astype(np.int16)  # an empty pattern matches anywhere
    for i in range(1, size + 1):
        new = row + (text[:, i - 1 : i - 1 + width] != patterns[:, i - 1 : i])
        np.minimum(new[:, :-1], row[:, 1:] + 1, out=new[:, :-1])
        new = np.minimum.accumulate(new - slope, axis=1) + slope
        row = np.where(inside[:, i : i + width], np.minimum(new, far), far).astype(np.int16)
        if i % 8 == 0 or i == size:
            good = row.min(axis=1) <= budget
            if not good.all():
                row, text, inside, patterns, left = row[good], text[good], inside[good], patterns[good], left[good]
            if not len(left):
                return out
    out[left] = row.min(axis=1)
    return out


class Index:
    """Items, and their q-grams in order of fingerprint."""

    def __init__(self, items: list[tuple[int, str]], q: int = Q, window: int = WINDOW, rate: float = RATE):
        self.q, self.whole, self.item, limits = q, [], [], []
        for item_id, text in items:
            whole = normal_text(text)
            if len(whole) < q:
                continue
            size = min(len(whole), window)
            e = int(rate * size)
            while e and size - q + 1 - q * e < 1:
                e -= 1
            self.whole.append(whole)
            self.item.append(item_id)
            limits.append(e)
        self.sizes = np.array([len(x) for x in self.whole], np.int64)
        self.spans = np.minimum(self.sizes, window)
        self.budgets = np.array(limits, np.int64)
        self.least = np.maximum(self.spans - q + 1 - q * self.budgets, 1)
        self.longest = int(self.sizes.max(initial=0))
        self.offsets = np.concatenate(([0], np.cumsum(self.sizes))).astype(np.int64)
        self.data = np.frombuffer(b"".join(self.whole), np.uint8)
        at, owner = self.starts(self.offsets)
        prints = self.prints(self.data, at)
        order = np.argsort(prints, kind="stable")
        self.grams, first, counts = np.unique(prints[order], return_index=True, return_counts=True)
        self.first, self.counts = first, counts
        self.owner, self.place = owner[order], (at - self.offsets[owner])[order]
        self.posted = np.repeat(np.arange(len(self.grams)), counts) * (len(self.data) + 1) + at[order]
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[self.grams >> np.uint64(64 - FILTER_BITS)] = True
        self.band = int(self.budgets.max(initial=0)) * 2 + 1

    @property
    def windows(self) -> list[bytes]:
        return [x[s : s + n] for x, n in zip(self.whole, self.spans.tolist(), strict=True) for s in range(len(x) - n + 1)]

    @property
    def budget(self) -> list[int]:
        return np.repeat(self.budgets, self.sizes - self.spans + 1).tolist()

    def starts(self, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where whole q-grams begin, and in which text."""
        n = np.maximum(np.diff(offsets) - self.q + 1, 0)
        owner = np.repeat(np.arange(len(n)), n)
        first = np.concatenate(([0], np.cumsum(n)[:-1])) if len(n) else np.zeros(0, np.int64)
        return np.arange(len(owner)) - first[owner] + offsets[:-1][owner], owner

    def prints(self, data: np.ndarray, at: np.ndarray) -> np.ndarray:
        block = textcore.Block(0, data, np.array([0, len(data)]))
        return block.prints(block.prefix(data), at, at + self.q)

    def matches(self, data: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """(text, item, edits, start, end) of contaminated regions of texts; places in normal bytes of the text."""
        at, text = self.starts(offsets)
        if not len(at) or not len(self.grams):
            return []
        prints = self.prints(data, at)
        some = np.flatnonzero(self.filter[prints >> np.uint64(64 - FILTER_BITS)])
        place = np.searchsorted(self.grams, prints[some])
        place[place == len(self.grams)] = 0
        good = self.grams[place] == prints[some]
        some, place = some[good], place[good]
        if not len(some):
            return []
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        for a, b, first, counts in self.tiles(at[some], place, len(data)):
            self.compare(data, offsets, at[some[a:b]], text[some[a:b]], first, counts, best)
        return [(t, item, *v) for (t, item), v in sorted(best.items(), key=lambda x: (x[0][0], x[0][1] is not None, x[0][1] or 0))]

    def tiles(self, at: np.ndarray, gram: np.ndarray, size: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """Ranges of at with, for each place, where its postings begin and how many there are: about HITS in all at most.

        Too many are split by places of the texts, then of the items. The halves overlap by the longest passage or window, so
        whatever matches is whole in one of them.
        """
        stride, over = len(self.data) + 1, int(self.spans.max()) + int(self.budgets.max())
        stack = [(0, size, 0, len(self.data))]
        while stack:
            low, high, item_low, item_high = stack.pop()
            a, b = np.searchsorted(at, (low, high)).tolist()
            own = gram[a:b]
            first, counts = self.first[own], self.counts[own]
            if item_low or item_high < len(self.data):
                first = np.searchsorted(self.posted, own * stride + item_low)
                counts = np.searchsorted(self.posted, own * stride + item_high) - first
            if counts.sum() <= HITS or max(high - low, item_high - item_low) <= 4 * over:
                if counts.any():
                    yield a, b, first, counts
            elif high - low > 16 * over or item_high - item_low <= 4 * over:
                middle = (low + high) // 2
                stack += [(middle, high, item_low, item_high), (low, middle + over, item_low, item_high)]
            else:
                middle = (item_low + item_high) // 2
                stack += [(low, high, middle, item_high), (low, high, item_low, middle + over)]

    def compare(self, data: np.ndarray, offsets: np.ndarray, at: np.ndarray, text: np.ndarray, first: np.ndarray, counts: np.ndarray, best: dict[tuple[int, int], tuple[int, int, int]]) -> None:
        """Puts the matches of places of texts with their postings into best."""
        hit = np.repeat(np.arange(len(at)), counts)
        posting = first[hit] + np.arange(len(hit)) - np.repeat(np.cumsum(counts) - counts, counts)
        n_items, who, own, place = len(self.item), text[hit], self.owner[posting], self.place[posting]
        diagonal = at[hit] - offsets[:-1][who] - place + self.longest  # never negative
        pair = who * n_items + own
        exact = []
        order = np.lexsort((place, diagonal, pair))
        x, d, p = pair[order], diagonal[order], place[order]
        far = self.spans[x % n_items] - self.q
        end = np.minimum(np.arange(len(x)) + far, len(x) - 1)
        runs = np.flatnonzero((x[end] == x) & (d[end] == d) & (p[end] - p == far))
        for k in runs[np.unique(x[runs], return_index=True)[1]].tolist():
            t, o = divmod(int(x[k]), n_items)
            a, size = int(p[k] + d[k]) - self.longest, int(self.spans[o])
            if data[offsets[t] + a : offsets[t] + a + size].tobytes() == self.whole[o][p[k] : p[k] + size]:
                exact.append(x[k])
                best.setdefault((t, self.item[o]), (0, a, a + size))
        rest = ~np.isin(pair, np.array(exact, np.int64))
        pair, diagonal, place = pair[rest], diagonal[rest], place[rest]
        wide = 2 * self.band
        for shift in (0, self.band) if len(pair) else ():
            for t, o, s, low in self.candidates(pair, (diagonal + shift) // wide, place):
                low = low * wide - shift - self.longest + s
                e, size = int(self.budgets[o[0]]), int(self.spans[o[0]])
                patterns = self.data[(self.offsets[o] + s)[:, None] + np.arange(size)]
                edits = aligned(patterns, data, offsets[t], offsets[t + 1], offsets[t] + low - e, wide + 2 * e, e)
                for k in np.flatnonzero(edits <= e).tolist():
                    key, length = (int(t[k]), self.item[o[k]]), int(offsets[t[k] + 1] - offsets[t[k]])
                    if key not in best or edits[k] < best[key][0]:
                        best[key] = (int(edits[k]), max(0, int(low[k]) - e), min(length, int(low[k]) + wide + size + e))

    def candidates(self, pair: np.ndarray, band: np.ndarray, place: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        """Text, item, first place and band of windows that may be within the budget, in groups of one length."""
        n_items, q, stride = len(self.item), self.q, self.longest + 1
        top = int(band.max()) + 1
        keys, group = np.unique(pair * top + band, return_inverse=True)
        places = np.unique(group * stride + place)
        group, p = places // stride, places % stride
        item = keys[group] // top % n_items
        end = np.arange(len(p)) + self.least[item] - 1
        fits = end < len(p)
        end = np.minimum(end, len(p) - 1)
        span = self.spans[item] - q
        some = np.flatnonzero(fits & (group[end] == group) & (p[end] - p <= span))
        if not len(some):
            return
        # windows that hold the places of some and end; each window once
        low, high = np.maximum(p[end] - span, 0)[some], np.minimum(p, self.sizes[item] - self.spans[item])[some]
        same = group[some][1:] == group[some][:-1]
        low[1:] = np.where(same, np.maximum(low[1:], high[:-1] + 1), low[1:])
        n = np.maximum(high - low + 1, 0)
        first = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(n.sum())
        group = np.repeat(group[some], n)
        item = keys[group] // top % n_items
        # least edits that break all q-grams of the window that aren't shared
        ends = np.flatnonzero(np.append(places[1:] != places[:-1] + 1, True))
        after = places[ends[np.searchsorted(ends, np.arange(len(places)))]] + 1
        x, edits = group * stride + first, np.zeros(len(group), np.int64)
        last = x + self.spans[item] - q
        for _ in range(int(self.budgets.max()) + 1):
            at = np.minimum(np.searchsorted(places, x), len(places) - 1)
            x = np.where(places[at] == x, after[at], x)
            missing = x <= last
            edits += missing
            x = x + q * missing
        good = edits <= self.budgets[item]
        group, item, first = group[good], item[good], first[good]
        for size in np.unique(self.spans[item]).tolist():
            of = np.flatnonzero(self.spans[item] == size)
            for k in range(0, len(of), BATCH):
                own = of[k : k + BATCH]
                yield keys[group[own]] // top // n_items, item[own], first[own], keys[group[own]] % top


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", q: int = Q, window: int = WINDOW, rate: float = RATE) -> DataFrame:
    """id, item, edits, region_start, region_end: one row for each document row and item that it holds a window of."""
    items = benchmark.where(F.col(item_text_col).isNotNull()).select(F.col(item_col).cast("long").alias("item"), F.col(item_text_col).alias("text"))
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n_parts = max(1, -(-size // PART_BYTES))
    kind = docs.schema[id_col].dataType.simpleString()
    found: DataFrame | None = None
    for part in range(n_parts):
        own = items if n_parts == 1 else items.where(F.pmod(F.xxhash64("item"), F.lit(n_parts)) == part)
        index = docs.sparkSession.sparkContext.broadcast(Index([(r.item, r.text) for r in own.orderBy("item", "text").collect()], q, window, rate))

        def run(batches: Iterator[pa.RecordBatch], index=index) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for block in textcore.blocks(batch.column(1)):
                    rows = index.value.matches(*normal(block.data, block.offsets))
                    ids = batch.column(0).take(pa.array([block.first + r[0] for r in rows], pa.int64()))
                    yield pa.RecordBatch.from_arrays([ids, *(pa.array([r[k] for r in rows], pa.int64()) for k in range(1, 5))], names=["id", "item", "edits", "start", "end"])

        one = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).mapInArrow(run, f"id {kind}, item long, edits long, `start` long, `end` long")
        found = one if found is None else found.union(one)
    return found.select(F.col("id").alias(id_col), F.col("item").alias(item_col), "edits", F.col("start").alias("region_start"), F.col("end").alias("region_end"))


def keep_clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that hold nothing of the benchmark, in one pass for each part of it."""
    items = benchmark.where(F.col("text").isNotNull()).select(F.col("item_id").cast("long").alias("item"), "text")
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n_parts = max(1, -(-size // PART_BYTES))
    at = docs.columns.index(text_col)
    for part in range(n_parts):
        own = items if n_parts == 1 else items.where(F.pmod(F.xxhash64("item"), F.lit(n_parts)) == part)
        index = docs.sparkSession.sparkContext.broadcast(Index([(r.item, r.text) for r in own.orderBy("item", "text").collect()], **options))

        def run(batches: Iterator[pa.RecordBatch], index=index) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = np.ones(batch.num_rows, bool)
                for block in textcore.blocks(batch.column(at)):
                    for r in index.value.matches(*normal(block.data, block.offsets)):
                        keep[block.first + r[0]] = False
                yield batch.filter(pa.array(keep))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
