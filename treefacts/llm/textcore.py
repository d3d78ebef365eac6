"""Words, lines and shingles of whole Arrow batches as 64-bit fingerprints, by numpy on the UTF-8 bytes.

A span's fingerprint is a polynomial over a random 64-bit value for each byte, taken from prefix sums, so all spans
of a block cost one pass. Words are runs of bytes other than 0x20 and 0x09-0x0D.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 1 << 18  #: texts are worked on in blocks of about so many bytes, never cut inside a text
U = np.uint64
WHITE = np.zeros(256, bool)
WHITE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_VALUES = np.random.default_rng(20240229).integers(1, 1 << 64, 256, dtype=np.uint64)
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, BLOCK_BYTES + 1)
        steps = np.full(size, base, np.uint64)
        steps[0] = 1
        have = np.multiply.accumulate(steps)
        if size <= 8 * BLOCK_BYTES:
            _powers[base] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads each bit over all 64 (a finaliser as in MurmurHash3)."""
    x = x ^ (x >> U(33))
    x = x * U(0xFF51AFD7ED558CCD)
    x ^= x >> U(33)
    x *= U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(33))


class Block:
    """Some texts: their bytes one after the other, and where each begins; offsets has one more entry than texts."""

    def __init__(self, first: int, data: np.ndarray, offsets: np.ndarray):
        self.first, self.data, self.offsets = first, data, offsets
        self.n = len(offsets) - 1

    def prefix(self, data: np.ndarray) -> np.ndarray:
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_VALUES[data] * _power(_BASE, len(data)), out=out[1:])
        return out

    @staticmethod
    def prints(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        raw = (prefix[ends] - prefix[starts]) * _power(_BASE_INVERSE, len(prefix))[starts]
        return mix(raw + (ends - starts).astype(np.uint64) * U(0xD6E8FEB86659FD93))

    def runs(self, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and texts of the runs of True, ended by the end of a text."""
        before = np.zeros(len(inside), bool)
        before[1:] = inside[:-1]
        edges = self.offsets[(self.offsets < len(inside))]
        before[edges] = False
        starts = np.flatnonzero(inside & ~before)
        after = np.zeros(len(inside), bool)
        after[:-1] = inside[1:]
        after[edges[edges > 0] - 1] = False
        ends = np.flatnonzero(inside & ~after) + 1
        return starts, ends, self.text_of(starts)

    def text_of(self, positions: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.offsets, positions, side="right") - 1

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.runs(~WHITE[self.data])

    def count(self, mask: np.ndarray) -> np.ndarray:
        """How many True each text has."""
        sums = np.zeros(len(mask) + 1, np.int64)
        np.cumsum(mask, out=sums[1:])
        return sums[self.offsets[1:]] - sums[self.offsets[:-1]]


def blocks(texts: pa.Array, limit: int = BLOCK_BYTES) -> Iterator[Block]:
    """The texts of an Arrow string array (null as empty) in blocks."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if not len(texts):
        return
    _, offsets, data = texts.buffers()
    ends = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < len(texts):
        j = max(i + 1, int(np.searchsorted(ends, ends[i] + limit, side="right")) - 1)
        j = min(j, len(texts))
        yield Block(i, data[ends[i] : ends[j]], ends[i : j + 1] - ends[i])
        i = j
    pa.default_memory_pool().release_unused()  # or the worker keeps what its largest batch took


def shingles(block: Block, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(text, fingerprint) of each distinct k-word shingle after lower-casing A-Z, sorted by both; a text of fewer
    words has its whole sequence as one, a text without words has none."""
    data = LOWER[block.data]
    starts, ends, text = block.words()
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    words = block.prints(block.prefix(data), starts, ends)
    counts = np.bincount(text, minlength=block.n)
    first = np.concatenate(([0], np.cumsum(counts)[:-1]))
    rank = np.arange(len(words)) - first[text]
    whole = rank + k <= counts[text]
    out = np.zeros(len(words), np.uint64)
    for step in range(k):
        shifted = words[step:] if step else words
        out[: len(shifted)] = mix(out[: len(shifted)] * U(0x9FB21C651E98DF25) + shifted + U(step + 1))
    t, h = text[whole], out[whole]
    short = np.flatnonzero((counts > 0) & (counts < k))
    if len(short):
        extra = []
        for i in short:
            x = np.full(1, counts[i], np.uint64)
            for w in words[first[i] : first[i] + counts[i]]:
                x = mix(x * U(0x8CB92BA72F3D8DD7) + w)
            extra.append(x[0])
        t, h = np.concatenate((t, short)), np.concatenate((h, np.array(extra, np.uint64)))
    order = np.lexsort((h, t))
    t, h = t[order], h[order]
    new = np.ones(len(t), bool)
    new[1:] = (t[1:] != t[:-1]) | (h[1:] != h[:-1])
    return t[new], h[new]
