"""Wavelet matrix of token ids: bit planes with rank and select in one compressed block of bytes.

A block holds the ids of some whole documents. Its layout, all integers little-endian:

    magic "TFWM", version u16, number of planes u16, tokens u64, documents u64, length of the body u64, body, and one
    line feed that ends the block. The body is a zstandard frame over: document ids (i64 each), token counts (u32
    each), then for each plane, most significant bit first: zeros u64 and the bits, packed, first token in the highest bit.

A file is one or more blocks. Ranks come from counts kept for every 512 bits (made on reading), select from a binary
search over them.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import zstandard

MAGIC, VERSION = b"TFWM", 1
HEADER = struct.Struct("<4sHHQQQ")
WORD = 512


class Plane:
    def __init__(self, packed: np.ndarray, n: int, zeros: int):
        self.packed, self.n, self.zeros = packed, n, zeros
        padded = np.zeros(-(-max(n, 1) // WORD) * (WORD // 8), np.uint8)
        padded[: len(packed)] = packed
        counts = np.bitwise_count(padded.reshape(-1, WORD // 8)).sum(axis=1, dtype=np.int64)
        self.ranks = np.concatenate(([0], np.cumsum(counts)))
        self.padded = padded

    def bit(self, i: int) -> int:
        return int(self.padded[i >> 3] >> (7 - (i & 7))) & 1

    def rank1(self, i: int) -> int:
        """Ones among the first i bits."""
        block, first = i // WORD, i // WORD * (WORD // 8)
        full, rest = self.padded[first : i >> 3], i & 7
        ones = int(self.ranks[block]) + int(np.bitwise_count(full).sum())
        return ones + (int(self.padded[i >> 3] >> (8 - rest)).bit_count() if rest else 0)

    def rank(self, bit: int, i: int) -> int:
        return self.rank1(i) if bit else i - self.rank1(i)

    def select(self, bit: int, k: int) -> int:
        """Position of the k-th (from 0) bit of this value."""
        low, high = 0, self.n
        while low < high:
            mid = (low + high) // 2
            if self.rank(bit, mid + 1) <= k:
                low = mid + 1
            else:
                high = mid
        return low


class WaveletMatrix:
    """Access, counting and occurrence lookup over one sequence of ids."""

    def __init__(self, planes: list[Plane], n: int):
        self.planes, self.n = planes, n

    @classmethod
    def build(cls, ids: np.ndarray, bits: int) -> WaveletMatrix:
        planes, current = [], np.ascontiguousarray(ids)
        for shift in range(bits - 1, -1, -1):
            ones = ((current >> current.dtype.type(shift)) & current.dtype.type(1)).astype(bool)
            low = current[~ones]
            planes.append(Plane(np.packbits(ones), len(ids), len(low)))
            current = np.concatenate((low, current[ones]))
        return cls(planes, len(ids))

    def decode(self, dtype=np.uint32) -> np.ndarray:
        """All ids, by undoing the stable partitions from the last plane up."""
        kind = np.uint16 if len(self.planes) <= 16 else np.uint32
        current = np.zeros(self.n, kind)
        for level, plane in enumerate(reversed(self.planes)):
            ones = np.unpackbits(plane.packed, count=self.n).astype(bool)
            above = np.empty_like(current)
            above[~ones] = current[: plane.zeros]
            above[ones] = current[plane.zeros :] | kind(1 << level)
            current = above
        return current.astype(dtype)

    def access(self, i: int) -> int:
        if not 0 <= i < self.n:
            raise IndexError(i)
        out = 0
        for plane in self.planes:
            bit = plane.bit(i)
            out = out << 1 | bit
            i = plane.zeros + plane.rank1(i) if bit else i - plane.rank1(i)
        return out

    def _range(self, token: int, start: int, end: int) -> tuple[int, int]:
        for level, plane in enumerate(self.planes):
            bit = token >> (len(self.planes) - 1 - level) & 1
            base = plane.zeros if bit else 0
            start, end = base + plane.rank(bit, start), base + plane.rank(bit, end)
        return start, end

    def count(self, token: int, start: int = 0, end: int | None = None) -> int:
        """How often a token occurs in [start, end)."""
        if token >> len(self.planes):
            return 0
        end = self.n if end is None else min(end, self.n)
        low, high = self._range(token, min(start, end), end)
        return high - low

    rank = count

    def select(self, token: int, k: int) -> int:
        """Position of the k-th (from 0) occurrence of a token."""
        if token >> len(self.planes) or k < 0:
            raise IndexError(k)
        low, high = self._range(token, 0, self.n)
        if low + k >= high:
            raise IndexError(k)
        i = low + k
        for level in range(len(self.planes) - 1, -1, -1):
            plane, bit = self.planes[level], token >> (len(self.planes) - 1 - level) & 1
            i = plane.select(bit, i - plane.zeros if bit else i)
        return i

    def locate(self, token: int) -> Iterator[int]:
        return (self.select(token, k) for k in range(self.count(token)))


@dataclass
class Shard:
    doc_ids: np.ndarray
    counts: np.ndarray
    matrix: WaveletMatrix


def to_bytes(doc_ids: np.ndarray, counts: np.ndarray, ids: np.ndarray, bits: int) -> bytes:
    """One block, from all ids of its documents in order."""
    matrix = WaveletMatrix.build(ids.astype(np.uint16 if bits <= 16 else np.uint32), bits)
    body = [doc_ids.astype("<i8").tobytes(), counts.astype("<u4").tobytes()]
    for p in matrix.planes:
        body += [struct.pack("<Q", p.zeros), p.packed.tobytes()]
    packed = zstandard.ZstdCompressor(level=1).compress(b"".join(body))
    return HEADER.pack(MAGIC, VERSION, bits, len(ids), len(doc_ids), len(packed)) + packed + b"\n"


def from_bytes(data: bytes) -> Iterator[Shard]:
    """The blocks of a file; anything that isn't one is an error."""
    at, view = 0, memoryview(data)
    while at < len(data):
        magic, version, bits, n, n_docs, length = HEADER.unpack_from(view, at)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not a block of token ids")
        at += HEADER.size
        body = zstandard.ZstdDecompressor().decompress(view[at : at + length])
        at += length
        if bytes(view[at : at + 1]) != b"\n":
            raise ValueError("a block of token ids is cut")
        at += 1
        doc_ids, counts = np.frombuffer(body, "<i8", n_docs), np.frombuffer(body, "<u4", n_docs, 8 * n_docs)
        planes, k, size = [], 12 * n_docs, -(-n // 8)
        for _ in range(bits):
            planes.append(Plane(np.frombuffer(body, np.uint8, size, k + 8), n, struct.unpack_from("<Q", body, k)[0]))
            k += 8 + size
        if int(counts.sum()) != n:
            raise ValueError("token counts don't add up")
        yield Shard(doc_ids, counts, WaveletMatrix(planes, n))
