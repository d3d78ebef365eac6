"""Pieces of many texts at once, by numpy on their UTF-8 bytes, and a compact table of the ids of pieces met before.

split() finds what the pattern tokens.PIECES finds in each text, for texts of the characters of tokens.PLAIN. Memory
keys a piece of up to 16 bytes by the bytes themselves, in two words, so no piece is ever taken for another.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import chain

import numpy as np

MARK = 1  #: the byte that ends each text; no text of plain characters holds it
KEY_BYTES = 16
SLICE = 1 << 15  #: pieces looked up at a time
MOST = 1 << 19  #: pieces that are remembered, at about 36 bytes each
LONG_BYTES, MOST_LONG = 64, 1 << 14
U = np.uint64
LETTER, DIGIT, OTHER, SPACE, END = range(5)


def _groups() -> bytes:
    out = np.full(256, OTHER, np.uint8)
    out[[*range(65, 91), *range(97, 123)]] = LETTER
    out[48:58] = DIGIT
    out[[32, *range(9, 14)]] = SPACE
    out[MARK] = END
    return out.tobytes()


GROUPS = _groups()
_MASKS = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)


def split(raw: bytes) -> np.ndarray:
    """Where the pieces of texts begin; each text is ended by MARK, which is a piece of its own."""
    data, group = np.frombuffer(raw, np.uint8), np.frombuffer(bytearray(raw.translate(GROUPS)), np.uint8)
    if not raw.isascii():  # of the plain characters beyond ASCII, the letters are those in two bytes from 0xC3 on but × and ÷
        at = np.flatnonzero(data == 0xC3)
        at = at[(data[at + 1] != 0x97) & (data[at + 1] != 0xB7)]
        group[at] = group[at + 1] = LETTER
    begins = np.ones(len(data), bool)
    np.not_equal(group[1:], group[:-1], out=begins[1:])
    begins[group == END] = True
    # the last of some white space goes with what follows if it is a space, and is alone otherwise
    white = group == SPACE
    last = np.flatnonzero(white[:-1] & (group[1:] < SPACE))
    begins[last] = True
    begins[last[data[last] == 32] + 1] = False
    # contractions: an apostrophe that begins a piece, and its letters
    at = np.flatnonzero(data == 39)
    if len(at):
        before = np.where(at > 0, at - 1, len(data) - 1)
        at = at[(group[before] != OTHER) & (data[before] != 32)]
        one, two = data[at + 1], data[np.minimum(at + 2, len(data) - 1)]
        short = (one == ord("s")) | (one == ord("t")) | (one == ord("m")) | (one == ord("d"))
        long = (two == ord("e")) & ((one == ord("r")) | (one == ord("v"))) | (one == ord("l")) & (two == ord("l"))
        begins[at[short | long] + 1] = False
        begins[at[short] + 2] = True
        begins[at[long] + 3] = True
    return np.flatnonzero(begins)


def grown(old: np.ndarray, size: int) -> np.ndarray:
    new = np.zeros(size, old.dtype)
    new[: len(old)] = old
    return new


class Memory:
    """Ids of pieces, asked for once. make: the ids of each of some pieces, from their bytes."""

    def __init__(self, make: Callable[[list[bytes]], list[list[int]]], end_id: int):
        self.make, self.end_id = make, end_id
        self.long: dict[bytes, list[int]] = {}
        self.clear()

    def clear(self) -> None:
        self.n, self.used = 1, 0  # entry 0 stands for none
        self.low, self.high, self.first = np.zeros(SLICE, np.uint64), np.zeros(SLICE, np.uint64), np.zeros(SLICE + 1, np.int32)
        self.pool = np.zeros(4 * SLICE, np.uint16)
        self.slots, self.bits = np.zeros(2 * SLICE, np.int32), (2 * SLICE).bit_length() - 1
        self.add(np.array([MARK], np.uint64), np.zeros(1, np.uint64), [[self.end_id]])

    def hashed(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        x = low * U(0x9E3779B97F4A7C15) ^ high * U(0xC2B2AE3D27D4EB4F)
        x ^= x >> U(32)
        x *= U(0xD6E8FEB86659FD93)
        return (x >> U(64 - self.bits)).astype(np.int64)

    def put(self, ids: list[list[int]]) -> np.ndarray:
        """Writes ids behind those in use; returns where those of each piece end."""
        ends = self.used + np.cumsum(np.fromiter(map(len, ids), np.int64, len(ids)))
        if ends[-1] > len(self.pool):
            self.pool = np.concatenate((self.pool[: self.used], np.zeros(max(int(ends[-1]) - self.used, self.used // 2), np.uint16)))
        self.pool[self.used : ends[-1]] = np.fromiter(chain.from_iterable(ids), np.uint16, int(ends[-1]) - self.used)
        return ends

    def place(self, entries: np.ndarray) -> None:
        slot, mask = self.hashed(self.low[entries], self.high[entries]), len(self.slots) - 1
        while len(entries):
            free = self.slots[slot] == 0
            self.slots[slot[free]] = entries[free]
            lost = self.slots[slot] != entries
            entries, slot = entries[lost], (slot[lost] + 1) & mask

    def add(self, low: np.ndarray, high: np.ndarray, ids: list[list[int]]) -> None:
        """Remembers distinct pieces that are not known yet."""
        n = self.n + len(ids)
        if n > len(self.low):
            size = max(2 * len(self.low), 1 << n.bit_length())
            self.low = grown(self.low, size)
            self.high = grown(self.high, size)
            self.first = grown(self.first, size + 1)
            self.slots = None  # given back before the larger one is made
            self.slots, self.bits = np.zeros(2 * size, np.int32), (2 * size).bit_length() - 1
            self.place(np.arange(1, self.n, dtype=np.int32))
        self.low[self.n : n], self.high[self.n : n] = low, high
        ends = self.put(ids)
        self.first[self.n + 1 : n + 1] = ends
        self.place(np.arange(self.n, n, dtype=np.int32))
        self.n, self.used = n, int(ends[-1])

    def find(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """The entry of each key, 0 if there is none."""
        slot, mask = self.hashed(low, high), len(self.slots) - 1
        out = self.slots[slot]
        rest = np.flatnonzero(((self.low[out] != low) | (self.high[out] != high)) & (out > 0))
        while len(rest):
            slot[rest] = (slot[rest] + 1) & mask
            found = self.slots[slot[rest]]
            out[rest] = found
            rest = rest[((self.low[found] != low[rest]) | (self.high[found] != high[rest])) & (found > 0)]
        return out

    def encode(self, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts, each with its end id, and how many each has. Each text is ended by MARK."""
        starts = split(raw)
        words = np.ndarray(len(raw) + KEY_BYTES - 7, np.dtype("<u8"), raw + bytes(KEY_BYTES), strides=(1,))
        parts, ends, before = [], [], 0
        for i in range(0, len(starts), SLICE):
            if self.n + SLICE > MOST:
                self.clear()
            begin = starts[i : i + SLICE]
            length = np.append(starts[i + 1 : i + SLICE + 1], len(raw))[: len(begin)] - begin
            low, high = words[begin] & _MASKS[np.minimum(length, 8)], words[begin + 8 * (length > 8)] & _MASKS[np.clip(length - 8, 0, 8)]
            entry = self.find(low, high)
            fits = length <= KEY_BYTES
            new = np.flatnonzero((entry == 0) & fits)
            if len(new):
                pieces: dict[bytes, int] = {}
                for k, a, b in zip(new.tolist(), begin[new].tolist(), (begin + length)[new].tolist(), strict=True):
                    pieces.setdefault(raw[a:b], k)
                first = np.fromiter(pieces.values(), np.int64, len(pieces))
                self.add(low[first], high[first], self.make(list(pieces)))
                entry[new] = self.find(low[new], high[new])
            at = self.first[entry].astype(np.int64)
            counts = self.first[entry + 1] - at
            over = np.flatnonzero(~fits)
            if len(over):  # their ids stand behind those in use, for this slice only
                ids = [self.of_long(raw[a:b]) for a, b in zip(begin[over].tolist(), (begin + length)[over].tolist(), strict=True)]
                counts[over] = np.diff(behind := self.put(ids), prepend=self.used)
                at[over] = behind - counts[over]
            upto = np.cumsum(counts)
            parts.append(self.pool[np.arange(int(upto[-1])) + np.repeat(at - upto + counts, counts)])
            ends.append(before + upto[low == MARK])
            before += int(upto[-1])
        ends = np.concatenate(ends)
        return np.concatenate(parts), np.diff(ends, prepend=0)

    def of_long(self, piece: bytes) -> list[int]:
        ids = self.long.get(piece)
        if ids is None:
            ids = self.make([piece])[0]
            if len(piece) < LONG_BYTES:
                if len(self.long) >= MOST_LONG:
                    self.long.clear()
                self.long[piece] = ids
        return ids
