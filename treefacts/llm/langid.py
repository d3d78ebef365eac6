"""Language identification by cross-parsing entropy.

For each language a suffix automaton holds some labelled text. A text is parsed greedily: each phrase is the longest
match from where the last one ended. Phrases, normalised to bits per character by the length of the automaton's text,
estimate the cross entropy; the language with the fewest wins.

Letters are the symbols; runs of other characters are one. The most frequent letters of each language have symbols of
their own, all others share HASHED symbols by a hash of the code point, so scripts stay apart. The automata are dense tables
over the symbols of their text, in which a failed step restarts at the root and marks a phrase: a step is one lookup, taken
for all segments of a batch at once. Segments of one text are first parsed from the root, then again from where the one
before ended, until both parses are in one state, which they stay in; so the phrases are those of the whole text.

Training text is a bounded sample: about train_rows rows a language by hash of the id, whole, as long as they come to
train_chars characters at most (a single longer row is left out). Null text or text without a letter: `und`, score 0. Repeated
rows are judged each on its own. Without training rows everything is `und`. Over MAX_LANGUAGES languages are an error.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefacts.llm import common

TRAIN_ROWS = 80
TRAIN_CHARS = 40_000
MAX_LANGUAGES = 200
ALPHABET = 62  #: most frequent letters of each language that have a symbol of their own
HASHED = 64  #: symbols that the other letters share
SEGMENT = 256  #: characters that are parsed side by side
BATCH_CHARS = 2_000_000
SHARPNESS = 6.0  #: how fast the score of a language falls with its extra bits a character
BREAK = 1 << 30
UNKNOWN = "und"


class Classes:
    """From code points to symbols: 0 all that isn't a letter, then frequent letters, then shared ones; the last is padding."""

    def __init__(self, texts: list[str]):
        chosen: set[str] = set()
        for x in texts:
            letters = Counter(c for c in x.lower() if c.isalpha())
            chosen.update(c for c, _ in sorted(letters.items(), key=lambda x: (-x[1], x[0]))[:ALPHABET])
        place = {c: i for i, c in enumerate(sorted(chosen), 1)}
        shared = len(place) + 1
        self.n = shared + HASHED + 1
        self.table = np.zeros(0x110000, np.uint16)
        for i in range(0x110000):
            c = chr(i)
            if c.isalpha():
                low = c.lower()[0]
                self.table[i] = place.get(low) or shared + ord(low) * 0x9E3779B1 % (1 << 32) % HASHED

    def codes(self, text: str) -> np.ndarray:
        """Classes of a text, runs of other than letters as one."""
        got = self.table[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
        if not len(got):
            return got
        keep = np.ones(len(got), bool)
        keep[1:] = (got[1:] != 0) | (got[:-1] != 0)
        return got[keep]


def automaton(codes: list[int]) -> list[dict[int, int]]:
    """Transitions of the suffix automaton of a sequence; state 0 is the root."""
    steps: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in codes:
        new = len(steps)
        steps.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in steps[p]:
            steps[p][c] = new
            p = link[p]
        if p >= 0:
            q = steps[p][c]
            if length[q] == length[p] + 1:
                link[new] = q
            else:
                copy = len(steps)
                steps.append(dict(steps[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and steps[p].get(c) == q:
                    steps[p][c] = copy
                    p = link[p]
                link[q] = link[new] = copy
        last = new
    return steps


def dense(steps: list[dict[int, int]], width: int) -> np.ndarray:
    """Flat table: row offset + class -> row offset of the next state, plus BREAK where a phrase ends before this class."""
    root = np.full(width, BREAK, np.int64)
    for c, s in steps[0].items():
        root[c] = s * width | BREAK
    root[width - 1] = 0
    out = np.tile(root, len(steps))
    places = np.fromiter((i * width + c for i, step in enumerate(steps) for c in step), np.int64)
    out[places] = np.fromiter((s * width for step in steps for s in step.values()), np.int64)
    out[np.arange(len(steps)) * width + width - 1] = 0
    return out.astype(np.int32)


def parsed(table: np.ndarray, columns: np.ndarray, follows: np.ndarray) -> np.ndarray:
    """Phrases that end in each segment (a column of symbols); those marked go on from the one before."""
    n = columns.shape[1]
    end, count = np.zeros(n, np.int32), np.zeros(n, np.int64)
    for column in columns:
        got = table.take(end + column)
        count += got >> 30
        end = got & (BREAK - 1)
    began = np.zeros(n, np.int32)  # the state from which a segment was parsed
    while n:
        true = np.concatenate(([0], end[:-1])).astype(np.int32) * follows
        lane = np.flatnonzero(true != began)
        if not len(lane):
            break
        old, new = began[lane], true[lane]
        began[lane] = new
        for k, column in enumerate(columns):
            symbols = column[lane]
            a, b = table.take(old + symbols), table.take(new + symbols)
            count[lane] += (b >> 30) - (a >> 30)
            old, new = a & (BREAK - 1), b & (BREAK - 1)
            if k % 4 == 3:
                apart = old != new
                lane, old, new = lane[apart], old[apart], new[apart]
                if not len(lane):
                    break
        end[lane] = new
    return count


class Model:
    def __init__(self, training: dict[str, str]):
        self.languages = sorted(x for x in training if training[x])
        self.classes = Classes([training[x] for x in self.languages])
        self.tables, self.local, self.bits = [], [], []
        for x in self.languages:
            codes = self.classes.codes(training[x])
            own = np.unique(codes)
            local = np.zeros(self.classes.n, np.int32)  # 0: symbols that the text doesn't have
            local[own] = np.arange(1, len(own) + 1)
            local[-1] = len(own) + 1
            self.local.append(local)
            self.tables.append(dense(automaton(local[codes].tolist()), len(own) + 2))
            self.bits.append(np.log2(max(2, len(codes))))

    def phrases(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Phrases by language and text, symbols and letters by text."""
        codes = [self.classes.codes(x) for x in texts]
        sizes = np.array([len(c) for c in codes], np.int64)
        letters = np.array([np.count_nonzero(c) for c in codes], np.int64)
        n_segments = -(-sizes // SEGMENT)
        owner = np.repeat(np.arange(len(texts)), n_segments)
        grid = np.full((int(n_segments.sum()), SEGMENT), self.classes.n - 1, np.uint16)
        flat, at = grid.reshape(-1), 0
        for c, n in zip(codes, n_segments.tolist(), strict=True):
            flat[at : at + len(c)] = c
            at += n * SEGMENT
        follows = np.concatenate(([False], owner[1:] == owner[:-1])) if len(owner) else np.zeros(0, bool)
        found = np.zeros((len(self.languages), len(texts)))
        for i, (table, local) in enumerate(zip(self.tables, self.local, strict=True)):
            columns = np.ascontiguousarray(local[grid].T)
            found[i] = np.bincount(owner, parsed(table, columns, follows), len(texts))
        return found, sizes, letters

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        if not self.languages:
            return [UNKNOWN] * len(texts), [0.0] * len(texts)
        names, scores, start = [], [], 0
        while start < len(texts):
            end, chars = start, 0
            while end < len(texts) and (end == start or chars + len(texts[end]) <= BATCH_CHARS):
                chars += len(texts[end])
                end += 1
            found, sizes, letters = self.phrases(texts[start:end])
            bits = (found + 1) * np.array(self.bits)[:, None] / np.maximum(sizes, 1)
            best = bits.argmin(axis=0)
            score = 1 / np.exp(-SHARPNESS * (bits - bits.min(axis=0))).sum(axis=0)
            names += [self.languages[b] if n else UNKNOWN for b, n in zip(best, letters, strict=True)]
            scores += np.where(letters > 0, score, 0.0).tolist()
            start = end
        return names, scores


_models: dict[int, Model] = {}


def model(training: dict[str, str]) -> Model:
    key = hash(tuple(sorted(training.items())))
    if key not in _models:
        _models.clear()
        _models[key] = Model(training)
    return _models[key]


def sample(labelled: DataFrame, id_col: str, text_col: str, lang_col: str, train_rows: int, train_chars: int) -> dict[str, str]:
    """About train_rows rows of each language (all, if it has fewer), by hash of the id, of train_chars characters in all at most."""
    rows = labelled.where(F.col(lang_col).isNotNull() & (F.char_length(F.col(text_col)) <= train_chars))
    counts = {r[0]: r[1] for r in rows.groupBy(lang_col).count().limit(MAX_LANGUAGES + 1).collect()}
    if len(counts) > MAX_LANGUAGES:
        raise ValueError(f"over {MAX_LANGUAGES} languages")
    if not counts:
        return {}
    place = F.pmod(F.xxhash64(F.col(id_col)), F.lit(1 << 30))
    share = F.element_at(F.create_map(*[F.lit(v) for k, n in counts.items() for v in (k, int((1 << 30) * min(1.0, train_rows / n)))]), F.col(lang_col))
    chosen = rows.where(place < share).select(F.col(lang_col).alias("lang"), place.alias("place"), F.col(text_col).alias("text")).collect()
    out: dict[str, list[str]] = {}
    left: dict[str, int] = {}
    for r in sorted(chosen, key=lambda r: (r.place, r.text)):
        if len(r.text) < left.get(r.lang, train_chars):
            out.setdefault(r.lang, []).append(r.text)
            left[r.lang] = left.get(r.lang, train_chars) - len(r.text) - 1
    return {k: "\n".join(v) for k, v in out.items()}


def identify(docs: DataFrame, labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", train_rows: int = TRAIN_ROWS, train_chars: int = TRAIN_CHARS) -> DataFrame:
    """id, lang_pred, score (0 to 1) of each row of docs; learnt from labelled."""
    common.ship(docs.sparkSession)
    training = sample(labelled, id_col, text_col, lang_col, train_rows, train_chars)
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = model(training)
        for batch in batches:
            for i in range(0, batch.num_rows, 1000):
                part = batch.slice(i, 1000)
                names, scores = own.predict(pc.fill_null(part.column(1), "").to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=[id_col, "lang_pred", "score"])

    return docs.select(docs[id_col], docs[text_col]).mapInArrow(run, schema)


def fold(id_col: str, n: int) -> Column:
    return F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(n))
