"""Quality rules by tokeniser fertility.

A public vocabulary with byte fallback measures each whole text: characters per token, the share of tokens that are
raw bytes, and the entropy of its tokens in bits. A text passes if all three lie in the band of its language, or of its
main script where the language has no band. Basic rules (word count, repeated word windows) come first.

Null or empty text: no words, so it fails the basic rules. Null language: the script's band. Repeated rows are measured
each on its own. Very long texts are measured whole; only one text and its tokens are held at a time.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from treefacts.llm import textcore

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
#: What counts as a character of a token: ASCII letters and digits, and the first byte of each code point beyond ASCII.
LETTERS = np.zeros(256, bool)
LETTERS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(0xC0, 256)]] = True
CACHE_WORDS = 100_000  #: distinct words that a worker keeps encoded


@dataclass(frozen=True)
class Band:
    """Bounds of a measure that passes; entropy counts only from min_tokens tokens on, as short texts have little."""

    chars_low: float
    chars_high: float
    fallback_high: float
    entropy_low: float
    entropy_high: float = 16.0
    min_tokens: int = 100


#: Bands per language, then per script, then for all else.
LANGUAGE_BANDS = {
    "en": Band(1.80, 6.5, 0.02, 4.0),
    "de": Band(1.90, 6.5, 0.02, 4.0),
    "fr": Band(1.65, 6.5, 0.02, 4.0),
    "es": Band(1.70, 6.5, 0.02, 4.0),
}
SCRIPT_BANDS = {
    "latin": Band(1.40, 7.0, 0.05, 4.0),
    "cyrillic": Band(1.00, 7.0, 0.10, 4.0),
    "greek": Band(0.50, 6.0, 0.60, 3.5),
    "han": Band(0.25, 3.0, 0.80, 3.5),
    "kana": Band(0.30, 3.0, 0.70, 3.5),
    "hangul": Band(0.25, 3.0, 0.85, 3.0),
    "arabic": Band(0.50, 5.0, 0.60, 3.5),
    "hebrew": Band(0.50, 5.0, 0.60, 3.5),
    "devanagari": Band(0.40, 5.0, 0.70, 3.5),
}
OTHER_BAND = Band(0.20, 8.0, 0.90, 3.0)
#: Where scripts begin and end (code points, end excluded).
SCRIPT_RANGES = {
    "latin": (0x41, 0x250), "greek": (0x370, 0x400), "cyrillic": (0x400, 0x530), "hebrew": (0x590, 0x600),
    "arabic": (0x600, 0x780), "devanagari": (0x900, 0x980), "kana": (0x3040, 0x3100), "han": (0x4E00, 0xA000),
    "hangul": (0xAC00, 0xD7B0),
}

MEASURES = T.StructType([
    T.StructField("n_words", T.LongType()), T.StructField("word_chars", T.LongType()), T.StructField("n_symbols", T.LongType()),
    T.StructField("n_dup_lines", T.LongType()), T.StructField("n_repeat_words", T.LongType()), T.StructField("base_failed", T.BooleanType()),
    T.StructField("kept", T.BooleanType()), T.StructField("n_tokens", T.LongType()), T.StructField("chars_per_token", T.DoubleType()),
    T.StructField("byte_fallback_share", T.DoubleType()), T.StructField("token_entropy", T.DoubleType()), T.StructField("band", T.StringType()),
])


def vocabulary_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class PieceWords(dict):
    """Token ids of a word as uint16 bytes, encoded when first met. Merges of the vocabulary don't cross white space,
    so the words of a text have the tokens of the text."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.is_byte = np.array([self.model.is_byte(i) for i in range(self.model.vocab_size())])

    def __missing__(self, word: str) -> bytes:
        if len(self) >= CACHE_WORDS:
            self.clear()
        ids = np.array(self.model.encode(word), np.uint16).tobytes()
        if len(word) < 64:
            self[word] = ids
        return ids


_encoders: dict[str, PieceWords] = {}


def encoder(path: str) -> PieceWords:
    if path not in _encoders:
        _encoders[path] = PieceWords(path)
    return _encoders[path]


def basic_counts(block: textcore.Block) -> dict[str, np.ndarray]:
    """Counts of each text of a block: words, code points in words, symbols, repeated lines, words in repeated windows."""
    starts, ends, text = block.words()
    n_words = np.bincount(text, minlength=block.n)
    data = block.data
    in_word = ~textcore.WHITE[data]
    prefix = block.prefix(data)
    word_chars = block.count(in_word & ((data & 0xC0) != 0x80))
    n_symbols = block.count(SYMBOLS[data])
    letters = block.count(LETTERS[data])

    line_start, line_end, line_text = block.runs(data != 10)
    words_before = np.searchsorted(starts, line_start), np.searchsorted(starts, line_end)
    full = words_before[1] > words_before[0]
    lines = block.prints(prefix, line_start[full], line_end[full])
    n_dup_lines = np.zeros(block.n, np.int64)
    if len(lines):
        key = textcore.mix(lines ^ (line_text[full].astype(np.uint64) * np.uint64(0xA0761D6478BD642F)))
        distinct = np.unique(key, return_index=True)[1]
        n_dup_lines = np.bincount(line_text[full], minlength=block.n) - np.bincount(line_text[full][distinct], minlength=block.n)

    repeated = np.zeros(len(starts), bool)
    if len(starts) > 2:
        words = block.prints(prefix, starts, ends)
        one = text[:-2] == text[2:]
        at = np.flatnonzero(one)
        m, c1, c2 = textcore.mix, np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3)
        window = m(m(m(words[at] + text[at].astype(np.uint64) * c2) * c1 + words[at + 1]) * c1 + words[at + 2])
        order = np.argsort(window)
        sorted_ = window[order]
        same = sorted_[1:] == sorted_[:-1]
        twice = np.zeros(len(window), bool)
        twice[1:] |= same
        twice[:-1] |= same
        hit = at[order[twice]]
        for step in range(3):
            repeated[hit + step] = True
    n_repeat = np.bincount(text[repeated], minlength=block.n)
    return {"n_words": n_words, "word_chars": word_chars, "n_symbols": n_symbols, "n_dup_lines": n_dup_lines, "n_repeat_words": n_repeat, "letters": letters}


def main_script(text: str) -> str:
    """The script of most of the letters; latin where all is ASCII."""
    if text.isascii():
        return "latin"
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    best, most = "other", 0
    for name, (low, high) in SCRIPT_RANGES.items():
        n = int(np.count_nonzero((points >= low) & (points < high)))
        if n > most:
            best, most = name, n
    return best


def token_measures(texts: list[str], words: PieceWords) -> tuple[np.ndarray, ...]:
    """Tokens, byte tokens, and entropy of tokens of each text."""
    pieces = [b"".join(map(words.__getitem__, x.split())) for x in texts]
    n = np.array([len(p) // 2 for p in pieces], np.int64)
    ids = np.frombuffer(b"".join(pieces), np.uint16)
    wide = np.uint32 if len(texts) <= 1 << 16 else np.uint64
    owner = np.repeat(np.arange(len(texts), dtype=wide), n)
    n_bytes = np.bincount(owner[words.is_byte[ids]], minlength=len(texts)) if len(ids) else np.zeros(len(texts), np.int64)
    key = np.sort(owner << wide(16) | ids)
    edges = np.concatenate(([0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)])) if len(key) else np.zeros(1, np.int64)
    counts = np.diff(edges).astype(np.float64)
    who = (key[edges[:-1]] >> wide(16)).astype(np.int64)
    logs = np.bincount(who, counts * np.log2(np.maximum(counts, 1)), len(texts)) if len(key) else np.zeros(len(texts))
    safe = np.maximum(n, 1)
    return n, n_bytes, np.log2(safe) - logs / safe


def measures(texts: pa.Array, langs: list, path: str, min_words: int, max_repeat_percent: int) -> dict[str, list]:
    words = encoder(path)
    out: dict[str, list] = {f.name: [] for f in MEASURES}
    for block in textcore.blocks(texts):
        counts = basic_counts(block)
        own = [x or "" for x in texts.slice(block.first, block.n).to_pylist()]
        n, n_bytes, entropy = token_measures(own, words)
        failed = (counts["n_words"] < min_words) | (100 * counts["n_repeat_words"] > max_repeat_percent * counts["n_words"])
        per_token = counts.pop("letters") / np.maximum(n, 1)
        share = n_bytes / np.maximum(n, 1)
        for i, text in enumerate(own):
            lang = langs[block.first + i]
            band, name = (LANGUAGE_BANDS.get(lang), lang) if isinstance(lang, str) else (None, None)
            if band is None:
                name = main_script(text)
                band = SCRIPT_BANDS.get(name, OTHER_BAND)
            long = n[i] >= band.min_tokens
            good = band.chars_low <= per_token[i] <= band.chars_high and share[i] <= band.fallback_high and (not long or band.entropy_low <= entropy[i] <= band.entropy_high)
            out["kept"].append(bool(good and not failed[i]))
            out["band"].append(name)
        for k, v in {**counts, "n_tokens": n, "base_failed": failed, "chars_per_token": per_token, "byte_fallback_share": share, "token_entropy": entropy}.items():
            out[k].extend(v.tolist())
    return out


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = "lang", vocabulary: str | None = None, min_words: int = 50, max_repeat_percent: int = 50) -> DataFrame:
    """One row per row of docs: its id and MEASURES. Other columns of docs are ignored, whatever their names."""
    path = vocabulary or vocabulary_path()
    source = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text"), *([docs[lang_col].alias("lang")] if lang_col else []))
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *MEASURES.fields])
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        for batch in batches:
            langs = batch.column(2).to_pylist() if batch.num_columns > 2 else [None] * batch.num_rows
            found = measures(batch.column(1), langs, path, min_words, max_repeat_percent)
            kinds = {"base_failed": pa.bool_(), "kept": pa.bool_(), "band": pa.string(), "chars_per_token": pa.float64(), "byte_fallback_share": pa.float64(), "token_entropy": pa.float64()}
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v, kinds.get(k, pa.int64())) for k, v in found.items())], names=[id_col, *found])

    return source.mapInArrow(run, schema)


def keep(docs: DataFrame, text_col: str = "text", lang_col: str | None = "lang", vocabulary: str | None = None, min_words: int = 50, max_repeat_percent: int = 50) -> DataFrame:
    """The rows of docs that pass, all columns as they were."""
    path = vocabulary or vocabulary_path()
    at_text, at_lang = docs.columns.index(text_col), docs.columns.index(lang_col) if lang_col in docs.columns else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs = batch.column(at_lang).to_pylist() if at_lang is not None else [None] * batch.num_rows
            found = measures(batch.column(at_text), langs, path, min_words, max_repeat_percent)
            yield batch.filter(pa.array(found["kept"], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
