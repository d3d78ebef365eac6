import itertools
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from treefacts.llm import common, pieces, tokens, wavelet


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 600), max_size=1200))
def test_wavelet_matrix(ids):
    m = wavelet.WaveletMatrix.build(np.array(ids, np.uint16), 10)
    assert m.decode().tolist() == ids
    for i in range(0, len(ids), 97):
        assert m.access(i) == ids[i]
    for t in set(ids[:5]) | {1, 1023, 5000}:
        assert m.count(t) == ids.count(t)
        assert m.count(t, 3, 50) == ids[3:50].count(t)
        assert list(m.locate(t)) == [i for i, x in enumerate(ids) if x == t]
    with pytest.raises(IndexError):
        m.access(len(ids))


def test_blocks_round_trip():
    ids = np.arange(3000) % 50_000
    raw = wavelet.to_bytes(np.array([7, -1]), np.array([1000, 2000]), ids, 16) * 2
    shards = list(wavelet.from_bytes(raw))
    assert len(shards) == 2 and all((s.matrix.decode() == ids).all() and s.doc_ids.tolist() == [7, -1] for s in shards)
    with pytest.raises(ValueError):
        list(wavelet.from_bytes(raw[:-1] + b"x"))


def test_files_hold_what_the_tokenizer_says(spark, tiny):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    encode, start, want = Tokenizer.from_file(tokens.tokenizer_path()), 0, {}
    for r in docs.orderBy("doc_id").collect():
        ids = [*encode.encode(r.text or "", add_special_tokens=False).ids, tokens.END_ID]
        want[r.doc_id] = (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    got = tokens.round_trip(docs, [F.col("doc_id")], n_files=3).collect()
    assert {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in got} == want


@pytest.mark.parametrize("text", ["naïve café – “quoted” 12½ x² don't  \n\n  end \t tabs", "'s 're A'll it's", "日本語 text", " lead", "trail  ", "€5…•\x00\x7f", "a\x85b\xa0c", "<|endoftext|>"])
def test_pieces_equal_whole_texts(text):
    e = tokens.encoder(tokens.tokenizer_path())
    assert e.encode(text) == e.whole(text)


def test_special_tokens_are_as_the_library_gives_them():
    from tokenizers import Tokenizer

    path = tokens.tokenizer_path()
    plain, own = Tokenizer.from_file(path), tokens.encoder(path)
    for text in ("x <|endoftext|> y", "<|endoftext|><|endoftext|>", "é <|endoftext|>", "a <|endof text|>"):
        assert np.frombuffer(own.encode(text), np.uint16).tolist() == plain.encode(text, add_special_tokens=False).ids


def test_number_of_files_is_bounded():
    assert tokens.files_for(0) == 1 and tokens.files_for(80_000_000) == 10
    assert tokens.files_for(10**14) < 500_000


def test_odd_rows(odd, none):
    rows = tokens.round_trip(odd, [F.col("doc_id"), F.xxhash64("text")]).orderBy("start").collect()
    assert [r.doc_id for r in rows] == [None, 1, 1, 2, 3, 4, 5, 6, 7, 8, 9]
    assert [r.n_tokens for r in rows if r.doc_id in (3, 4, 9)] == [1, 1, 1]
    assert tokens.round_trip(none, [F.col("doc_id")]).count() == 0
    assert common.shared_dir(odd.sparkSession)


def test_words_are_split_first():
    """Most pieces are words: no other alternative is tried before them, and the pieces are those of any order."""
    assert tokens.PIECES.pattern.startswith(f" ?[{tokens.LETTERS}]+|")
    text = "It's 'd we'll 'they 'sound ''t don't 12's  'm\n\n'Ünï've (re)'re "
    assert "".join(tokens.PIECES.findall(text)) == text
    made = tokens.encoder(tokens.tokenizer_path())
    assert made.encode(text) == made.whole(text)


def test_pieces_met_before_are_not_encoded_again():
    """A worker meets about 500,000 different pieces in 40 MB of text: they have to be known when they come again."""
    made, calls = tokens.Pieces(tokens.tokenizer_path()), []
    merge = made.merge
    made.merge = lambda piece: calls.append(piece) or merge(piece)
    text = " ".join(map("".join, itertools.islice(itertools.product("abcdefghijklmnopqrstuvwxyz", repeat=4), 160_000)))
    assert made.encode(text) == made.encode(text)
    assert len(calls) == len(set(calls))


PLAIN_TEXTS = st.lists(st.text("aZéß7½ \t\n'stmdrevl.,–€×÷", max_size=40) | st.sampled_from(["'ll", " 's", "\n're 've", "''d", "x" * 80, " " * 30, "abcdefghijklmnop qrstuvwxyzabcdefgh"]), min_size=1, max_size=8)


@settings(max_examples=300, deadline=None)
@given(PLAIN_TEXTS)
def test_split_finds_the_pieces_of_the_pattern(texts):
    texts = [t.replace("½", "") for t in texts]
    raw = "".join(t + chr(pieces.MARK) for t in texts).encode()
    begins = [*pieces.split(raw).tolist(), len(raw)]
    assert [raw[a:b].decode() for a, b in itertools.pairwise(begins)] == [p for t in texts for p in [*tokens.PIECES.findall(t), chr(pieces.MARK)]]


@settings(max_examples=150, deadline=None)
@given(PLAIN_TEXTS)
def test_texts_encoded_together_with_little_memory(texts):
    """Slices of four pieces, a table that is cleared all the time, plain texts and others."""
    made = tokens.Pieces.__new__(tokens.Pieces)
    made.__dict__ |= tokens.encoder(tokens.tokenizer_path()).__dict__
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(pieces, "SLICE", 4)
        patch.setattr(pieces, "MOST", 16)
        patch.setattr(pieces, "MOST_LONG", 2)
        made.memory = pieces.Memory(made.of_pieces, tokens.END_ID)
        for _ in range(2):
            ids, counts = made.encode_all(texts)
            assert ids.tolist() == [i for t in texts for i in [*made.tokenizer.encode(t, add_special_tokens=False).ids, tokens.END_ID]]
            assert counts.sum() == len(ids) and len(counts) == len(texts)


def test_texts_are_taken_some_at_a_time(monkeypatch):
    monkeypatch.setattr(tokens, "CHUNK_CHARS", 5)
    found = list(tokens.some_texts(pa.array(["abc", None, "de", "", "abcdefgh", "x"])))
    assert found == [(0, ["abc", "", "de"]), (3, ["", "abcdefgh"]), (5, ["x"])]
    assert not list(tokens.some_texts(pa.array([], pa.string())))
