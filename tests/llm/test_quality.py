import re
from collections import Counter

import numpy as np
import sentencepiece

from treefacts.llm import quality


def brute(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    windows = Counter(zip(words, words[1:], words[2:]))
    hit = set()
    for i in range(len(words) - 2):
        if windows[tuple(words[i : i + 3])] > 1:
            hit |= {i, i + 1, i + 2}
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), dup, len(hit)


def test_counts_match_brute_force(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    model = sentencepiece.SentencePieceProcessor(model_file=quality.vocabulary_path())
    rows = quality.measure(docs).collect()
    assert len(rows) == len(texts)
    for r in rows:
        want = brute(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0])
        assert not (r.base_failed and r.kept)
        ids = [i for w in (texts[r.doc_id] or "").split() for i in model.encode(w)]
        assert r.n_tokens == len(ids)
        p = np.array(list(Counter(ids).values())) / max(1, len(ids))
        assert abs(r.token_entropy + (p * np.log2(p)).sum()) < 1e-6


def test_odd_rows(odd, none):
    rows = quality.measure(odd).collect()
    assert len(rows) == 11
    assert all(not r.kept for r in rows if r.n_words == 0)
    assert quality.measure(none).count() == 0
    assert quality.keep(odd).columns == odd.columns


def test_bands_reject_other_scripts_of_bytes(spark):
    df = spark.createDataFrame([(1, " ".join(["𐎠𐎡𐎢𐎣" + chr(0x103A0 + i % 30) for i in range(80)]), None)], "doc_id long, text string, lang string")
    r = quality.measure(df).first()
    assert r.byte_fallback_share > 0.5 and not r.kept


def test_many_short_texts_in_one_batch():
    texts = ["", "alpha", "alpha beta beta"] * 30_000
    n, n_bytes, entropy = quality.token_measures(texts, quality.encoder(quality.vocabulary_path()))
    few = quality.token_measures(texts[:3], quality.encoder(quality.vocabulary_path()))
    for got, want in zip((n, n_bytes, entropy), few, strict=True):
        assert np.allclose(got.reshape(-1, 3), want)
    assert quality.token_measures([""], quality.encoder(quality.vocabulary_path()))[0].tolist() == [0]
