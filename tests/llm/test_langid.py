import random

from treefacts.llm import langid


def brute_phrases(text, training, classes):
    """Greedy longest matches over the whole text."""
    text, base = ("".join(map(chr, classes.codes(x).tolist())) for x in (text, training))
    n, start, at = 0, 0, 0
    while at < len(text):
        if text[start : at + 1] in base:
            at += 1
        elif at == start:  # a symbol that the training text doesn't have
            n, at, start = n + 1, at + 1, at + 1
        else:
            n, start = n + 1, at
            if text[at] not in base:
                at, start = at + 1, at + 1
    return n


def test_phrases_are_longest_matches():
    training = {"x": "the cat sat on the mat and the dog ate it all", "y": "der hund und die katze assen alles auf"}
    model = langid.Model(training)
    rng = random.Random(1)
    made = " ".join(rng.choice(["the", "dog", "sat", "hund", "katze", "q", "allesauf", "mat"]) for _ in range(700))
    repeated = "the cat sat on the mat and the dog ate it all " * 30  # matches run over the ends of segments
    texts = ["the dog sat on it", "die katze", "", "zzz the zz", "hund " * 200, made, repeated, "x" + repeated, "a" * 1000]
    found, _, _ = model.phrases(texts)
    for i, lang in enumerate(model.languages):
        assert found[i].tolist() == [brute_phrases(t, training[lang], model.classes) for t in texts]


def test_parts_of_segments_are_parsed_as_whole_texts(monkeypatch):
    monkeypatch.setattr(langid, "SEGMENT", 3)
    test_phrases_are_longest_matches()


def test_predictions_match_brute_force():
    training = {"en": "the cat sat on the mat and the dog ate it all", "de": "der hund und die katze assen alles auf", "ja": "\u3053\u308c\u306f\u732b\u3067\u3059\u3002\u732b\u306f\u5c0f\u3055\u3044"}
    model = langid.Model(training)
    texts = ["the dog and the mat", "die katze und der hund", "\u732b\u3067\u3059", "\U00030001\U00030002", "12 !"]
    names, scores = model.predict(texts)
    assert names[:3] == ["en", "de", "ja"] and names[3] != "und" and names[4] == "und"
    for t, name in zip(texts[:3], names, strict=False):
        bits = {x: (brute_phrases(t, training[x], model.classes) + 1) * b for x, b in zip(model.languages, model.bits, strict=True)}
        assert name == min(bits, key=bits.get)


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    fold = langid.fold("doc_id", 5)
    got = {r.doc_id: r for r in langid.identify(docs, docs.where(fold != 0)).collect()}
    test = docs.where(fold == 0).collect()
    assert sum(got[r.doc_id].lang_pred == r.lang for r in test) / len(test) > 0.97
    assert all(0 <= r.score <= 1 for r in got.values())


def test_odd_rows(odd, none):
    rows = langid.identify(odd, odd).collect()
    assert len(rows) == 11
    assert {r.lang_pred for r in rows if r.doc_id in (3, 4, 7, 9)} == {"und"}
    assert langid.identify(none, none).count() == 0
    assert {r.lang_pred for r in langid.identify(odd, none).collect()} == {"und"}
