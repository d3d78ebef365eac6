import random

import numpy as np

from treefacts.llm import decontaminate


def edit_distance_anywhere(pattern, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(pattern, 1):
        new = [i]
        for j, d in enumerate(text, 1):
            new.append(min(row[j - 1] + (c != d), row[j] + 1, new[j - 1] + 1))
        row = new
    return min(row)


def brute(texts, items):
    out = set()
    for i, t in texts.items():
        for k, item in items.items():
            index = decontaminate.Index([(k, item)])
            whole = decontaminate.normal_text(t)
            if any(edit_distance_anywhere(w, whole) <= e for w, e in zip(index.windows, index.budget, strict=True)):
                out.add((i, k))
    return out


def test_edited_passages(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdeionst") for _ in range(rng.randint(2, 8)))
    text = lambda n: " ".join(word() for _ in range(n))
    items = {k: text(30) for k in range(6)}
    texts = {i: text(60) for i in range(12)}
    for i in range(6):
        passage = list(items[i])
        for _ in range(3 * (i % 4)):
            passage[rng.randrange(len(passage))] = rng.choice("xyz ")
        texts[i] = text(20) + "  " + "".join(passage).upper() + "\n" + text(20)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    bench = spark.createDataFrame(list(items.items()), "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, bench).collect()}
    assert got == brute(texts, items)
    assert len(got) >= 4
    assert {r.doc_id for r in decontaminate.keep_clean(docs, bench).collect()} == set(texts) - {i for i, _ in got}


def test_whole_items_are_found(spark, tiny):
    docs, bench = spark.read.parquet(f"{tiny}/documents.parquet"), spark.read.parquet(f"{tiny}/benchmark.parquet")
    items = {r.item_id: r.text for r in bench.collect()}
    want = {(r.doc_id, k) for r in docs.collect() for k, x in items.items() if r.text and x in r.text}
    assert want <= {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, bench).collect()}


def test_odd_rows(spark, odd, none, tiny):
    bench = spark.createDataFrame([(1, None), (2, ""), (3, "short"), (None, "a text without id")], "item_id long, text string")
    assert [r.doc_id for r in decontaminate.contaminated(odd, bench).collect()] == [None]
    assert decontaminate.contaminated(none, bench).count() == 0
    assert decontaminate.keep_clean(odd, bench).columns == odd.columns
    assert decontaminate.contaminated(odd, bench.limit(0)).count() == 0


def test_passages_at_every_offset():
    rng = random.Random(5)
    item = "".join(rng.choice("abcdefghijklmnopqrstuvw") for _ in range(300))
    other = lambda n: "".join(rng.choice("ABCDEFGHIJKLMNOPQ0123456789") for _ in range(n))
    index = decontaminate.Index([(1, item), (2, item[:60])])

    def found(passage):
        raw = f"{other(70)}{passage}{other(50)}".encode()
        rows = index.matches(*decontaminate.normal(np.frombuffer(raw, np.uint8), np.array([0, len(raw)])))
        return {r[1]: r[2] for r in rows}

    for s in range(201):
        assert found(item[s : s + 100])[1] == 0
        edited = list(item[s : s + 100])
        for k in range(8):
            edited[6 + 12 * k] = ("", "z", edited[6 + 12 * k] + "z")[(s + k) % 3]  # deleted, replaced, one more
        assert 0 < found("".join(edited))[1] <= 8
        assert 1 not in found(item[s : s + 80])


def test_few_shared_grams_at_once(monkeypatch):
    """Tiles, however small, find the same pairs and edits."""
    rng = random.Random(11)
    items = ["".join(rng.choice("ab") for _ in range(n)) for n in (600, 40, 500, 120)] + ["a" * 450]
    texts = ["".join(rng.choice("ab") for _ in range(700)), "b" * 30 + items[0][300:420] + items[2][5:200], "a" * 900, "", items[1] * 4]
    for k in (20, 60, 100):
        texts.append(items[0][300 : 300 + k] + "c" + items[0][301 + k : 500])
    raw = [np.frombuffer(t.encode(), np.uint8) for t in texts]
    places = np.cumsum([0, *(len(x) for x in raw)])
    index = decontaminate.Index(list(enumerate(items)))

    def found():
        return [r[:3] for r in index.matches(*decontaminate.normal(np.concatenate(raw), places))]

    want = found()
    assert {(1, 0), (1, 2), (2, 4), (4, 1), (5, 0), (6, 0), (7, 0)} <= {r[:2] for r in want}
    monkeypatch.setattr(decontaminate, "HITS", 10_000)
    assert found() == want


def test_long_text_of_one_letter():
    import tracemalloc

    raw = np.full(100_000, ord("a"), np.uint8)
    index = decontaminate.Index([(1, "a" * 400), (2, "ab" * 200)])
    tracemalloc.start()
    rows = index.matches(raw, np.array([0, len(raw)]))
    _, most = tracemalloc.get_traced_memory()
    tracemalloc.stop()
    assert [r[:3] for r in rows] == [(0, 1, 0)]
    assert most < 1_000_000_000
