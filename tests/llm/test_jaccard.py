import random
import re
from collections import Counter, defaultdict

import pytest

from treefacts.llm import jaccard

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()


def brute(texts, k, percent):
    sets = {d: shingles(t, k) for d, t in texts.items()}
    inverse, parent = defaultdict(list), {d: d for d in texts}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for d, s in sets.items():
        for g in s:
            inverse[g].append(d)
    for d, s in sets.items():
        shared = Counter(o for g in s for o in inverse[g] if o > d)
        for o, n in shared.items():
            if 100 * n >= percent * (len(s) + len(sets[o]) - n):
                a, b = find(d), find(o)
                parent[max(a, b)] = min(a, b)
    return {d: (len(sets[d]), find(d)) for d in texts}


def random_texts(seed, n=160):
    rng = random.Random(seed)
    word = lambda: f"w{int(rng.paretovariate(0.6)) % 3000}"
    passage = " ".join(f"shared{i}" for i in range(12))
    texts = {}
    for d in range(n):
        kind = rng.random()
        if kind < 0.5 and texts:
            words = texts[rng.randrange(min(len(texts), 8))].split()
            for _ in range(rng.randint(0, 4)):
                words[rng.randrange(len(words))] = word()
            texts[d] = " ".join(words)
        else:
            texts[d] = " ".join(word() for _ in range(rng.choice([1, 2, 5, 40, 60, 120])))
        if kind > 0.8:
            texts[d] += " " + passage
    return texts


@pytest.mark.parametrize(("seed", "k", "percent"), [(1, 3, 90), (2, 5, 80)])
def test_classes_match_brute_force(spark, monkeypatch, seed, k, percent):
    monkeypatch.setattr(jaccard, "RARE", 4)  # so that small data have frequent tokens
    texts = random_texts(seed)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.join(df, words=k, percent=percent).collect()}
    assert got == brute(texts, k, percent)


def test_last_round_alone_is_exact(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "RARE", 3)
    monkeypatch.setattr(jaccard, "SPREAD_ROUNDS", 0)
    monkeypatch.setattr(jaccard.Join, "pivots", lambda self, rows, highest: rows.select(rows.id.alias("a"), rows.id.alias("b")).limit(0))
    texts = random_texts(5, 100)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.join(df, words=3, percent=90).collect()}
    assert got == brute(texts, 3, 90)


def test_odd_rows(odd, none):
    rows = jaccard.join(odd, words=3, percent=90).collect()
    assert len(rows) == 11
    by_id = {r.doc_id: r for r in rows}
    assert by_id[2].component_id == 1 and by_id[3].component_id == 3 and by_id[None].component_id is None and by_id[4].n_shingles == 0
    assert jaccard.join(none).count() == 0
    kept = jaccard.keep_one(odd, words=3, percent=90)
    assert kept.columns == odd.columns
    assert sorted((r.doc_id for r in kept.collect()), key=str) == [1, 3, 4, 5, 6, 7, 8, 9, None]


def test_rows_of_one_id_with_unrelated_texts_stay(spark):
    rows = [(1, "alpha beta gamma delta epsilon zeta"), (1, "quite another text of other words here"), (2, "alpha beta gamma delta epsilon zeta"), (1, "alpha beta gamma delta epsilon zeta"), (None, "x"), (3, ""), (3, "")]
    kept = sorted(((r.doc_id, r.text) for r in jaccard.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert kept == sorted([(1, rows[0][1]), (1, rows[1][1]), (None, "x"), (3, ""), (3, "")], key=str)


def test_large_family_of_near_copies(spark):
    rng = random.Random(5)
    base = [f"base{i}" for i in range(80)]
    texts = {}
    for d in range(3000):
        words = list(base)
        words[rng.randrange(80)] = f"own{d}"
        texts[d] = " ".join(words)
    texts[3000] = " ".join(f"far{i}" for i in range(80))
    df = spark.createDataFrame([(d, t) for d, t in texts.items()], "doc_id long, text string")
    got = {r.component_id for r in jaccard.join(df).collect()}
    assert got == {0, 3000}


def test_ids_that_are_no_numbers(spark):
    df = spark.createDataFrame([("b", "one two three four five six"), ("a", "one two three four five six"), ("c", "other")], "doc_id string, text string")
    assert {r.doc_id: r.component_id for r in jaccard.join(df).collect()} == {"a": "a", "b": "a", "c": "c"}


def test_sets_of_pairs_are_held_in_bounded_rounds(spark, monkeypatch):
    held = []
    both_sets = jaccard.Join.both_sets
    monkeypatch.setattr(jaccard, "RARE", 4)
    monkeypatch.setattr(jaccard, "ROUND_BYTES", 1_000)
    monkeypatch.setattr(jaccard, "ROUND_SHARE", 1 << 30)
    monkeypatch.setattr(jaccard, "BROADCAST_ROWS", 3)
    monkeypatch.setattr(jaccard.Join, "both_sets", lambda self, pairs, a, b: held.append(pairs.count()) or both_sets(self, pairs, a, b))
    texts = random_texts(7, 90)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.join(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), words=3, percent=90).collect()}
    assert got == brute(texts, 3, 90)
    assert len(held) > 8  # more rounds than there are calls


def test_many_ids_without_a_shuffle_of_texts(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "BROADCAST_ROWS", 100)
    docs = spark.range(3000).selectExpr("id", "cast(id as string) as text")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = jaccard.of_ids(docs, spark.range(0, 3000, 3))
        got = {r.id for r in found.collect()}
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert set(range(0, 3000, 3)) <= got and len(got) < 1100
    assert "SortMergeJoin" not in found._jdf.queryExecution().toString()


def test_unrelated_sets_of_a_frequent_token_make_no_pairs(spark, monkeypatch):
    """Documents that share a few frequent tokens and nothing else: no candidates among them, though they all lack what the pivot has."""
    monkeypatch.setattr(jaccard, "RARE", 4)
    monkeypatch.setattr(jaccard, "HOT_SHARE", 1.0)  # frequent tokens stand among the others
    seen = []
    monkeypatch.setattr(jaccard.Join, "pivots", lambda self, rows, highest: rows.select(rows.id.alias("a"), rows.id.alias("b")).limit(0))
    by_differences = jaccard.Join.by_differences
    monkeypatch.setattr(jaccard.Join, "by_differences", lambda self, rows: seen.append(by_differences(self, rows)) or seen[-1])
    texts = {d: " ".join([f"common{i}" for i in range(42)] + [f"own{d}x{i}" for i in range(60)]) for d in range(40)}
    texts[40] = texts[39].replace("own39x59", "other")
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.join(df, words=3, percent=90).collect()}
    assert got == brute(texts, 3, 90)
    assert {tuple(r) for r in seen[0].distinct().collect()} <= {(39, 40)}
