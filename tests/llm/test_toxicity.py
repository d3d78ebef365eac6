import math
import random
from collections import Counter

import numpy as np

from treefacts.llm import langid, toxicity


def test_nearest_are_exact():
    rng = random.Random(2)
    vocabulary = {f"t{i}": 1 + rng.random() for i in range(30)}
    examples = [(i, rng.randint(0, 1), dict(Counter(f"t{min(29, int(rng.expovariate(0.2)))}" for _ in range(rng.randint(0, 6))))) for i in range(900)]
    index = toxicity.Index(vocabulary, examples)
    full = [e for e in examples if e[2]]
    vectors = [dict(v) for v in index.vectors]
    assert len(vectors) == len(full) and all(math.isclose(sum(w * w for w in v.values()), 1) for v in vectors)
    for _ in range(40):
        q = index.vector(dict(Counter(rng.randrange(30) for _ in range(rng.randint(1, 6)))))
        scores = sorted((-round(sum(w * v.get(t, 0) for t, w in q), 12), i) for i, v in enumerate(vectors))
        want = [(-s, i) for s, i in scores if s < 0][: toxicity.NEAREST]
        got = index.nearest(q)
        assert len(got) == len(want)
        assert all(math.isclose(a[0], b[0], abs_tol=1e-9) for a, b in zip(got, want))


def test_held_out(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    fold = langid.fold("doc_id", 3)
    found = toxicity.score(docs.join(labels.select("doc_id"), "doc_id"), labels.where(fold != 1))
    rows = found.join(labels.where(fold == 1), "doc_id").join(docs.select("doc_id", "lang"), "doc_id").collect()
    for lang in ("en", "de", "fr", "es"):
        own = [r for r in rows if r.lang == lang]
        hit, marked, toxic = sum(r.score >= 0.7 and r.toxic == 1 for r in own), sum(r.score >= 0.7 for r in own), sum(r.toxic for r in own)
        assert hit >= 0.8 * toxic and hit >= 0.85 * marked, lang
    assert sum(r.score >= 0.7 and r.toxic == 1 for r in rows) >= 0.9 * sum(r.toxic for r in rows)
    assert all(0 <= r.score <= 1 for r in rows)
    # calibrated: the mean score is near the share of label 1, over all and among the doubtful
    assert abs(sum(r.score for r in rows) / len(rows) - sum(r.toxic for r in rows) / len(rows)) < 0.03


def test_weights_and_scores_match_brute_force(spark):
    rng = random.Random(4)
    texts = [(i, " ".join([rng.choice(["rotten", "rottenly"])] * (i % 5 == 0) + [f"w{chr(97 + rng.randrange(20))}x" for _ in range(8)]), int(i % 5 == 0)) for i in range(200)]
    df = spark.createDataFrame(texts, "doc_id long, text string, toxic int")
    weight, examples = toxicity.fit(df, "doc_id", "text", "toxic")
    n, rate = len(texts), (sum(y for _, _, y in texts) + 0.5) / (len(texts) + 1)
    seen = {}
    for _, text, y in texts:
        for t in set(toxicity.terms(text)):
            a = seen.setdefault(t, [0, 0])
            a[0], a[1] = a[0] + 1, a[1] + y
    chance, want = math.log(len(seen)) + toxicity.SURE, {}
    for t, (df_, a) in seen.items():
        p = a / df_
        evidence = df_ * ((p * math.log(p / rate) if p else 0) + ((1 - p) * math.log((1 - p) / (1 - rate)) if p < 1 else 0))
        if evidence > chance:
            want[t] = (math.log((1 + n) / (1 + df_)) + 1) * (1 - chance / evidence) * abs(p - rate) / max(rate, 1 - rate)
    assert set(weight) == set(want) and "rot*1" in want and all(math.isclose(weight[t], want[t], rel_tol=1e-6) for t in want)
    assert len(examples) == n


def test_counts_by_cache_are_those_of_terms():
    text = "rotten rottenly rotting apple apple rot"
    vocabulary = {"rot*1": 1.0, "rot*3": 2.0, "rot*4": 1.0, "apple": 1.0, "rotte*2": 1.0}
    index = toxicity.Index(vocabulary, [(1, 1, toxicity.terms(text)), (2, 0, toxicity.terms("pear"))])
    for _ in range(2):
        assert {t: n for t, n in toxicity.terms(text).items() if t in vocabulary} == {t: index.counts(text)[i] for t, i in index.place.items() if index.counts(text)[i]}


def test_isotonic():
    x, y = toxicity.isotonic(np.array([0.1, 0.2, 0.3, 0.9]), np.array([0.0, 1.0, 0.0, 1.0]))
    assert list(x) == [0.1, 0.25, 0.9] and all(np.diff(y) > 0)


def test_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(1, 1), (3, 0), (None, 1), (5, None)], "doc_id long, toxic int")
    assert toxicity.score(odd, labels).count() == 11
    assert toxicity.score(none, labels).count() == 0
    assert {r.score for r in toxicity.score(odd, labels.limit(0)).collect()} == {0.0}
