import re
from collections import defaultdict

from treefacts.llm import lines


def brute(rows, min_lines=3, min_words=50):
    docs = [(d, [y.strip(" \t\r\x0b\x0c") for y in (t or "").split("\n")]) for d, t in rows]
    places, out = defaultdict(list), {}
    for k, (_, own) in enumerate(docs):
        for i, y in enumerate(own):
            places[y].append((k, i))
    for k, (d, own) in enumerate(docs):
        gone = set()
        for i, y in enumerate(own):
            best = 0
            for k2, j in places[y] if y else []:
                n, other = 0, docs[k2][1]
                while (k2, j) < (k, i) and i + n < len(own) and j + n < len(other) and own[i + n] and own[i + n] == other[j + n]:
                    n += 1
                best = max(best, n)
            if best and (best >= min_lines or sum(len(re.findall(lines.WORD, x)) for x in own[i : i + best]) >= min_words):
                gone |= set(range(i, i + best))
        out[d] = len(gone)
    return out


def test_runs_match_brute_force(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.orderBy("doc_id").collect()]
    assert {r.doc_id: r.n_removed for r in lines.dedup(docs).collect()} == brute(rows)


def test_small_runs(spark):
    rows = [(1, "a\nb\nc\nd"), (2, "x\nb\nc\nd\ny"), (3, "b\nc"), (4, "a\nb\nc\na\nb\nc"), (5, "q\nq\nq\nq")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in lines.dedup(df).collect()}
    assert got == {1: "a\nb\nc\nd", 2: "x\ny", 3: "b\nc", 4: "", 5: "q"}
    assert {r.doc_id: r.n_removed for r in lines.dedup(df).collect()} == brute(rows)


def test_suffix_array_orders_suffixes(spark):
    rows = [(1, "a\nb\na\nb\na\nb\nc"), (2, "b\na\nb\nc")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = lines.suffix_array(df).collect()
    text = {d: t.split("\n") for d, t in rows}
    for x in got:
        for y in got:
            same = 0
            a, b = text[x.doc_id][x.line :], text[y.doc_id][y.line :]
            while same < min(len(a), len(b)) and a[same] == b[same]:
                same += 1
            for k, (p, q) in enumerate(zip(x.ranks, y.ranks)):
                assert (p == q) == (same >= 1 << k)


def test_odd_rows(odd, none):
    rows = lines.dedup(odd).collect()
    assert len(rows) == 11
    assert all(r.text is None and r.n_lines == 0 for r in rows if r.doc_id in (3, 9))
    assert lines.dedup(none).count() == 0


def test_runs_go_across_blank_lines(spark):
    words = lambda k: " ".join(f"w{k}x{i}" for i in range(30))
    notice = [words(k) for k in range(4)]
    rows = [
        (1, "\n\n".join(["own 1", *notice])), (2, "\n \t\r\n\n".join([*notice, "own 2"])), (3, " \r\n" + "\n".join(notice[:2]) + "\n\n"), (4, "own 4\n\n" + notice[0]),
        (5, "\n\na\n\nb\n\n\nc\n"), (6, "a\r\n\r\nb\r\n\r\nc"), (7, "a\n\nb\n\nd"), (8, "\n \n"),
    ]
    got = {r.doc_id: r for r in lines.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {d: r.n_removed for d, r in got.items()} == {1: 0, 2: 4, 3: 2, 4: 0, 5: 0, 6: 3, 7: 0, 8: 0}
    assert all(got[d].text == dict(rows)[d] for d in (1, 4, 5, 7, 8))
    assert got[2].text.split() == ["own", "2"] and not got[3].text.strip() and not got[6].text.strip()
    found = lines.suffix_array(spark.createDataFrame(rows[4:7], "doc_id long, text string")).collect()
    assert {(r.doc_id, r.line) for r in found} == {(5, 2), (5, 4), (5, 7), (6, 0), (6, 2), (6, 4), (7, 0), (7, 2)}
