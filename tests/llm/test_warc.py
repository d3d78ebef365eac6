import hashlib

import pytest

from treefacts.llm import common, warc


def test_round_trip(spark):
    big = "<p>" + "x y z é " * 20_000
    rows = [(5, "http://a/5", "<p>" + "same " * 40), (3, "http://a/3", "<p>" + "same " * 40), (9, "http://a/9", "<p>" + "same " * 40), (1, "http://a/1", "tiny"), (2, None, "tiny"), (4, "http://a/4", None), (6, "http://a/6", ""), (7, "http://a/7", big), (8, "http://a/8", big), (None, "http://a/0", "<p>" + "same " * 40), (10, "http://a/1 0", "\r\n\r\nWARC/1.1\r\n0\r\n\r\n" * 9), (11, "u", "z" * 300), (11, "u", "z" * 300)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder = common.new_folder(spark, "archives")
    warc.write(pages, folder, segment_bytes=1000, chunk_bytes=64)
    got = warc.read(spark, folder).withColumns({"page_id": warc.page_id_of("record_id"), "to": warc.page_id_of("refers_to")}).collect()
    assert len(got) == len(rows)
    first = {5: 3, 9: 3, 8: 7}
    for page_id, _, html in rows:
        r = next(x for x in got if x.page_id == page_id)
        payload = (html or "").encode()
        assert (r.payload_bytes, r.payload_digest) == (len(payload), hashlib.sha256(payload).hexdigest())
        assert (r.record_type, r.to) == (("revisit", first[page_id]) if page_id in first else ("response", None))
        assert page_id in first or bytes(r.payload) == payload


def test_damage_is_an_error():
    parts = list(warc.page_records(1, "u", b"a" * 5000, None, 1000, 64))
    content = b"".join(p + b"\n" for p in parts)
    assert len(list(warc.records(content))) == len(parts)
    with pytest.raises(ValueError):
        list(warc.records(content[:-30]))
    with pytest.raises(ValueError):
        warc.unchunked(b"5\r\nabc\r\n0\r\n\r\n")
    assert warc.unchunked(warc.chunked(b"abc" * 100, 7)) == b"abc" * 100


def test_missing_segment_is_an_error(spark):
    folder = common.new_folder(spark, "archives")
    parts = list(warc.page_records(1, "u", b"a" * 5000, None, 1000, 64))
    spark.createDataFrame([(bytearray(p),) for p in parts[:2] + parts[3:]], "value binary").selectExpr("cast(value as string) as value").coalesce(1).write.text(folder)
    with pytest.raises(Exception, match="segments"):
        warc.read(spark, folder).collect()


def test_no_pages(spark):
    assert warc.round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_query_equals_its_sql(spark, tiny):
    import duckdb

    from treefacts.llm import queries

    db = duckdb.connect()
    db.execute(f"create view pages as select * from '{tiny}/pages.parquet'")
    found = db.execute(queries.WARC_SQL)
    names = [d[0] for d in found.description]
    want = sorted(tuple(row[names.index(c)] for c in sorted(names)) for row in found.fetchall())
    df = queries.op4_warc(spark, tiny)
    assert sorted(df.columns) == sorted(names)
    assert sorted((tuple(r[c] for c in sorted(names)) for r in df.collect()), key=str) == sorted(want, key=str)
