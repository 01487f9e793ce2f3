import gzip
import hashlib

import duckdb
from lexfold.llm import warc as W
from lexfold.llm.common import fresh_dir

BIG = "ü" * 200_000


def rows():
    a = "same payload " * 100
    return [(1, "http://a/x y", a), (5, "http://a/2", a), (3, None, a), (7, "u\r\nWARC-Type: x", "short"), (8, "u", "short"), (9, "u", None), (10, "u", ""), (11, "u", BIG), (None, "u", a), (12, "u", "WARC/1.1\r\n\r\n" * 200)]


def test_chunks_round_trip(spark):
    df = spark.createDataFrame(rows(), "page_id long, url string, html string").selectExpr("*", "1 as payload").repartition(3)
    files = W.write_archives(W.planned(df.drop("payload")), fresh_dir(spark, "w"))
    chunks = W.read_chunks(files).collect()
    got = {}
    for c in sorted(chunks, key=lambda c: c.chunk_no):
        got.setdefault(c.page_id, []).append(c)
        assert c.n_bytes <= W.CHUNK
    html = {p: (h or "").encode() for p, _, h in rows()}
    assert got.keys() == html.keys()
    for p, cs in got.items():
        assert [c.chunk_no for c in cs] == list(range(len(cs))) and [c.last for c in cs] == [False] * (len(cs) - 1) + [True]
        assert (cs[-1].total_bytes, cs[-1].running_sha1) == (len(html[p]), hashlib.sha1(html[p]).hexdigest())
        if cs[0].record_type == "response":
            assert b"".join(bytes(c.data) for c in cs) == html[p]
            so_far = b""
            for c in cs:
                so_far += bytes(c.data)
                assert hashlib.sha1(so_far).hexdigest() == c.running_sha1
    kinds = {p: (cs[0].record_type, cs[0].refers_to) for p, cs in got.items()}
    assert [kinds[p] for p in (1, 3, 5, None)] == [("revisit", 5), ("revisit", 5), ("response", None), ("revisit", 5)]
    assert {kinds[p][0] for p in (7, 8, 9, 10, 11, 12)} == {"response"}
    assert len(got[11]) > 4


def test_members_are_plain_gzip(spark):
    df = spark.createDataFrame(rows()[:2], "page_id long, url string, html string").coalesce(1)
    (f,) = W.write_archives(W.planned(df), fresh_dir(spark, "w")).collect()
    raw = gzip.decompress(open(f.path.removeprefix("file:"), "rb").read())
    assert raw.startswith(b"WARC/1.1\r\n") and raw.count(b"WARC-Record-ID") == 2


def test_query_against_sql(spark, sf):
    c = duckdb.connect()
    c.sql(f"create view pages as select * from '{sf}/pages.parquet'")
    want = sorted(c.sql(W.OP7_SQL).fetchall())
    assert sorted(map(tuple, W.op7_warc(spark, sf).collect())) == want
    assert W.read_chunks(W.write_archives(W.planned(spark.createDataFrame([], "page_id long, url string, html string")), fresh_dir(spark, "w"))).count() == 0
