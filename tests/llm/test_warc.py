import gzip
import io
import json

import pytest
from recmatch.llm import warc as W
from recmatch.llm.common import scratch


def test_normalise_round_trip():
    pages = [(1, "http://a/é x", b"one"), (2, None, b""), (3, "u", b"\r\n\r\nWARC/1.1\r\n" * 40000)]
    plain = b"".join(W.page_record(*p, None, 0) for p in pages)
    for stream in (gzip.compress(plain), gzip.compress(plain[:50]) + gzip.compress(plain[50:])):
        sink, side = io.BytesIO(), io.BytesIO()
        places = W.normalise(io.BytesIO(stream), sink, side)
        assert [json.loads(x)["offset"] for x in side.getvalue().splitlines()] == [p[0] for p in places]
        for (off, n), (_, _, body) in zip(places, pages):
            head, got = W.parse(gzip.decompress(sink.getvalue()[off : off + n]))
            assert got == body and head["warc-payload-digest"] == "sha1:" + W.digest(body)
        assert gzip.decompress(sink.getvalue()) == plain
    with pytest.raises((ValueError, EOFError)):
        W.normalise(io.BytesIO(gzip.compress(plain)[:-20]), io.BytesIO(), io.BytesIO())


def test_revisits(spark):
    rows = [(5, "b", "x", 1), (4, "a", "x", 1), (7, "a", None, 1), (8, "a", "", 1), (9, "u", "solo", 1), (4, "a", "x", 1), (6, "z", "big " * 30000, 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, sha int").repartition(3)
    where = scratch(spark, "t")
    index = W.normalise_all(W.write_monolithic(W.digested(pages.drop("sha")), where), where)
    got = sorted((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in W.read(index, where).collect())
    assert [g for g in got if g[0] != 4] == [(5, 1, "revisit", 4), (6, 120000, "response", None), (7, 0, "response", None), (8, 0, "revisit", 7), (9, 4, "response", None)]
    assert len([g for g in got if g[0] == 4]) == 2 and (4, 1, "response", None) in got


def test_empty(spark):
    where = scratch(spark, "t")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    assert W.read(W.normalise_all(W.write_monolithic(W.digested(pages), where), where), where).count() == 0
