import base64
import hashlib
import io

from structcurve.llm import warc


def test_round_trip_in_chunks(spark, tmp_path):
    payloads = {1: "x" * 5000, 2: "", 3: "ünï" * 700, 4: "x" * 5000, 5: ""}
    rows = spark.createDataFrame([(i, f"http://a.example/{i} b\r\nX: y", t) for i, t in payloads.items()], "page_id bigint, url string, html string")
    manifest = warc.write_archives(rows, f"file://{tmp_path}", archive_bytes=300, chunk_bytes=512)
    assert manifest.agg({"records": "sum"}).first()[0] == 5 and manifest.count() > 1
    chunks = warc.read_archives(spark, manifest, chunk_bytes=1000).collect()
    for i in (1, 3):
        own = sorted((c for c in chunks if c.page_id == i), key=lambda c: c.chunk_no)
        data = b"".join(bytes(c.chunk) for c in own)
        assert data == payloads[i].encode() and len(own) == -(-len(data) // 1000) and [c.last for c in own] == [False] * (len(own) - 1) + [True]
        seen = b""
        for c in own:
            seen += bytes(c.chunk)
            assert c.bytes_so_far == len(seen) and c.digest_so_far == base64.b32encode(hashlib.sha1(seen).digest()).decode()
    got = {r.page_id: r for r in warc.records_of(warc.read_archives(spark, manifest, keep=False)).collect()}
    assert all(r.verified for r in got.values())
    assert {i: (r.record_type, r.refers_to) for i, r in got.items()} == {1: ("response", None), 4: ("revisit", 1), 2: ("response", None), 5: ("revisit", 2), 3: ("response", None)}
    assert all(got[i].payload_bytes == len(t.encode()) and got[i].payload_digest == base64.b32encode(hashlib.sha1(t.encode()).digest()).decode() for i, t in payloads.items())


def test_small_payloads_stay_responses(spark):
    rows = spark.createDataFrame([(1, "u", "same"), (2, "u", "same"), (3, "u", "longer text"), (4, "u", "longer text")], "page_id bigint, url string, html string")
    got = {r.page_id: r.record_type for r in warc.records_of(warc.read_archives(spark, warc.write_archives(rows, min_bytes=5))).collect()}
    assert got == {1: "response", 2: "response", 3: "response", 4: "revisit"}


def test_record_ids():
    for i in (0, 5, -7, 2**63 - 1, -(2**63), None):
        assert warc.page_of(warc.record_id(i)) == i


def test_truncated_archives_raise():
    import gzip

    head = warc.record_head(1, "u", None, 100, "D")
    try:
        list(warc.read_chunks(io.BytesIO(gzip.compress(head + b"short")), 64, True))
    except ValueError as e:
        assert "ends inside" in str(e)
    else:
        raise AssertionError
