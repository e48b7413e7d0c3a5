import gzip
import hashlib

import pytest

from markerpanel.llm import archives as ar


@pytest.mark.parametrize("version", [1, 2])
def test_arc_layouts(version):
    bodies = [b"", b"one\n\ntwo", "\r\n\r\né".encode() * 50]
    data = ar.arc_version_block(version) + b"".join(ar.arc_record(version, f"http://x/{k} y", b) for k, b in enumerate(bodies))
    for packed in (data, gzip.compress(data)):
        got = list(ar.parse_arc(packed))
        assert [g["body"] for g in got] == bodies
        assert got[1]["URL"] == "http://x/1%20y" and got[0]["version"] == version
    with pytest.raises(ValueError):
        list(ar.parse_arc(data[:-20]))


def test_dates():
    assert ar.iso_date("19990102030405") == "1999-01-02T03:04:05Z"
    assert ar.iso_date("1999") == "1999-01-01T00:00:00Z"


def test_round_trip(spark, tmp_path, monkeypatch):
    big, other = "é<p>\r\n\r\nWARC/1.1\r\n" * 100, "x" * 1000
    rows = [(1, "http://a/ b", big), (2, None, big), (9, "u", big), (3, "u", None), (4, "u", ""), (5, "u", "x" * 999), (6, "u", "x" * 999), (7, "u", other), (8, "u", other), (8, "u", other), (None, "u", big)]
    pages = spark.createDataFrame([(a, b, c, "z") for a, b, c in rows], "page_id long, url string, html string, digest string").repartition(3)
    for k, limit in enumerate((10, 0)):
        monkeypatch.setattr(ar, "BROADCAST_ROWS", limit)
        ar.write_archives(ar.convert_pages(pages, version=1 + k), f"{tmp_path}/w{k}", "gzip" if k else "none")
        got = ar.read_archives(spark, f"{tmp_path}/w{k}").collect()
        keep = lambda i, h: {big: 9, other: 8}.get(h) if h and len(h.encode()) >= 1000 and {big: 9, other: 8}[h] != i else None
        want = sorted((i or -1, len((h or "").encode()), hashlib.sha1((h or "").encode()).hexdigest(), keep(i, h)) for i, _, h in rows)
        assert sorted((r.page_id or -1, r.payload_bytes, r.payload_digest, r.refers_to) for r in got) == want
        assert all((r.record_type == "revisit") == (r.refers_to is not None) for r in got)
        assert {r.page_id: bytes(r.payload).decode() for r in got if r.page_id == 9} == {9: big}
    ar.write_archives(ar.convert_pages(pages.limit(0)), f"{tmp_path}/none")
    assert ar.read_archives(spark, f"{tmp_path}/none").count() == 0
