import base64
import hashlib
import io

from ergodica.llm import warc


def pages(spark):
    rows = [(1, "http://a/\r\nx", "same"), (2, None, "same"), (3, "http://c", None), (4, "http://d", ""), (5, "http://e", "WARC/1.0\r\n\r\nContent-Length: 9\r\n\r\n ünï \x00"), (5, "http://e", "twice"), (None, "http://n", "same"), (None, None, "alone"), (7, "u", "twice"), (7, "u", "twice")]
    return rows, spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, digest string")


def test_archive(spark):
    rows, df = pages(spark)
    got = sorted((tuple(r) for r in warc.archive(df).collect()), key=str)
    want = []
    for page, _, html in rows:
        data = (html or "").encode()
        top = max((p for p, _, h in rows if (h or "") == (html or "") and p is not None), default=None)
        revisit = top is not None and page != top
        want.append((page, len(data), base64.b32encode(hashlib.sha1(data).digest()).decode(), "revisit" if revisit else "response", top if revisit else None))
    assert got == sorted(want, key=str)
    assert warc.archive(df.where("false")).isEmpty()
    least = {(r.page_id, r.record_type) for r in warc.archive(df, least=5).collect()}
    assert (1, "response") in least and (5, "revisit") in least


def test_round_trip(spark, tmp_path):
    rows, df = pages(spark)
    warc.write(df, f"file://{tmp_path}/w")
    payloads, headers = warc.store(spark, f"file://{tmp_path}/w")
    assert headers.count() == len(rows) and payloads.count() == len({h or "" for _, _, h in rows}) + 0
    whole = warc.originals(payloads, headers).collect()
    assert sorted((r.page_id, bytes(r.payload).decode()) for r in whole if r.page_id is not None) == sorted((p, h or "") for p, _, h in rows if p is not None)
    for r in whole:
        head = bytes(r.header)
        assert head.startswith(b"WARC/1.0\r\nWARC-Type: ") and head.endswith(b"\r\n\r\n")
        assert warc.field(head, b"WARC-Payload-Digest") == "sha1:" + base64.b32encode(hashlib.sha1(bytes(r.payload)).digest()).decode()
    assert not any("\n" in (warc.field(bytes(r.header), b"WARC-Target-URI") or "") for r in whole)


def test_broken_archive_is_noticed():
    import pytest

    record = b"WARC/1.0\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    assert list(warc.parse(io.BytesIO(record * 2))) == [(0, record[:-7], b"abc"), (len(record), record[:-7], b"abc")]
    with pytest.raises(ValueError):
        list(warc.parse(io.BytesIO(record.replace(b"3", b"2"))))


def test_changed_payload_is_noticed(spark, tmp_path):
    import gzip

    import pytest

    _, df = pages(spark)
    warc.write(df.where("page_id = 4"), f"file://{tmp_path}/w", date="2024-01-01T00:00:00Z")
    (one,) = [f for f in (tmp_path / "w").glob("*.gz") if gzip.open(f).read()]
    data = gzip.open(one).read()
    assert b"WARC-Date: 2024-01-01T00:00:00Z\r\n" in data and b"WARC-Block-Digest: sha256:" in data
    with gzip.open(one, "wb") as f:
        f.write(data.replace(b"Content-Length: 0\r\n\r\n", b"Content-Length: 1\r\n\r\nx"))
    (tmp_path / "w" / f".{one.name}.crc").unlink(missing_ok=True)
    with pytest.raises(Exception, match="SHA-256"):
        warc.read(spark, f"file://{tmp_path}/w").collect()


def test_hot_and_large_payloads(spark, tmp_path):
    """A payload that half of the pages share, and pages of all size classes: each file within its bound."""
    import gzip

    rows = [(i, "hot" if i % 2 else f"page {i}") for i in range(3000)] + [(5000 + i, "x" * (100_000 + i)) for i in range(3)] + [(6000 + i, chr(97 + i) * 3_000_000) for i in range(2)]
    df = spark.createDataFrame([(i, "u", h) for i, h in rows], "page_id long, url string, html string")
    got = {r.page_id: r for r in warc.archive(df).collect()}
    assert len(got) == len(rows) and all(got[i].payload_bytes == len(h) for i, h in rows)
    assert {r.refers_to for r in got.values() if r.record_type == "revisit"} == {2999} and sum(r.record_type == "revisit" for r in got.values()) == 1499
    warc.write(df.coalesce(1), f"file://{tmp_path}/w")
    sizes = [[len(x) for _, _, x in warc.parse(gzip.open(f))] for f in (tmp_path / "w").glob("*.gz")]
    assert sum(map(len, sizes)) == len(rows) and max(map(len, sizes)) <= 1024 and all(max(s) <= 64 << 10 or min(s) > 64 << 10 for s in sizes if s)
