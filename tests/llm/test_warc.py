import gzip
import hashlib
import io

import pytest

from sealed_frames.llm import warc as W


def archive(*records):
    return io.BytesIO(b"".join(records))


def page(i, body, refers=None):
    return W.page_member(i, f"http://a/{i}", body, hashlib.sha256(body).hexdigest(), refers)


def test_members_are_read_in_order_whatever_the_chunks():
    bodies = [b"x" * n for n in (0, 1, 99, 100_000)]
    data = b"".join(page(i, b) for i, b in enumerate(bodies))
    for chunk in (1, 7, 1000, 1 << 20):
        got = [b"".join(m) for m in W.members(io.BytesIO(data), chunk)]
        assert got == [gzip.decompress(page(i, b)) for i, b in enumerate(bodies)]
    assert [r.http()[1] for r in W.records(io.BytesIO(data))] == bodies


def test_damage_is_found():
    good = page(1, b"hello " * 50)
    with pytest.raises(W.ArchiveError, match="cut short"):
        list(W.records(archive(good[:-9])))
    with pytest.raises(W.ArchiveError):
        list(W.records(archive(b"plain text")))
    text = gzip.decompress(good)
    with pytest.raises(W.ArchiveError, match="digest"):
        list(W.records(archive(gzip.compress(text.replace(b"hello hello", b"hullo hello", 1)))))
    with pytest.raises(W.ArchiveError, match="length"):
        list(W.records(archive(gzip.compress(text[:-6] + b"\r\n\r\n"))))
    assert list(W.records(archive())) == []


def test_header_values_cannot_break_out():
    record = next(W.records(archive(W.page_member(1, "http://a/\r\nWARC-Type: revisit", b"", hashlib.sha256(b"").hexdigest(), None))))
    assert record.kind == "response" and record.headers["warc-target-uri"].startswith("http://a/%0D%0A")


def test_round_trip_with_edge_rows(spark):
    big = "<p>" + "ü" * 300_000
    same = "<p>" + "s" * 200
    rows = [(5, "u", same), (3, "v", same), (9, None, same), (1, "w", None), (2, "x", ""), (4, "y", "short"), (6, "z", "short"), (7, "q", big), (None, "n", same), (3, "again", same)]
    pages = spark.createDataFrame([(*r, "clash", 1) for r in rows], "page_id long, url string, html string, digest string, file int")
    got = sorted(((r.page_id or -1), r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in W.archive_round_trip(pages).drop("url").collect())
    want = []
    for i, _, html in rows:
        data = (html or "").encode()
        revisit = html == same and i != 3
        want.append((i or -1, len(data), hashlib.sha256(data).hexdigest(), "revisit" if revisit else "response", 3 if revisit else None))
    assert got == sorted(want, key=str) or sorted(got, key=str) == sorted(want, key=str)
    folder = W.new_path(spark, "archives")
    payloads = {r.page_id: bytes(r.payload).decode() for r in W.read_archives(W.write_pages(pages, folder), folder, payloads=True).collect() if r.record_type == "response"}
    assert payloads[7] == big and payloads[1] == ""


def test_empty_table(spark):
    assert W.archive_round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
