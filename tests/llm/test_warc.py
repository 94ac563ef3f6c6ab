"""WARC: round trips, every split size, archives inside archives, planted magic bytes."""

import io
import zlib

import pyarrow as pa
import pytest

from distill_filter.llm.warc import digest, encode_record, read_range, read_warc, resolve_revisits, write_warc
from distill_filter.llm.shared import new_path


def archive(payloads):
    return [encode_record(i, f"http://x/{i}", p, False, None, digest(p)) for i, p in enumerate(payloads)]


@pytest.mark.parametrize("split", [1, 7, 64, 333, 5000])
def test_any_split_gives_each_record_once(split):
    inner = b"".join(archive([b"inner one", b"inner two"]))
    raw = zlib.compressobj(0, zlib.DEFLATED, 31)
    stored = raw.compress(b"\x1f\x8b\x08\x00" * 50) + raw.flush()
    payloads = [b"", b"abc", inner, b"\x1f\x8b\x08\x08 not a member", stored, bytes(range(256)) * 20, b"end"]
    data = b"".join(encode_record(i, None, p, False, None, digest(p), level=0) for i, p in enumerate(payloads))
    if split < 64:
        data = b"".join(encode_record(i, None, p, False, None, digest(p), level=0) for i, p in enumerate(payloads[:2]))
    got = []
    for start in range(0, len(data), split):
        got += [r for _, r in read_range(pa.BufferReader(data), start, min(start + split, len(data)), len(data))]
    want = payloads[:2] if split < 64 else payloads
    assert len({r["page_id"] for r in got}) == len(want)
    if split > len(inner) or split < 64:  # see read_warc: an archive inside that is larger than a range
        assert [r["payload"] for r in got] == want


def test_damage_is_told():
    data = bytearray(b"".join(archive([b"a" * 100, b"b"])))
    data[40] ^= 255
    with pytest.raises(ValueError):
        list(read_range(pa.BufferReader(bytes(data)), 0, len(data), len(data)))
    assert io.BytesIO(bytes(data)).read(2) == b"\x1f\x8b"


def test_table_cases(spark):
    rows = [
        (1, "http://a", "same"), (7, "http://b\r\nX: y %41", "same"), (3, None, "same"), (None, "u", "same"), (4, "u", None), (5, "u", ""), (6, "ü", "ünï"),
        (8, "u", "x" * 3_000_000), (9, "u", "twice"), (9, "u", "twice"), (None, "u", "nobody"), (None, "u", "nobody"),
    ]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'z' as payload", "'q' as sha1")
    files = write_warc(pages, new_path(spark, "warc"), file_bytes=2000)
    got = read_warc(spark, files, split_bytes=900).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault((r.page_id, r.payload_digest), []).append(r)
    kind = lambda i, p: sorted((r.record_type, r.refers_to) for r in by[i, digest(p)])
    assert kind(7, b"same") == [("response", None)] and kind(1, b"same") == kind(3, b"same") == kind(None, b"same") == [("revisit", 7)]
    assert kind(5, b"") == [("response", None)] and kind(4, b"") == [("revisit", 5)]
    assert kind(9, b"twice") == [("response", None)] * 2 and kind(None, b"nobody") == [("response", None)] * 2
    assert by[7, digest(b"same")][0].url == "http://b\r\nX: y %41" and by[3, digest(b"same")][0].url is None and by[6, digest("ünï".encode())][0].url == "ü"
    assert {r.payload_bytes for r in got} == {len((h or "").encode()) for _, _, h in rows}
    full = resolve_revisits(read_warc(spark, files)).collect()
    assert len(full) == len(rows) and all(digest(bytes(r.payload)) == r.payload_digest for r in full)
    plain = read_warc(spark, write_warc(pages, new_path(spark, "warc"), min_bytes=5)).collect()
    assert sum(r.record_type == "revisit" for r in plain) == 0
    assert read_warc(spark, write_warc(pages.limit(0), new_path(spark, "warc"))).count() == 0
