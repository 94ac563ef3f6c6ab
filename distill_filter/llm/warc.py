"""WARC archives: a writer with payload de-duplication and a splittable reader.

Every record is a gzip member of its own. The reader cuts files into byte ranges and gives each range to a task. A task
that starts inside a file looks for the gzip magic, accepts a place only if a member there decodes whole, holds a WARC
header, and leads on from member to member past the end of the range, and then owns the records that start inside.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator
from typing import BinaryIO

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import new_path

MAGIC = b"\x1f\x8b\x08"
BLOCK = 1 << 16
#: Fixed values of the format.
VERSION, PROFILE = "WARC/1.1", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
FILE_SCHEMA = "path string, size long, records long"
RECORD_SCHEMA = "path string, offset long, page_id long, url string, record_type string, refers_to long, payload_digest string, payload_bytes long, payload binary"


def _safe(value: str) -> str:
    """Header values hold no control characters, spaces or percent signs of their own: those are percent-escaped."""
    return re.sub(r"[\x00-\x20\x7f%]", lambda m: f"%{ord(m[0]):02X}", value)


def _plain(value: str) -> str:
    return re.sub(r"%([0-9A-F]{2})", lambda m: chr(int(m[1], 16)), value)


def _urn(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def _of_urn(value: str | None) -> int | None:
    got = re.fullmatch(r"<urn:page:(-?\d+)>", value or "")
    return int(got[1]) if got else None


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def encode_record(page_id: int | None, url: str | None, payload: bytes, revisits: bool, refers_to: int | None, sha1: str, level: int = 6) -> bytes:
    """One gzip member. A revisit keeps the HTTP header, with the full payload's length, and no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if revisits else http + payload
    head = [VERSION, f"WARC-Type: {'revisit' if revisits else 'response'}", f"WARC-Record-ID: {_urn(page_id)}", f"WARC-Date: {DATE}"]
    head += [f"WARC-Target-URI: {_safe(url)}"] if url is not None else []
    head += [f"WARC-Payload-Digest: sha1:{sha1}"]
    head += [f"WARC-Refers-To: {_urn(refers_to)}", f"WARC-Profile: {PROFILE}"] if revisits else []
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join([*head, "", ""]).encode() + block + b"\r\n\r\n") + packer.flush()


def _file(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path)


def write_warc(pages: DataFrame, path: str, min_bytes: int = 0, file_bytes: int = 1 << 30, level: int = 6) -> DataFrame:
    """Write a record for each row of pages(page_id, url, html) below path; return the files' (path, size, records).

    Of rows with equal payloads of min_bytes at least, that with the largest page_id is a response and the others are
    revisits of it; smaller payloads are all responses. Null html: an empty payload. Null page_id: loses to any other;
    a group of nulls only is all responses. The same page_id twice with equal payloads: both are responses. Null url:
    a record without a target. No rows: no files. The digest alone is aggregated (partly before the shuffle); the join
    back is one that adaptive execution splits where a payload is hot. A task that is run again writes new files;
    only those of the run that counted are listed.
    """
    body = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), body.alias("payload"))
    rows = rows.withColumn("sha1", F.sha1("payload"))
    seen = pages.select(F.col("page_id").cast("long").alias("page_id"), F.sha1(body).alias("sha1"))
    best = seen.groupBy("sha1").agg(F.max("page_id").alias("best"), F.count("*").alias("copies")).where("copies > 1 and best is not null").drop("copies")
    rows = rows.join(best, "sha1", "left")
    again = (F.octet_length("payload") >= min_bytes) & F.col("best").isNotNull() & ~F.col("best").eqNullSafe(F.col("page_id"))
    rows = rows.select("page_id", "url", "payload", "sha1", again.alias("again"), "best")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ctx = TaskContext.get()
        fs, root = _file(path)
        fs.create_dir(root, recursive=True)
        out: BinaryIO | None = None
        done: list[tuple[str, int, int]] = []
        for b in batches:
            for page_id, url, payload, sha1, again, best in zip(*(b.column(i) for i in range(6)), strict=True):
                if out is not None and done[-1][1] >= file_bytes:
                    out.close()
                    out = None
                if out is None:
                    name = f"part-{ctx.partitionId():05d}-{ctx.taskAttemptId()}-{len(done):03d}.warc.gz"
                    out = fs.open_output_stream(f"{root}/{name}", compression=None)
                    done.append((f"{path}/{name}", 0, 0))
                text = base64.b32encode(bytes.fromhex(sha1.as_py())).decode()
                member = encode_record(page_id.as_py(), url.as_py(), payload.as_py(), again.as_py(), best.as_py() if again.as_py() else None, text, level)
                out.write(member)
                done[-1] = (done[-1][0], done[-1][1] + len(member), done[-1][2] + 1)
        if out is not None:
            out.close()
        yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64()))], names=["path", "size", "records"])

    spark = pages.sparkSession
    manifest = new_path(spark, "warc-manifest")
    rows.mapInArrow(run, FILE_SCHEMA).write.parquet(manifest)
    return spark.read.schema(FILE_SCHEMA).parquet(manifest)


def _member(f: pa.NativeFile, at: int) -> tuple[bytes, int] | None:
    """The content of the gzip member at a place, and where it ends; None if none decodes there."""
    f.seek(at)
    unpack, content = zlib.decompressobj(31), []
    end = at
    try:
        while not unpack.eof:
            if not (data := f.read(BLOCK)):
                return None
            content.append(unpack.decompress(data))
            end += len(data) - len(unpack.unused_data)
            if len(content) == 1 and len(content[0]) >= 7 and content[0][:7] != b"WARC/1.":
                return None
    except zlib.error:
        return None
    whole = b"".join(content)
    return (whole, end) if whole[:7] == b"WARC/1." else None


def _leads_on(f: pa.NativeFile, at: int, end: int, size: int) -> bool:
    """Whether members follow one another from a place to the first one past the range."""
    while at < size:
        if (got := _member(f, at)) is None:
            return False
        if at >= end:
            return True
        at = got[1]
    return True


def first_member(f: pa.NativeFile, start: int, end: int, size: int) -> int | None:
    """The first place in [start, end) where a true member starts."""
    at = start
    while at < end:
        f.seek(at)
        data = f.read(min(BLOCK, end - at) + len(MAGIC) - 1)
        found = data.find(MAGIC)
        while found >= 0 and at + found < end:
            if _leads_on(f, at + found, end, size):
                return at + found
            found = data.find(MAGIC, found + 1)
        at += BLOCK
    return None


def parse_record(content: bytes) -> dict:
    head, _, rest = content.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    length = int(re.search(rb"(?m)^Content-Length: (\d+)", http)[1])
    sha1 = fields["WARC-Payload-Digest"].removeprefix("sha1:")
    revisit = fields["WARC-Type"] == "revisit"
    if not revisit and (len(payload) != length or digest(payload) != sha1):
        raise ValueError(f"record {fields['WARC-Record-ID']}: the payload does not have its digest or length")
    url = fields.get("WARC-Target-URI")
    return {
        "page_id": _of_urn(fields["WARC-Record-ID"]), "url": None if url is None else _plain(url), "record_type": fields["WARC-Type"],
        "refers_to": _of_urn(fields.get("WARC-Refers-To")), "payload_digest": sha1, "payload_bytes": length, "payload": None if revisit else payload,
    }


def read_range(f: pa.NativeFile, start: int, end: int, size: int) -> Iterator[tuple[int, dict]]:
    """(offset, record) of the records that start inside [start, end) of an open archive."""
    at = 0 if start == 0 else first_member(f, start, end, size)
    while at is not None and at < min(end, size):
        if (got := _member(f, at)) is None:
            raise ValueError(f"no WARC record at byte {at}")
        yield at, parse_record(got[0])
        at = got[1]


def read_warc(spark: SparkSession, files: DataFrame, split_bytes: int = 32 << 20) -> DataFrame:
    """The records of archives listed in files(path, size), one task a byte range of split_bytes at most.

    A revisit has the length and digest of the full payload and a null payload. A payload that does not have its
    digest raises. Memory: one record and a batch of small ones. No files: an empty result. Known limit: if a record
    holds a whole archive of more than split_bytes that deflate stored as it is, a range that starts inside can't tell.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = RECORD_SCHEMA.replace(",", "").split()[::2]
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary()]
        held: list[dict] = []
        held_bytes = 0

        def flush() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[n] for r in held], k) for n, k in zip(names, kinds, strict=True)], names=names)

        for b in batches:
            for path, size, start in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                fs, local = _file(path)
                with fs.open_input_file(local) as f:
                    for offset, record in read_range(f, start, min(start + split_bytes, size), size):
                        held.append(record | {"path": path, "offset": offset})
                        held_bytes += len(record["payload"] or b"") + 200
                        if held_bytes > 8 << 20:
                            yield flush()
                            held, held_bytes = [], 0
        yield flush()

    starts = F.sequence(F.lit(0).cast("long"), F.col("size") - 1, F.lit(split_bytes).cast("long"))
    ranges = files.where("size > 0").select("path", "size", F.explode(starts).alias("start"))
    return ranges.repartition(max(1, ranges.count())).mapInArrow(run, RECORD_SCHEMA)


def resolve_revisits(records: DataFrame) -> DataFrame:
    """Give revisits the payload of the response that they refer to."""
    full = records.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), F.col("payload_digest"), F.col("payload").alias("full"))
    full = full.dropDuplicates(["refers_to", "payload_digest"])
    return records.join(full, ["refers_to", "payload_digest"], "left").withColumn("payload", F.coalesce("payload", "full")).drop("full")
