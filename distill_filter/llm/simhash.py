"""Near-duplicates by SimHash fingerprints, found through a Golay-code fuzzy hash.

A 64-bit fingerprint is cut into three segments of 22, 21 and 21 bits; a Golay decoder gives every segment its nearest
codeword and, for most, five others at distance 4. Of two segments one bit apart, the nearest codeword of either is on
the list of the other. Where two fingerprints differ in three bits at most, either a segment is equal and one of the
others is one bit off at most, or each segment is one bit off. So a fingerprint gets, for each of the six ordered pairs
of segments, the keys (one segment's bits, any on the other's list), and for the last case the keys (nearest, nearest,
any on the list) and (any, any, nearest): 66 in the mean. Fingerprints that link share a key; keys have 33 bits at
least, so few others meet. A bucket gives a spanning forest of its true links, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import golay
from .components import connected_components
from .shared import binary, materialise, remove, tidy

MAX_BITS = 3
SEGMENTS = ((42, 22), (21, 21), (0, 21))
PAIRS = ((0, 1), (0, 2), (1, 0), (1, 2), (2, 0), (2, 1))
#: Fingerprints whose keys one task makes: 66 keys each in the mean.
KEYED = 250_000
#: A bucket with more fingerprints is split into blocks of about half as many, compared two at a time.
BUCKET = 2048


def fingerprint(text: bytes | None, width: int = 3, seed: int = 42) -> int:
    """SimHash of the XXH64 of every word shingle, A-Z lower-cased; a bit is set where over half the hashes set it."""
    words = (text or b"").lower().split()  # on bytes: the six ASCII white-space characters, and A-Z only
    if not words:
        return 0
    shingles = map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False)) if len(words) >= width else iter([b" ".join(words)])
    n, ones, digest = max(1, len(words) - width + 1), np.zeros(64, np.int64), xxhash.xxh64_intdigest
    for at in range(0, n, 1 << 16):
        some = min(n - at, 1 << 16)
        h = np.fromiter((digest(s, seed) for s, _ in zip(shingles, range(some), strict=False)), dtype="<u8", count=some)
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id long, fp long) of every row; null and blank texts have the fingerprint zero."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t, width, seed) for t in binary(b, "text")], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], names=["id", "fp"])
            tidy()

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "id long, fp long")


def golay_keys(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) for every key of every fingerprint."""
    fps, at = fps.view(np.uint64), np.arange(len(fps))
    bits = [(fps >> np.uint64(shift) & np.uint64((1 << n) - 1)).astype(np.int64) for shift, n in SEGMENTS]
    nearest, lists = [], []
    for x in bits:
        near, others = golay.decode(x)
        nearest.append(near)
        lists.append(np.column_stack([near, others]))
    rows, keys = [], []

    def add(tag: int, key: np.ndarray, *listed: np.ndarray) -> None:
        ok = np.logical_and.reduce([x >= 0 for x in listed])
        rows.append(at[ok])
        keys.append((tag << 40 | key)[ok])

    for tag, (same, off) in enumerate(PAIRS):
        for k in range(6):
            add(tag, bits[same] << 12 | lists[off][:, k], lists[off][:, k])
    a, b, c = nearest
    for k in range(6):
        add(6, a << 24 | b << 12 | lists[2][:, k], lists[2][:, k])
        for j in range(6):
            if k or j:  # the two nearest ones with the third are among the keys above
                add(6, lists[0][:, k] << 24 | lists[1][:, j] << 12 | c, lists[0][:, k], lists[1][:, j])
    return np.concatenate(rows), np.concatenate(keys)


def _emit_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fps, reps = b.column(0).to_numpy(), b.column(1).to_numpy()
        for at in range(0, len(fps), 10_000):
            rows, keys = golay_keys(fps[at : at + 10_000])
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(fps[at : at + 10_000][rows]), pa.array(reps[at : at + 10_000][rows])], names=["key", "fp", "rep"])


def bucket_forest(fps: np.ndarray, max_bits: int = MAX_BITS) -> list[tuple[int, int]]:
    """Positions (parent, child) of a spanning forest of the links among fps.

    A link found takes its child out of the rest, so a dense group costs about its size.
    """
    rest, edges = np.arange(1, len(fps)), []
    front = [0]
    while front or len(rest):
        if not front:
            front, rest = [int(rest[0])], rest[1:]
        p = front.pop()
        near = np.bitwise_count(fps[rest] ^ fps[p]) <= max_bits
        if near.any():
            found = rest[near].tolist()
            edges += [(p, c) for c in found]
            front += found
            rest = rest[~near]
    return edges


def _link(max_bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        names = ["key", "i", "j", "fp", "rep"]

        def work(cols: list[np.ndarray], ends: np.ndarray) -> pa.RecordBatch:
            fps, reps = cols[3].view(np.uint64), cols[4]
            starts = np.concatenate([[0], ends[:-1]])
            size = ends - starts
            two = starts[size == 2]
            two = two[np.bitwise_count(fps[two] ^ fps[two + 1]) <= max_bits]
            a, b = [reps[two]], [reps[two + 1]]
            for s, e in zip(starts[size > 2], ends[size > 2], strict=True):
                if edges := bucket_forest(fps[s:e], max_bits):
                    p, c = np.array(edges).T
                    a.append(reps[s:e][p])
                    b.append(reps[s:e][c])
            a, b = np.concatenate(a), np.concatenate(b)
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])

        for batch in batches:
            cols = [batch.column(batch.schema.get_field_index(n)).to_numpy() for n in names]
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols, strict=True)]
            new = (np.diff(cols[0]) != 0) | (np.diff(cols[1]) != 0) | (np.diff(cols[2]) != 0)
            ends = np.flatnonzero(new) + 1
            if len(ends):
                yield work([c[: ends[-1]] for c in cols], ends)
                cols = [c[ends[-1] :] for c in cols]
            held = cols
        if held is not None and len(held[0]):
            yield work(held, np.array([len(held[0])]))

    return run


def links(reps: DataFrame, max_bits: int = MAX_BITS, bucket: int = BUCKET) -> DataFrame:
    """Edges (a, b) between the ids of `reps(fp, rep)`, fp distinct, whose closure is that of all links.

    A key that many fingerprints share is dealt out: its rows go to about 2 * count / bucket blocks by a hash and each
    pair of blocks is one group of `bucket` rows or so; none is dropped. Keys are made once and written; they go when the
    edges are written.
    """
    if not 0 <= max_bits <= MAX_BITS:
        raise ValueError(f"the segments prove links of {MAX_BITS} differing bits at most")
    spark = reps.sparkSession
    # few bytes become many: by number, as adaptive execution would join the small partitions again
    spread = reps.select("fp", "rep").repartition(max(spark.sparkContext.defaultParallelism, reps.count() // KEYED))
    keys = materialise(spread.mapInArrow(_emit_keys, "key long, fp long, rep long"), "keys")
    shared = keys.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    dealt = keys.join(shared, "key").withColumn("blocks", F.when(F.col("n") > bucket, F.ceil(F.col("n") * 2 / bucket)).otherwise(1).cast("int"))
    own: Column = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
    dealt = dealt.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "fp", "rep")
    found = dealt.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(_link(max_bits), "a long, b long").distinct()
    found = materialise(found, "links")
    remove(keys, spark)
    return found


def simhash_components(docs: DataFrame, width: int = 3, max_bits: int = MAX_BITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 lower-case hex digits) and component_id of every row of docs.

    component_id is the smallest doc_id reachable over fingerprints that differ in max_bits bits at most, itself
    included. Null or blank text: fingerprint zero, linked like any other. Rows with equal text: one fingerprint, so
    one component. A doc_id that occurs twice is one document: both its rows lie in one component. Null doc_id: the
    row is returned; its component is that of its fingerprint where a named row has the same one, else null, and it
    links nothing. No rows: an empty result. Other columns of docs are not looked at, whatever their names.
    """
    found = materialise(fingerprints(docs, width, id_col=id_col, text_col=text_col), "fingerprints")
    reps = found.where("id is not null").groupBy("fp").agg(F.min("id").alias("rep"))
    reps = materialise(reps, "representatives")
    twice = found.where("id is not null").groupBy("id").agg(F.min("fp").alias("lo"), F.max("fp").alias("hi")).where("lo <> hi").select("id")
    same = found.join(twice, "id").join(reps, "fp").selectExpr("rep as a", "id as b")  # a doc_id that has two texts
    labels = connected_components(links(reps, max_bits).union(same))
    named = reps.join(labels, reps.rep == labels.node, "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return found.join(named, "fp", "left").select(
        F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def drop_near_duplicates(docs: DataFrame, width: int = 3, max_bits: int = MAX_BITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one document of each component: the one with the smallest id. All columns stay as they are.

    Rows that share an id are one document: they stay or go together. Rows with a null id can't be named, so they stay.
    """
    found = simhash_components(docs, width, max_bits, id_col, text_col).where("doc_id is not null and doc_id <> component_id")
    lost = materialise(found.selectExpr("doc_id as __lost").distinct(), "near-duplicates")
    return docs.join(lost, F.col(id_col) == F.col("__lost"), "left_anti")
