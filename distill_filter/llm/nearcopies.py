"""Near copies by the exact share of word shingles that two texts have in common.

Two texts are near copies where the Jaccard similarity of their sets of five-word shingles is 0.8 at least. At that bound
about a tenth of the bits of two fingerprints differ, too many for the segment keys of `simhash`, so candidates come from
minimum hashes: BANDS keys of ROWS minima each, of which a pair at similarity s shares one with probability
1 - (1 - s^ROWS)^BANDS, over 0.9999 at 0.8. Texts that share a key are compared by their whole sets, so nothing is linked
that is not a near copy. A bucket gives a spanning forest of its true links, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .shared import binary, materialise, tidy

WIDTH, SIMILARITY = 5, 0.8
BANDS, ROWS = 24, 5
FACTORS = np.random.default_rng(17).integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: A bucket of more texts or words is split into blocks of about half as much, compared two at a time.
BUCKET, BUCKET_WORDS = 2048, 1 << 20


def shingles(text: bytes | None, width: int = WIDTH) -> np.ndarray:
    """XXH64 of every word shingle, A-Z lower-cased; a text of fewer words is one shingle, a blank one has none."""
    words = (text or b"").lower().split()  # as in simhash.fingerprint
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - width + 1)
    return np.fromiter((xxhash.xxh64_intdigest(b" ".join(words[i : i + width])) for i in range(n)), dtype="<u8", count=n)


def band_keys(hashes: np.ndarray) -> list[int]:
    """BANDS signed 64-bit keys of a set of shingles; none of an empty one."""
    if not len(hashes):
        return []
    least = np.full(len(FACTORS), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 1024):
        least = np.minimum(least, np.multiply.outer(FACTORS, hashes[at : at + 1024]).min(axis=1))
    bands = least.reshape(BANDS, ROWS)
    return [xxhash.xxh64_intdigest(b.tobytes(), seed=k) - (1 << 63) for k, b in enumerate(bands)]


def signatures(docs: DataFrame, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest, words, keys) of every row: digest is equal for texts of equal words, words the count of shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, digests, sizes, keys = binary(b, "text"), [], [], []
            for t in texts:
                h = shingles(t, width)
                digests.append(xxhash.xxh3_128_digest(b" ".join((t or b"").lower().split())))
                sizes.append(len(h))
                keys.append(band_keys(h))
            cols = [b.column(0), pa.array(digests, pa.binary()), pa.array(sizes, pa.int64()), pa.array(keys, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(cols, names=["id", "digest", "words", "keys"])
            tidy()

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, digest binary, words long, keys array<long>")


def text_forest(sets: list[np.ndarray], similarity: float = SIMILARITY) -> list[tuple[int, int]]:
    """Positions (parent, child) of a spanning forest of the links among sets of hashes, none of them empty."""
    sets = [np.unique(s) for s in sets]
    size = np.array([len(s) for s in sets])
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.concatenate([[0], np.cumsum(size)[:-1]])
    mask = np.zeros(codes.max() + 1, bool)
    rest, edges, front = np.arange(1, len(sets)), [], [0]
    while front or len(rest):
        if not front:
            front, rest = [int(rest[0])], rest[1:]
        p = front.pop()
        if not len(rest):
            continue
        own = codes[starts[p] : starts[p] + size[p]]
        mask[own] = True
        both = np.add.reduceat(mask[codes], starts, dtype=np.int64)[rest]
        mask[own] = False
        near = both >= similarity * (size[rest] + size[p] - both) - 1e-9
        found = rest[near].tolist()
        edges += [(p, c) for c in found]
        front += found
        rest = rest[~near]
    return edges


def _compare(width: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def work(ids: list[int], sets: list[np.ndarray]) -> pa.RecordBatch:
            pairs = [(ids[p], ids[c]) for p, c in text_forest(sets, similarity)] if len(ids) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([min(x) for x in pairs], pa.int64()), pa.array([max(x) for x in pairs], pa.int64())], names=["a", "b"])

        group, ids, sets = None, [], []
        for b in batches:
            for *at, i, text in zip(*(b.column(b.schema.get_field_index(n)).to_pylist() for n in ("key", "i", "j", "id")), binary(b, "text"), strict=True):
                if at != group:
                    if len(ids) > 1:
                        yield work(ids, sets)
                    group, ids, sets = at, [], []
                h = shingles(text, width)
                if len(h):
                    ids.append(i)
                    sets.append(h)
            tidy()
        yield work(ids, sets)

    return run


def links(docs: DataFrame, reps: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY, bucket: int = BUCKET, bucket_words: int = BUCKET_WORDS) -> DataFrame:
    """Edges (a, b) between ids of `reps(rep, words, keys)`, whose closure is that of all near copies that share a key.

    Buckets of the same texts are compared once. A large one is dealt out as in simhash.links; none is dropped.
    """
    keys = reps.select("rep", "words", F.explode("keys").alias("key"))
    members = [F.bit_xor(F.xxhash64("rep", F.lit(k))).alias(f"m{k}") for k in range(2)]
    shared = keys.groupBy("key").agg(F.count("*").alias("n"), F.sum("words").alias("w"), *members).where("n > 1")
    shared = shared.groupBy("m0", "m1", "n", "w").agg(F.min("key").alias("key"))
    parts = F.greatest(F.col("n") / bucket, F.col("w") / bucket_words)
    shared = shared.select("key", F.when(parts > 1, F.ceil(2 * parts)).otherwise(1).cast("int").alias("blocks"))
    dealt = keys.join(shared, "key").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), F.col("rep").alias("id"))
    rows = dealt.join(docs, "id").select("key", "i", "j", "id", "text")
    return rows.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(_compare(width, similarity), "a long, b long").where("a <> b").distinct()


def drop_near_copies(docs: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one document of each group of near copies, links taken on: the one with the smallest id.

    Null and blank texts are copies of each other. Rows that share an id are one document: they stay or go together.
    Rows with a null id can't be named, so they stay. All columns stay as they are.
    """
    found = materialise(signatures(docs, width, id_col, text_col), "signatures").where("id is not null")
    first = found.groupBy("digest").agg(F.min(F.struct("id", "words", "keys")).alias("x"))
    reps = materialise(first.select("digest", F.col("x.id").alias("rep"), "x.words", "x.keys"), "representatives")
    same = found.join(reps, "digest").where("id <> rep").select(F.col("rep").alias("a"), F.col("id").alias("b"))
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    labels = connected_components(links(texts, reps, width, similarity).union(same))
    lost = materialise(labels.where("node <> component").select(F.col("node").alias("__lost")), "near-copies")
    return docs.join(lost, F.col(id_col) == F.col("__lost"), "left_anti")
