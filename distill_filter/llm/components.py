"""Connected components of a large graph, without collecting it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialise, remove


def forest(pairs: Iterator[tuple[int, int]]) -> dict[int, int]:
    """Union-find over pairs: every node that occurs with the smallest node of its tree."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (nxt := up.setdefault(top, top)) != top:
            top = nxt
        while up[x] != top:
            up[x], x = top, up[x]
        return top

    for a, b in pairs:
        a, b = root(a), root(b)
        if a != b:
            up[max(a, b)] = min(a, b)
    return {x: root(x) for x in up}


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def pairs() -> Iterator[tuple[int, int]]:
        for b in batches:
            yield from zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)

    tree = [(x, r) for x, r in forest(pairs()).items() if x != r]
    found = np.array(tree, dtype=np.int64).reshape(-1, 2)
    yield pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], names=["u", "v"])


def _state(edges: DataFrame) -> tuple[int, int]:
    n, digest = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").bitwiseAND(F.lit(0xFFFFFFFF)))).first()
    return n, digest or 0


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of `edges(a long, b long)`; component: the smallest node reachable.

    Each partition first contracts its own edges to a star forest; then rounds of two star steps (hang all larger
    neighbours on the smallest one, then all smaller ones) go on until nothing changes. A step is an aggregate that
    combines before it shuffles and a join that adaptive execution splits where one node is hot. Nulls in either
    end: the row is left out. Self loops and repeated edges change nothing. No edges: an empty result.
    """
    plain = edges.where("a is not null and b is not null and a <> b").select("a", "b")
    now = materialise(plain.mapInArrow(_contract, "u long, v long").distinct(), "edges")
    before = _state(now)
    while before[0]:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        # every edge of `large` now points down (u > v): the small step needs only u's own edges
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("v", "m"), F.struct(F.col("u").alias("v"), "m"))).alias("e"))
        nxt = materialise(small.select(F.col("e.v").alias("u"), F.col("e.m").alias("v")).where("u <> v").distinct(), "edges")
        after = _state(nxt)
        remove(now, now.sparkSession)
        now = nxt
        if after == before:
            break
        before = after
    named = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return named.union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
