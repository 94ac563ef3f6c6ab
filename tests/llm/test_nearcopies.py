"""Near copies against brute force over all pairs."""

import random

import numpy as np
import pytest

import corpus_pipeline
from distill_filter.llm.nearcopies import band_keys, drop_near_copies, links, shingles, signatures, text_forest


def slow_shingles(text, width=5):
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))} if words else set()


def alike(a, b):
    return not a and not b or 5 * len(a & b) >= 4 * len(a | b)


def slow_components(texts):
    """texts: {id: text}; the smallest id reachable over pairs of similarity 0.8 or more."""
    sets, left, out = {i: slow_shingles(t) for i, t in texts.items()}, set(texts), {}
    while left:
        first = min(left)
        left.remove(first)
        out[first], front = first, [first]
        while front:
            p = front.pop()
            found = {q for q in left if alike(sets[p], sets[q])}
            left -= found
            front += found
            out |= dict.fromkeys(found, first)
    return out


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_stage_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"/root/testdata/{sf}/documents.parquet")
    groups = slow_components({r.doc_id: r.text for r in docs.collect()})
    left = {r.doc_id for r in corpus_pipeline.simhash_near_dedup(spark, docs, "").select("doc_id").collect()}
    assert left == {i for i, g in groups.items() if i == g} and len(left) < len(groups)


def test_edited_copies_go(spark):
    rng = random.Random(3)
    texts = {}
    for k in range(40):
        words = [f"w{rng.randrange(5000)}" for _ in range(rng.randrange(60, 400))]
        texts[10 * k] = " ".join(words)
        for c in range(1, 4):  # one edit of a word spoils five shingles
            for _ in range(len(words) // 60):
                words[rng.randrange(len(words))] = f"x{rng.randrange(5000)}"
            texts[10 * k + c] = " ".join(words)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    groups = slow_components(texts)
    assert {r.doc_id for r in drop_near_copies(docs).collect()} == set(groups.values()) and len(set(groups.values())) < 120


def test_large_buckets_are_dealt_out(spark):
    rng = random.Random(4)
    base = [f"w{i}" for i in range(200)]
    texts = {i: " ".join(w if j != i % 200 else f"x{i}" for j, w in enumerate(base)) for i in range(120)}
    texts |= {1000 + i: " ".join(rng.sample(base, 200)) for i in range(20)}
    docs = spark.createDataFrame(list(texts.items()), "id long, text string")
    reps = signatures(docs, id_col="id").selectExpr("id as rep", "words", "keys")
    for bucket, words in ((2048, 1 << 20), (16, 1 << 20), (2048, 4000)):
        edges = [(r.a, r.b) for r in links(docs, reps, bucket=bucket, bucket_words=words).collect()]
        seen, front = {0}, [0]
        while front:
            p = front.pop()
            new = {x for e in edges if p in e for x in e} - seen
            seen |= new
            front += new
        assert seen == set(range(120)) and all(a < 1000 and b < 1000 for a, b in edges)


def test_forest_follows_chains():
    sets = [np.arange(k * 8, k * 8 + 100, dtype=np.uint64) for k in range(6)] + [np.arange(1000, 1100, dtype=np.uint64)]
    assert sorted(c for _, c in text_forest(sets)) == [1, 2, 3, 4, 5]


def test_keys():
    assert band_keys(shingles(None)) == [] and band_keys(shingles(b" \n")) == []
    assert band_keys(shingles(b"A b")) == band_keys(shingles(b"a  B")) != band_keys(shingles(b"a b c"))
