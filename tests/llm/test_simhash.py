"""SimHash near-duplicates against brute force."""

import random

import numpy as np
import pytest
import xxhash

from distill_filter.llm import golay
from distill_filter.llm.components import connected_components
from distill_filter.llm.simhash import bucket_forest, fingerprint, golay_keys, links, simhash_components


def slow_fingerprint(text, width=3):
    words, word = [], ""
    for c in text or "":
        if c in " \t\n\r\x0b\x0c":
            words, word = words + [word] * bool(word), ""
        else:
            word += c.lower() if "A" <= c <= "Z" else c
    words += [word] * bool(word)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    h = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(fps):
    """fps: {id: fingerprint}"""
    left, out = dict(fps), {}
    while left:
        first = min(left)
        group, front = {first}, [first]
        while front:
            p = front.pop()
            for q in [q for q in left if q not in group and (fps[p] ^ fps[q]).bit_count() <= 3]:
                group.add(q)
                front.append(q)
        for q in group:
            out[q] = first
            del left[q]
    return out


@pytest.mark.parametrize("text", [None, "", " \n\t", "One", "a B", "É Ü ß x\x85y z w", "a b c d a b c d\x0ba b", "The " * 50 + "end"])
def test_fingerprint(text):
    assert fingerprint(None if text is None else text.encode()) == slow_fingerprint(text)


def test_golay_keys_meet():
    rng = np.random.default_rng(5)
    a = rng.integers(0, 1 << 64, 4000, dtype=np.uint64)
    b = a.copy()
    for i in range(len(b)):
        for bit in rng.choice(64, rng.integers(0, 4), replace=False):
            b[i] ^= np.uint64(1) << np.uint64(bit)
    ra, ka = golay_keys(a)
    rb, kb = golay_keys(b)
    left, right = set(zip(ra.tolist(), ka.tolist())), set(zip(rb.tolist(), kb.tolist()))
    assert {r for r, _ in left & right} == set(range(len(a)))
    assert len(ka) <= 77 * len(a) and len(set(zip(ra.tolist(), ka.tolist()))) == len(ka)
    nearest, others = golay.decode(np.arange(1 << 23))
    assert len(np.unique(nearest)) == 4096 and set((others >= 0).sum(axis=1)) == {0, 5}


def test_bucket_forest_is_complete():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 64, 20, dtype=np.uint64)
    fps = np.unique(np.array([x ^ np.uint64(1 << int(rng.integers(64))) ^ np.uint64(1 << int(rng.integers(64))) for x in base for _ in range(20)], dtype=np.uint64))
    up = {i: {i} for i in range(len(fps))}
    for p, c in bucket_forest(fps):
        both = up[p] | up[c]
        for x in both:
            up[x] = both
    want = slow_components({i: int(f) for i, f in enumerate(fps)})
    assert {i: min(g) for i, g in up.items()} == want


@pytest.mark.parametrize("bucket", [2048, 8])
def test_components_of_dense_groups(spark, bucket):
    rnd, fps = random.Random(3), {}
    for g in range(12):
        base = rnd.getrandbits(64)
        for i in range(40 if g else 300):
            x = base
            for _ in range(rnd.randrange(4)):
                x ^= 1 << rnd.randrange(64)
            fps[len(fps) * 3 + 1] = x
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    first = {}
    for i, x in sorted(fps.items()):
        first.setdefault(x, i)
    reps = spark.createDataFrame([(signed(x), i) for x, i in first.items()], "fp long, rep long")
    found = {r.node: r.component for r in connected_components(links(reps, bucket=bucket)).collect()}
    want = slow_components({i: x for x, i in first.items()})
    assert {i: found.get(i, i) for i in want} == want


def test_edges_of_graphs(spark):
    chain = [(i, i + 1) for i in range(200)]
    rows = chain + [(300, 301), (301, 300), (305, 305), (None, 4), (4, None), (500, 400), (400, 600)]
    found = {r.node: r.component for r in connected_components(spark.createDataFrame(rows, "a long, b long").repartition(7)).collect()}
    assert found == {i: 0 for i in range(201)} | {300: 300, 301: 300, 400: 400, 500: 400, 600: 400}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_query_cases(spark):
    text = " ".join(f"w{i}" for i in range(300))
    rows = [
        (5, text, "x"), (3, text, "x"), (9, text + " end", "y"), (7, None, None), (4, "", "x"), (8, "  \n", "x"), (None, text, "x"), (None, "only here", "x"),
        (20, "first text of it", "x"), (20, "some other text entirely", "x"), (21, "some other text entirely", None), (40, "long " * 200_000, "x"),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp string").withColumnRenamed("fp", "component_id")
    found = sorted(((r.doc_id, r.fingerprint, r.component_id) for r in simhash_components(docs).collect()), key=str)
    fps = {(i, t): slow_fingerprint(t) for i, t, _ in rows if i != 40}
    assert len(found) == len(rows)
    by = {(i, f): c for i, f, c in found}
    for (i, t), f in fps.items():
        c = by[i, f"{f:016x}"]
        want = {5: 3, 3: 3, 7: 4, 4: 4, 8: 4, 20: 20, 21: 20}
        if i in want:
            assert c == want[i]
        if i is None:
            assert c == (3 if t == text else None)
    assert simhash_components(docs.limit(0)).count() == 0


def test_query_on_table(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    fps = {r.doc_id: slow_fingerprint(r.text) for r in docs.collect()}
    want = slow_components(fps)
    got = simhash_components(docs).collect()
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {i: (f"{f:016x}", want[i]) for i, f in fps.items()}
