"""Decontamination: exact edit distances, recall of the sampling, no false matches."""

import random

import numpy as np
import pytest

from distill_filter.llm.decontaminate import Index, Settings, allowed, best_match, find_contamination, item_blocks, runs_of, without_contaminated, words_of


def slow_best(item, text):
    """Fewest edits of item against any stretch of text."""
    row = list(range(len(item) + 1))
    best = row[-1]
    for w in text:
        nxt = [0]
        for i, x in enumerate(item):
            nxt.append(min(row[i] + (x != w), row[i + 1] + 1, nxt[i] + 1))
        row = nxt
        best = min(best, row[-1])
    return best


def edit(rnd, words, k, pool):
    words = list(words)
    for _ in range(k):
        at, what = rnd.randrange(len(words)), rnd.randrange(3)
        words[at : at + (what < 2)] = [rnd.choice(pool)] * (what > 0)
    return words


def test_edit_distance():
    rnd = random.Random(1)
    for _ in range(1500):
        item, text = [[rnd.randrange(1, 5) for _ in range(rnd.randrange(1, m))] for m in (80, 120)]
        got, end = best_match(item, text)
        assert got == slow_best(item, text) and slow_best(item, text[:end]) == got


@pytest.fixture(scope="module")
def tables(spark):
    items = [(r.item_id, words_of(r.text)) for r in spark.read.parquet("/root/testdata/sf0.1/benchmark.parquet").collect()]
    docs = [words_of(r.text) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    return items, docs


def test_recall_at_the_bound(tables):
    items, docs = tables
    index, rnd, pool = Index(items), random.Random(9), [w for d in docs[:40] for w in d]
    for share, least in ((1.0, 0.95), (0.5, 0.99), (0.0, 1.0)):
        found = tries = 0
        for item_id, ws in items:
            for _ in range(3):
                copy = edit(rnd, ws, int(share * allowed(len(ws), 0.8)), pool)
                doc = docs[rnd.randrange(len(docs))]
                cut = rnd.randrange(len(doc) + 1)
                text = np.array([index.vocabulary.get(w, 0) for w in doc[:cut] + copy + doc[cut:]])
                tries += 1
                found += item_id in index.matches(text)
        assert found / tries >= least, (share, found / tries)


def test_recall_where_edits_lie_together(tables):
    items, docs = tables
    index, rnd, pool = Index(items), random.Random(4), [w for d in docs[:40] for w in d]
    found = 0
    for item_id, ws in items:
        at, copy = rnd.randrange(len(ws)), list(ws)
        for _ in range(allowed(len(ws), 0.8)):
            place, what = min(at + rnd.randrange(3), len(copy) - 1), rnd.randrange(3)
            copy[place : place + (what < 2)] = [rnd.choice(pool)] * (what > 0)
        doc = docs[rnd.randrange(len(docs))]
        found += item_id in index.matches(index.number([" ".join(doc[:30] + copy + doc[30:])])[0])
    assert found / len(items) >= 0.95


def test_short_items_are_found_without_a_loss():
    rnd = random.Random(3)
    items = [(i, [f"w{rnd.randrange(12)}" for _ in range(1 + i % 7)]) for i in range(60)]
    index = Index(items)
    for _ in range(300):
        words = np.array([index.vocabulary.get(f"w{rnd.randrange(16)}", 0) for _ in range(rnd.randrange(25))], dtype=np.int64)
        want = {i: d for i, ws in index.items if (d := slow_best(ws, words.tolist())) <= allowed(len(ws), 0.8)}
        assert {i: m[0] for i, m in index.matches(words).items()} == want


def test_windows_that_can_match_all_walk(tables):
    items, docs = tables
    index, rnd, pool = Index(items), random.Random(6), [w for d in docs[:40] for w in d]
    for c in index.classes:
        for ws in [ws for _, ws in items if c.least <= len(ws) <= c.most][:10]:
            copy = edit(rnd, ws, allowed(len(ws), 0.8), pool)
            line = np.array([index.vocabulary.get(w, 0) for w in docs[0][:50] + copy + docs[1][:50]])
            runs = runs_of(line, c.q)
            start = min(50, len(docs[0]))
            assert start in index._starts(np.flatnonzero(np.isin(runs, c.runs) & (runs > 0)), c, len(line))


def test_no_false_matches_and_brute_force(tables):
    items, docs = tables
    index = Index(items)
    for doc in docs[:60]:
        numbers = np.array([index.vocabulary.get(w, 0) for w in doc], dtype=np.int64)
        got = index.matches(numbers)
        want = {i: d for i, ws in index.items if (d := best_match(ws, numbers.tolist())[0]) <= allowed(len(ws), 0.8)}
        assert {i: m[0] for i, m in got.items()} == want
        for i, (edits, n, start, end) in got.items():
            ws = dict(index.items)[i]
            assert n == len(ws) and slow_best(ws, numbers[start:end].tolist()) == edits


def test_cases(spark):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu"
    bench = spark.createDataFrame([(1, item), (2, None), (3, "too short"), (None, item), (4, item), (5, "")], "item_id long, text string").selectExpr("*", "1 as doc_id")
    texts = [None, "", item, f"so: {item.upper().replace(' ', ', ')}!", "x " * 100_000 + item.replace("beta", "BETA2") + " y" * 100, item[:30], "clean words only " * 30, f"{item} {item}", item[6:]]
    docs = spark.createDataFrame([*enumerate(texts), (None, item), (2, item)], "doc_id long, text string").selectExpr("*", "0 as item_id")
    got = [(r.doc_id, r.item_id, r.edit_distance) for r in find_contamination(docs, bench).collect()]
    want = [(d, i, e) for d, e in [(2, 0), (2, 0), (3, 0), (4, 1), (7, 0), (8, 1), (None, 0)] for i in (1, 4)]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert sorted(r.doc_id for r in without_contaminated(docs, bench).collect() if r.doc_id is not None) == [0, 1, 5, 6]
    assert find_contamination(docs.limit(0), bench).count() == 0 == find_contamination(docs, bench.limit(0)).count()
    assert [len(b) for b in item_blocks(bench.select("item_id", "text").where("text is not null"), 12)] == [1, 2, 1, 1] and Settings().similarity == 0.8


def test_rows_without_an_id_are_judged_by_their_text(spark):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu"
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    docs = spark.createDataFrame([(None, item), (None, "clean " * 20), (7, item), (7, "clean too " * 20), (None, None)], "doc_id long, text string")
    assert sorted(map(str, without_contaminated(docs, bench).collect())) == sorted(map(str, docs.where("text is null or text like 'clean%'").collect()))
    assert without_contaminated(docs, bench.limit(0)).count() == 5 and without_contaminated(docs.limit(0), bench).count() == 0
