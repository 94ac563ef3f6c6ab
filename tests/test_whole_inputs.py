"""Queries use every row of their inputs."""

import math
import datetime
import random
import shutil

import pytest

from distill_filter import queries

SF = "/root/testdata/sf0.001"


@pytest.fixture()
def recipe_tables(spark, tmp_path):
    """Documents of ids that 4 divides, and more than 2,000 assistant turns of which the last have a word of their own."""
    common = "the of and to in"
    docs = [(4 * i, f"{common} " + ("late *** ###" if i % 2 else "crawl")) for i in range(400)]
    turns = [(i, f"{common} " + ("late" if i >= 2000 else "early")) for i in range(3000)]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(turns, "conv_id long, text string").selectExpr("conv_id", "0 as turn", "'assistant' as role", "text").coalesce(1).write.parquet(f"{tmp_path}/conversations.parquet")
    spark.read.parquet(f"{SF}/pages.parquet").limit(5).write.parquet(f"{tmp_path}/pages.parquet")
    return str(tmp_path)


def test_recipes_learn_from_all_rows(spark, recipe_tables):
    margins = {r.doc_id: r.margin_micro for r in queries.QUERIES["b10_ngram_recipe"](spark, recipe_tables).collect() if r.doc_id >= 0}
    assert margins[0] < 0 and margins[4] != margins[0]  # 'crawl' is known from documents alone, 'late' and the marks from both
    grades = {r.doc_id: r.kept for r in queries.QUERIES["b11_score_recipe"](spark, recipe_tables).collect() if r.doc_id >= 0}
    assert grades[0] == 1 and grades[4] == 0


def test_recipe_keeps_its_share(spark):
    rows = queries.QUERIES["b10_ngram_recipe"](spark, "/root/testdata/sf0.01").collect()
    assert 0.45 * len(rows) <= sum(r.kept for r in rows) <= 0.55 * len(rows)


@pytest.mark.parametrize("name", ["t08b_stream_stream_all", "j11b_interval_all"])
def test_interval_joins_pair_all_events(spark, tmp_path, name):
    rng = random.Random(6)
    start = datetime.datetime(2026, 1, 1)
    rows = [(i, start + datetime.timedelta(seconds=rng.randrange(7200)), rng.randrange(4), rng.choice(["view", "click", "buy"]), 1.0) for i in range(120)]
    rows += [(120, start, 9, "click", 1.0), (121, start + datetime.timedelta(minutes=10), 9, "buy", 1.0), (122, start + datetime.timedelta(minutes=10, seconds=1), 9, "buy", 1.0)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double").coalesce(1).write.parquet(f"{tmp_path}/events.parquet/part")
    for f in (tmp_path / "events.parquet/part").glob("*.parquet"):
        f.rename(tmp_path / "all.parquet")
    shutil.rmtree(tmp_path / "events.parquet")
    (tmp_path / "all.parquet").rename(tmp_path / "events.parquet")
    limit = datetime.timedelta(minutes=10)
    want = sorted((a[0], b[0]) for a in rows for b in rows if a[2] == b[2] and a[1] < b[1] <= a[1] + limit)
    assert sorted(map(tuple, queries.QUERIES[name](spark, str(tmp_path)).collect())) == want and (120, 121) in want


def test_unlabelled_come_last_and_none_is_dropped(spark):
    sf = "/root/testdata/sf0.1"  # more labels than the 450 rows that k08 returns
    rows = [(r.quality is None, r.quality or 0, r.doc_id) for r in queries.QUERIES["k08b_nulls_order_all"](spark, sf).collect()]
    assert rows == sorted(rows) and len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count() and rows[-1][0]


def test_replacement_and_annotation_cover_all(spark):
    assert not any(set("aeiou") & set(r.c or "") for r in queries.QUERIES["f01b_replace_all"](spark, SF).collect())
    assert queries.QUERIES["x02b_remote_teacher_all"](spark, SF).count() == queries.QUERIES["m02_stream_order"](spark, SF).count() > 300


def test_mainstream_is_among_the_filters(spark):
    rows = queries.QUERIES["w01_five_filters"](spark, SF).collect()
    assert {r.spec for r in rows} == {"topic_hostile", "topic_legal", "topic_private", "mainstream", "quality"} and len(rows) == 15
    assert {(r.spec, r.group_no) for r in queries.QUERIES["w07_human_eval"](spark, SF).collect()} == {(s, g) for s in ("mainstream", "quality") for g in (0, 1, 2)}


def test_pair_and_run_measures_on_odd_rows(spark):
    from distill_filter.plans import recipes

    docs = spark.createDataFrame([(1, "a b a b"), (2, None), (3, ""), (4, "A"), (5, "x a B c")], "doc_id long, text string").selectExpr("*", "'k' as run", "0 as n")
    items = spark.createDataFrame([("a  b c",), (None,), ("a",)], "text string")
    nats = recipes.bigram_cross_entropy(docs, items).first().nats
    assert abs(nats - (-math.log(4 / (3 + 3 + 1)) - math.log(2 / (2 + 3 + 1))) / 2) < 1e-12
    assert recipes.bigram_cross_entropy(docs, items.limit(0)).first().nats is None
    assert [r.doc_id for r in recipes.contaminated(docs, items, 3).collect()] == [5]
    assert recipes.contaminated(docs.limit(0), items, 3).count() == 0
