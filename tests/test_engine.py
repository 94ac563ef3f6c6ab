"""The engine against literal renderings: cuts, bands, rounds, measures, theory, costs."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from distill_filter.config import RunConfig, StudentConfig, TeacherConfig
from distill_filter.functions.losses import focal_gradient, focal_loss
from distill_filter.operators import cost, metrics, snippets, students, teacher, theory, threshold
from distill_filter.plans import active, engine, recipes
from distill_filter.schemas import DOCUMENTS, require_columns
from distill_filter.sources.tables import shared_dir
from distill_filter.streaming.live import Collector, load_model, save_model


def literal_update(seen, t, n, config):
    """seen: (margin, label or None) of the round; by definition, one candidate at a time."""
    cuts = [threshold.ZERO, *sorted({m for m, _ in seen})]
    known = [(m, y) for m, y in seen if y is not None]

    def loss(s):
        wrong = sum(y == 1 for m, y in known if m <= s) + sum(y == 0 for m, y in known if m > s)
        if config.unlabelled == "constant":
            wrong += len(seen) - len(known)
        return wrong / max(1, len(known) if config.unlabelled == "labelled_only" else len(seen))

    best = min(cuts, key=lambda s: (loss(s), s))
    b = config.radius_scale * math.sqrt(2 * math.log(2 * math.log2(t + 1) ** 2 * n**2 / config.delta) / (t + 1))
    good = []
    for s in cuts:
        mass = sum(min(s, best) <= c <= max(s, best) for c in cuts) - 1
        if loss(s) - loss(best) <= b * b / 2 + b * math.sqrt(mass / t) + 1e-12:
            good.append(s)
    return min(good), max(good), best, loss(best)


def literal_round(rows, need, n, config):
    """One snippet at a time: the procedure as it is defined."""
    lo, hi, seen, bought, trace = active.OPEN_LO, active.OPEN_HI, [], [], []
    for t, (m, y) in enumerate(rows):
        if len(bought) == need:
            break
        if lo <= m <= hi:
            bought.append(t)
            seen.append((m, y))
            if len(bought) == need:
                break
        else:
            seen.append((m, (0 if m < lo else 1) if config.unlabelled == "implied" else None))
        if t >= 2 and t & (t - 1) == 0:
            a, b, best, loss = literal_update(seen, t, n, config)
            lo, hi = (max(lo, a), hi if b == max(m for m, _ in seen) else min(hi, b)) if config.nested else (a, b)
            trace.append((t, lo, hi, best, round(loss, 12)))
    return bought, trace


def some_rows(seed, n=700):
    rnd = random.Random(seed)
    rows = []
    for _ in range(n):
        m = rnd.choice([rnd.randrange(-60, 60), rnd.randrange(-6, 6)]) * 100_000
        rows.append((m, int(rnd.random() < 1 / (1 + math.exp(-m / 1_500_000)))))
    return rows


CONFIGS = [RunConfig(radius_scale=s, unlabelled=u, nested=k) for s, u, k in ((1.0, "implied", True), (0.2, "implied", True), (0.1, "constant", True), (0.1, "labelled_only", False), (0.15, "implied", False), (0.02, "implied", True))]


@pytest.mark.parametrize("config", CONFIGS)
def test_round_equals_literal_loop(config):
    for seed in range(4):
        rows = some_rows(seed)
        m, y = (np.array(x) for x in zip(*rows))
        for need in (1, 3, 40, 300, 5000):
            want, want_trace = literal_round(rows, need, 5000, config)
            trace: list = []
            got, _ = active.local_round(np.arange(len(m)), m, y, need, 5000, config, trace)
            assert got.tolist() == want
            assert [(t, lo, hi, s, round(loss, 12)) for _, t, lo, hi, s, loss, *_ in trace] == want_trace
            for size in (1, 7, 64):
                live = Collector(5000, need, config, counts=threshold.Counts(config.unlabelled))
                out = [at + k for at in range(0, len(m), size) for k in live.feed(m[at : at + size], y[at : at + size])]
                assert out == want


@pytest.mark.parametrize("config", [CONFIGS[0], CONFIGS[1]])
def test_frame_round_equals_literal_loop(spark, config):
    rows = some_rows(9, 300)
    df = spark.createDataFrame([(10 + i, f"s{i}", m, y) for i, (m, y) in enumerate(rows)], "stream_pos bigint, snippet_id string, margin_micro bigint, label int").repartition(3)
    for need in (40, 1000):
        trace: list = []
        got, head = active.frame_round(df, 10, need, 310, config, trace)
        want, want_trace = literal_round(rows, need, 310, config)
        assert [g.stream_pos - 10 for g in got] == want
        assert [(t, lo, hi, s, round(loss, 12)) for _, t, lo, hi, s, loss, *_ in trace] == want_trace
        assert head == (10 + want[-1] + 1 if len(want) == need else 310)


def curve_of(spark, rows):
    return threshold.loss_curve(spark.createDataFrame(rows, "margin_micro bigint, label int"))


def test_worked_cuts(spark):
    rows = curve_of(spark, list(zip(range(1, 9), [0, 0, 1, 0, 1, 1, 1, 1]))).orderBy("cut").collect()
    assert [round(r.loss * 8) for r in rows] == [3, 2, 1, 2, 1, 2, 3, 4, 5]
    assert threshold.empirical_cut(curve_of(spark, list(zip(range(1, 9), [0, 0, 1, 0, 1, 1, 1, 1])))).first().s_hat == 2
    same = curve_of(spark, [(3, 0), (3, 1), (3, 0), (7, 1)]).orderBy("cut").collect()
    assert [r.loss * 4 for r in same] == [2, 1, 2]
    one = threshold.empirical_cut(curve_of(spark, [(5, 1), (9, 1)])).first()
    assert (one.s_hat, one.loss) == (threshold.ZERO, 0.0)
    assert threshold.band(curve_of(spark, [(5, 1), (9, 1)]), 8, 8, 0.1).first().hi == 9


def test_radius(spark):
    for t, n, want in ((1024, 6593, 0.221695), (256, 67706, 0.478339), (2**20, 10**11, 0.010666)):
        assert abs(threshold.beta(t + 1, n, 0.1) - want) < 1e-6
        row = spark.range(1).select(threshold.beta_column(F.lit(t + 1), F.lit(n), F.lit(0.1)).alias("b")).first()
        assert abs(row.b - threshold.beta(t + 1, n, 0.1)) < 1e-12
    values = [threshold.beta(t, 10**6, 0.1) for t in range(4, 5000)]
    assert values == sorted(values, reverse=True) and threshold.beta(100, 10**7, 0.1) > threshold.beta(100, 10**6, 0.1) > threshold.beta(100, 10**6, 0.2)


def test_running_sums_equal_a_window(spark):
    rnd = random.Random(3)
    rows = [(rnd.randrange(-50, 50), rnd.randrange(5)) for _ in range(500)]
    got = threshold.running_sums(spark.createDataFrame(rows, "m bigint, x bigint"), "m", ["x"], 7).collect()
    assert len(got) == 500 and all(r.x_upto == sum(x for m, x in rows if m <= r.m) for r in got)


def test_snippets(spark):
    texts = [None, "", "  \n", "one", " ".join(map(str, range(64))), " ".join(map(str, range(65))), "ä\té " * 100]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {}
    for r in snippets.cut(docs).collect():
        got.setdefault(r.doc_id, []).append((r.seq, r.text, r.n_tokens))
    assert {i: len(v) for i, v in got.items()} == {3: 1, 4: 1, 5: 2, 6: 4}
    assert " ".join(t for _, t, _ in sorted(got[6])).split() == texts[6].split()
    over = snippets.cut(docs, 10, 3).where("doc_id = 4").orderBy("seq").collect()
    assert [r.text.split()[0] for r in over] == [str(7 * k) for k in range(len(over))] and over[-1].text.split()[-1] == "63"
    rows = snippets.order_ids(snippets.cut(docs)).collect()
    assert sorted(r.stream_pos for r in rows) == list(range(8))
    again = snippets.order_ids(snippets.cut(docs).repartition(5)).collect()
    assert {(r.snippet_id, r.stream_pos) for r in rows} == {(r.snippet_id, r.stream_pos) for r in again}
    with pytest.raises(ValueError):
        require_columns(docs, DOCUMENTS)


def test_teacher_and_cache(spark):
    assert spark.range(1).select(teacher.rule("topic_hostile", F.lit("You MORON!"))).first()[0] == 1
    rows = spark.createDataFrame([(f"s{i}", "fine words here" if i % 3 else "bad *** text") for i in range(600)], "snippet_id string, text string")
    noisy = TeacherConfig().noisy(0.1)
    v = rows.select(teacher.rule("quality", F.col("text")).alias("y"), *(teacher.verdict("quality", F.col("text"), F.col("snippet_id"), noisy, k).alias(f"c{k}") for k in (0, 1)))
    agree, right = v.agg(F.avg((F.col("c0") == F.col("c1")).cast("int")), F.avg((F.col("c0") == F.col("y")).cast("int"))).first()
    assert abs(agree - (1 - 2 * 0.1 * 0.9)) < 0.06 and abs(right - 0.9) < 0.05
    empty = spark.createDataFrame([], "spec string, teacher_id string, snippet_id string, call_no int, verdict int")
    new, all_ = teacher.ask(rows.limit(50).union(rows.limit(50)), empty, "quality")
    assert new.count() == 50 == all_.count()
    more, both = teacher.ask(rows, new, "quality")
    assert more.count() == 550 and both.count() == 600 and teacher.ask(rows, both, "quality")[0].count() == 0


def test_students(spark):
    rnd = random.Random(5)
    rows = [(" ".join(rnd.choice(["good", "plain", "word"]) for _ in range(8)) + (" ***" if i % 4 == 0 else ""), int(i % 4 != 0)) for i in range(200)]
    labels = spark.createDataFrame(rows, "text string, verdict int")
    model = students.fit(labels)
    again = students.fit(labels.repartition(7))
    assert model == again and model.weights
    df = labels.withColumn("snippet_id", F.monotonically_increasing_id().cast("string"))
    a = {r.snippet_id: r.margin_micro for r in students.score(df, model).collect()}
    b = {r.snippet_id: r.margin_micro for r in students.score_by_join(df, students.logodds_weights(labels)).collect()}
    assert a == b
    for kind in ("logodds", "focal"):
        m = students.fit(labels, StudentConfig(kind=kind))
        pred = students.score(labels, m).withColumn("pred", engine.passes(F.col("margin_micro")))
        assert metrics.balanced_accuracy(pred, "verdict", "pred").first()[0] > 0.95
    one_class = students.fit(labels.where("verdict = 1"))
    assert students.score(labels, one_class).where("margin_micro <= 0").count() == 0
    save_model(model, f"{shared_dir(spark)}/model", spark)
    assert load_model(f"{shared_dir(spark)}/model", spark) == model


def test_losses():
    z, y = np.array([0.0, 0.0, 2.0, -1.0]), np.array([1, 1, 0, 1])
    assert abs(focal_loss(z, y, 0)[0] - math.log(2)) < 1e-12 and abs(focal_loss(z, y, 2)[0] - math.log(2) / 4) < 1e-12
    for focus in (0.0, 1.0, 2.0, 5.0):
        step = 1e-6
        numeric = (focal_loss(z + step, y, focus) - focal_loss(z - step, y, focus)) / (2 * step)
        assert np.allclose(numeric, focal_gradient(z, y, focus), atol=1e-6)
    p = 1 / (1 + np.exp(-z))
    assert np.allclose(focal_gradient(z, y, 0), p - y)


def test_measures(spark):
    rows = [(1, 1)] * 8 + [(1, 0)] * 2 + [(0, 0)] * 85 + [(0, 1)] * 5
    m = metrics.confusion(spark.createDataFrame(rows, "t int, p int"), "t", "p").first()
    assert (m.tp, m.fp, m.tn, m.fn) == (8, 5, 85, 2) and abs(m.balanced_accuracy - 0.872222) < 1e-6
    assert metrics.confusion(spark.createDataFrame([(1, 1)], "t int, p int"), "t", "p").first().balanced_accuracy is None
    assert metrics.auc(spark.createDataFrame([(1, 0), (2, 1), (2, 0), (3, 1)], "s int, y int"), "s", "y").first().auc == 0.875
    people = metrics.human_preference(spark.createDataFrame([(f"s{i}", 1, 0, 1) for i in range(150)], "snippet_id string, truth int, teacher int, student int"), "teacher", "student", "truth", "q").collect()
    assert len(people) == 2 and all(r.n_snippets == 100 and r.preference > 0.95 for r in people)


def test_theory(spark):
    rows = theory.rank_linear(spark.createDataFrame([(f"s{i:04d}", i / 1000) for i in range(1, 1001)], "snippet_id string, score double"))
    risk = threshold.true_cut(rows)
    lo, hi = 0.450, 0.560
    g = theory.band_gap(risk, lo, hi).first()
    assert abs(g.s_star - 0.5) < 1e-9
    smooth = theory.smoothness(rows).first()[0]
    bound, measured = theory.balance_bound(1000, g.gap_lo, g.gap_hi, smooth), theory.interval_balance(rows, lo, hi).first().balance
    assert abs(measured - 0.982) < 0.002 and abs(bound - 0.888) < 0.01 and bound <= measured
    r = {x.cut: x.risk for x in risk.collect()}
    between = rows.where((F.col("score") > lo) & (F.col("score") <= hi)).agg(F.sum(1 - 2 * F.col("eta"))).first()[0]
    assert abs(r[hi] - r[lo] - between / 1000) < 1e-9
    assert theory.balance_bound(1000, 0.0, 0.1, 0.1) is None and theory.balance_bound(1000, 0.1, 0.1, 0.3) < 0
    assert theory.balance_bound_case_b(1000, 0.0001, 0.0, 4.0) == 1 and theory.risk_envelope([(0.1, 0.05)], 0.1)[1] > theory.risk_envelope([(0.1, 0.05)], 0.1)[0]


def test_costs(spark):
    rows = {r["filter"]: r for r in cost.totals(cost.published(spark)).collect()}
    assert {k: round(r.computed_usd, 2) for k, r in rows.items()} == {"climate": 117.22, "AI": 109.78, "politics": 467.78, "mainstream": 796.3, "quality": 467.78}
    assert all(abs(r.computed_usd - r.total_usd) <= 5 for r in rows.values()) and [k for k, r in rows.items() if not r.below_one_percent] == ["mainstream"]


def test_distil_policies(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = snippets.order(snippets.cut(docs)).select("snippet_id", "stream_pos", "text").cache()
    seeds = []
    for policy in ("band", "random", "uncertainty", "pool_uncertainty", "pool_cut"):
        run = active.distil(rows, "quality", RunConfig(batch=128, budget=384, radius_scale=0.5, policy=policy))
        ids = [i for _, _, i, _, _ in run.labels]
        assert len(ids) == len(set(ids)) and (len(ids) == 384 and len(run.models) == 3 or run.exhausted and len(ids) > 128)
        assert len(ids) == 384 or policy in ("band", "uncertainty")
        seeds.append(ids[:128])
        again = active.distil(rows.repartition(5), "quality", RunConfig(batch=128, budget=384, radius_scale=0.5, policy=policy))
        assert again.labels == run.labels and again.model == run.model
    assert all(s == seeds[0] for s in seeds)
    closed = active.distil(rows, "quality", RunConfig(batch=128, budget=1280, radius_scale=0.01))
    assert closed.exhausted and len(closed.labels) < 1280
    extra = RunConfig(batch=128, budget=256, budget_mode="extra", policy="random")
    assert extra.rounds == 2 and len(active.distil(rows, "quality", extra).labels) == 384


def test_recipes(spark):
    docs = spark.createDataFrame([(i, 10 + i % 7) for i in range(300)], "doc_id long, n_tokens int")
    for budget in (0, 100, 1500, 10**6):
        got = recipes.take_tokens(docs, budget, 1, 16)
        total = got.agg(F.coalesce(F.sum("n_tokens"), F.lit(0))).first()[0]
        assert total <= budget and (total > budget - 20 or got.count() == 300)
    same = recipes.take_tokens(docs.repartition(9), 1500, 1, 16).select("doc_id").collect()
    assert sorted(r.doc_id for r in same) == sorted(r.doc_id for r in recipes.take_tokens(docs, 1500, 1, 64).select("doc_id").collect())


def test_snippets_wait_for_python_without_their_documents_tokens(spark):
    """Each of a document's snippets was copied with all its tokens while it waited: the square of a document's length, on disk."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = engine.filter_corpus(snippets.cut(docs), students.LogOdds({"the": 5}, 1)).select("snippet_id", "doc_id", "n_tokens")
    node = rows._jdf.queryExecution().optimizedPlan()
    while node.nodeName() != "ArrowEvalPython":
        node = node.children().apply(0)
    held = node.children().apply(0).output()
    assert sorted(held.apply(i).dataType().simpleString() for i in range(held.size())) == ["bigint", "int", "int", "string"]


def test_plans_push_down_and_stay_narrow(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    model = students.LogOdds({"the": 5}, 1)
    plan = engine.filter_corpus(snippets.cut(docs), model)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "ReadSchema: struct<doc_id:bigint,text:string>" in plan
    gate = docs.where(F.col("n_chars").between(200, 5000)).select("doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(n_chars,200)" in gate and "text" not in gate.split("ReadSchema")[1]
