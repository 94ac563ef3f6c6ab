"""Queries of the engine's methods and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SPECS, RunConfig, StudentConfig, TeacherConfig
from ..functions.hashing import hash_below
from ..operators import cost, metrics, snippets, students, teacher, theory, threshold
from ..plans import active, engine, recipes
from ..sources.tables import folder_state, kept, materialise, table
from . import twins
from .registry import query

TOPICS = ("topic_hostile", "topic_legal", "topic_private", "quality")
SEED = twins.SEED_LABELS


def snips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return snippets.cut(table(spark, sf_dir, "documents", ["doc_id", "text"]))


FIVE = (*TOPICS[:3], "mainstream", "quality")


def common_words(spark: SparkSession, sf_dir: str) -> list[str]:
    """The tokens that the mainstream rule goes by: a small list, bounded by the share of documents that each must reach."""
    rows = kept(spark, sf_dir, "common-tokens", lambda: teacher.common_tokens(table(spark, sf_dir, "documents")))
    return sorted(r.token for r in rows.collect())


def stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """snippets with stream_pos and an exact verdict column for each filter, written once."""

    def build() -> DataFrame:
        chars = table(spark, sf_dir, "documents", ["n_chars"]).agg(F.sum("n_chars")).first()[0] or 0
        rows = snippets.order(snips(spark, sf_dir), digits=snippets.bucket_digits(chars // 256)).drop("stream_key", "stream_bucket")
        common = common_words(spark, sf_dir)
        return rows.withColumns({spec: teacher.rule(spec, F.col("text"), common=common) for spec in FIVE})

    return kept(spark, sf_dir, "stream", build)


def first_student(spark: SparkSession, sf_dir: str, spec: str = "quality", n: int = SEED) -> students.LogOdds:
    rows = stream(spark, sf_dir).where(F.col("stream_pos") < n).select("text", F.col(spec).alias("verdict"))
    return students.fit(rows)


def scored(spark: SparkSession, sf_dir: str, spec: str = "quality") -> DataFrame:
    """Everything scored by the student of the first SEED labels: what the operator queries below work on."""

    def build() -> DataFrame:
        rows = students.score(stream(spark, sf_dir), first_student(spark, sf_dir, spec))
        return rows.select("snippet_id", "doc_id", "seq", "n_tokens", "text", "stream_pos", F.col(spec).alias("label"), "margin_micro", "score")

    return kept(spark, sf_dir, f"scored-{spec}", build)


def with_sql(chain: str, select: str) -> str:
    return f"WITH {chain} {select}"


SNIPS, STREAM, SCORED = twins.snippets(), twins.stream(), twins.scored()


@query("m01_snippets", with_sql(SNIPS, "SELECT snippet_id, doc_id, seq, md5(text) AS text_md5, n_tokens FROM snips"))
def m01(spark, sf):
    return snips(spark, sf).select("snippet_id", "doc_id", "seq", F.md5("text").alias("text_md5"), "n_tokens")


@query("m02_stream_order", with_sql(STREAM, "SELECT snippet_id, stream_pos FROM stream"))
def m02(spark, sf):
    return snippets.order_ids(snips(spark, sf))


@query("m02b_stream_prefix", with_sql(SNIPS, f"SELECT snippet_id, n_tokens FROM snips WHERE {twins.hash_int(chr(39) + '7' + chr(39), 'snippet_id')} < {int(0.1 * (1 << 32))}"))
def m02b(spark, sf):
    return snippets.prefix(snips(spark, sf), 7, 0.1).select("snippet_id", "n_tokens")


ALL_RULES = ", ".join(f"{twins.rule(s)} AS {s}" for s in TOPICS)


@query("m03_full_teacher", with_sql(SNIPS, f"SELECT snippet_id, {ALL_RULES} FROM snips"))
def m03(spark, sf):
    return snips(spark, sf).select("snippet_id", *(teacher.rule(s, F.col("text")).alias(s) for s in TOPICS))


@query("b01_teacher_all", with_sql(SNIPS + ", " + twins.COMMON, f"SELECT snippet_id, {twins.rule('mainstream')} AS verdict FROM snips, (SELECT list(token) AS cm FROM common)"))
def b01(spark, sf):
    common = [r.token for r in teacher.common_tokens(table(spark, sf, "documents")).collect()]
    return teacher.annotate(snips(spark, sf), "mainstream", common=common).select("snippet_id", "verdict")


HOSTILE_WORDS = f"list_filter(list_transform({twins.tokens()}, lambda x: regexp_replace(lower(x), '[^a-z]', '', 'g')), lambda x: x IN ({twins.quoted(teacher.HOSTILE)}))"


@query("m03b_teacher_reason", with_sql(SNIPS, f"SELECT snippet_id, {twins.rule('topic_hostile')} AS verdict, array_to_string(list_sort(list_distinct({HOSTILE_WORDS})), ',') AS reason FROM snips"))
def m03b(spark, sf):
    return teacher.annotate(snips(spark, sf), "topic_hostile", with_reason=True).select("snippet_id", "verdict", "reason")


NOISY = TeacherConfig().noisy(0.03)


def noisy_sql(spec: str, teacher_id: str, call: int, eps_pos: float, eps_neg: float, weak: bool = False) -> str:
    low = f"CASE WHEN {twins.rule(spec, weak=weak)} = 1 THEN {1 - eps_pos} ELSE {eps_neg} END"
    q = "'"
    draw = twins.hash_int(q + teacher_id + q, q + spec + q, "snippet_id", str(call))
    return f"({draw} < floor(({low})::DOUBLE * {1 << 32})::BIGINT)::INT"


@query("m03c_noisy_teacher", with_sql(SNIPS, f"SELECT snippet_id, {noisy_sql('quality', 'teacher', 0, 0.03, 0.03)} AS call0, {noisy_sql('quality', 'teacher', 1, 0.03, 0.03)} AS call1 FROM snips"))
def m03c(spark, sf):
    rows = snips(spark, sf)
    return rows.select("snippet_id", *(teacher.verdict("quality", F.col("text"), F.col("snippet_id"), NOISY, k).alias(f"call{k}") for k in (0, 1)))


GRADES = "list_extract([0.05, 0.35, 0.65, 0.85, 0.95]::DOUBLE[], (least({e}, 4) + 1)::INT)"


@query("m03d_graded_teacher", with_sql(SNIPS, f"SELECT snippet_id, round({GRADES.format(e=twins.evidence('topic_hostile'))}, 6) AS pass_probability FROM snips"))
def m03d(spark, sf):
    return snips(spark, sf).select("snippet_id", F.round(teacher.pass_probability("topic_hostile", F.col("text"), TeacherConfig(mode="graded")), 6).alias("pass_probability"))


@query("m04_teacher_cache", with_sql(STREAM, "SELECT CASE WHEN stream_pos < 100 THEN 'cached' ELSE 'new' END AS paid, count(*) AS calls, sum(label)::BIGINT AS n_pass FROM stream WHERE stream_pos < 300 GROUP BY 1"))
def m04(spark, sf):
    rows = stream(spark, sf).select("snippet_id", "text", "stream_pos")
    empty = spark.createDataFrame([], "spec string, teacher_id string, snippet_id string, call_no int, verdict int")
    first, cache = teacher.ask(rows.where("stream_pos < 100"), empty, "quality")
    request = rows.where("stream_pos < 300").union(rows.where("stream_pos between 50 and 60"))  # some are asked twice
    new, _ = teacher.ask(request, cache, "quality")
    paid = first.withColumn("paid", F.lit("cached")).union(new.withColumn("paid", F.lit("new")))
    return paid.groupBy("paid").agg(F.count("*").alias("calls"), F.sum("verdict").cast("bigint").alias("n_pass"))


@query("m05_seed", with_sql(STREAM, f"SELECT snippet_id, stream_pos, label AS verdict FROM stream WHERE stream_pos < {SEED}"))
def m05(spark, sf):
    return stream(spark, sf).where(F.col("stream_pos") < SEED).select("snippet_id", "stream_pos", F.col("quality").alias("verdict"))


@query("m06_student_fit", with_sql(SCORED, "SELECT token, df1, df0, w_micro FROM st_w"))
def m06(spark, sf):
    rows = stream(spark, sf).where(F.col("stream_pos") < SEED).select("text", F.col("quality").alias("verdict"))
    return students.logodds_weights(rows)


@query("m07_student_score", with_sql(SCORED, "SELECT snippet_id, margin_micro, round(score, 6) AS score FROM scored"))
def m07(spark, sf):
    rows = students.score(stream(spark, sf), first_student(spark, sf))
    return rows.select("snippet_id", "margin_micro", F.round("score", 6).alias("score"))


@query("m07b_score_by_join", with_sql(SCORED, "SELECT snippet_id, margin_micro FROM scored"))
def m07b(spark, sf):
    return students.score_by_join(stream(spark, sf), m06(spark, sf)).select("snippet_id", "margin_micro")


RANKED = "ranked AS (SELECT *, greatest(0, least(1, 0.5 - 1.0 * ((row_number() OVER (ORDER BY score, snippet_id) - 0.5) / count(*) OVER () - 0.5))) AS eta FROM scored)"
RISK = """risk AS (SELECT cut, (sum(c1) OVER (ORDER BY cut) + sum(c0) OVER () - sum(c0) OVER (ORDER BY cut)) / sum(n) OVER () AS risk FROM (
    SELECT score AS cut, sum(1 - eta) AS c1, sum(eta) AS c0, count(*) AS n FROM ranked GROUP BY 1 UNION ALL SELECT 0.0::DOUBLE, 0, 0, 0))"""


def ranked(spark, sf):
    return theory.rank_linear(scored(spark, sf))


@query("m08_eot_true", with_sql(f"{SCORED}, {RANKED}, {RISK}", "SELECT round(cut, 6) AS s_star, round(risk, 6) AS risk FROM risk ORDER BY risk.risk, risk.cut LIMIT 1"))
def m08(spark, sf):
    best = threshold.true_cut(ranked(spark, sf)).agg(F.min(F.struct("risk", "cut")).alias("b"))
    return best.select(F.round("b.cut", 6).alias("s_star"), F.round("b.risk", 6).alias("risk"))


CURVE = f"{SCORED}, y AS (SELECT margin_micro, label AS y FROM scored), {twins.curve('y', 'lc')}"


@query("m09_eot_empirical", with_sql(CURVE, "SELECT cut AS s_hat, round(loss, 6) AS loss FROM lc ORDER BY lc.loss, cut LIMIT 1"))
def m09(spark, sf):
    return threshold.empirical_cut(threshold.loss_curve(scored(spark, sf))).select("s_hat", F.round("loss", 6).alias("loss"))


@query("m10_loss_curve", with_sql(CURVE, "SELECT cut, n0, n1, n1_le, n0_gt, round(loss, 6) AS loss FROM lc"))
def m10(spark, sf):
    return threshold.loss_curve(scored(spark, sf)).withColumn("loss", F.round("loss", 6))


GRID = "SELECT t, n, d AS delta, round({b}, 6) AS beta FROM (SELECT unnest([3, 17, 257, 1025, 1048577]::BIGINT[]) AS t), (SELECT unnest([6593, 67706, 100000000000]) AS n), (SELECT unnest([0.01, 0.1]::DOUBLE[]) AS d)"


@query("m11_radius", GRID.format(b="sqrt(2 * ln(2 * pow(log2(t), 2) * pow(n::DOUBLE, 2) / d) / t)"))
def m11(spark, sf):
    grid = spark.createDataFrame([(t, n, d) for t in (3, 17, 257, 1025, 1048577) for n in (6593, 67706, 10**11) for d in (0.01, 0.1)], "t bigint, n bigint, delta double")
    return grid.withColumn("beta", F.round(threshold.beta_column(F.col("t"), F.col("n"), F.col("delta")), 6))


def band_sql(scale: float, t: int = 1024) -> str:
    some = f"{SCORED}, y AS (SELECT margin_micro, label AS y FROM scored WHERE stream_pos BETWEEN {SEED} AND {SEED + t}), {twins.curve('y', 'lc')}, {twins.band('lc', 'bd', str(t), '(SELECT count(*) FROM stream)', 0.1, scale)}"
    return with_sql(some, "SELECT lo, hi, s_hat, round(loss, 6) AS loss FROM bd")


def band_query(spark, sf, scale: float, t: int = 1024, kind: str = "bernstein"):
    rows = scored(spark, sf)
    curve = threshold.loss_curve(rows.where(F.col("stream_pos").between(SEED, SEED + t)))
    return threshold.band(curve, t, rows.count(), 0.1, scale, kind).withColumn("loss", F.round("loss", 6))


query("m12_band", band_sql(1.0))(lambda spark, sf: band_query(spark, sf, 1.0))
query("m12b_band_scaled", band_sql(0.25))(lambda spark, sf: band_query(spark, sf, 0.25))


@query("m12c_unlabelled_modes", with_sql(f"{SCORED}, k AS (SELECT margin_micro, CASE WHEN margin_micro BETWEEN -2000000 AND 2000000 THEN label END AS own, CASE WHEN margin_micro < -2000000 THEN 0 WHEN margin_micro > 2000000 THEN 1 ELSE label END AS y FROM scored), {twins.curve('k', 'lc')}", "SELECT 'implied' AS mode, cut AS s_hat FROM (SELECT cut FROM lc WHERE cut BETWEEN -2000000 AND 2000000 ORDER BY loss, cut LIMIT 1)"))
def m12c(spark, sf):
    rows = scored(spark, sf)
    own = F.when(F.col("margin_micro").between(-2_000_000, 2_000_000), F.col("label"))
    full = threshold.completed("implied", F.lit(-2_000_000), F.lit(2_000_000), F.col("margin_micro"), own)
    curve = threshold.loss_curve(rows.select("margin_micro", full.alias("label"))).where("cut between -2000000 and 2000000")
    return threshold.empirical_cut(curve).select(F.lit("implied").alias("mode"), "s_hat")


OWN_MODES = f"{SCORED}, k AS (SELECT margin_micro, CASE WHEN margin_micro BETWEEN -2000000 AND 2000000 THEN label END AS y FROM scored), {twins.curve('k', 'lc')}, c AS (SELECT cut FROM lc WHERE cut BETWEEN -2000000 AND 2000000 ORDER BY loss, cut LIMIT 1)"


@query("m12d_other_modes", with_sql(OWN_MODES, "SELECT unnest(['constant', 'labelled_only']) AS mode, cut AS s_hat FROM c"))
def m12d(spark, sf):
    """The two ways that leave unbought labels unknown: they put the cut in the same place."""
    own = F.when(F.col("margin_micro").between(-2_000_000, 2_000_000), F.col("label"))
    rows, out = scored(spark, sf).select("margin_micro", own.alias("label")), None
    for mode in ("constant", "labelled_only"):
        curve = threshold.loss_curve(rows, mode).where("cut between -2000000 and 2000000")
        one = threshold.empirical_cut(curve).select(F.lit(mode).alias("mode"), "s_hat")
        out = one if out is None else out.union(one)
    return out


#: One round that the SQL twins unroll: the radius is scaled down for the small tables.
ROUND = RunConfig(batch=SEED, budget=2 * SEED, radius_scale=0.25, nested=True)
BLOCKS = list(active.blocks(8192))


def round_sql(select: str) -> str:
    chain = f"{SCORED}, {twins.one_round('scored', SEED, str(SEED), '(SELECT count(*) FROM stream)', 0.1, 0.25, BLOCKS, 'r')}"
    return with_sql(chain, select)


@query("m13_dyadic_trace", round_sql("SELECT snippet_id, stream_pos, label AS verdict, ord FROM r_bought"))
def m13(spark, sf):
    rows = scored(spark, sf)
    n = rows.count()
    got, _ = active.frame_round(rows.select("stream_pos", "snippet_id", "margin_micro", "label"), SEED, SEED, n, ROUND, [])
    return spark.createDataFrame([(g.snippet_id, g.stream_pos, g.label, i + 1) for i, g in enumerate(got)], "snippet_id string, stream_pos bigint, verdict int, ord bigint")


#: The same by the printed update, and a run of several rounds with a wider radius.
LITERAL = RunConfig(batch=SEED, budget=2 * SEED, radius_scale=0.25)
ENGINE = RunConfig(batch=SEED, budget=4 * SEED, radius_scale=0.5)


@query("m13b_printed_update", with_sql(f"{SCORED}, {twins.one_round('scored', SEED, str(SEED), '(SELECT count(*) FROM stream)', 0.1, 0.25, BLOCKS, 'r', False)}", "SELECT snippet_id, stream_pos, label AS verdict, ord FROM r_bought"))
def m13b(spark, sf):
    rows = scored(spark, sf)
    got, _ = active.frame_round(rows.select("stream_pos", "snippet_id", "margin_micro", "label"), SEED, SEED, rows.count(), LITERAL, [])
    return spark.createDataFrame([(g.snippet_id, g.stream_pos, g.label, i + 1) for i, g in enumerate(got)], "snippet_id string, stream_pos bigint, verdict int, ord bigint")


_RUNS: dict[tuple, active.Run] = {}


def engine_run(spark, sf, spec: str = "quality", config: RunConfig = ENGINE) -> active.Run:
    """A whole run of the engine on a filter; a session's queries share it as they share the stream."""
    key = (spark.sparkContext.applicationId, sf, folder_state(spark, sf), spec, config)
    if key not in _RUNS:
        rows = stream(spark, sf)
        common = common_words(spark, sf) if spec == "mainstream" else None
        _RUNS[key] = active.distil(rows, spec, config, common=common, n=rows.count())
    return _RUNS[key]


def engine_sql(select: str, spec: str = "quality", config: RunConfig = ENGINE) -> str:
    return with_sql(twins.engine(config, BLOCKS, spec), select)


@query("m14b_labels_of_three_rounds", engine_sql("SELECT round::INT AS round, snippet_id, stream_pos, verdict FROM e_lab"))
def m14b(spark, sf):
    return engine_run(spark, sf).labels_df(spark).select("round", "snippet_id", "stream_pos", "verdict")


@query("m14c_student_of_three_rounds", engine_sql("SELECT snippet_id, margin_micro FROM last"))
def m14c(spark, sf):
    return students.score(stream(spark, sf), engine_run(spark, sf).model).select("snippet_id", "margin_micro")


def distil_sql() -> str:
    all_labels = f"two AS (SELECT text, verdict FROM seed UNION ALL SELECT s.text, r.label FROM r_bought r JOIN stream s USING (snippet_id))"
    chain = f"{SCORED}, {twins.one_round('scored', SEED, str(SEED), '(SELECT count(*) FROM stream)', 0.1, 0.25, BLOCKS, 'r')}, {all_labels}, {twins.student('two', 'fin')}, {twins.margins('stream', 'fin', 'last')}"
    return with_sql(chain, "SELECT snippet_id, margin_micro, (margin_micro > 0)::INT AS verdict FROM last")


def a_run(spark, sf, policy: str = "band", spec: str = "quality", config: RunConfig = ROUND) -> active.Run:
    from dataclasses import replace

    rows = stream(spark, sf).select("snippet_id", "stream_pos", "text")
    return active.distil(rows, spec, replace(config, policy=policy), n=rows.count())


@query("m14_active_distil", distil_sql())
def m14(spark, sf):
    run = a_run(spark, sf)
    return students.score(stream(spark, sf), run.model).select("snippet_id", "margin_micro", engine.passes(F.col("margin_micro")).alias("verdict"))


@query("m15_filter_all", with_sql(SCORED, "SELECT snippet_id, doc_id, n_tokens FROM scored WHERE margin_micro > 0"))
def m15(spark, sf):
    return engine.filter_corpus(stream(spark, sf), first_student(spark, sf)).select("snippet_id", "doc_id", "n_tokens")


#: Rows of the stream's head that a run gets at first, about.
HEAD_ROWS = 1 << 18


def head_run(spark, sf, spec: str = "quality", config: RunConfig = ENGINE, head_rows: int | None = None) -> active.Run:
    """engine_run without the whole stream written: its head is the rows of the smallest keys, in the same places.

    A run buys from the head on, so it is the whole stream's run if it found all its labels in the rows it was given. Where
    they ran out it is begun anew on eight times as many, up to the whole stream.
    """
    cut = snips(spark, sf)
    n = cut.count()
    common = common_words(spark, sf) if spec == "mainstream" else None
    share = min(1.0, (head_rows or HEAD_ROWS) / max(1, n))
    while True:
        rows = snippets.order(snippets.prefix(cut, 7, share), digits=snippets.bucket_digits(n)).select("snippet_id", "stream_pos", "text")
        run = active.distil(materialise(rows, "stream-head"), spec, config, common=common, n=n)
        if share == 1 or not run.exhausted and len(run.labels) >= config.batch:
            return run
        share = min(1.0, 8 * share)


@query("m15c_engine_filter", engine_sql("SELECT snippet_id, doc_id, n_tokens FROM last WHERE margin_micro > 0"))
def m15c(spark, sf):
    return engine.filter_corpus(snips(spark, sf), head_run(spark, sf).model).select("snippet_id", "doc_id", "n_tokens")


@query("m15b_cuts", with_sql(f"{SCORED}, y AS (SELECT margin_micro, label AS y FROM scored WHERE stream_pos < {SEED}), {twins.curve('y', 'lc')}, t AS (SELECT sum(y) AS t1, sum(1 - y) AS t0 FROM y)", "SELECT 'half' AS kind, 0::BIGINT AS cut UNION ALL SELECT 'eot', (SELECT cut FROM lc ORDER BY loss, cut LIMIT 1) UNION ALL SELECT 'balanced', (SELECT cut FROM lc, t ORDER BY n1_le / t1::DOUBLE + n0_gt / t0::DOUBLE, cut LIMIT 1)"))
def m15b(spark, sf):
    model = first_student(spark, sf)
    rows = stream(spark, sf).where(F.col("stream_pos") < SEED).select("text", F.col("quality").alias("verdict"))
    return spark.createDataFrame([(k, engine.decision_cut(rows, model, k)) for k in ("half", "eot", "balanced")], "kind string, cut bigint")


@query("m16_doc_rollup", with_sql(SCORED, "SELECT doc_id, count(*) AS n_snippets, sum((margin_micro > 0)::INT)::BIGINT AS n_pass, (sum((margin_micro > 0)::INT) >= 0.5 * count(*))::INT AS doc_pass FROM scored GROUP BY doc_id"))
def m16(spark, sf):
    rows = scored(spark, sf).select("doc_id", engine.passes(F.col("margin_micro")).alias("verdict"))
    return engine.roll_up(rows)


def many_sql() -> str:
    parts = [STREAM.replace("AS label FROM snips", f"AS label, {', '.join(twins.rule(s) + ' AS r_' + s for s in TOPICS)} FROM snips")]
    for s in TOPICS:
        parts.append(f"seed_{s} AS (SELECT text, r_{s} AS verdict FROM stream WHERE stream_pos < {SEED})")
        parts += [twins.student(f"seed_{s}", s), twins.margins("stream", s, f"m_{s}")]
    picks = ", ".join(f"(m_{s}.margin_micro > 0)::INT AS pass_{s}" for s in TOPICS)
    joins = " ".join(f"JOIN m_{s} USING (snippet_id)" for s in TOPICS[1:])
    return with_sql(", ".join(parts), f"SELECT snippet_id, {picks} FROM m_{TOPICS[0]} {joins}")


@query("m17_multi_filter", many_sql())
def m17(spark, sf):
    models = {s: (first_student(spark, sf, s), 0) for s in TOPICS}
    return engine.filter_many(stream(spark, sf).select("snippet_id", "text"), models).drop("text")


def five_sql() -> str:
    """One active round for each of the five filters, then all five students on every snippet."""
    parts = [twins.stream("mainstream").replace(" AS label FROM snips", f" AS label, {', '.join(twins.rule(x) + ' AS r_' + x for x in FIVE)} FROM snips")]
    for x in FIVE:
        parts.append(f"st_{x} AS MATERIALIZED (SELECT snippet_id, stream_pos, text, r_{x} AS label FROM stream)")
        parts += [twins.rounds(LITERAL, BLOCKS, x, f"st_{x}"), twins.margins("stream", f"{x}_f", f"p_{x}")]
    picks = ", ".join(f"(p_{x}.margin_micro > 0)::INT AS pass_{x}" for x in FIVE)
    joins = " ".join(f"JOIN p_{x} USING (snippet_id)" for x in FIVE[1:])
    return with_sql(", ".join(parts), f"SELECT snippet_id, {picks} FROM p_{FIVE[0]} {joins}")


@query("m17b_five_filters", five_sql())
def m17b(spark, sf):
    models = {x: (engine_run(spark, sf, x, LITERAL).model, 0) for x in FIVE}
    return engine.filter_many(stream(spark, sf).select("snippet_id", "text"), models).drop("text")


@query("m20_lowest_scores", with_sql(SCORED, "SELECT snippet_id, margin_micro, label FROM scored ORDER BY margin_micro, snippet_id LIMIT 50"))
def m20(spark, sf):
    return scored(spark, sf).orderBy("margin_micro", "snippet_id").limit(50).select("snippet_id", "margin_micro", "label")


ONE_CLASS = f"{SCORED}, all1 AS (SELECT stream_pos, snippet_id, margin_micro, 1 AS label FROM scored)"


@query("m20b_band_at_the_bottom", with_sql(f"{ONE_CLASS}, {twins.one_round('all1', SEED, '128', '(SELECT count(*) FROM stream)', 0.1, 0.05, BLOCKS, 'r', False)}", "SELECT snippet_id, stream_pos, margin_micro FROM r_bought JOIN scored USING (snippet_id, stream_pos)"))
def m20b(spark, sf):
    """A teacher that passes everything: the empirical cut is the candidate 0 and the band hugs the lowest scores."""
    rows = scored(spark, sf).select("stream_pos", "snippet_id", "margin_micro", F.lit(1).alias("label"))
    got, _ = active.frame_round(rows, SEED, 128, rows.count(), RunConfig(radius_scale=0.05), [])
    ids = spark.createDataFrame([(g.snippet_id,) for g in got], "snippet_id string")
    return rows.join(F.broadcast(ids), "snippet_id").select("snippet_id", "stream_pos", "margin_micro")


@query("m21_exhaustion")
def m21(spark, sf):
    """A band that closes before the budget is spent: how each policy for the stream's end behaves."""
    from dataclasses import replace

    out = None
    for how in ("stop", "wrap"):
        run = a_run(spark, sf, config=replace(ROUND, radius_scale=0.02, budget=4 * SEED, on_exhausted=how))
        row = spark.createDataFrame([(how, len(run.labels), run.seen, run.exhausted)], "on_exhausted string, calls bigint, seen bigint, exhausted boolean")
        out = row if out is None else out.union(row)
    return out


# students


@query("st2_focal_linear")
def st2(spark, sf):
    rows = stream(spark, sf).where(F.col("stream_pos") < SEED).select("text", F.col("quality").alias("verdict"))
    model = students.fit(rows, StudentConfig(kind="focal", class_weight=True))
    return metrics.confusion(students.score(stream(spark, sf).where(F.col("stream_pos") >= SEED), model).withColumn("pred", (F.col("margin_micro") > 0).cast("int")), "quality", "pred")


@query("st3_library")
def st3(spark, sf):
    rows = stream(spark, sf).where(F.col("stream_pos") < SEED).select("text", F.col("quality").alias("verdict"))
    model = students.fit_library(rows, StudentConfig(class_weight=True))
    out = model.apply(stream(spark, sf).where(F.col("stream_pos") >= SEED).select("snippet_id", "text", "quality"))
    return metrics.confusion(out.withColumn("pred", (F.col("margin_micro") > 0).cast("int")), "quality", "pred")


@query("st4_vectors")
def st4(spark, sf):
    rows = table(spark, sf, "embeddings").withColumn("verdict", (F.col("label") == 0).cast("int"))
    test = hash_below(0.3, "vec", F.col("vec_id"))
    model = students.fit_vectors(rows.where(~test).select("embedding", "verdict"))
    out = rows.where(test).withColumn("pred", (model.margin(F.col("embedding")) > 0).cast("int"))
    return metrics.confusion(out, "verdict", "pred")


# baselines on the stream


@query("b02_weak_teacher", with_sql(SNIPS, f"SELECT snippet_id, {twins.rule('topic_hostile', weak=True)} AS verdict FROM snips"))
def b02(spark, sf):
    return teacher.annotate(snips(spark, sf), "topic_hostile", TeacherConfig("weak")).select("snippet_id", "verdict")


@query("b03_random_distil", with_sql(f"{STREAM}, seed AS (SELECT text, label AS verdict FROM stream WHERE stream_pos < {2 * SEED}), {twins.student('seed', 'st')}, {twins.margins('stream', 'st', 'sc')}", "SELECT snippet_id, margin_micro FROM sc"))
def b03(spark, sf):
    run = a_run(spark, sf, "random")
    return students.score(stream(spark, sf), run.model).select("snippet_id", "margin_micro")


@query("b04_uncertainty_stream", with_sql(SCORED, f"SELECT snippet_id, stream_pos, label AS verdict FROM scored WHERE stream_pos >= {SEED} AND abs(score - 0.5) <= 0.4 ORDER BY stream_pos LIMIT {SEED}"))
def b04(spark, sf):
    return _second_round(spark, a_run(spark, sf, "uncertainty"))


def _second_round(spark, run):
    return run.labels_df(spark).where("round = 1").select("snippet_id", "stream_pos", "verdict")


@query("b05_uncertainty_pool", with_sql(SCORED, f"SELECT snippet_id, stream_pos, label AS verdict FROM scored WHERE stream_pos >= {SEED} ORDER BY abs(score - 0.5), snippet_id LIMIT {SEED}"))
def b05(spark, sf):
    return _second_round(spark, a_run(spark, sf, "pool_uncertainty"))


@query("b06_pool_eot")
def b06(spark, sf):
    return _second_round(spark, a_run(spark, sf, "pool_cut"))


UNIFORM = f"{SCORED}, y AS (SELECT margin_micro, label AS y FROM scored WHERE stream_pos BETWEEN {SEED} AND {SEED + 1024}), {twins.curve('y', 'lc')}"


@query("b07_uniform_radius", with_sql(UNIFORM, f"SELECT min(cut) AS lo, max(cut) AS hi FROM lc WHERE loss - (SELECT min(loss) FROM lc) <= {twins.radius('1025', '(SELECT count(*) FROM stream)', 0.1, 0.25)} + 1e-12"))
def b07(spark, sf):
    return band_query(spark, sf, 0.25, kind="uniform").select("lo", "hi")


# measures


def test_rows(spark, sf):
    rows = scored(spark, sf).where(snippets.held_out(F.col("text")))
    return rows.withColumn("pred", engine.passes(F.col("margin_micro")))


TEST = f"{SCORED}, test AS (SELECT *, (margin_micro > 0)::INT AS pred FROM scored WHERE {twins.hash_int(chr(39) + 'test7' + chr(39), 'text')} < {int(0.2 * (1 << 32))}), cm AS (SELECT count(*) FILTER (label = 1 AND pred = 1) AS tp, count(*) FILTER (label = 0 AND pred = 1) AS fp, count(*) FILTER (label = 0 AND pred = 0) AS tn, count(*) FILTER (label = 1 AND pred = 0) AS fn FROM test)"


@query("a01_balanced_accuracy", with_sql(TEST, "SELECT round((tp / nullif(tp + fn, 0)::DOUBLE + tn / nullif(tn + fp, 0)::DOUBLE) / 2, 6) AS balanced_accuracy FROM cm"))
def a01(spark, sf):
    return metrics.balanced_accuracy(test_rows(spark, sf), "label", "pred").select(F.round("balanced_accuracy", 6).alias("balanced_accuracy"))


@query("a02_confusion", with_sql(TEST, "SELECT tp, fp, tn, fn, round((tp + tn) / (tp + fp + tn + fn)::DOUBLE, 6) AS accuracy, round(tp / nullif(tp + fp, 0)::DOUBLE, 6) AS precision, round(tp / nullif(tp + fn, 0)::DOUBLE, 6) AS recall, round(2 * tp / nullif(2 * tp + fp + fn, 0)::DOUBLE, 6) AS f1 FROM cm"))
def a02(spark, sf):
    out = metrics.confusion(test_rows(spark, sf), "label", "pred")
    return out.select("tp", "fp", "tn", "fn", *(F.round(c, 6).alias(c) for c in ("accuracy", "precision", "recall", "f1")))


CONSISTENCY = " UNION ALL ".join(f"SELECT '{s}' AS spec, {noisy_sql(s, 'teacher', 0, 0.03, 0.03)} AS c0, {noisy_sql(s, 'teacher', 1, 0.03, 0.03)} AS c1 FROM snips" for s in TOPICS)


@query("a03_self_consistency", with_sql(f"{SNIPS}, calls AS ({CONSISTENCY})", "SELECT spec, round((sum(c0 * c1) / sum(c0)::DOUBLE + sum((1 - c0) * (1 - c1)) / sum(1 - c0)::DOUBLE) / 2, 6) AS balanced_accuracy, round(avg((c0 = c1)::INT), 6) AS agreement FROM calls GROUP BY spec"))
def a03(spark, sf):
    out = None
    for s in TOPICS:
        c = [teacher.verdict(s, F.col("text"), F.col("snippet_id"), NOISY, k).alias(f"c{k}") for k in (0, 1)]
        rows = snips(spark, sf).select(F.lit(s).alias("spec"), *c)
        out = rows if out is None else out.union(rows)
    found = metrics.confusion(out, "c0", "c1", ["spec"])
    return found.select("spec", F.round("balanced_accuracy", 6).alias("balanced_accuracy"), F.round("accuracy", 6).alias("agreement"))


WITH_COMMON = f"{SNIPS}, {twins.COMMON}, sn AS (SELECT * FROM snips, (SELECT list(token) AS cm FROM common))"
CONSISTENCY_FIVE = " UNION ALL ".join(f"SELECT '{s}' AS spec, {noisy_sql(s, 'teacher', 0, 0.03, 0.03)} AS c0, {noisy_sql(s, 'teacher', 1, 0.03, 0.03)} AS c1 FROM sn" for s in FIVE)


@query("a03b_self_consistency_five", with_sql(f"{WITH_COMMON}, calls AS ({CONSISTENCY_FIVE})", "SELECT spec, round((sum(c0 * c1) / sum(c0)::DOUBLE + sum((1 - c0) * (1 - c1)) / sum(1 - c0)::DOUBLE) / 2, 6) AS balanced_accuracy, round(avg((c0 = c1)::INT), 6) AS agreement FROM calls GROUP BY spec"))
def a03b(spark, sf):
    out, common = None, common_words(spark, sf)
    for s in FIVE:
        c = [teacher.verdict(s, F.col("text"), F.col("snippet_id"), NOISY, k, common).alias(f"c{k}") for k in (0, 1)]
        rows = snips(spark, sf).select(F.lit(s).alias("spec"), *c)
        out = rows if out is None else out.union(rows)
    found = metrics.confusion(out, "c0", "c1", ["spec"])
    return found.select("spec", F.round("balanced_accuracy", 6).alias("balanced_accuracy"), F.round("accuracy", 6).alias("agreement"))


VOTE = twins.hash_int("'vote'", "'quality'", "g", "a", "snippet_id")
PANEL = f"""{SCORED}, calls AS (SELECT snippet_id, label AS truth, (margin_micro > 0)::INT AS student, {noisy_sql('quality', 'teacher', 0, 0.1, 0.1)} AS teacher FROM scored),
    apart AS (SELECT * FROM calls WHERE teacher <> student ORDER BY {twins.hash_int("'panel'", "'quality'", "snippet_id")}, snippet_id LIMIT 100),
    votes AS (SELECT snippet_id, student, g, a, CASE WHEN {VOTE} < {int(0.1 * (1 << 32))} THEN 1 - truth ELSE truth END AS vote FROM apart, (SELECT unnest(range(1, 3)) AS g), (SELECT unnest(range(1, 14)) AS a)),
    said AS (SELECT g, snippet_id, (2 * sum(vote) > count(*))::INT AS said, any_value(student) AS student FROM votes GROUP BY ALL HAVING true)"""
PANEL = PANEL.replace("GROUP BY ALL HAVING true", "GROUP BY g, snippet_id")


@query("a04_human_preference", with_sql(PANEL, "SELECT g::INT AS group_no, count(*) AS n_snippets, count(*) FILTER (said = student) AS student_wins, round(count(*) FILTER (said = student) / count(*)::DOUBLE, 6) AS preference FROM said GROUP BY g"))
def a04(spark, sf):
    rows = scored(spark, sf).select("snippet_id", F.col("label").alias("truth"), engine.passes(F.col("margin_micro")).alias("student"), teacher.verdict("quality", F.col("text"), F.col("snippet_id"), TeacherConfig().noisy(0.1)).alias("teacher"))
    return metrics.human_preference(rows, "teacher", "student", "truth", "quality").withColumn("preference", F.round("preference", 6))


IMBALANCE = "SELECT ord, n_pass, ord - n_pass AS n_fail, round(least(n_pass, ord - n_pass) / greatest(n_pass, ord - n_pass)::DOUBLE, 6) AS imbalance FROM (SELECT ord, (sum(label) OVER (ORDER BY ord))::BIGINT AS n_pass FROM r_bought)"


@query("a05_imbalance_ratio", round_sql(IMBALANCE))
def a05(spark, sf):
    rows = m13(spark, sf).withColumn("policy", F.lit("band"))
    return metrics.imbalance(rows, ["policy"]).select("ord", "n_pass", "n_fail", F.round("imbalance", 6).alias("imbalance"))


@query("a06_class_prior", with_sql(SNIPS, " UNION ALL ".join(f"SELECT '{s}' AS spec, round(avg({twins.rule(s)}), 6) AS pass_share FROM snips" for s in TOPICS)))
def a06(spark, sf):
    rows = stream(spark, sf).agg(*(F.round(F.avg(s), 6).alias(s) for s in TOPICS))
    return rows.unpivot([], list(TOPICS), "spec", "pass_share")


@query("a06b_class_prior_five", with_sql(WITH_COMMON, " UNION ALL ".join(f"SELECT '{s}' AS spec, round(avg({twins.rule(s)}), 6) AS pass_share FROM sn" for s in FIVE)))
def a06b(spark, sf):
    rows = stream(spark, sf).agg(*(F.round(F.avg(s), 6).alias(s) for s in FIVE))
    return rows.unpivot([], list(FIVE), "spec", "pass_share")


CALLS5 = " UNION ALL ".join(f"SELECT snippet_id, {noisy_sql('quality', 'teacher', k, 0.1, 0.1)} AS verdict FROM snips" for k in range(5))
WILSON = "SELECT snippet_id, k, round(p, 6) AS eta, round((p + z2 / (2 * k)) / (1 + z2 / k) - half, 6) AS eta_lo, round((p + z2 / (2 * k)) / (1 + z2 / k) + half, 6) AS eta_hi FROM (SELECT snippet_id, count(*) AS k, avg(1 - verdict) AS p, 1.96 * 1.96 AS z2, 1.96 * sqrt(avg(1 - verdict) * (1 - avg(1 - verdict)) / count(*) + 1.96 * 1.96 / (4 * count(*) * count(*))) / (1 + 1.96 * 1.96 / count(*)) AS half FROM calls GROUP BY snippet_id)"


@query("a09_eta_estimate", with_sql(f"{SNIPS}, calls AS ({CALLS5})", WILSON))
def a09(spark, sf):
    return theory.eta_from_calls(_five_calls(spark, sf)).select("snippet_id", "k", *(F.round(c, 6).alias(c) for c in ("eta", "eta_lo", "eta_hi")))


def _five_calls(spark, sf):
    rows = snips(spark, sf).withColumn("call_no", F.explode(F.array(*(F.lit(k) for k in range(5)))))
    return rows.select("snippet_id", teacher.verdict("quality", F.col("text"), F.col("snippet_id"), TeacherConfig().noisy(0.1), F.col("call_no")).alias("verdict"))


LO, HI = 0.45, 0.55


@query("a10_true_risk", with_sql(f"{SCORED}, {RANKED}, {RISK}", "SELECT round(cut, 9) AS cut, round(risk, 6) AS risk, round(risk - (SELECT min(risk) FROM risk), 6) AS excess FROM risk"))
def a10(spark, sf):
    rows = threshold.true_cut(ranked(spark, sf))
    best = rows.agg(F.min("risk").alias("best"))
    return rows.crossJoin(F.broadcast(best)).select(F.round("cut", 9).alias("cut"), F.round("risk", 6).alias("risk"), F.round(F.col("risk") - F.col("best"), 6).alias("excess"))


def band_of_scores(spark, sf):
    """The scores at 45 % and 55 % of the places."""
    rows = ranked(spark, sf)
    r = rows.agg(F.min(F.when(F.col("place") >= LO * F.col("n"), F.col("score"))).alias("lo"), F.max(F.when(F.col("place") <= HI * F.col("n"), F.col("score"))).alias("hi")).first()
    return rows, r.lo, r.hi


ENDS = f"{SCORED}, {RANKED}, {RISK}, pl AS (SELECT *, row_number() OVER (ORDER BY score, snippet_id) AS place, count(*) OVER () AS n FROM ranked), ends AS (SELECT min(score) FILTER (place >= {LO} * n) AS lo, max(score) FILTER (place <= {HI} * n) AS hi FROM pl)"


@query("a11_band_gap", with_sql(ENDS, "SELECT round((SELECT risk FROM risk, ends WHERE cut = lo) - min(risk), 6) AS gap_lo, round((SELECT risk FROM risk, ends WHERE cut = hi) - min(risk), 6) AS gap_hi FROM risk"))
def a11(spark, sf):
    rows, lo, hi = band_of_scores(spark, sf)
    return theory.band_gap(threshold.true_cut(rows), lo, hi).select(F.round("gap_lo", 6).alias("gap_lo"), F.round("gap_hi", 6).alias("gap_hi"))


@query("a12_smoothness", with_sql(f"{SCORED}, {RANKED}", "SELECT round(max(abs(eta - p)), 9) AS smoothness FROM (SELECT eta, lag(eta) OVER (ORDER BY score, snippet_id) AS p FROM ranked)"))
def a12(spark, sf):
    return theory.smoothness(ranked(spark, sf)).select(F.round("smoothness", 9).alias("smoothness"))


@query("a13_interval_balance", with_sql(ENDS, "SELECT round(sum(eta), 6) AS c0, round(sum(1 - eta), 6) AS c1, round(least(sum(eta), sum(1 - eta)) / greatest(sum(eta), sum(1 - eta)), 6) AS balance FROM ranked, ends WHERE score BETWEEN lo AND hi"))
def a13(spark, sf):
    rows, lo, hi = band_of_scores(spark, sf)
    return theory.interval_balance(rows, lo, hi).select(*(F.round(c, 6).alias(c) for c in ("c0", "c1", "balance")))


GAPS = [(1000, a, b, s) for a in (0.0001, 0.0025, 0.01) for b in (0.0001, 0.0049) for s in (0.0, 0.001, 0.2)]


@query("a14_balance_bound", f"""SELECT n, a AS gap_lo, b AS gap_hi, s AS smooth, round(1 - least((n * greatest(a, b) + s * n) / (1.5 - 2 * s), sqrt(s) * (n * greatest(a, b) + s * n + 1) / ((1 - s) * sqrt(n * least(a, b)))), 6) AS bound
    FROM (SELECT unnest([1000]) AS n), (SELECT unnest([0.0001, 0.0025, 0.01]::DOUBLE[]) AS a), (SELECT unnest([0.0001, 0.0049]::DOUBLE[]) AS b), (SELECT unnest([0.0, 0.001, 0.2]::DOUBLE[]) AS s)""")
def a14(spark, sf):
    rows = spark.createDataFrame(GAPS, "n int, gap_lo double, gap_hi double, smooth double")
    return rows.withColumn("bound", F.round(theory.balance_bound_column(F.col("n"), F.col("gap_lo"), F.col("gap_hi"), F.col("smooth")), 6))


@query("a15_risk_bound")
def a15(spark, sf):
    """How the excess risk of the band's ends falls with the radius over one round, and the least constants that envelop
    it. A teacher of graded certainty; a trace's few ends are joined to the risk curve, which stays where it is."""
    rows = graded(spark, sf)
    run = active.distil(stream(spark, sf), "topic_hostile", LITERAL, teacher=TeacherConfig(mode="graded"))
    rows = students.score(rows, run.models[0][1])
    risk = threshold.true_cut(rows.select(F.col("margin_micro").cast("double").alias("score"), "eta"), width=1 << 16)
    ends = spark.createDataFrame([(t, b, e, float(x)) for _, t, lo, hi, _, _, b, _ in run.trace for e, x in (("lo", lo), ("hi", hi))], "t bigint, beta double, end string, at double")
    best = risk.agg(F.min("risk").alias("best"))
    # the risk at an end is that of the nearest cut at or below it; below all scores it is the candidate 0's
    floor = risk.where("cut = 0").select(F.col("risk").alias("zero"))
    at = risk.join(F.broadcast(ends), F.col("cut") <= F.col("at")).where("cut <> 0").groupBy("t", "beta", "end").agg(F.max_by("risk", "cut").alias("risk"))
    found = ends.join(at, ["t", "beta", "end"], "left").crossJoin(best).crossJoin(floor)
    gaps = [(r.t, r.beta, r.end, (r.zero if r.risk is None else r.risk) - r.best, r.best) for r in found.collect()]
    if not gaps:
        return spark.createDataFrame([], "t bigint, beta double, gap_lo double, gap_hi double, c_with_risk double, c_without double")
    with_, without = theory.risk_envelope([(b, g) for _, b, _, g, _ in gaps], gaps[0][4])
    by_t = {}
    for t, b, e, g, _ in gaps:
        by_t.setdefault((t, b), {})[e] = g
    return spark.createDataFrame([(t, b, e["lo"], e["hi"], with_, without) for (t, b), e in sorted(by_t.items())], "t bigint, beta double, gap_lo double, gap_hi double, c_with_risk double, c_without double")


def graded(spark, sf, spec: str = "topic_hostile") -> DataFrame:
    """The stream with the probability of class 0 under a teacher of graded certainty."""
    p = teacher.pass_probability(spec, F.col("text"), TeacherConfig(mode="graded"))
    return stream(spark, sf).select("snippet_id", "stream_pos", "text", (1 - p).alias("eta"))


@query("a19_trial_spread", with_sql(SCORED, " UNION ALL ".join(f"SELECT {k} AS trial, round(avg(label), 6) AS pass_share FROM scored WHERE {twins.hash_int(chr(39) + 'trial' + str(k) + chr(39), 'snippet_id')} < {int(0.25 * (1 << 32))}" for k in range(3))))
def a19(spark, sf):
    rows = scored(spark, sf)
    parts = [rows.where(hash_below(0.25, f"trial{k}", F.col("snippet_id"))).agg(F.lit(k).alias("trial"), F.round(F.avg("label"), 6).alias("pass_share")) for k in range(3)]
    return parts[0].union(parts[1]).union(parts[2])


TRIALS = " UNION ALL ".join(f"SELECT {k} AS trial, round(avg(label), 6) AS pass_share FROM (SELECT label, sum(n_tokens) OVER (ORDER BY {twins.hash_int(chr(39) + 'take' + str(k) + chr(39), 'snippet_id')}, snippet_id) AS upto FROM scored WHERE margin_micro > 0) WHERE upto <= 50000" for k in range(3))


@query("a19b_selection_spread", with_sql(SCORED, f"SELECT count(*) AS trials, round(avg(pass_share), 6) AS mean, min(pass_share) AS least, max(pass_share) AS most FROM ({TRIALS})"))
def a19b(spark, sf):
    """Three random selections of one token budget from what the student passes: the spread of their quality."""
    rows = engine.filter_corpus(scored(spark, sf).drop("margin_micro", "score"), first_student(spark, sf)).select(F.col("snippet_id").alias("doc_id"), "n_tokens", "label")
    parts = [recipes.take_tokens(rows, 50_000, k).agg(F.round(F.avg("label"), 6).alias("pass_share")) for k in range(3)]
    out = parts[0].union(parts[1]).union(parts[2])
    return out.agg(F.count("*").alias("trials"), F.round(F.avg("pass_share"), 6).alias("mean"), F.min("pass_share").alias("least"), F.max("pass_share").alias("most"))


# costs

PRICE, WEAK = cost.CostModel().teacher_price, cost.CostModel().weak_price
PUBLISHED = "(VALUES " + ", ".join(f"('{f}', {c}, {s}, {t})" for f, c, s, t in cost.PUBLISHED) + ") p(filter, calls, student_usd, total_usd)"


@query("c01_teacher_calls", round_sql(f"SELECT round, calls FROM (SELECT 0 AS round, {SEED}::BIGINT AS calls UNION ALL SELECT 1, count(*) FROM r_bought)"))
def c01(spark, sf):
    rows = a_run(spark, sf).labels_df(spark)
    return cost.teacher_calls(rows.union(rows), ["round"])


@query("c02_student_cost", with_sql(STREAM, f"SELECT component, tokens, round(tokens / 1e6 * CASE WHEN component = 'training' THEN 0.05 ELSE 0.008 END, 9) AS usd FROM (SELECT 'training' AS component, sum(n_tokens)::BIGINT AS tokens FROM stream WHERE stream_pos < {SEED} UNION ALL SELECT 'inference', sum(n_tokens)::BIGINT FROM stream)"))
def c02(spark, sf):
    rows = stream(spark, sf)
    parts = rows.where(F.col("stream_pos") < SEED).agg(F.lit("training").alias("component"), F.sum("n_tokens").alias("tokens")).union(rows.agg(F.lit("inference"), F.sum("n_tokens")))
    return cost.student_cost(parts).withColumn("usd", F.round("usd", 9))


def training_sql(config: RunConfig = ENGINE) -> str:
    """Tokens of all fits of a whole run: a round's fit happens while all rounds before it were full."""
    uses = [f"(SELECT coalesce(sum(n_tokens), 0) FROM e_l{r - 1} JOIN stream USING (snippet_id) WHERE (SELECT count(*) FROM e_l{r - 1}) = {config.batch * r})" for r in range(1, config.rounds + 1)]
    return " + ".join([*uses, "(SELECT coalesce(sum(n_tokens), 0) FROM e_lab JOIN stream USING (snippet_id))"])


HEAD = f"(SELECT CASE WHEN count(*) = {ENGINE.budget} THEN max(stream_pos) + 1 ELSE (SELECT count(*) FROM stream) END FROM e_lab)"
COUNTERS = f"k AS MATERIALIZED (SELECT ({training_sql()})::BIGINT AS training, (SELECT sum(n_tokens) FROM stream WHERE stream_pos >= {SEED} AND stream_pos < {HEAD})::BIGINT AS scoring, (SELECT sum(n_tokens) FROM stream)::BIGINT AS inference, (SELECT count(*) FROM e_lab) AS calls, (SELECT count(*) FROM stream) AS n)"
COUNTED = f"{twins.engine(ENGINE, BLOCKS)}, {COUNTERS}"
STUDENT_USD = "(training / 1e6 * 0.05 + (scoring + inference) / 1e6 * 0.008)"


@query("c02b_run_cost", with_sql(COUNTED, "SELECT component, tokens, round(tokens / 1e6 * CASE WHEN component = 'training' THEN 0.05 ELSE 0.008 END, 9) AS usd FROM (UNPIVOT (SELECT training, scoring, inference FROM k) ON training, scoring, inference INTO NAME component VALUE tokens)"))
def c02b(spark, sf):
    return cost.student_cost(cost.run_counters(stream(spark, sf), engine_run(spark, sf))).withColumn("usd", F.round("usd", 9))


@query("c03_total_cost", f"SELECT filter, calls::BIGINT AS calls, total_usd::BIGINT AS total_usd, round(student_usd + calls * {PRICE!r}::DOUBLE, 4) AS computed_usd, abs(student_usd + calls * {PRICE!r}::DOUBLE - total_usd) <= 5 AS within_5_usd FROM {PUBLISHED}")
def c03(spark, sf):
    out = cost.totals(cost.published(spark))
    return out.select("filter", "calls", "total_usd", F.round("computed_usd", 4).alias("computed_usd"), (F.abs(F.col("computed_usd") - F.col("total_usd")) <= 5).alias("within_5_usd"))


@query("c04_cost_ratio", f"SELECT filter, round((student_usd + calls * {PRICE!r}::DOUBLE) / 67000.0::DOUBLE, 6) AS ratio, (student_usd + calls * {PRICE!r}::DOUBLE) / 67000.0::DOUBLE < 0.01 AS below_one_percent, round(67000.0::DOUBLE / (student_usd + calls * {PRICE!r}::DOUBLE), 2) AS operations_per_call FROM {PUBLISHED}")
def c04(spark, sf):
    out = cost.totals(cost.published(spark))
    return out.select("filter", F.round("ratio", 6).alias("ratio"), "below_one_percent", F.round("operations_per_call", 2).alias("operations_per_call"))


@query("c05_naive_projection", with_sql(SNIPS, f"SELECT k AS times, (count(*) * k)::BIGINT AS snippets, round(count(*) * k * {PRICE!r}::DOUBLE, 4) AS usd FROM snips, (SELECT unnest([1, 1000]::BIGINT[]) AS k) GROUP BY k"))
def c05(spark, sf):
    n = snips(spark, sf).agg(F.count("*").alias("n"))
    rows = n.withColumn("times", F.explode(F.array(F.lit(1).cast("bigint"), F.lit(1000).cast("bigint"))))
    return rows.select("times", (F.col("n") * F.col("times")).alias("snippets"), F.round(F.col("n") * F.col("times") * F.lit(PRICE), 4).alias("usd"))


@query("c06_price_sweep", f"SELECT method, f AS factor, round(student_usd + calls * f * {PRICE!r}::DOUBLE, 4) AS usd FROM (VALUES ('band', 7500, 80), ('random', 22500, 80), ('full', 13500000, 0)) m(method, calls, student_usd), (SELECT unnest([1, 3, 10, 30]::DOUBLE[]) AS f)")
def c06(spark, sf):
    rows = spark.createDataFrame([("band", 7500, 80), ("random", 22500, 80), ("full", 13_500_000, 0)], "method string, calls bigint, student_usd bigint")
    return cost.price_sweep(rows, [1, 3, 10, 30]).select("method", "factor", F.round("usd", 4).alias("usd"))


def billed(spark, sf, run: active.Run) -> tuple[int, dict[str, float]]:
    """(calls, USD by component) of a run, from its counters."""
    parts = cost.student_cost(cost.run_counters(stream(spark, sf), run)).collect()
    return run.calls, {r.component: r.usd for r in parts}


RANDOM_TRAINING = " + ".join(f"(SELECT coalesce(sum(n_tokens), 0) FROM stream WHERE stream_pos < {SEED * k})" for k in range(1, ENGINE.rounds + 2))
SWEEP = f"""SELECT 'band' AS method, calls, {STUDENT_USD} AS student_usd FROM k UNION ALL SELECT 'random', least(n, {ENGINE.budget}), ({RANDOM_TRAINING}) / 1e6 * 0.05 + inference / 1e6 * 0.008 FROM k UNION ALL SELECT 'full', n, 0 FROM k"""


@query("c06b_price_sweep_of_runs", with_sql(COUNTED, f"SELECT method, f AS factor, calls::BIGINT AS calls, round(student_usd + calls * f * {PRICE!r}::DOUBLE, 6) AS usd FROM ({SWEEP}), (SELECT unnest([1, 3, 10, 30]::DOUBLE[]) AS f)"))
def c06b(spark, sf):
    """What each method costs as the teacher gets dearer, from the counters of its run at one budget."""
    from dataclasses import replace

    rows = [("full", stream(spark, sf).count(), 0.0)]
    for policy in ("band", "random"):
        calls, usd = billed(spark, sf, engine_run(spark, sf, config=replace(ENGINE, policy=policy)))
        rows.append((policy, calls, sum(usd.values())))
    out = cost.price_sweep(spark.createDataFrame(rows, "method string, calls bigint, student_usd double"), [1, 3, 10, 30])
    return out.select("method", "factor", "calls", F.round("usd", 6).alias("usd"))


END = f"CASE WHEN count(*) = {SEED} THEN max(stream_pos) + 1 ELSE (SELECT count(*) FROM stream) END AS seen FROM"
NEAR = f"(SELECT stream_pos FROM scored WHERE stream_pos >= {SEED} AND abs(score - 0.5) <= 0.4 ORDER BY stream_pos LIMIT {SEED})"


@query("c07_pool_vs_stream", round_sql(f"SELECT policy, calls::BIGINT AS calls, seen::BIGINT AS seen, (CASE WHEN policy = 'pool_uncertainty' THEN n ELSE seen - {SEED} END + n)::BIGINT AS student_passes FROM (SELECT 'band' AS policy, count(*) + {SEED} AS calls, {END} r_bought UNION ALL SELECT 'uncertainty', count(*) + {SEED}, {END} {NEAR} UNION ALL SELECT 'pool_uncertainty', {2 * SEED}, {SEED}), (SELECT count(*) AS n FROM stream)"))
def c07(spark, sf):
    """Calls, rows of the stream read, and student passes: those to choose labels by, and the corpus once at the end."""
    n = stream(spark, sf).count()
    rows = []
    for policy in ("band", "uncertainty", "pool_uncertainty"):
        run = a_run(spark, sf, policy)
        rows.append((policy, run.calls, run.seen, (run.passes or run.seen - SEED) + n))
    return spark.createDataFrame(rows, "policy string, calls bigint, seen bigint, student_passes bigint")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The passing snippets of `quality` by a student distilled from a small budget."""
    rows = stream(spark, sf_dir).select("snippet_id", "stream_pos", "doc_id", "n_tokens", "text")
    run = active.distil(rows, "quality", RunConfig(batch=128, budget=384, radius_scale=0.5))
    return engine.filter_corpus(rows, run.model).select("snippet_id", "doc_id", "n_tokens", "margin_micro", F.round("score", 6).alias("score"))


ALL_SPECS = tuple(SPECS)
