"""The experiment workloads and option sweeps on the given tables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import RunConfig, StudentConfig, TeacherConfig
from ..functions.hashing import hash_below
from ..functions.text import tokens
from ..operators import cost, metrics, snippets, students, teacher, theory, threshold
from ..plans import active, engine, recipes
from ..sources.html import pages_as_documents
from ..sources.tables import kept, materialise, table
from . import twins
from .methods import BLOCKS, COUNTED, ENGINE, LITERAL, PRICE, SCORED, SEED, WEAK, billed, common_words, engine_run, engine_sql, first_student, graded, m13b, noisy_sql, scored, snips, stream, test_rows, with_sql
from .registry import query

#: Runs of the workloads: a test split of a fifth by text is never bought; the radius is scaled for the small tables.
WORK = RunConfig(batch=256, budget=1024, radius_scale=0.5)


def train_stream(spark, sf, seed: int = 7) -> DataFrame:
    """The stream without the test split, positions made dense again, in the order of a seed."""

    def build():
        rows = stream(spark, sf).where(~snippets.held_out(F.col("text"))).drop("stream_pos")
        return snippets.order(rows, seed).drop("stream_key", "stream_bucket")

    return kept(spark, sf, f"train-stream-{seed}", build)


def test_split(spark, sf) -> DataFrame:
    return stream(spark, sf).where(snippets.held_out(F.col("text")))


def accuracies(spark, sf, cuts: list[tuple[students.Student, int]], spec: str) -> list[float | None]:
    """Balanced accuracy on the test split of each (student, cut): one scan for all of them."""
    rows = engine.filter_many(test_split(spark, sf).select("text", spec), {str(k): c for k, c in enumerate(cuts)})
    long = rows.select(spec, F.posexplode(F.array(*(f"pass_{k}" for k in range(len(cuts))))).alias("k", "pred"))
    found = {r.k: r.balanced_accuracy for r in metrics.balanced_accuracy(long, spec, "pred", ["k"]).collect()}
    return [found.get(k) for k in range(len(cuts))]


def accuracy(spark, sf, model, spec: str, cut: int = 0) -> float:
    return accuracies(spark, sf, [(model, cut)], spec)[0]


def run_of(spark, sf, policy: str, spec: str, config: RunConfig = WORK, student: StudentConfig = StudentConfig(), teacher_: TeacherConfig = TeacherConfig(), common: list[str] | None = None, seed: int = 7) -> active.Run:
    """policy: one of the loop's, or band_nested: the band that only narrows."""
    rows = train_stream(spark, sf, seed).select("snippet_id", "stream_pos", "text")
    own = replace(config, policy="band", nested=True) if policy == "band_nested" else replace(config, policy=policy)
    return active.distil(rows, spec, own, student, teacher_, common, n=rows.count())


def equal_odds(spark, run: active.Run) -> list[int]:
    """The empirical cut of each of a run's students over the labels it was fit on: their margins as numbers, one scan."""
    rows = spark.read.schema(active.LABELS).parquet(*run.paths)
    rows = rows.select("ord", F.col("verdict").cast("bigint").alias("verdict"), *(m.margin(F.col("text")).alias(f"m{k}") for k, (_, m) in enumerate(run.models))).toArrow()
    order, y, out = rows["ord"].to_numpy(), rows["verdict"].to_numpy(), []
    for k, (calls, _) in enumerate(run.models):
        counts = threshold.Counts()
        counts.add(rows[f"m{k}"].to_numpy()[order < calls], y[order < calls])
        out.append(counts.update(calls, calls, 0.1, 1.0)[2])
    return out


POLICIES = ("band", "band_nested", "random", "uncertainty")
CURVE = "spec string, policy string, stream_order int, calls bigint, n_pass bigint, n_fail bigint, balanced_accuracy double, balanced_accuracy_eot double"


def curve(spark, sf, spec: str, policies=POLICIES, config: RunConfig = WORK, orders=(7,)) -> DataFrame:
    """A row for each policy, stream order and student on the way: its calls, their classes, and its accuracy at both cuts."""
    out = []
    for seed in orders:
        for policy in policies:
            run = run_of(spark, sf, policy, spec, config, seed=seed)
            verdicts, models = [v for *_, v in run.labels], {calls: (m, cut) for (calls, m), cut in zip(run.models, equal_odds(spark, run), strict=True)}
            found = accuracies(spark, sf, [(m, c) for m, cut in models.values() for c in (0, cut)], spec)
            for (calls, _), half, eot in zip(models.items(), found[::2], found[1::2], strict=True):
                ones = sum(verdicts[:calls])
                out.append((spec, policy, seed, calls, ones, calls - ones, half, eot))
    return spark.createDataFrame(out, CURVE)


def spread(rows: DataFrame) -> DataFrame:
    """Over stream orders: mean, least and most of the measures at each number of calls."""
    share = rows.withColumn("minority", F.least("n_pass", "n_fail") / F.col("calls"))
    return share.groupBy("spec", "policy", "calls").agg(F.count("*").alias("orders"), *(f(c).alias(f"{c}{end}") for c in ("minority", "balanced_accuracy", "balanced_accuracy_eot") for f, end in ((F.avg, ""), (F.min, "_least"), (F.max, "_most"))))


@query("a07_accuracy_curve")
def a07(spark, sf):
    return curve(spark, sf, "quality")


@query("a08_savings_factor")
def a08(spark, sf):
    """Calls that random choice needs against the band's to reach the lower of their best accuracies."""
    rows = curve(spark, sf, "quality", ("band", "random"))
    best = rows.groupBy("policy").agg(F.max("balanced_accuracy").alias("m")).agg(F.min("m")).first()[0]
    return metrics.savings(rows, float(best))


@query("a16_coverage")
def a16(spark, sf):
    """Of 30 seeded rounds on synthetic scores: how many bands held the true cut at every update."""
    import numpy as np

    rows = []
    for seed in range(30):
        rng = np.random.default_rng(seed)
        n = 4000
        margin = np.sort(rng.permutation(n * 10)[:n]) - 20_000
        eta = 1 - (np.arange(n) + 0.5) / n
        order = rng.permutation(n)
        label = (rng.random(n) > eta).astype(int)
        trace: list = []
        active.local_round(np.arange(n), margin[order], label[order], n, n, RunConfig(delta=0.1, nested=True), trace)
        best = margin[n // 2]
        rows.append((seed, all(lo <= best <= hi for _, _, lo, hi, *_ in trace), len(trace)))
    return spark.createDataFrame(rows, "seed int, covered boolean, updates int")


@query("a16b_coverage_by_rule")
def a16b(spark, sf):
    """Of 40 seeded rounds on synthetic scores: how many bands held the true cut at every update, by either update rule."""
    import numpy as np

    rows = []
    for seed in range(1000, 1040):
        rng = np.random.default_rng(seed)
        n = 4000
        margin = np.sort(rng.permutation(n * 10)[:n]) - 20_000
        eta = 1 - (np.arange(n) + 0.5) / n
        order = rng.permutation(n)
        label = (rng.random(n) > eta).astype(int)
        best = margin[n // 2]
        for rule, nested in (("printed", False), ("nested", True)):
            trace: list = []
            active.local_round(np.arange(n), margin[order], label[order], n, n, RunConfig(delta=0.1, nested=nested), trace)
            # an end at the highest score seen so far says nothing of scores above it
            tops = [max(margin[order][: t + 1]) for _, t, *_ in trace]
            rows.append((seed, rule, all(lo <= best <= hi for _, _, lo, hi, *_ in trace), all(lo <= best and (best <= hi or hi == top) for (_, _, lo, hi, *_), top in zip(trace, tops, strict=True)), len(trace)))
    return spark.createDataFrame(rows, "seed int, rule string, covered boolean, covered_among_seen boolean, updates int")


PREFERRED = ("mainstream", "quality")


@query("w01_five_filters")
def w01(spark, sf):
    """Per filter and method: balanced accuracy against one call of the teacher, the panel's preference, calls and costs.

    The teacher's own row is a second call, on the whole corpus; the student's costs come from its run's counters.
    """
    eps = {"topic_hostile": 0.02, "topic_legal": 0.025, "topic_private": 0.025, "mainstream": 0.07, "quality": 0.07}
    common, model = common_words(spark, sf), cost.CostModel()
    every = stream(spark, sf).agg(*(F.avg(x).alias(x) for x in eps), F.count("*").alias("n")).first()
    out = []
    for spec in eps:
        # errors in proportion to the classes, so that a call repeated agrees about equally well on both
        up, down = (eps[spec] * min(1.0, (1 - every[spec]) / max(every[spec], 1e-6)), eps[spec] * min(1.0, every[spec] / max(1 - every[spec], 1e-6)))
        noisy = TeacherConfig(mode="noisy", eps_pos=up, eps_neg=down)
        weak = TeacherConfig("weak", "noisy", 3 * up, 3 * down)
        run = run_of(spark, sf, "band", spec, WORK, StudentConfig(), noisy, common)
        sid, text = F.col("snippet_id"), F.col("text")
        calls = [teacher.verdict(spec, text, sid, noisy, 10, common).alias("call"), teacher.verdict(spec, text, sid, noisy, 11, common).alias("teacher"), teacher.verdict(spec, text, sid, weak, 10, common).alias("weak"), engine.passes(F.col("margin_micro")).alias("student")]
        rows = materialise(students.score(test_split(spark, sf), run.model).select("snippet_id", F.col(spec).alias("truth"), *calls), "verdicts")
        long = rows.select("call", F.posexplode(F.array("teacher", "weak", "student")).alias("k", "pred"))
        found = {r.k: r.balanced_accuracy for r in metrics.balanced_accuracy(long, "call", "pred", ["k"]).collect()}
        preference = None
        if spec in PREFERRED:
            said = metrics.human_preference(rows, "call", "student", "truth", spec).agg(F.sum("student_wins") / F.sum("n_snippets")).first()[0]
            preference = None if said is None else float(said)
        used = {r.component: r.usd for r in cost.student_cost(cost.run_counters(train_stream(spark, sf), run)).collect()}
        for k, (method, billed, price, own) in enumerate((("teacher", every.n, model.teacher_price, 0.0), ("weak", every.n, model.weak_price, 0.0), ("student", run.calls, model.teacher_price, sum(used.values())))):
            total = own + billed * price
            prefers = {"teacher": 0.5, "student": preference}.get(method) if spec in PREFERRED else None
            out.append((spec, method, found.get(k), prefers, billed, own, total, total / (every.n * model.teacher_price)))
    return spark.createDataFrame(out, "spec string, method string, balanced_accuracy double, preference double, calls bigint, student_usd double, total_usd double, ratio double")


#: The curves of the published figure: 512 labels a round up to 2,048, over three stream orders.
CURVES = replace(WORK, batch=512, budget=2048)
query("w02_active_vs_random_a")(lambda spark, sf: spread(curve(spark, sf, "topic_hostile", config=CURVES, orders=(7, 8, 9))))
query("w03_active_vs_random_b")(lambda spark, sf: spread(curve(spark, sf, "topic_legal", config=CURVES, orders=(7, 8, 9))))


@query("w04_query_imbalance")
def w04(spark, sf):
    parts = []
    for spec in ("quality", "topic_hostile"):
        for policy in POLICIES:
            rows = run_of(spark, sf, policy, spec).labels_df(spark).withColumn("policy", F.lit(policy)).withColumn("spec", F.lit(spec))
            parts.append(metrics.imbalance(rows, ["spec", "policy"]).where("(ord + 1) % 128 = 0").select("spec", "policy", (F.col("ord") + 1).alias("calls"), "n_pass", "n_fail", "imbalance"))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


# recipes and the selection challenge


@query("b08_source_filter", "SELECT doc_id FROM documents WHERE source IN ('src0', 'src2', 'src4', 'src6')")
def b08(spark, sf):
    return recipes.trusted_sources(table(spark, sf, "documents"), ["src0", "src2", "src4", "src6"]).select("doc_id")


PRESET = f"(len({twins.tokens()}) >= 20 AND length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) <= 0.02 * length(text) AND len(list_distinct(list_transform({twins.tokens()}, lambda x: lower(x)))) >= 0.3 * len({twins.tokens()}) AND {twins.evidence('topic_hostile')} = 0)"


@query("b09_heuristic_quality", f"SELECT doc_id, {PRESET}::INT AS good FROM documents")
def b09(spark, sf):
    return table(spark, sf, "documents").select("doc_id", recipes.preset_detectors(F.col("text")).alias("good"))


def pool(spark, sf) -> DataFrame:
    """Documents and page texts in one pool; page ids are negative."""
    docs = table(spark, sf, "documents", ["doc_id", "text"])
    pages = pages_as_documents(table(spark, sf, "pages")).select((-F.col("doc_id") - 1).alias("doc_id"), "text")
    return docs.union(pages).withColumn("n_tokens", F.size(tokens(F.col("text"))))


def ngram_selection(spark, sf, share: float = 0.5) -> DataFrame:
    def build():
        positives = table(spark, sf, "conversations").where("role = 'assistant'").select("text")
        negatives = table(spark, sf, "documents").select("text")
        return recipes.ngram_classifier(pool(spark, sf), positives, negatives, share)

    return kept(spark, sf, "ngram-selection", build)


@query("b10_ngram_recipe")
def b10(spark, sf):
    return ngram_selection(spark, sf).select("doc_id", "margin_micro", "kept")


def score_selection(spark, sf) -> DataFrame:
    def build():
        graded = table(spark, sf, "documents").select("text", recipes.grade(F.col("text")).alias("grade"))
        return recipes.annotated_score(pool(spark, sf), graded)

    return kept(spark, sf, "score-selection", build)


@query("b11_score_recipe")
def b11(spark, sf):
    return score_selection(spark, sf).select("doc_id", F.round("grade", 6).alias("grade"), "kept")


@query("b12_cascade")
def b12(spark, sf):
    """The n-gram recipe's survivors, then the distilled quality student on them alone."""
    some = ngram_selection(spark, sf).where("kept = 1").select("doc_id", "text", "n_tokens")
    return engine.filter_corpus(some, engine_run(spark, sf).model).select("doc_id", "n_tokens")


TAKE = twins.hash_int("'take0'", "doc_id")


@query("b13_budget_select", f"SELECT doc_id, n_chars FROM (SELECT doc_id, n_chars, sum(n_chars) OVER (ORDER BY {TAKE}, doc_id) AS upto FROM documents) WHERE upto <= 500000")
def b13(spark, sf):
    rows = table(spark, sf, "documents", ["doc_id", "n_chars"]).withColumnRenamed("n_chars", "n_tokens")
    return recipes.take_tokens(rows, 500_000).withColumnRenamed("n_tokens", "n_chars")


ENTROPY = f"""c AS (SELECT token, count(*) AS n FROM (SELECT unnest({twins.tokens('lower(text)')}) AS token FROM documents WHERE lang = 'en') GROUP BY token), z AS (SELECT sum(n) AS total, count(*) AS kinds FROM c),
    a AS (SELECT token, count(*) AS m FROM (SELECT unnest({twins.tokens('lower(text)')}) AS token FROM benchmark) GROUP BY token)"""


@query("a17_lm_proxy", with_sql(ENTROPY, "SELECT round(sum(m * -ln((coalesce(n, 0) + 1.0::DOUBLE) / (total + kinds + 1.0::DOUBLE))) / sum(m), 6) AS nats FROM a LEFT JOIN c USING (token), z"))
def a17(spark, sf):
    docs = table(spark, sf, "documents").where("lang = 'en'")
    return recipes.unigram_cross_entropy(docs, table(spark, sf, "benchmark")).select(F.round("nats", 6).alias("nats"))


@query("a18_selection_quality", f"SELECT good, count(*) AS n, round(avg(quality), 6) AS quality, round(avg(toxic), 6) AS toxic, count(*) - count(DISTINCT md5(text)) AS copies FROM (SELECT doc_id, text, {PRESET}::INT AS good FROM documents) JOIN labels USING (doc_id) GROUP BY good")
def a18(spark, sf):
    rows = table(spark, sf, "documents").select("doc_id", "text", recipes.preset_detectors(F.col("text")).alias("good")).join(table(spark, sf, "labels"), "doc_id")
    return rows.groupBy("good").agg(F.count("*").alias("n"), F.round(F.avg("quality"), 6).alias("quality"), F.round(F.avg("toxic"), 6).alias("toxic"), (F.count("*") - F.countDistinct(F.md5("text"))).alias("copies"))


def pair_sql(source: str) -> str:
    return f"SELECT w[i] AS a, w[i + 1] AS b FROM (SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT {twins.tokens('lower(text)')} AS w FROM {source}))"


def bigram_sql(name: str, source: str) -> str:
    return f"""{name}_s AS (SELECT a, b, count(*) AS n FROM ({pair_sql(source)}) GROUP BY a, b), {name}_h AS (SELECT a, sum(n) AS total FROM {name}_s GROUP BY a), {name}_k AS (SELECT count(DISTINCT b) AS kinds FROM {name}_s),
    {name} AS (SELECT '{name}' AS selection, round(sum(m * -ln((coalesce(n, 0) + 1.0::DOUBLE) / (coalesce(total, 0) + kinds + 1.0::DOUBLE))) / sum(m), 6) AS nats FROM asked LEFT JOIN {name}_s USING (a, b) LEFT JOIN {name}_h USING (a), {name}_k)"""


GOOD = f"SELECT text FROM documents WHERE {PRESET}"


@query("a17b_bigram_proxy", f"WITH asked AS (SELECT a, b, count(*) AS m FROM ({pair_sql('benchmark')}) GROUP BY a, b), {bigram_sql('whole', 'documents')}, {bigram_sql('preset', f'({GOOD})')} SELECT * FROM whole UNION ALL SELECT * FROM preset")
def a17b(spark, sf):
    """Bigram cross-entropy of the benchmark under all documents and under those that preset rules find nothing wrong with."""
    docs = table(spark, sf, "documents")
    found = {"whole": docs, "preset": docs.where(recipes.preset_detectors(F.col("text")) == 1)}
    one = {k: recipes.bigram_cross_entropy(d, table(spark, sf, "benchmark")).select(F.lit(k).alias("selection"), F.round("nats", 6).alias("nats")) for k, d in found.items()}
    return one["whole"].union(one["preset"])


def runs_sql(source: str, names: str = "", width: int = 8) -> str:
    return f"SELECT {names} array_to_string(w[i:i + {width - 1}], ' ') AS run FROM (SELECT {names} w, unnest(range(1, len(w) - {width - 2})) AS i FROM (SELECT {names} {twins.tokens('lower(text)')} AS w FROM {source}))"


@query("a18b_contamination", f"SELECT good, count(*) AS n, count(c.doc_id) AS contaminated, round(count(c.doc_id) / count(*)::DOUBLE, 6) AS share FROM (SELECT doc_id, {PRESET}::INT AS good FROM documents) LEFT JOIN (SELECT DISTINCT doc_id FROM ({runs_sql('documents', 'doc_id,')}) WHERE run IN (SELECT run FROM ({runs_sql('benchmark')}))) c USING (doc_id) GROUP BY good")
def a18b(spark, sf):
    """Share of documents that hold eight words in a row of a benchmark item, among those that pass the preset rules and the rest."""
    docs = table(spark, sf, "documents")
    hit = recipes.contaminated(docs, table(spark, sf, "benchmark")).select("doc_id", F.lit(1).alias("hit"))
    rows = docs.select("doc_id", recipes.preset_detectors(F.col("text")).alias("good")).join(hit, "doc_id", "left")
    return rows.groupBy("good").agg(F.count("*").alias("n"), F.count("hit").alias("contaminated"), F.round(F.count("hit") / F.count("*"), 6).alias("share"))


@query("w05_challenge")
def w05(spark, sf):
    """Selections of an equal token budget by recipe, three trials each: cross-entropy of the benchmark texts, and label quality."""
    base = pool(spark, sf)
    budget = int(base.agg(F.sum("n_tokens")).first()[0] * 0.25)
    picks = {"ngram": ngram_selection(spark, sf).where("kept = 1"), "score": score_selection(spark, sf).where("kept = 1"), "ngram_engine": engine.filter_corpus(ngram_selection(spark, sf).where("kept = 1").select("doc_id", "text", "n_tokens"), engine_run(spark, sf).model)}
    bench, labels = table(spark, sf, "benchmark"), table(spark, sf, "labels")
    out = None
    for name, rows in picks.items():
        for trial in range(3):
            chosen = recipes.take_tokens(rows.select("doc_id", "text", "n_tokens"), budget, trial)
            facts = chosen.join(labels, "doc_id", "left").agg(F.sum("n_tokens").alias("tokens"), F.avg("quality").alias("quality"), F.avg("toxic").alias("toxic"))
            row = recipes.unigram_cross_entropy(chosen, bench).crossJoin(facts).select(F.lit(name).alias("selection"), F.lit(trial).alias("trial"), "tokens", "nats", "quality", "toxic")
            out = row if out is None else out.union(row)
    return out


@query("w06_student_ablation")
def w06(spark, sf):
    rows = train_stream(spark, sf).where(F.col("stream_pos") < 1024).select("text", F.col("quality").alias("verdict"))
    test, out = test_split(spark, sf), []
    for name in ("logodds", "focal"):
        out.append((name, accuracy(spark, sf, students.fit(rows, StudentConfig(kind=name)), "quality")))
    pred = students.fit_library(rows).apply(test.select("snippet_id", "text", "quality")).withColumn("pred", (F.col("margin_micro") > 0).cast("int"))
    out.append(("library", metrics.balanced_accuracy(pred, "quality", "pred").first().balanced_accuracy))
    return spark.createDataFrame(out, "student string, balanced_accuracy double")


def panel_sql() -> str:
    """The panel on both filters: the students of one active round each, a teacher who errs in 6 of 100 calls."""
    wrong = twins.hash_int("'vote'", "spec", "g", "a", "snippet_id")
    parts = [twins.stream("mainstream").replace(" AS label FROM snips", f" AS label, cm, {', '.join(twins.rule(x) + ' AS r_' + x for x in PREFERRED)} FROM snips")]
    for x in PREFERRED:
        parts.append(f"st_{x} AS MATERIALIZED (SELECT snippet_id, stream_pos, text, r_{x} AS label FROM stream)")
        parts += [twins.rounds(LITERAL, BLOCKS, x, f"st_{x}"), twins.margins("stream", f"{x}_f", f"p_{x}")]
        parts.append(f"apart_{x} AS (SELECT '{x}' AS spec, snippet_id, truth, student FROM (SELECT snippet_id, r_{x} AS truth, (margin_micro > 0)::INT AS student, {noisy_sql(x, 'teacher', 0, 0.06, 0.06)} AS teacher FROM p_{x}) WHERE teacher <> student ORDER BY {twins.hash_int(chr(39) + 'panel' + chr(39), chr(39) + x + chr(39), 'snippet_id')}, snippet_id LIMIT 100)")
    both = " UNION ALL ".join(f"SELECT * FROM apart_{x}" for x in PREFERRED)
    parts.append(f"votes AS (SELECT spec, snippet_id, student, g, CASE WHEN {wrong} < {int(0.1 * (1 << 32))} THEN 1 - truth ELSE truth END AS vote FROM ({both}), (SELECT unnest(range(1, 3)) AS g), (SELECT unnest(range(1, 14)) AS a))")
    parts.append("said AS (SELECT spec, g, snippet_id, (2 * sum(vote) > count(*))::INT = any_value(student) AS wins FROM votes GROUP BY spec, g, snippet_id)")
    rows = "SELECT spec, {g}::INT AS group_no, count(*) AS n_snippets, count(*) FILTER (wins) AS student_wins, round(count(*) FILTER (wins) / count(*)::DOUBLE, 6) AS preference FROM said GROUP BY spec{by}"
    return with_sql(", ".join(parts), rows.format(g="g", by=", g") + " UNION ALL " + rows.format(g="0", by=""))


@query("w07_human_eval", panel_sql())
def w07(spark, sf):
    """The panel's preference on mainstream and quality; group 0 is both groups pooled."""
    common, out = common_words(spark, sf), None
    text, sid = F.col("text"), F.col("snippet_id")
    for spec in PREFERRED:
        rows = students.score(stream(spark, sf), engine_run(spark, sf, spec, LITERAL).model)
        rows = rows.select("snippet_id", F.col(spec).alias("truth"), engine.passes(F.col("margin_micro")).alias("student"), teacher.verdict(spec, text, sid, TeacherConfig().noisy(0.06), 0, common).alias("teacher"))
        groups = metrics.human_preference(rows, "teacher", "student", "truth", spec)
        pooled = groups.agg(F.lit(0).alias("group_no"), F.sum("n_snippets").alias("n_snippets"), F.sum("student_wins").alias("student_wins")).where("n_snippets > 0")
        both = groups.union(pooled.withColumn("preference", F.col("student_wins") / F.col("n_snippets"))).select(F.lit(spec).alias("spec"), "*")
        out = both if out is None else out.union(both)
    return out.withColumn("preference", F.round("preference", 6))


FULL = f"n * {PRICE!r}::DOUBLE"
COST_ROWS = f"SELECT 'full' AS method, n AS calls, {FULL} AS call_usd, 0.0 AS training_usd, 0.0 AS scoring_usd, 0.0 AS inference_usd FROM k UNION ALL SELECT 'weak', n, n * {WEAK!r}::DOUBLE, 0.0, 0.0, 0.0 FROM k UNION ALL SELECT 'distilled', calls, calls * {PRICE!r}::DOUBLE, training / 1e6 * 0.05, scoring / 1e6 * 0.008, inference / 1e6 * 0.008 FROM k"


@query("w08_cost_table", with_sql(COUNTED, f"SELECT method, calls::BIGINT AS calls, {', '.join(f'round({c}, 6) AS {c}' for c in ('call_usd', 'training_usd', 'scoring_usd', 'inference_usd'))}, round(call_usd + training_usd + scoring_usd + inference_usd, 6) AS total_usd, round((call_usd + training_usd + scoring_usd + inference_usd) / ({FULL}), 6) AS ratio, (call_usd + training_usd + scoring_usd + inference_usd) / ({FULL}) < 0.01 AS below_one_percent FROM ({COST_ROWS}), (SELECT n FROM k)"))
def w08(spark, sf):
    """Costs by component, against full annotation of the same corpus, from the run's counters."""
    n, run = stream(spark, sf).count(), engine_run(spark, sf)
    calls, usd = billed(spark, sf, run)
    rows = [("full", n, n * PRICE, 0.0, 0.0, 0.0), ("weak", n, n * WEAK, 0.0, 0.0, 0.0), ("distilled", calls, calls * PRICE, usd["training"], usd["scoring"], usd["inference"])]
    parts = ("call_usd", "training_usd", "scoring_usd", "inference_usd")
    out = spark.createDataFrame(rows, "method string, calls bigint, " + ", ".join(f"{c} double" for c in parts))
    total = sum((F.col(c) for c in parts[1:]), F.col(parts[0]))
    out = out.withColumn("total_usd", total).withColumn("ratio", F.try_divide(total, F.lit(n * PRICE)))
    return out.select("method", "calls", *(F.round(c, 6).alias(c) for c in (*parts, "total_usd", "ratio")), (F.col("ratio") < 0.01).alias("below_one_percent"))


@query("w09_threshold_demo", with_sql(SCORED, "SELECT decile::INT AS decile, count(*) AS n, sum(label)::BIGINT AS n_pass, count(*) FILTER (score > 0.5) AS above_half FROM (SELECT *, ntile(10) OVER (ORDER BY margin_micro, snippet_id) AS decile FROM scored) GROUP BY decile"))
def w09(spark, sf):
    from pyspark.sql.window import Window

    rows = scored(spark, sf).withColumn("decile", F.ntile(10).over(Window.orderBy("margin_micro", "snippet_id")))
    return rows.groupBy("decile").agg(F.count("*").alias("n"), F.sum("label").alias("n_pass"), F.count_if(F.col("score") > 0.5).alias("above_half"))


DEMO = f"{SCORED}, {twins.one_round('scored', SEED, str(SEED), '(SELECT count(*) FROM stream)', 0.1, 0.25, BLOCKS, 'r', False)}, y AS (SELECT margin_micro, label AS y FROM scored), {twins.curve('y', 'lc')}, eot AS (SELECT cut FROM lc ORDER BY loss, cut LIMIT 1)"


@query("w09b_threshold_demo", with_sql(DEMO, "SELECT decile::INT AS decile, count(*) AS n, sum(label)::BIGINT AS n_pass, count(b.ord) AS bought, count(*) FILTER (score > 0.5) AS above_half, count(*) FILTER (margin_micro > eot.cut) AS above_eot FROM (SELECT *, ntile(10) OVER (ORDER BY margin_micro, snippet_id) AS decile FROM scored) d LEFT JOIN (SELECT snippet_id, ord FROM r_bought) b USING (snippet_id), eot GROUP BY decile"))
def w09b(spark, sf):
    """Score deciles: class counts, purchases of one round, and how many lie above either cut."""
    rows = scored(spark, sf)
    bought = m13b(spark, sf).select("snippet_id", F.lit(1).alias("bought"))
    cut = threshold.empirical_cut(threshold.loss_curve(rows)).first().s_hat
    placed = theory.rank_linear(rows.withColumn("score", F.col("margin_micro"))).select("snippet_id", "place", "n")
    # the first n mod 10 tenths have one row more than the others
    small, extra = F.floor(F.col("n") / 10), F.col("n") % 10
    decile = F.when(F.col("place") <= extra * (small + 1), F.floor((F.col("place") - 1) / (small + 1))).otherwise(extra + F.floor((F.col("place") - 1 - extra * (small + 1)) / small))
    rows = rows.join(placed, "snippet_id").join(F.broadcast(bought), "snippet_id", "left").withColumn("decile", (decile + 1).cast("int"))
    return rows.groupBy("decile").agg(F.count("*").alias("n"), F.sum("label").cast("bigint").alias("n_pass"), F.count("bought").alias("bought"), F.count_if(F.col("score") > 0.5).alias("above_half"), F.count_if(F.col("margin_micro") > cut).alias("above_eot"))


@query("w10_theory_check")
def w10(spark, sf):
    """The balance bound against the measured balance, for the bands of a run under a graded teacher (its own class
    probabilities) and for wide and narrow bands on rank-linear ones."""
    out = []

    def row(kind, t, rows, risk, smooth, n, lo, hi):
        g = theory.band_gap(risk, lo, hi).first()
        bound = theory.balance_bound(n, g.gap_lo or 0.0, g.gap_hi or 0.0, smooth)
        measured = theory.interval_balance(rows, lo, hi).first().balance
        out.append((kind, t, g.gap_lo, g.gap_hi, smooth, bound, measured, bound is None or bound < 0))

    rows = graded(spark, sf)
    run = active.distil(stream(spark, sf), "topic_hostile", LITERAL, teacher=TeacherConfig(mode="graded"))
    rows = materialise(students.score(rows, run.models[0][1]).select("snippet_id", "eta", F.col("margin_micro").cast("double").alias("score")), "graded")
    risk, smooth, n = materialise(threshold.true_cut(rows, width=1 << 16), "risk"), theory.smoothness(rows).first()[0], rows.count()
    for _, t, lo, hi, *_ in run.trace:
        row("graded_run", t, rows, risk, smooth, n, float(lo), float(hi))
    rows = materialise(theory.rank_linear(scored(spark, sf)), "ranked")
    risk, smooth, n = materialise(threshold.true_cut(rows), "risk"), theory.smoothness(rows).first()[0], rows.count()
    for half in (0.05, 0.2):
        ends = rows.agg(F.min(F.when(F.col("place") >= (0.5 - half) * F.col("n"), F.col("score"))), F.max(F.when(F.col("place") <= (0.5 + half) * F.col("n"), F.col("score")))).first()
        row("rank_linear", int(2 * half * n), rows, risk, smooth, n, *ends)
    return spark.createDataFrame(out, "kind string, t bigint, gap_lo double, gap_hi double, smoothness double, bound double, balance double, vacuous boolean")


@query("w11_quality_on_labels")
def w11(spark, sf):
    """The given labels as the teacher: fit on four fifths of the labelled documents, judge on the rest."""
    docs = table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id")
    test, out = snippets.held_out(F.col("text")), None
    for name in ("quality", "toxic"):
        model = students.fit(docs.where(~test).select("text", F.col(name).alias("verdict")))
        rows = students.score(docs.where(test), model).withColumn("pred", engine.passes(F.col("margin_micro")))
        row = metrics.confusion(rows, name, "pred").withColumn("label", F.lit(name))
        out = row if out is None else out.union(row)
    return out


@query("w12_vectors")
def w12(spark, sf):
    rows, out = table(spark, sf, "embeddings"), None
    test = hash_below(0.3, "vec", F.col("vec_id"))
    for k in range(10):
        one = rows.withColumn("verdict", (F.col("label") == k).cast("int"))
        model = students.fit_vectors(one.where(~test).select("embedding", "verdict"))
        row = metrics.confusion(one.where(test).withColumn("pred", (model.margin(F.col("embedding")) > 0).cast("int")), "verdict", "pred").withColumn("label", F.lit(k))
        out = row if out is None else out.union(row)
    return out


@query("w14_conversations", f"SELECT role, count(*) AS n, sum({twins.rule('quality')})::BIGINT AS good, sum({twins.rule('topic_private')})::BIGINT AS private FROM conversations GROUP BY role")
def w14(spark, sf):
    t = F.col("text")
    return table(spark, sf, "conversations").groupBy("role").agg(F.count("*").alias("n"), F.sum(teacher.rule("quality", t)).alias("good"), F.sum(teacher.rule("topic_private", t)).alias("private"))


PAGES = f"pg AS (SELECT page_id AS doc_id, {twins.page_text('html')} AS text FROM pages), {twins.snippets(64, 'pg', 'doc_id', 'ps')}"


@query("w15_pages", with_sql(f"{twins.engine(ENGINE, BLOCKS)}, {PAGES}, {twins.margins('ps', 'e_f', 'pm')}", "SELECT doc_id, count(*) AS n_snippets, sum((margin_micro > 0)::INT)::BIGINT AS n_pass, (sum((margin_micro > 0)::INT) >= 0.5 * count(*))::INT AS doc_pass FROM pm GROUP BY doc_id"))
def w15(spark, sf):
    """The engine's student on the texts of web pages."""
    rows = students.score(snippets.cut(pages_as_documents(table(spark, sf, "pages"))), engine_run(spark, sf).model)
    return engine.roll_up(rows.select("doc_id", engine.passes(F.col("margin_micro")).alias("verdict")))


@query("w16_scale", with_sql(SCORED, "SELECT count(*) AS snippets, count(*) FILTER (margin_micro > 0) AS passed, sum(n_tokens) FILTER (margin_micro > 0)::BIGINT AS tokens FROM scored"))
def w16(spark, sf):
    rows = students.score(snips(spark, sf), first_student(spark, sf))
    ok = F.col("margin_micro") > 0
    return rows.agg(F.count("*").alias("snippets"), F.count_if(ok).alias("passed"), F.sum(F.when(ok, F.col("n_tokens"))).alias("tokens"))


@query("w16b_engine_scale", engine_sql("SELECT count(*) AS snippets, count(*) FILTER (margin_micro > 0) AS passed, sum(n_tokens) FILTER (margin_micro > 0)::BIGINT AS tokens, (SELECT count(*) FROM e_lab) AS calls, count(*) AS full_calls FROM last"))
def w16b(spark, sf):
    """The whole corpus by the engine's student, and the calls it took against those of full annotation."""
    run = engine_run(spark, sf)
    ok = F.col("margin_micro") > 0
    return students.score(snips(spark, sf), run.model).agg(F.count("*").alias("snippets"), F.count_if(ok).alias("passed"), F.sum(F.when(ok, F.col("n_tokens"))).alias("tokens"), F.lit(run.calls).cast("bigint").alias("calls"), F.count("*").alias("full_calls"))


# sweeps


def sweep(spark, sf, name: str, options: list, change) -> DataFrame:
    out = []
    for o in options:
        run = run_of(spark, sf, *change(o))
        ones = sum(v for *_, v in run.labels)
        out.append((name, str(o), len(run.labels), ones, run.seen, run.exhausted, accuracy(spark, sf, run.model, "quality")))
    return spark.createDataFrame(out, "option string, value string, calls bigint, n_pass bigint, seen bigint, exhausted boolean, balanced_accuracy double")


SMALL = replace(WORK, budget=512)
query("s01_delta")(lambda spark, sf: sweep(spark, sf, "delta", [0.01, 0.05, 0.1, 0.2], lambda d: ("band", "quality", replace(SMALL, delta=d))))
query("s02_batch")(lambda spark, sf: sweep(spark, sf, "batch", [128, 256, 512, 1024, 2048], lambda b: ("band", "quality", replace(SMALL, batch=b, budget=2 * b))))
query("s03_radius_scale")(lambda spark, sf: sweep(spark, sf, "radius_scale", [1.0, 0.5, 0.25], lambda x: ("band", "quality", replace(SMALL, radius_scale=x))))
query("s04_unlabelled")(lambda spark, sf: sweep(spark, sf, "unlabelled", ["implied", "constant", "labelled_only"], lambda x: ("band", "quality", replace(SMALL, unlabelled=x))))
query("s05_nested")(lambda spark, sf: sweep(spark, sf, "nested", [True, False], lambda x: ("band", "quality", replace(SMALL, nested=x))))
query("s06_focal_gamma")(lambda spark, sf: sweep(spark, sf, "focal_gamma", [0.0, 1.0, 2.0, 5.0], lambda x: ("random", "quality", SMALL, StudentConfig(kind="focal", focal_gamma=x))))
query("s08_teacher_noise")(lambda spark, sf: sweep(spark, sf, "eps", [0.0, 0.05, 0.15], lambda x: ("band", "quality", SMALL, StudentConfig(), TeacherConfig().noisy(x))))


query("s11_fit_policy")(lambda spark, sf: sweep(spark, sf, "warm_start", [False, True], lambda x: ("band", "quality", SMALL, StudentConfig(kind="focal", warm_start=x))))
query("s12_loss")(lambda spark, sf: sweep(spark, sf, "class_weight", [False, True], lambda x: ("random", "quality", SMALL, StudentConfig(kind="focal", class_weight=x))))
query("b07b_uniform_policy")(lambda spark, sf: sweep(spark, sf, "radius", ["bernstein", "uniform"], lambda x: ("band", "quality", replace(SMALL, radius=x))))


@query("s10_seed")
def s10(spark, sf):
    """The band and random choice over five stream orders: mean and spread of the student's accuracy and of the labels' balance."""
    rows = curve(spark, sf, "quality", ("band", "band_nested", "random"), SMALL, range(5))
    last = rows.groupBy("policy", "stream_order").agg(F.max_by(F.struct("*"), "calls").alias("r")).select("r.*")
    return spread(last.withColumn("calls", F.lit(SMALL.budget).cast("bigint")))


@query("s07_width", " UNION ALL ".join(f"SELECT {w}::INT AS width, count(*) AS snippets, sum(n_tokens)::BIGINT AS tokens FROM (WITH {twins.snippets(w)} SELECT * FROM snips)" for w in (64, 128, 256, 1024)))
def s07(spark, sf):
    out = None
    for w in (64, 128, 256, 1024):
        row = snippets.cut(table(spark, sf, "documents"), w).agg(F.lit(w).alias("width"), F.count("*").alias("snippets"), F.sum("n_tokens").alias("tokens"))
        out = row if out is None else out.union(row)
    return out


@query("s09_decision_cut")
def s09(spark, sf):
    model = first_student(spark, sf)
    rows = stream(spark, sf).where(F.col("stream_pos") < SEED).select("text", F.col("quality").alias("verdict"))
    out = None
    for cut in ("half", "eot", "balanced", 0.9):
        at = engine.decision_cut(rows, model, cut)
        row = metrics.confusion(test_rows(spark, sf).withColumn("pred", engine.passes(F.col("margin_micro"), at)), "label", "pred").select(F.lit(str(cut)).alias("cut"), F.lit(at).alias("margin"), "balanced_accuracy", "accuracy")
        out = row if out is None else out.union(row)
    return out

