"""The operators around the engine, each on the given or derived tables, with SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..functions.hashing import hash_below, hash_int
from ..operators import metrics, snippets, teacher, threshold
from ..sources.html import page_text
from ..sources.tables import table
from . import twins
from .methods import SCORED, SNIPS, scored, snips, with_sql
from .registry import query

Q = "'"


def r6(name: str):
    return F.round(name, 6).alias(name)


def s(select: str) -> str:
    return with_sql(SCORED, select)


# scans, projections, filters


@query("o01_scan_parquet", "SELECT doc_id, n_chars FROM documents")
def o01(spark, sf):
    return table(spark, sf, "documents", ["doc_id", "n_chars"])


@query("o06_html_text", f"SELECT page_id, length(t) AS n_chars, md5(t) AS text_md5 FROM (SELECT page_id, {twins.page_text('html')} AS t FROM pages)")
def o06(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.length(page_text(F.col("html"))).alias("n_chars"), F.md5(page_text(F.col("html"))).alias("text_md5"))


@query("o10_project_rule", f"SELECT doc_id, length(text) AS n, {twins.rule('quality')} AS good, CASE WHEN length(text) > 2000 THEN 'long' WHEN length(text) > 500 THEN 'middle' ELSE 'short' END AS size FROM documents")
def o10(spark, sf):
    size = F.when(F.length("text") > 2000, "long").when(F.length("text") > 500, "middle").otherwise("short")
    return table(spark, sf, "documents").select("doc_id", F.length("text").cast("bigint").alias("n"), teacher.rule("quality", F.col("text")).alias("good"), size.alias("size"))


@query("o11_band_filter", s("SELECT snippet_id, margin_micro FROM scored WHERE margin_micro BETWEEN -1000000 AND 1500000"))
def o11(spark, sf):
    return scored(spark, sf).where(F.col("margin_micro").between(-1_000_000, 1_500_000)).select("snippet_id", "margin_micro")


@query("o12_case_cut", s("SELECT snippet_id, CASE WHEN margin_micro > 2000000 THEN 1 ELSE 0 END AS side FROM scored"))
def o12(spark, sf):
    return scored(spark, sf).select("snippet_id", F.when(F.col("margin_micro") > 2_000_000, 1).otherwise(0).alias("side"))


@query("o13_null_blank", "SELECT count(*) AS n, count(*) FILTER (text IS NOT NULL AND trim(text) <> '') AS filled FROM (SELECT CASE WHEN doc_id % 10 = 0 THEN NULL WHEN doc_id % 10 = 1 THEN '  ' ELSE text END AS text FROM documents)")
def o13(spark, sf):
    text = F.when(F.col("doc_id") % 10 == 0, F.lit(None)).when(F.col("doc_id") % 10 == 1, F.lit("  ")).otherwise(F.col("text"))
    return table(spark, sf, "documents").select(text.alias("text")).agg(F.count("*").alias("n"), F.count_if(F.col("text").isNotNull() & (F.trim("text") != "")).alias("filled"))


@query("o14_in_list", "SELECT doc_id, source FROM documents WHERE source IN ('src1', 'src3', 'src7')")
def o14(spark, sf):
    return table(spark, sf, "documents").where(F.col("source").isin("src1", "src3", "src7")).select("doc_id", "source")


@query("o15_patterns", "SELECT doc_id, text LIKE '%ing%' AS a, regexp_matches(text, '[0-9]{3}') AS b, contains(text, ' | ') AS c, starts_with(text, 'The') AS d FROM documents")
def o15(spark, sf):
    t = F.col("text")
    return table(spark, sf, "documents").select("doc_id", t.like("%ing%").alias("a"), t.rlike("[0-9]{3}").alias("b"), t.contains(" | ").alias("c"), t.startswith("The").alias("d"))


@query("o16_hash_split", with_sql(SNIPS, f"SELECT {twins.hash_int(Q + 'test7' + Q, 'text')} < {int(0.2 * (1 << 32))} AS test, count(*) AS n FROM snips GROUP BY 1"))
def o16(spark, sf):
    return snips(spark, sf).groupBy(snippets.held_out(F.col("text")).alias("test")).agg(F.count("*").alias("n"))


@query("o17_near_half", s("SELECT snippet_id FROM scored WHERE abs(score - 0.5) <= 0.3"))
def o17(spark, sf):
    return scored(spark, sf).where(F.abs(F.col("score") - 0.5) <= 0.3).select("snippet_id")


@query("o18_lang_gate", "SELECT lang, count(*) AS n FROM documents WHERE lang IN ('en', 'fr') GROUP BY lang")
def o18(spark, sf):
    return table(spark, sf, "documents").where(F.col("lang").isin("en", "fr")).groupBy("lang").agg(F.count("*").alias("n"))


@query("o19_length_gate", "SELECT doc_id FROM documents WHERE n_chars BETWEEN 200 AND 5000")
def o19(spark, sf):
    return table(spark, sf, "documents").where(F.col("n_chars").between(200, 5000)).select("doc_id")


@query("o20_struct_fields", "SELECT doc_id, quality AS verdict, 'bad=' || (1 - quality) AS note FROM labels")
def o20(spark, sf):
    v = F.struct(F.col("quality").alias("verdict"), F.col("toxic").alias("other")).alias("v")
    rows = table(spark, sf, "labels").select("doc_id", v).withColumn("v", F.col("v").withField("note", F.concat(F.lit("bad="), (1 - F.col("v.verdict")).cast("string"))).dropFields("other"))
    return rows.select("doc_id", "v.*")


@query("o21_sample", f"SELECT doc_id FROM documents WHERE {twins.hash_int(Q + 's' + Q, 'doc_id')} < {int(0.1 * (1 << 32))}")
def o21(spark, sf):
    return table(spark, sf, "documents").where(hash_below(0.1, "s", F.col("doc_id"))).select("doc_id")


# joins


def some_snippets(spark, sf):
    return scored(spark, sf).select("snippet_id", "doc_id", "stream_pos", "margin_micro", "score", "label", "n_tokens")


@query("j01_broadcast_weights", s(f"SELECT snippet_id, count(*) AS known FROM (SELECT snippet_id, unnest({twins.features()}) AS token FROM stream) JOIN st_w USING (token) GROUP BY snippet_id"))
def j01(spark, sf):
    from ..functions.text import features
    from .methods import m06

    rows = scored(spark, sf).select("snippet_id", F.explode(features(F.col("text"))).alias("token"))
    return rows.join(F.broadcast(m06(spark, sf).select("token")), "token").groupBy("snippet_id").agg(F.count("*").alias("known"))


@query("j02_sortmerge_labels", s("SELECT snippet_id, quality FROM scored JOIN labels USING (doc_id)"))
def j02(spark, sf):
    return some_snippets(spark, sf).hint("merge").join(table(spark, sf, "labels"), "doc_id").select("snippet_id", "quality")


@query("j03_shuffle_hash", s("SELECT snippet_id, lang FROM scored JOIN documents USING (doc_id)"))
def j03(spark, sf):
    return some_snippets(spark, sf).join(table(spark, sf, "documents", ["doc_id", "lang"]).hint("shuffle_hash"), "doc_id").select("snippet_id", "lang")


@query("j04_left_anti_cache", s("SELECT snippet_id FROM scored WHERE stream_pos >= 256"))
def j04(spark, sf):
    rows = some_snippets(spark, sf)
    return rows.join(rows.where("stream_pos < 256").select("snippet_id"), "snippet_id", "left_anti").select("snippet_id")


@query("j05_left_semi", s("SELECT snippet_id FROM scored WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)"))
def j05(spark, sf):
    return some_snippets(spark, sf).join(table(spark, sf, "labels").where("toxic = 1"), "doc_id", "left_semi").select("snippet_id")


@query("j06_left_outer", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def j06(spark, sf):
    return table(spark, sf, "documents", ["doc_id"]).join(table(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("j06b_right_outer", "SELECT l.doc_id, d.lang FROM (SELECT * FROM documents WHERE lang = 'en') d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
def j06b(spark, sf):
    d = table(spark, sf, "documents").where("lang = 'en'").select("doc_id", "lang")
    return d.join(table(spark, sf, "labels"), "doc_id", "right").select("doc_id", "lang")


@query("j06c_full_outer", "SELECT coalesce(d.doc_id, l.doc_id + 1) AS id, d.lang, l.quality FROM (SELECT * FROM documents WHERE lang = 'fr') d FULL JOIN (SELECT * FROM labels WHERE toxic = 1) l ON d.doc_id = l.doc_id")
def j06c(spark, sf):
    d = table(spark, sf, "documents").where("lang = 'fr'").select(F.col("doc_id").alias("a"), "lang")
    l = table(spark, sf, "labels").where("toxic = 1").select(F.col("doc_id").alias("b"), "quality")  # noqa: E741
    return d.join(l, d.a == l.b, "full").select(F.coalesce("a", F.col("b") + 1).alias("id"), "lang", "quality")


@query("j07_cross_small", "SELECT lang, f AS factor, count(*) * f AS n FROM documents, (SELECT unnest([1, 10]::BIGINT[]) AS f) GROUP BY lang, f")
def j07(spark, sf):
    counts = table(spark, sf, "documents").groupBy("lang").agg(F.count("*").alias("n"))
    return counts.crossJoin(F.broadcast(spark.createDataFrame([(1,), (10,)], "factor bigint"))).select("lang", "factor", (F.col("n") * F.col("factor")).alias("n"))


BANDS = [("a", -2_000_000, 0), ("b", -500_000, 500_000), ("c", 1_000_000, 3_000_000)]


@query("j08_theta_band", s(f"SELECT band, count(*) AS n FROM scored JOIN (VALUES {', '.join(map(str, BANDS))}) b(band, lo, hi) ON margin_micro >= lo AND margin_micro <= hi GROUP BY band"))
def j08(spark, sf):
    bands = F.broadcast(spark.createDataFrame(BANDS, "band string, lo bigint, hi bigint"))
    rows = some_snippets(spark, sf).select("margin_micro")
    return rows.join(bands, (F.col("margin_micro") >= F.col("lo")) & (F.col("margin_micro") <= F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("j09_range_block", s("SELECT block::INT AS block, count(*) AS n, min(stream_pos) AS first FROM (SELECT stream_pos, CASE WHEN stream_pos < 3 THEN 1 ELSE ceil(log2(stream_pos))::INT END AS block FROM scored) GROUP BY block"))
def j09(spark, sf):
    block = F.when(F.col("stream_pos") < 3, 1).otherwise(F.length(F.bin(F.col("stream_pos") - 1))).cast("int")
    rows = some_snippets(spark, sf).withColumn("block", block)
    names = spark.createDataFrame([(k,) for k in range(1, 40)], "block int")
    return rows.join(F.broadcast(names), "block").groupBy("block").agg(F.count("*").alias("n"), F.min("stream_pos").alias("first"))


@query("j10_asof_model", "SELECT e.event_id, m.version FROM events e ASOF JOIN (SELECT event_id AS version, ts FROM events WHERE event_id % 1000 = 0) m ON e.ts >= m.ts")
def j10(spark, sf):
    e = table(spark, sf, "events").select("event_id", "ts")
    models = e.where("event_id % 1000 = 0").select(F.lit(None).cast("bigint").alias("event_id"), "ts", F.col("event_id").alias("version"))
    both = models.unionByName(e.withColumn("version", F.lit(None).cast("bigint")))
    w = W.partitionBy().orderBy("ts", F.col("version").asc_nulls_last()).rowsBetween(W.unboundedPreceding, W.currentRow)
    return both.withColumn("version", F.last("version", ignorenulls=True).over(w)).where("event_id is not null and version is not null").select("event_id", "version")


@query("j11_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'view' OR a.event_id % 7 = 0")
def j11(spark, sf):
    e = table(spark, sf, "events")
    a = e.where("event_type = 'view' or event_id % 7 = 0").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("u"))
    return a.join(b, "user_id").where("u > t and u <= t + interval 10 minutes").select("a", "b")


@query("j11b_interval_all")
def j11b(spark, sf):
    """j11 with all events on both sides; the SQL of j11 states a part of the left one, so it has no twin."""
    e = table(spark, sf, "events")
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("u"))
    return a.join(b, "user_id").where("u > t and u <= t + interval 10 minutes").select("a", "b")


@query("j12_self_pairs", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id")
def j12(spark, sf):
    d = table(spark, sf, "documents").select("doc_id", F.md5("text").alias("h"))
    a, b = d.toDF("a", "h"), d.toDF("b", "h")
    return a.join(b, "h").where("a < b").select("a", "b")


@query("j13_lateral", f"SELECT snippet_id, w AS word FROM (SELECT snippet_id, unnest({twins.tokens()}) AS w FROM (WITH {SNIPS} SELECT * FROM snips)) WHERE regexp_matches(w, '[0-9]')")
def j13(spark, sf):
    snips(spark, sf).createOrReplaceTempView("__snips")
    return spark.sql("SELECT snippet_id, word FROM __snips LATERAL VIEW explode(split(text, ' ')) t AS word WHERE word RLIKE '[0-9]'")


@query("j14_salted_skew", "SELECT source, count(*) AS n, count(DISTINCT d.doc_id) AS docs FROM documents d JOIN labels l ON d.doc_id % 50 = l.doc_id % 50 GROUP BY source")
def j14(spark, sf):
    """A skewed equi-join: the large side gets a random salt by hash, the small one a copy for each salt."""
    salts = 4
    d = table(spark, sf, "documents").select("doc_id", "source", (F.col("doc_id") % 50).alias("k"), F.pmod(hash_int("salt", F.col("doc_id")), F.lit(salts)).alias("salt"))
    l = table(spark, sf, "labels").select((F.col("doc_id") % 50).alias("k"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))).alias("salt"))  # noqa: E741
    return d.join(l, ["k", "salt"]).groupBy("source").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("docs"))


@query("j15_multi_way", s("SELECT lang, quality, count(*) AS n, round(avg(score), 6) AS score FROM scored JOIN documents USING (doc_id) JOIN labels USING (doc_id) JOIN (SELECT DISTINCT source FROM documents WHERE source < 'src5') USING (source) GROUP BY lang, quality"))
def j15(spark, sf):
    d = table(spark, sf, "documents", ["doc_id", "lang", "source"])
    few = d.where("source < 'src5'").select("source").distinct()
    rows = some_snippets(spark, sf).join(d, "doc_id").join(table(spark, sf, "labels"), "doc_id").join(few, "source")
    return rows.groupBy("lang", "quality").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("score"))


@query("j16_null_safe", "SELECT d.doc_id, (l.quality IS NOT DISTINCT FROM m.quality) AS same FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id LEFT JOIN labels m ON d.doc_id + 1 = m.doc_id")
def j16(spark, sf):
    l = table(spark, sf, "labels").select("doc_id", "quality")  # noqa: E741
    m = l.select((F.col("doc_id") - 1).alias("doc_id"), F.col("quality").alias("next"))
    return table(spark, sf, "documents", ["doc_id"]).join(l, "doc_id", "left").join(m, "doc_id", "left").select("doc_id", F.col("quality").eqNullSafe(F.col("next")).alias("same"))


# aggregations


@query("g01_hash_agg", s("SELECT margin_micro, count(*) AS n, sum(label)::BIGINT AS n1 FROM scored GROUP BY margin_micro"))
def g01(spark, sf):
    return scored(spark, sf).groupBy("margin_micro").agg(F.count("*").alias("n"), F.sum("label").cast("bigint").alias("n1"))


@query("g02_sort_agg", with_sql(SNIPS, "SELECT doc_id, md5(string_agg(text, ' ' ORDER BY seq)) AS text_md5 FROM snips GROUP BY doc_id"))
def g02(spark, sf):
    rows = snips(spark, sf).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("seq", "text"))).alias("a"))
    return rows.select("doc_id", F.md5(F.array_join(F.transform("a", lambda x: x["text"]), " ")).alias("text_md5"))


@query("g03_partial_final", f"SELECT token, count(*) AS n FROM (SELECT lower(unnest({twins.tokens()})) AS token FROM documents) GROUP BY token HAVING count(*) >= 20")
def g03(spark, sf):
    from ..functions.text import tokens

    rows = table(spark, sf, "documents").select(F.explode(tokens(F.col("text"))).alias("token"))
    return rows.groupBy(F.lower("token").alias("token")).agg(F.count("*").alias("n")).where("n >= 20")


@query("g04_distinct", s("SELECT count(DISTINCT margin_micro) AS scores, count(DISTINCT doc_id) AS docs FROM scored"))
def g04(spark, sf):
    return scored(spark, sf).agg(F.countDistinct("margin_micro").alias("scores"), F.countDistinct("doc_id").alias("docs"))


GROUPED = "SELECT lang, source, quality, count(*) AS n, grouping_id(lang, source, quality)::BIGINT AS g FROM documents JOIN labels USING (doc_id) GROUP BY {}"


def labelled_docs(spark, sf):
    return table(spark, sf, "documents", ["doc_id", "lang", "source"]).join(table(spark, sf, "labels"), "doc_id")


def grouped(df):
    return df.agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("g05_grouping_sets", GROUPED.format("GROUPING SETS ((lang, source, quality), (lang), ())"))
def g05(spark, sf):
    c = [F.col("lang"), F.col("source"), F.col("quality")]
    return grouped(labelled_docs(spark, sf).groupingSets([c, c[:1], []], *c))


@query("g06_cube", GROUPED.format("CUBE (lang, source, quality)"))
def g06(spark, sf):
    return grouped(labelled_docs(spark, sf).cube("lang", "source", "quality"))


@query("g07_rollup", GROUPED.format("ROLLUP (lang, source, quality)"))
def g07(spark, sf):
    return grouped(labelled_docs(spark, sf).rollup("lang", "source", "quality"))


@query("g08_conditional", s("SELECT count(*) FILTER (label = 1 AND margin_micro > 0) AS tp, sum(CASE WHEN label = 0 AND margin_micro > 0 THEN n_tokens ELSE 0 END)::BIGINT AS fp_tokens FROM scored"))
def g08(spark, sf):
    return scored(spark, sf).agg(F.count_if((F.col("label") == 1) & (F.col("margin_micro") > 0)).alias("tp"), F.sum(F.when((F.col("label") == 0) & (F.col("margin_micro") > 0), F.col("n_tokens")).otherwise(0)).alias("fp_tokens"))


@query("g09_pivot", "SELECT lang, count(*) FILTER (quality = 0) AS bad, count(*) FILTER (quality = 1) AS good FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def g09(spark, sf):
    rows = labelled_docs(spark, sf).withColumn("q", F.when(F.col("quality") == 1, "good").otherwise("bad"))
    return rows.groupBy("lang").pivot("q", ["bad", "good"]).agg(F.count("doc_id")).na.fill(0)


@query("g09b_unpivot", "SELECT doc_id, k, v FROM labels UNPIVOT (v FOR k IN (quality, toxic))")
def g09b(spark, sf):
    return table(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v")


@query("g10_approx")
def g10(spark, sf):
    return scored(spark, sf).agg(F.approx_count_distinct("margin_micro", 0.02).alias("scores"), F.percentile_approx("margin_micro", 0.5, 10_000).alias("median"))


@query("g11_histogram", s("SELECT floor(score * 50)::BIGINT AS bin, label, count(*) AS n FROM scored GROUP BY 1, 2"))
def g11(spark, sf):
    return scored(spark, sf).groupBy(F.floor(F.col("score") * 50).alias("bin"), "label").agg(F.count("*").alias("n"))


@query("g12_arg_min", s("SELECT arg_min(snippet_id, (margin_micro, snippet_id)) AS lowest, arg_max(snippet_id, (margin_micro, snippet_id)) AS highest FROM scored"))
def g12(spark, sf):
    key = F.struct("margin_micro", "snippet_id")
    return scored(spark, sf).agg(F.min_by("snippet_id", key).alias("lowest"), F.max_by("snippet_id", key).alias("highest"))


@query("g13_stats", s("SELECT round(avg(score), 6) AS mean, round(stddev_samp(score), 6) AS sd, round(var_pop(score), 6) AS v, round(corr(score, label), 6) AS c, round(covar_samp(score, label), 6) AS cv, round(regr_slope(score, label), 6) AS slope, round(kurtosis_pop(score), 4) AS k FROM scored"))
def g13(spark, sf):
    x, y = F.col("score"), F.col("label").cast("double")
    stats = {"mean": F.avg(x), "sd": F.stddev_samp(x), "v": F.var_pop(x), "c": F.corr(x, y), "cv": F.covar_samp(x, y), "slope": F.regr_slope(x, y)}
    return scored(spark, sf).agg(*(F.round(e, 6).alias(n) for n, e in stats.items()), F.round(F.kurtosis(x), 4).alias("k"))


@query("g14_bool", s("SELECT doc_id, bool_or(margin_micro > 0) AS some, bool_and(margin_micro > 0) AS every FROM scored GROUP BY doc_id"))
def g14(spark, sf):
    ok = F.col("margin_micro") > 0
    return scored(spark, sf).groupBy("doc_id").agg(F.bool_or(ok).alias("some"), F.bool_and(ok).alias("every"))


@query("g15_collect_set", "SELECT lang, array_to_string(list_sort(list(DISTINCT source)), ',') AS sources FROM documents GROUP BY lang")
def g15(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.array_join(F.sort_array(F.collect_set("source")), ",").alias("sources"))


@query("g16_majority", "SELECT source, (sum(quality) * 2 > count(*)) AS good FROM documents JOIN labels USING (doc_id) GROUP BY source")
def g16(spark, sf):
    return labelled_docs(spark, sf).groupBy("source").agg((F.sum("quality") * 2 > F.count("*")).alias("good"))


@query("g17_having", "SELECT source, count(*) AS n FROM documents GROUP BY source HAVING min(n_chars) < 20")
def g17(spark, sf):
    return table(spark, sf, "documents").groupBy("source").agg(F.count("*").alias("n"), F.min("n_chars").alias("m")).where("m < 20").select("source", "n")


@query("g18_sketch")
def g18(spark, sf):
    from ..functions.text import tokens

    rows = table(spark, sf, "documents").select("lang", F.explode(tokens(F.col("text"))).alias("t")).groupBy("lang").agg(F.hll_sketch_agg("t", F.lit(14)).alias("k"))
    return rows.agg(F.hll_sketch_estimate(F.hll_union_agg("k")).alias("tokens"))


@query("g19_auc", s("SELECT round(sum(n1 * (below + n0 / 2)) / (sum(n1) * sum(n0))::DOUBLE, 6) AS auc FROM (SELECT margin_micro, sum(label) AS n1, sum(1 - label) AS n0, coalesce(sum(sum(1 - label)) OVER (ORDER BY margin_micro ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM scored GROUP BY 1)"))
def g19(spark, sf):
    return metrics.auc(scored(spark, sf), "margin_micro", "label").select(r6("auc"))


@query("g20_percentile_exact", s("SELECT round(quantile_cont(score, 0.25), 6) AS q1, round(median(score), 6) AS q2, round(quantile_cont(n_tokens, 0.1), 6) AS t1 FROM scored"))
def g20(spark, sf):
    return scored(spark, sf).agg(F.round(F.percentile("score", 0.25), 6).alias("q1"), F.round(F.median("score"), 6).alias("q2"), F.round(F.percentile("n_tokens", 0.1), 6).alias("t1"))


@query("g21_global_no_rows", s("SELECT count(*) AS n, sum(label)::BIGINT AS n1, NULL::DOUBLE AS share FROM scored WHERE margin_micro > 99000000"))
def g21(spark, sf):
    rows = scored(spark, sf).where("margin_micro > 99000000").agg(F.count("*").alias("n"), F.sum("label").alias("n1"))
    return rows.withColumn("share", F.try_divide(F.col("n1").cast("double"), F.col("n")))


# windows


@query("n01_row_number", "SELECT doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars, doc_id)::INT AS rn FROM documents")
def n01(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.row_number().over(W.partitionBy("source").orderBy("n_chars", "doc_id")).alias("rn"))


@query("n02_rank_dense", "SELECT doc_id, (rank() OVER (PARTITION BY source ORDER BY lang))::INT AS r, (dense_rank() OVER (PARTITION BY source ORDER BY lang))::INT AS d FROM documents")
def n02(spark, sf):
    w = W.partitionBy("source").orderBy("lang")
    return table(spark, sf, "documents").select("doc_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"))


@query("n03_ntile_dist", "SELECT doc_id, (ntile(10) OVER w)::INT AS decile, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)")
def n03(spark, sf):
    w = W.partitionBy("lang").orderBy("n_chars", "doc_id")
    return table(spark, sf, "documents").select("doc_id", F.ntile(10).over(w).alias("decile"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@query("n04_lag_lead", "SELECT doc_id, n_chars - lag(n_chars) OVER w AS back, lead(n_chars, 2, 0) OVER w AS ahead FROM documents WINDOW w AS (PARTITION BY source ORDER BY doc_id)")
def n04(spark, sf):
    w = W.partitionBy("source").orderBy("doc_id")
    return table(spark, sf, "documents").select("doc_id", (F.col("n_chars") - F.lag("n_chars").over(w)).alias("back"), F.lead("n_chars", 2, 0).over(w).alias("ahead"))


@query("n05_range_frame", s("SELECT snippet_id, (sum(label) OVER (PARTITION BY doc_id ORDER BY margin_micro))::BIGINT AS upto FROM scored"))
def n05(spark, sf):
    w = W.partitionBy("doc_id").orderBy("margin_micro").rangeBetween(W.unboundedPreceding, W.currentRow)
    return scored(spark, sf).select("snippet_id", F.sum("label").over(w).alias("upto"))


@query("n06_rows_frame", "SELECT doc_id, round(avg(n_chars) OVER (PARTITION BY lang ORDER BY doc_id ROWS BETWEEN 99 PRECEDING AND CURRENT ROW), 6) AS mean100 FROM documents")
def n06(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.round(F.avg("n_chars").over(W.partitionBy("lang").orderBy("doc_id").rowsBetween(-99, 0)), 6).alias("mean100"))


@query("n07_running_total", "SELECT doc_id, (sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id))::BIGINT AS total FROM documents")
def n07(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.sum("n_chars").over(W.partitionBy("source").orderBy("doc_id")).alias("total"))


@query("n08_first_last", "SELECT doc_id, last_value(CASE WHEN doc_id % 5 = 0 THEN doc_id END IGNORE NULLS) OVER (PARTITION BY source ORDER BY doc_id) AS latest, first_value(doc_id) OVER (PARTITION BY source ORDER BY doc_id) AS first FROM documents")
def n08(spark, sf):
    w = W.partitionBy("source").orderBy("doc_id")
    return table(spark, sf, "documents").select("doc_id", F.last(F.when(F.col("doc_id") % 5 == 0, F.col("doc_id")), ignorenulls=True).over(w).alias("latest"), F.first("doc_id").over(w).alias("first"))


@query("n09_two_level_prefix", s("SELECT snippet_id, (sum(label) OVER (ORDER BY margin_micro))::BIGINT AS label_upto FROM scored"))
def n09(spark, sf):
    return threshold.running_sums(scored(spark, sf).select("snippet_id", "margin_micro", "label"), "margin_micro", ["label"], 1_000_000).select("snippet_id", "label_upto")


@query("n10_nth_value", "SELECT DISTINCT source, nth_value(doc_id, 3) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS third FROM documents")
def n10(spark, sf):
    w = W.partitionBy("source").orderBy("doc_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, sf, "documents").select("source", F.nth_value("doc_id", 3).over(w).alias("third")).distinct()


@query("n11_per_filter", "SELECT k, doc_id, (sum(v) OVER (PARTITION BY k ORDER BY doc_id))::BIGINT AS n FROM labels UNPIVOT (v FOR k IN (quality, toxic))")
def n11(spark, sf):
    rows = table(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v")
    return rows.select("k", "doc_id", F.sum("v").over(W.partitionBy("k").orderBy("doc_id")).alias("n"))


@query("n12_reverse_frame", s("SELECT snippet_id, coalesce(sum(1 - label) OVER (PARTITION BY doc_id ORDER BY margin_micro RANGE BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0)::BIGINT AS above FROM scored"))
def n12(spark, sf):
    w = W.partitionBy("doc_id").orderBy("margin_micro").rangeBetween(1, W.unboundedFollowing)
    return scored(spark, sf).select("snippet_id", F.coalesce(F.sum(1 - F.col("label")).over(w), F.lit(0)).alias("above"))


# sorts and limits


@query("k01_global_sort", s("SELECT snippet_id, margin_micro FROM scored ORDER BY margin_micro, snippet_id"))
def k01(spark, sf):
    return scored(spark, sf).select("snippet_id", "margin_micro").orderBy("margin_micro", "snippet_id")


@query("k02_topk", s("SELECT snippet_id FROM scored ORDER BY abs(margin_micro - 1000000), snippet_id LIMIT 100"))
def k02(spark, sf):
    return scored(spark, sf).orderBy(F.abs(F.col("margin_micro") - 1_000_000), "snippet_id").limit(100).select("snippet_id")


@query("k03_topk_per_group", s("SELECT label, snippet_id FROM scored QUALIFY row_number() OVER (PARTITION BY label ORDER BY margin_micro DESC, snippet_id) <= 20"))
def k03(spark, sf):
    rows = scored(spark, sf).withColumn("r", F.row_number().over(W.partitionBy("label").orderBy(F.desc("margin_micro"), "snippet_id")))
    return rows.where("r <= 20").select("label", "snippet_id")


@query("k04_limit_offset", "SELECT doc_id FROM documents ORDER BY n_chars, doc_id LIMIT 50 OFFSET 100")
def k04(spark, sf):
    return table(spark, sf, "documents").orderBy("n_chars", "doc_id").offset(100).limit(50).select("doc_id")


@query("k05_sort_within")
def k05(spark, sf):
    rows = scored(spark, sf).repartition(8, "doc_id").sortWithinPartitions("doc_id", "seq")
    return rows.groupBy(F.spark_partition_id().alias("part")).agg(F.count("*").alias("n"))


@query("k06_range_partition")
def k06(spark, sf):
    rows = scored(spark, sf).repartitionByRange(8, "margin_micro")
    return rows.groupBy(F.spark_partition_id().alias("part")).agg(F.min("margin_micro").alias("lo"), F.max("margin_micro").alias("hi"), F.count("*").alias("n"))


@query("k07_first_in_band", s("SELECT snippet_id, stream_pos FROM scored WHERE margin_micro BETWEEN -3000000 AND 3000000 AND stream_pos >= 256 ORDER BY stream_pos LIMIT 64"))
def k07(spark, sf):
    rows = scored(spark, sf).where(F.col("margin_micro").between(-3_000_000, 3_000_000) & (F.col("stream_pos") >= 256))
    return rows.orderBy("stream_pos").limit(64).select("snippet_id", "stream_pos")


@query("k08_nulls_order", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id) ORDER BY quality NULLS LAST, doc_id LIMIT 450")
def k08(spark, sf):
    rows = table(spark, sf, "documents", ["doc_id"]).join(table(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality")
    return rows.orderBy(F.asc_nulls_last("quality"), "doc_id").limit(450)


@query("k08b_nulls_order_all", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def k08b(spark, sf):
    """All documents in k08's order: unlabelled last."""
    rows = table(spark, sf, "documents", ["doc_id"]).join(table(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality")
    return rows.orderBy(F.asc_nulls_last("quality"), "doc_id")


# sets


def side(spark, sf, which: str) -> DataFrame:
    rows = scored(spark, sf)
    return rows.where("label = 1" if which == "teacher" else "margin_micro > 0").select("snippet_id")


T_, S_ = "SELECT snippet_id FROM scored WHERE label = 1", "SELECT snippet_id FROM scored WHERE margin_micro > 0"


@query("u01_union_all", s(f"SELECT count(*) AS n FROM ({T_} UNION ALL {S_})"))
def u01(spark, sf):
    return side(spark, sf, "teacher").union(side(spark, sf, "student")).agg(F.count("*").alias("n"))


@query("u02_union_by_name", "SELECT doc_id, quality, NULL::INT AS toxic FROM labels UNION ALL SELECT doc_id, NULL::INT, toxic FROM labels")
def u02(spark, sf):
    l = table(spark, sf, "labels")  # noqa: E741
    return l.select("doc_id", "quality").unionByName(l.select("toxic", "doc_id"), allowMissingColumns=True)


@query("u03_union_distinct", s(f"{T_} UNION {S_}"))
def u03(spark, sf):
    return side(spark, sf, "teacher").union(side(spark, sf, "student")).distinct()


@query("u04_intersect", s(f"{T_} INTERSECT {S_}"))
def u04(spark, sf):
    return side(spark, sf, "teacher").intersect(side(spark, sf, "student"))


@query("u04b_intersect_all", "SELECT source FROM documents WHERE lang = 'en' INTERSECT ALL SELECT source FROM documents WHERE lang = 'fr'")
def u04b(spark, sf):
    d = table(spark, sf, "documents")
    return d.where("lang = 'en'").select("source").intersectAll(d.where("lang = 'fr'").select("source"))


@query("u05_except", s(f"{T_} EXCEPT {S_}"))
def u05(spark, sf):
    return side(spark, sf, "teacher").subtract(side(spark, sf, "student"))


@query("u05b_except_all", "SELECT source FROM documents WHERE lang = 'en' EXCEPT ALL SELECT source FROM documents WHERE lang = 'fr'")
def u05b(spark, sf):
    d = table(spark, sf, "documents")
    return d.where("lang = 'en'").select("source").exceptAll(d.where("lang = 'fr'").select("source"))


@query("u06_symmetric_difference", s(f"({T_} EXCEPT {S_}) UNION ALL ({S_} EXCEPT {T_})"))
def u06(spark, sf):
    a, b = side(spark, sf, "teacher"), side(spark, sf, "student")
    return a.subtract(b).union(b.subtract(a))


@query("u07_distinct_text", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text)")
def u07(spark, sf):
    return table(spark, sf, "documents").groupBy(F.md5("text")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).select("doc_id", "copies")


# scalar functions


@query("f01_string", """SELECT doc_id, lower(substr(text, 1, 5)) AS a, length(trim(text)) AS b, regexp_replace(substr(text, 1, 40), '[aeiou]', '_', 'g') AS c, regexp_extract(text, '([a-z]+)ing', 1) AS d,
    lpad(source, 6, '*') AS e, rpad(lang, 4, '.') AS f, translate(lang, 'ef', 'EF') AS g, instr(text, 'the') AS h, levenshtein(source, 'src10') AS i, ascii(lang) AS j, reverse(source) AS k, repeat(lang, 2) AS l, split_part(text, ' ', 2) AS m FROM documents""")
def f01(spark, sf):
    t = F.col("text")
    return table(spark, sf, "documents").select(
        "doc_id", F.lower(F.substring(t, 1, 5)).alias("a"), F.length(F.trim(t)).cast("bigint").alias("b"), F.regexp_replace(F.substring(t, 1, 40), "[aeiou]", "_").alias("c"), F.regexp_extract(t, "([a-z]+)ing", 1).alias("d"),
        F.lpad("source", 6, "*").alias("e"), F.rpad("lang", 4, ".").alias("f"), F.translate("lang", "ef", "EF").alias("g"), F.instr(t, "the").cast("bigint").alias("h"), F.levenshtein("source", F.lit("src10")).cast("bigint").alias("i"),
        F.ascii("lang").alias("j"), F.reverse("source").alias("k"), F.repeat("lang", 2).alias("l"), F.split_part(t, F.lit(" "), F.lit(2)).alias("m"),
    )


@query("f01b_replace_all", "SELECT doc_id, regexp_replace(text, '[aeiou]', '_', 'g') AS c FROM documents")
def f01b(spark, sf):
    """f01's replacement over whole texts."""
    return table(spark, sf, "documents").select("doc_id", F.regexp_replace("text", "[aeiou]", "_").alias("c"))


@query("f02_hash", f"SELECT doc_id, md5(text) AS a, sha256(text) AS b, {twins.hash_int(Q + '7' + Q, 'doc_id')} AS c FROM documents")
def f02(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.md5("text").alias("a"), F.sha2("text", 256).alias("b"), hash_int("7", F.col("doc_id")).alias("c"))


@query("f03_math", "SELECT doc_id, round(ln(n_chars), 6) AS a, round(log2(n_chars), 6) AS b, round(log10(n_chars), 6) AS c, round(sqrt(n_chars), 6) AS d, round(exp(-n_chars / 1000.0::DOUBLE), 6) AS e, round(pow(n_chars, 0.3::DOUBLE), 6) AS f, greatest(n_chars, 500) AS g, least(n_chars, 500) AS h, sign(n_chars - 500)::DOUBLE AS i, ceil(n_chars / 7.0::DOUBLE)::BIGINT AS j, floor(n_chars / 7.0::DOUBLE)::BIGINT AS k, n_chars % 7 AS l FROM documents")
def f03(spark, sf):
    n = F.col("n_chars")
    six = {"a": F.ln(n), "b": F.log2(n), "c": F.log10(n), "d": F.sqrt(n), "e": F.exp(-n / 1000.0), "f": F.pow(n, F.lit(0.3))}
    return table(spark, sf, "documents").select("doc_id", *(F.round(e, 6).alias(k) for k, e in six.items()), F.greatest(n, F.lit(500)).alias("g"), F.least(n, F.lit(500)).alias("h"), F.sign(n - 500).alias("i"), F.ceil(n / 7.0).alias("j"), F.floor(n / 7.0).alias("k"), F.pmod(n, F.lit(7)).alias("l"))


@query("f04_date", "SELECT event_id, date_trunc('hour', ts) AS a, (ts::DATE + 3)::DATE AS b, datediff('day', DATE '2020-01-01', ts::DATE)::INT AS c, last_day(ts::DATE) AS d, year(ts)::INT AS e, month(ts)::INT AS f, (dayofweek(ts) + 1)::INT AS g, hour(ts)::INT AS h, ts + INTERVAL 90 MINUTE AS i FROM events")
def f04(spark, sf):
    t, day = F.col("ts"), F.to_date("ts")
    return table(spark, sf, "events").select(
        "event_id", F.date_trunc("hour", t).cast("timestamp_ntz").alias("a"), F.date_add(day, 3).alias("b"), F.date_diff(day, F.lit("2020-01-01").cast("date")).alias("c"), F.last_day(day).alias("d"),
        F.year(t).alias("e"), F.month(t).alias("f"), F.dayofweek(t).alias("g"), F.hour(t).alias("h"), (t + F.expr("interval 90 minutes")).alias("i"),
    )


@query("f05_array", f"SELECT snippet_id, len(tk) AS a, array_to_string(list_slice(tk, 1, 3), ' ') AS b, len(list_distinct(tk)) AS c, list_contains(tk, 'the') AS d, coalesce(list_position(tk, 'of'), 0)::BIGINT AS e, len(list_intersect(tk, ['the', 'of', 'and'])) AS f, (list_reduce(list_transform(tk, lambda x: length(x)), lambda a, b: a + b))::BIGINT AS g, array_to_string(list_slice(list_sort(tk), 1, 2), ' ') AS h FROM (SELECT snippet_id, string_split(text, ' ') AS tk FROM (WITH {SNIPS} SELECT * FROM snips))")
def f05(spark, sf):
    k = F.split("text", " ")
    total = F.aggregate(F.transform(k, F.length), F.lit(0), lambda a, b: a + b)
    return snips(spark, sf).select(
        "snippet_id", F.size(k).cast("bigint").alias("a"), F.array_join(F.slice(k, 1, 3), " ").alias("b"), F.size(F.array_distinct(k)).cast("bigint").alias("c"), F.array_contains(k, "the").alias("d"), F.array_position(k, "of").cast("bigint").alias("e"),
        F.size(F.array_intersect(k, F.array(F.lit("the"), F.lit("of"), F.lit("and")))).cast("bigint").alias("f"), total.cast("bigint").alias("g"), F.array_join(F.slice(F.sort_array(k), 1, 2), " ").alias("h"),
    )


@query("f06_map", "SELECT doc_id, cardinality(m)::BIGINT AS n, coalesce(m['quality'], -1)::INT AS q, array_to_string(list_sort(map_keys(m)), ',') AS keys, list_sum(map_values(m))::BIGINT AS total FROM (SELECT doc_id, MAP(['quality', 'toxic'], [quality, toxic]) AS m FROM labels)")
def f06(spark, sf):
    m = F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array("quality", "toxic"))
    total = F.aggregate(F.map_values("m"), F.lit(0), lambda a, b: a + b)
    return table(spark, sf, "labels").select("doc_id", m.alias("m")).select("doc_id", F.size("m").cast("bigint").alias("n"), F.coalesce(F.element_at("m", "quality"), F.lit(-1)).alias("q"), F.array_join(F.sort_array(F.map_keys("m")), ",").alias("keys"), total.cast("bigint").alias("total"))


@query("f08_conditional", "SELECT doc_id, coalesce(quality, -1)::INT AS a, nullif(quality, 0)::INT AS b, CASE WHEN quality IS NULL THEN 'none' ELSE 'some' END AS c, try_cast(lang AS INT) AS d, CASE WHEN quality = 0 THEN NULL ELSE round(toxic / quality::DOUBLE, 6) END AS e FROM documents LEFT JOIN labels USING (doc_id)")
def f08(spark, sf):
    q, t = F.col("quality"), F.col("toxic")
    rows = table(spark, sf, "documents", ["doc_id", "lang"]).join(table(spark, sf, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.coalesce(q, F.lit(-1)).alias("a"), F.nullif(q, F.lit(0)).alias("b"), F.nvl2(q, F.lit("some"), F.lit("none")).alias("c"), F.col("lang").try_cast("int").alias("d"), F.round(F.try_divide(t.cast("double"), q), 6).alias("e"))


@query("f09_url_html", "SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host, regexp_extract(url, '^([a-z]+):', 1) AS scheme FROM pages")
def f09(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"))


@query("f10_vector", "SELECT vec_id, round(list_dot_product(embedding, embedding), 4) AS norm2, round(list_cosine_similarity(embedding, list_reverse(embedding)), 4) AS c FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS embedding FROM embeddings)")
def f10(spark, sf):
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda p, q: p + q)
    v = F.transform("embedding", lambda x: x.cast("double"))
    rows = table(spark, sf, "embeddings").select("vec_id", v.alias("v"), F.reverse(v).alias("r"))
    return rows.select("vec_id", F.round(dot(F.col("v"), F.col("v")), 4).alias("norm2"), F.round(dot(F.col("v"), F.col("r")) / dot(F.col("v"), F.col("v")), 4).alias("c"))


@query("f11_struct", "SELECT source, max(struct_pack(n := n_chars, d := doc_id)).d AS longest FROM documents GROUP BY source")
def f11(spark, sf):
    return table(spark, sf, "documents").groupBy("source").agg(F.max(F.struct(F.col("n_chars").alias("n"), F.col("doc_id").alias("d"))).alias("s")).select("source", F.col("s.d").alias("longest"))


@query("f12_casts", "SELECT l_orderkey, l_linenumber, round(l_extendedprice)::BIGINT AS a, l_quantity::INT AS b, (l_discount::DECIMAL(9, 4))::DOUBLE AS c, l_orderkey::VARCHAR AS d FROM lineitem")
def f12(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.round("l_extendedprice").cast("bigint").alias("a"), F.col("l_quantity").cast("int").alias("b"), F.col("l_discount").cast("decimal(9,4)").cast("double").alias("c"), F.col("l_orderkey").cast("string").alias("d"))


@query("f07_json", "SELECT event_id, json_keys(props)[1] AS k, json_valid(props) AS ok FROM events")
def f07(spark, sf):
    return table(spark, sf, "events").select("event_id", F.element_at(F.json_object_keys("props"), 1).alias("k"), F.try_parse_json("props").isNotNull().alias("ok"))


# star schema


@query("r01_scan_filter_agg", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(sum(l_extendedprice), 2) AS p, round(sum(l_extendedprice * (1 - l_discount)), 2) AS d, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def r01(spark, sf):
    rows = table(spark, sf, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp_ntz"))
    two = lambda e, n: F.round(F.sum(e), 2).alias(n)
    return rows.groupBy("l_returnflag", "l_linestatus").agg(two("l_quantity", "q"), two("l_extendedprice", "p"), two(F.col("l_extendedprice") * (1 - F.col("l_discount")), "d"), F.count("*").alias("n"))


@query("r02_three_way_join", "SELECT n_name, year(o_orderdate)::INT AS y, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2")
def r02(spark, sf):
    t = lambda n: table(spark, sf, n)
    rows = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("n_name", F.year("o_orderdate").alias("y")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("r03_topk", "SELECT o_custkey, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1 ORDER BY sum(o_totalprice) DESC, o_custkey LIMIT 10")
def r03(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.sum("o_totalprice").alias("t")).orderBy(F.desc("t"), "o_custkey").limit(10).select("o_custkey", F.round("t", 2).alias("total"))


@query("r04_rollup", "SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name, c_mktsegment)")
def r04(spark, sf):
    t = lambda n: table(spark, sf, n)
    rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.rollup("r_name", "n_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("r05_semi_anti", "SELECT 'with' AS k, count(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate >= TIMESTAMP '1997-01-01') UNION ALL SELECT 'without', count(*) FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) UNION ALL SELECT 'parts', count(*) FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem)")
def r05(spark, sf):
    t = lambda n: table(spark, sf, n)
    late = t("orders").where(F.col("o_orderdate") >= F.lit("1997-01-01").cast("timestamp_ntz"))
    on = F.col("o_custkey") == F.col("c_custkey")
    count = lambda df, k: df.agg(F.lit(k).alias("k"), F.count("*").alias("n"))
    parts = t("part").join(t("lineitem"), F.col("p_partkey") == F.col("l_partkey"), "left_anti")
    return count(t("customer").join(late, on, "left_semi"), "with").union(count(t("customer").join(t("orders"), on, "left_anti"), "without")).union(count(parts, "parts"))


@query("r06_window_share", "SELECT s_suppkey, round(s_acctbal / sum(s_acctbal) OVER (PARTITION BY s_nationkey), 6) AS share, (rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey))::INT AS r FROM supplier")
def r06(spark, sf):
    w = W.partitionBy("s_nationkey")
    return table(spark, sf, "supplier").select("s_suppkey", F.round(F.col("s_acctbal") / F.sum("s_acctbal").over(w), 6).alias("share"), F.rank().over(w.orderBy(F.desc("s_acctbal"), "s_suppkey")).alias("r"))

