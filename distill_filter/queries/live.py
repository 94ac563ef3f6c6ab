"""Queries of streams and of the function surface."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import snippets, students, teacher
from ..sources.tables import materialise, shared_dir, table
from ..streaming import live
from . import twins
from ..plans.active import RuleAnnotator
from .methods import BLOCKS, ENGINE, FIVE, ROUND, SCORED, SEED, SNIPS, STREAM, common_words, engine_sql, first_student, round_sql, scored, snips, stream, with_sql
from .registry import query


def event_stream(spark, sf):
    rows = table(spark, sf, "events")
    return live.file_stream(spark, f"{sf}/events.parque[t]", rows.schema, None)  # a pattern: the source wants a folder or one


HOURLY = "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2"


@query("t01_tumbling", HOURLY)
def t01(spark, sf):
    out = live.drain(live.hourly(event_stream(spark, sf)), "complete")
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("hour"), "event_type", "n", "total")


@query("t02_sliding", "SELECT h AS start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY h")
def t02(spark, sf):
    return live.drain(live.sliding(event_stream(spark, sf)), "complete").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("t03_session", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE >= ts THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def t03(spark, sf):
    return live.sessions(table(spark, sf, "events")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("t04_watermark")
def t04(spark, sf):
    """Windows that the watermark has closed."""
    rows = event_stream(spark, sf).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "10 minutes")
    return live.drain(live.hourly(rows), "append").select(F.col("w.start").alias("hour"), "event_type", "n", "total")


@query("t05_stream_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")
def t05(spark, sf):
    rows = event_stream(spark, sf).withColumn("ts", F.col("ts").cast("timestamp"))
    twice = rows.union(rows).withWatermark("ts", "100 days").dropDuplicatesWithinWatermark(["event_id"])
    return live.drain(twice.select("event_id")).agg(F.count("*").alias("n"))


@query("t06_keyed_state", "SELECT user_id, count(*) AS n, round(max(value), 6) AS top FROM events GROUP BY user_id")
def t06(spark, sf):
    out = live.drain(live.keyed_counts(event_stream(spark, sf).select("user_id", "value")), "update")
    return out.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max("top"), 6).alias("top"))


@query("t07_stream_static", with_sql(SCORED, f"SELECT snippet_id, sum(w_micro)::BIGINT AS w FROM (SELECT snippet_id, unnest({twins.features()}) AS token FROM stream) JOIN st_w USING (token) WHERE token <> '' GROUP BY snippet_id"))
def t07(spark, sf):
    """Arrivals need no order: the snippets go to files as they are cut, and the weights come from the stream's first rows alone."""
    rows = snips(spark, sf).select("snippet_id", "text")
    path = f"{shared_dir(spark)}/arrivals-{uuid.uuid4().hex}"
    rows.write.parquet(path)
    head = snippets.first(spark.read.schema(rows.schema).parquet(path), SEED).withColumn("verdict", teacher.rule("quality", F.col("text")))
    weights = materialise(students.logodds_weights(materialise(head, "labels")).where("token <> ''").select("token", "w_micro"), "weights")
    return live.drain(live.score_live(live.file_stream(spark, path, rows.schema, None), weights)).groupBy("snippet_id").agg(F.sum("w_micro").alias("w"))


@query("t08_stream_stream", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_id % 7 = 0")
def t08(spark, sf):
    rows = event_stream(spark, sf).withColumn("ts", F.col("ts").cast("timestamp"))
    a = rows.where("event_id % 7 = 0").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 day")
    b = rows.select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("s")).withWatermark("s", "1 day")
    return live.drain(a.join(b, F.expr("u = v and s > t and s <= t + interval 10 minutes")).select("a", "b"))


@query("t08b_stream_stream_all")
def t08b(spark, sf):
    """The interval join of all events with all events; the SQL of t08 states a seventh of the left side, so it has no twin."""
    rows = event_stream(spark, sf).withColumn("ts", F.col("ts").cast("timestamp"))
    a = rows.select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 day")
    b = rows.select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("s")).withWatermark("s", "1 day")
    return live.drain(a.join(b, F.expr("u = v and s > t and s <= t + interval 10 minutes")).select("a", "b"))


@query("m18_live_round", round_sql("SELECT snippet_id, stream_pos, label AS verdict FROM r_bought"))
def m18(spark, sf):
    """The round of m13 over micro-batches: files of the stream in order of position, a few to a batch."""
    rows = stream(spark, sf).where(F.col("stream_pos") >= SEED).select("snippet_id", "stream_pos", "text")
    path = f"{shared_dir(spark)}/live-arrivals-{uuid.uuid4().hex}"
    for k, (lo, hi) in enumerate([(SEED, 1000), (1000, 1777), (1777, 4000), (4000, 1 << 40)]):
        rows.where(F.col("stream_pos").between(lo, hi - 1)).coalesce(1).write.parquet(f"{path}/part={k}")
    model = first_student(spark, sf)
    arrivals = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(f"{path}/part=*")
    n = stream(spark, sf).count()
    return live.collect_live(arrivals, model, "quality", n, SEED, ROUND).select("snippet_id", "stream_pos", "verdict")


def arriving(spark, rows, parts) -> str:
    """rows written as one folder for each part, in order of arrival; returns a pattern that a file stream reads them by."""
    path = f"{shared_dir(spark)}/live-arrivals-{uuid.uuid4().hex}"
    for k, part in enumerate(parts):
        rows.where(part).coalesce(1).write.parquet(f"{path}/part={k}")
    return f"{path}/part=*"


@query("m18b_live_rounds", engine_sql("SELECT round::INT AS round, snippet_id, stream_pos, verdict FROM e_lab"))
def m18b(spark, sf):
    """The whole loop on live arrivals, refits and all: its labels are those of the batch run."""
    rows = stream(spark, sf).select("snippet_id", "stream_pos", "text")
    n = rows.count()
    edges = [0, 300, 1000, 1777, 4000, n + 4001]
    path = arriving(spark, rows, [F.col("stream_pos").between(a, b - 1) for a, b in zip(edges, edges[1:])])
    got = live.run_live(live.file_stream(spark, path, rows.schema), RuleAnnotator("quality"), n, ENGINE)
    return got.select("round", "snippet_id", "stream_pos", "verdict")


LATE = "(doc_id % 50 = 7 AND doc_id < (SELECT max(doc_id) - 2 FROM documents))"
IN_ORDER = f"{STREAM}, fed AS (SELECT snippet_id, text, label, n_tokens, row_number() OVER (ORDER BY doc_id, seq) - 1 AS stream_pos FROM stream WHERE NOT {LATE}), {twins.rounds(ENGINE, BLOCKS, 'e', 'fed')}"


@query("w13b_live_documents", with_sql(IN_ORDER, "SELECT round::INT AS round, snippet_id, verdict FROM e_lab"))
def w13b(spark, sf):
    """Documents arrive in order of their ids, one an hour; each fiftieth comes when all others are there, too late for
    the watermark. The loop runs on what is on time, in the order of arrival."""
    hours = F.timestamp_seconds(1_700_000_000 + F.col("doc_id") * 3600)  # well after the time that a watermark starts from
    top = table(spark, sf, "documents", ["doc_id"]).agg(F.max("doc_id")).first()[0] or 0
    late = (F.col("doc_id") % 50 == 7) & (F.col("doc_id") < top - 2)
    rows = stream(spark, sf).select("snippet_id", "text", "doc_id", (F.col("doc_id") * (1 << 20) + F.col("seq")).alias("stream_pos"), hours.alias("arrived"))
    step = top // 3 + 1
    parts = [~late & F.col("doc_id").between(k * step, (k + 1) * step - 1) for k in range(3)]
    path = arriving(spark, rows, [*parts, late])
    fed = live.on_time(live.file_stream(spark, path, rows.schema), "arrived", "1 hour", "snippet_id")
    n = rows.where(~late).count()
    return live.run_live(fed, RuleAnnotator("quality"), n, ENGINE).select("round", "snippet_id", "verdict")


@query("t03b_session_stream", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE >= ts THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def t03b(spark, sf):
    """t03's sessions as a stream."""
    return live.drain(live.sessions(event_stream(spark, sf)), "complete").select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("w13_live_stream", HOURLY)
def w13(spark, sf):
    return t01(spark, sf)


@query("x05_table_function", with_sql(SNIPS, "SELECT doc_id, seq, n_tokens FROM snips"))
def x05(spark, sf):
    udfs.register(spark)
    table(spark, sf, "documents").createOrReplaceTempView("__documents")
    return spark.sql("SELECT doc_id, seq, n_tokens FROM __documents, LATERAL cut_snippets(text, 64)")


@query("x06_sql_rules", with_sql(SNIPS, f"SELECT snippet_id, {twins.rule('topic_hostile')} AS hostile, {twins.rule('quality')} AS quality FROM snips"))
def x06(spark, sf):
    udfs.register(spark)
    stream(spark, sf).createOrReplaceTempView("__stream")
    return spark.sql("SELECT snippet_id, teacher_verdict('topic_hostile', text) AS hostile, teacher_verdict('quality', text) AS quality FROM __stream")


RULES_SQL = ", ".join(f"{twins.rule(x)} AS {x}" for x in FIVE)
ODD = "SELECT 'odd1' AS snippet_id, concat('one', chr(160), 'idiot two', chr(160), '5') AS text UNION ALL SELECT 'odd2', '' UNION ALL SELECT 'odd3', 'IDIOT! \t Copyright'"


@query("x06b_five_rules", with_sql(f"{SNIPS}, {twins.COMMON}, t AS (SELECT snippet_id, text FROM snips UNION ALL {ODD})", f"SELECT snippet_id, {RULES_SQL} FROM t, (SELECT list(token) AS cm FROM common)"))
def x06b(spark, sf):
    """All five rules by name from SQL, also on texts with other white space than the rules split on."""
    udfs.register(spark, common=common_words(spark, sf))
    stream(spark, sf).select("snippet_id", "text").union(spark.sql(ODD.replace("chr(160)", "decode(unhex('C2A0'), 'UTF-8')"))).createOrReplaceTempView("__stream")
    return spark.sql(f"SELECT snippet_id, {', '.join(f"teacher_verdict('{x}', text) AS {x}" for x in FIVE)} FROM __stream")


@query("x07_sql_view", with_sql(SCORED, "SELECT snippet_id FROM scored WHERE margin_micro > 0"))
def x07(spark, sf):
    udfs.register(spark, {"quality": first_student(spark, sf)})
    stream(spark, sf).createOrReplaceTempView("__stream")
    spark.sql("CREATE OR REPLACE TEMPORARY VIEW __passed AS SELECT snippet_id FROM __stream WHERE passes('quality', text) = 1")
    return spark.table("__passed")


@query("x04_grouped_cuts", with_sql(f"{SCORED}, y AS (SELECT margin_micro, label AS y FROM scored), {twins.curve('y', 'lc')}", "SELECT 'quality' AS filter, (SELECT cut FROM lc ORDER BY lc.loss, cut LIMIT 1) AS cut, (SELECT min(n1_le + n0_gt) FROM lc)::BIGINT AS errors"))
def x04(spark, sf):
    return udfs.cuts_per_filter(scored(spark, sf).select(F.lit("quality").alias("filter"), "margin_micro", "label"))


@query("o02_formats")
def o02(spark, sf):
    """Round trips through other formats: rows that come back as they were."""
    rows = table(spark, sf, "documents", ["doc_id", "lang", "source"])
    out, base = None, f"{shared_dir(spark)}/formats-{uuid.uuid4().hex}"
    for kind in ("json", "csv", "orc"):
        rows.write.format(kind).save(f"{base}/{kind}")
        back = spark.read.schema(rows.schema).format(kind).load(f"{base}/{kind}")
        row = back.join(rows, rows.columns, "left_semi").agg(F.lit(kind).alias("format"), F.count("*").alias("same"))
        out = row if out is None else out.union(row)
    return out


@query("o03_partitioned_sink", with_sql(SCORED, "SELECT label, count(*) AS n FROM scored WHERE label = 1 GROUP BY label"))
def o03(spark, sf):
    rows = materialise(scored(spark, sf).select("snippet_id", "label"), "passes", ["label"])
    return rows.where("label = 1").groupBy("label").agg(F.count("*").alias("n"))

