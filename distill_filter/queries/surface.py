"""Queries of sinks, the cache source and user-defined aggregates."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..plans.explain import facts
from ..sources import verdicts
from ..sources.tables import shared_dir, table
from .methods import SCORED, SEED, STREAM, a_run, m15, scored, stream, with_sql
from .registry import query


@query("o04_sized_sink", "SELECT count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents")
def o04(spark, sf):
    """Files of a bounded number of rows, packed with zstandard, read back."""
    path = f"{shared_dir(spark)}/sized-{uuid.uuid4().hex}"
    table(spark, sf, "documents").write.option("maxRecordsPerFile", 200).option("compression", "zstd").parquet(path)
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("o07_cache_source", with_sql(STREAM, f"SELECT snippet_id, label AS verdict FROM stream WHERE stream_pos < {SEED}"))
def o07(spark, sf):
    path = f"{shared_dir(spark)}/cache-{uuid.uuid4().hex}"
    first = stream(spark, sf).where(F.col("stream_pos") < SEED)
    for spec in ("quality", "topic_private"):
        calls = first.select(F.lit(spec).alias("spec"), F.lit("teacher").alias("teacher_id"), "snippet_id", F.lit(0).alias("call_no"), F.col(spec).alias("verdict"))
        verdicts.append(calls.union(calls.limit(20)), path)
    verdicts.register(spark)
    return verdicts.distinct_calls(spark.read.format("verdict_cache").option("spec", "quality").load(path)).select("snippet_id", "verdict")


@query("x02_remote_teacher", with_sql(STREAM, "SELECT snippet_id, contains(text, '***')::INT AS verdict FROM stream WHERE stream_pos < 300"))
def x02(spark, sf):
    def call(texts: list[str]) -> list[int]:
        return [int("***" in t) for t in texts]

    rows = stream(spark, sf).where("stream_pos < 300")
    return verdicts.annotate_remote(rows, call).select("snippet_id", "verdict")


@query("x02b_remote_teacher_all", with_sql(STREAM, "SELECT snippet_id, contains(text, '***')::INT AS verdict FROM stream"))
def x02b(spark, sf):
    """x02 over the whole stream."""

    def call(texts: list[str]) -> list[int]:
        return [int("***" in t) for t in texts]

    return verdicts.annotate_remote(stream(spark, sf), call).select("snippet_id", "verdict")


@query("x03_grouped_aggregate", with_sql(SCORED, "SELECT doc_id % 3 AS part, round(max(score) - min(score), 6) AS spread FROM scored GROUP BY 1"))
def x03(spark, sf):
    @F.pandas_udf(DoubleType())
    def spread(s: pd.Series) -> float:
        return float(s.max() - s.min())

    return scored(spark, sf).groupBy((F.col("doc_id") % 3).alias("part")).agg(F.round(spread("score"), 6).alias("spread"))


@query("c08_call_latency")
def c08(spark, sf):
    return verdicts.call_latency(a_run(spark, sf).trace_df(spark), 64, 1.5)


@query("x09_plan_facts")
def x09(spark, sf):
    """What the corpus filter's plan holds: no exchange, one hand-over to Python, the columns it reads."""
    found = facts(m15(spark, sf))
    return spark.createDataFrame([(k, str(v)) for k, v in found.items()], "fact string, value string")

