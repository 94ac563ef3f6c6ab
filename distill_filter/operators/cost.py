"""Costs: billed calls, the student's share, totals, ratios, projections."""

from __future__ import annotations

from dataclasses import dataclass
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

if TYPE_CHECKING:
    from ..plans.active import Run


@dataclass(frozen=True)
class CostModel:
    """Prices in USD. The call prices are the published totals over 13.5 million calls."""

    teacher_price: float = 67_000 / 13_500_000
    weak_price: float = 13_000 / 13_500_000
    student_price_per_mtoken: float = 0.008
    train_price_per_mtoken: float = 0.05


#: Published calls, student cost and total of each filter, in USD, and the full-annotation rows.
PUBLISHED = (("climate", 7_500, 80, 120), ("AI", 6_000, 80, 110), ("politics", 60_000, 170, 470), ("mainstream", 100_000, 300, 800), ("quality", 60_000, 170, 470))
FULL_CALLS, FULL_TEACHER_USD, FULL_WEAK_USD = 13_500_000, 67_000, 13_000


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([tuple(map(lambda x: x if isinstance(x, str) else int(x), r)) for r in PUBLISHED], "filter string, calls bigint, student_usd bigint, total_usd bigint")


def totals(rows: DataFrame, model: CostModel = CostModel(), full_usd: float = float(FULL_TEACHER_USD)) -> DataFrame:
    """rows(calls, student_usd) with teacher_usd, total, ratio to full annotation of the same corpus (by default the
    published one), a below-one-percent flag and student runs per call."""
    out = rows.withColumn("teacher_usd", F.col("calls") * F.lit(model.teacher_price)).withColumn("computed_usd", F.col("student_usd") + F.col("calls") * F.lit(model.teacher_price))
    out = out.withColumn("ratio", F.col("computed_usd") / F.lit(full_usd))
    return out.withColumn("below_one_percent", F.col("ratio") < 0.01).withColumn("operations_per_call", 1 / F.col("ratio"))


def run_counters(stream: DataFrame, run: Run) -> DataFrame:
    """(component, tokens) of a run over stream(stream_pos, n_tokens): training counts each fit's labels, scoring the
    rows that were read to choose from (whole scans for pools), inference the whole corpus once."""
    spark, batch = stream.sparkSession, run.config.batch
    fits = [n for n, _ in run.models]
    uses = spark.createDataFrame([(p, sum(i < n for n in fits)) for i, (_, _, _, p, _) in enumerate(run.labels)], "stream_pos bigint, fits int")
    training = stream.join(F.broadcast(uses), "stream_pos").agg(F.lit("training").alias("component"), F.sum(F.col("n_tokens") * F.col("fits")).cast("bigint").alias("tokens"))
    whole = stream.agg(F.sum("n_tokens").cast("bigint").alias("tokens"))
    if run.config.policy.startswith("pool"):
        rounds = sum(1 for n in fits) - 1
        scoring = whole.select(F.lit("scoring").alias("component"), (F.col("tokens") * rounds).alias("tokens"))
    else:
        read = F.col("stream_pos").between(batch, run.seen - 1) & F.lit(run.config.policy != "random")
        scoring = stream.where(read).agg(F.lit("scoring").alias("component"), F.coalesce(F.sum("n_tokens"), F.lit(0)).cast("bigint").alias("tokens"))
    return training.union(scoring).union(whole.select(F.lit("inference").alias("component"), "tokens"))


def teacher_calls(labels: DataFrame, by: list[str]) -> DataFrame:
    """Billed calls: distinct keys, however often a row was written."""
    return labels.groupBy(*by).agg(F.countDistinct("snippet_id").alias("calls"))


def student_cost(counters: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """counters(component, tokens) with usd: training has its own price, scoring and inference share one."""
    price = F.when(F.col("component") == "training", F.lit(model.train_price_per_mtoken)).otherwise(F.lit(model.student_price_per_mtoken))
    return counters.withColumn("usd", F.col("tokens") / 1e6 * price)


def price_sweep(totals_: DataFrame, factors: list[float], model: CostModel = CostModel()) -> DataFrame:
    """totals(method, calls, student_usd) at dearer teachers: a small cross join with a list of price factors."""
    prices = totals_.sparkSession.createDataFrame([(float(f),) for f in factors], "factor double")
    return totals_.crossJoin(F.broadcast(prices)).withColumn("usd", F.col("student_usd") + F.col("calls") * F.col("factor") * F.lit(model.teacher_price))
