"""Quantities of the risk and balance bounds."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.tables import materialise


def eta_from_calls(calls: DataFrame, z: float = 1.96) -> DataFrame:
    """(snippet_id, k, eta, eta_lo, eta_hi): the probability of class 0 from repeat calls, with Wilson's interval."""
    rows = calls.groupBy("snippet_id").agg(F.count("*").alias("k"), F.avg(1 - F.col("verdict")).alias("eta"))
    k, p = F.col("k").cast("double"), F.col("eta")
    middle, half = (p + z * z / (2 * k)) / (1 + z * z / k), z * F.sqrt(p * (1 - p) / k + z * z / (4 * k * k)) / (1 + z * z / k)
    return rows.select("snippet_id", "k", "eta", (middle - half).alias("eta_lo"), (middle + half).alias("eta_hi"))


def in_ranges(df: DataFrame, *order: str) -> DataFrame:
    """df in ranges of `order`, written: with __part and __at, a row's place inside its part. A score that many rows share
    is cut by the later columns, so no part grows with one value."""
    rows = df.repartitionByRange(*order).withColumn("__part", F.spark_partition_id())
    rows = materialise(rows, "ranges")  # ranges come from a sample: fixed once, for both uses
    return rows.withColumn("__at", F.row_number().over(Window.partitionBy("__part").orderBy(*order)))


def rank_linear(df: DataFrame, score: str = "score", slope: float = 1.0, centre: float = 0.5) -> DataFrame:
    """df with place (1 to n by score, id) and an eta that falls evenly along it, clipped to [0, 1]."""
    rows = in_ranges(df, score, "snippet_id")
    sizes = rows.groupBy("__part").agg(F.count("*").alias("__n"))
    earlier = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("__part", F.coalesce(F.sum("__n").over(earlier), F.lit(0)).alias("__before"), F.sum("__n").over(Window.partitionBy()).alias("n"))
    rows = rows.join(F.broadcast(sizes), "__part").withColumn("place", F.col("__before") + F.col("__at")).drop("__part", "__at", "__before")
    return rows.withColumn("eta", F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.lit(0.5) - slope * ((F.col("place") - 0.5) / F.col("n") - centre))))


def smoothness(df: DataFrame, score: str = "score", eta: str = "eta") -> DataFrame:
    """(smoothness): the largest step of eta between neighbours in score order, inside parts and from part to part."""
    rows = in_ranges(df.select(score, eta, "snippet_id"), score, "snippet_id")
    inside = F.abs(F.col(eta) - F.lag(eta).over(Window.partitionBy("__part").orderBy(score, "snippet_id")))
    ends = rows.withColumn("__step", inside).groupBy("__part").agg(F.max("__step").alias("step"), F.min_by(eta, "__at").alias("first"), F.max_by(eta, "__at").alias("last"))
    across = F.abs(F.col("first") - F.lag("last").over(Window.orderBy("__part")))
    return ends.select(F.greatest("step", across).alias("step")).agg(F.coalesce(F.max("step"), F.lit(0.0)).alias("smoothness"))


def interval_balance(df: DataFrame, lo: float, hi: float, score: str = "score", eta: str = "eta") -> DataFrame:
    """(c0, c1, balance): expected class counts of scores in [lo, hi], and the smaller over the larger."""
    rows = df.where(F.col(score).between(lo, hi)).agg(F.coalesce(F.sum(eta), F.lit(0.0)).alias("c0"), F.coalesce(F.sum(1 - F.col(eta)), F.lit(0.0)).alias("c1"))
    return rows.withColumn("balance", F.try_divide(F.least("c0", "c1"), F.greatest("c0", "c1")))


def band_gap(risk: DataFrame, lo: float, hi: float) -> DataFrame:
    """(s_star, risk_star, gap_lo, gap_hi): excess true risk of the band's ends."""
    best = F.min(F.struct("risk", "cut")).alias("b")
    at = [F.min(F.when(F.col("cut") == x, F.col("risk"))).alias(n) for x, n in ((lo, "r_lo"), (hi, "r_hi"))]
    rows = risk.agg(best, *at)
    return rows.select(F.col("b.cut").alias("s_star"), F.col("b.risk").alias("risk_star"), (F.col("r_lo") - F.col("b.risk")).alias("gap_lo"), (F.col("r_hi") - F.col("b.risk")).alias("gap_hi"))


def balance_bound(n: int, gap_lo: float, gap_hi: float, smooth: float) -> float | None:
    """The lower bound of minority : majority in a band; None where its conditions fail. Below 0 it says nothing."""
    low, high = min(gap_lo, gap_hi), max(gap_lo, gap_hi)
    if not (0 < low and high < 1 and 0 <= smooth < 1):
        return None
    options = [math.sqrt(smooth) * (n * high + smooth * n + 1) / ((1 - smooth) * math.sqrt(n * low))]
    if 1.5 - 2 * smooth > 0:
        options.append((n * high + smooth * n) / (1.5 - 2 * smooth))
    return 1 - min(options)


def balance_bound_column(n: Column, gap_lo: Column, gap_hi: Column, smooth: Column) -> Column:
    low, high, n = F.least(gap_lo, gap_hi), F.greatest(gap_lo, gap_hi), n.cast("double")
    second = F.sqrt(smooth) * (n * high + smooth * n + 1) / ((1 - smooth) * F.sqrt(n * low))
    first = F.when(1.5 - 2 * smooth > 0, (n * high + smooth * n) / (1.5 - 2 * smooth))
    return F.when((low > 0) & (high < 1) & (smooth < 1), 1 - F.least(first, second))


def balance_bound_case_b(n: int, gap_hi: float, smooth: float, c: float, printed: bool = False) -> float:
    """The case where the smaller gap is at least c / n. Putting that in gives sqrt(c); the published form divides by c."""
    return 1 - math.sqrt(smooth) * (n * gap_hi + smooth * n + 1) / ((c if printed else math.sqrt(c)) * (1 - smooth))


def risk_envelope(gaps: list[tuple[float, float]], risk_star: float) -> tuple[float, float]:
    """(with, without): the least constants c for which gap <= c * (R* + beta sqrt(R*) + beta^2), and without the R* term, for all (beta, gap)."""
    with_ = max((g / (risk_star + b * math.sqrt(risk_star) + b * b) for b, g in gaps), default=0.0)
    without = max((g / (b * math.sqrt(risk_star) + b * b) for b, g in gaps), default=0.0)
    return with_, without
