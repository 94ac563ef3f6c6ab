"""The cut where both classes are equally likely, its empirical form, and the confidence band around it.

Scores are ordered integers (margin_micro). The candidate cut 0 lies below every score and is the margin ZERO. A score
that equals a cut is class 0.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

ZERO = -(1 << 62)
#: Running sums go by bins of so many micro-units of margin: clipped margins have 916 bins of 65,536 distinct values at most.
BIN = 1 << 16
#: Both sides of the band's test are doubles; they count as equal this close.
CLOSE = 1e-12


def beta(t: float, n: int, delta: float, scale: float = 1.0) -> float:
    """The radius after t + 1 snippets of n: called with t + 1 at an update at t."""
    return scale * math.sqrt(2 * math.log(2 * math.log2(t) ** 2 * n**2 / delta) / t) if t > 1 else math.inf


def beta_column(t: Column, n: Column, delta: Column, scale: float = 1.0) -> Column:
    inside = F.lit(2.0) * F.pow(F.log2(t), F.lit(2.0)) * F.pow(n.cast("double"), F.lit(2.0)) / delta
    return F.lit(scale) * F.sqrt(F.lit(2.0) * F.ln(inside) / t)


def slack(distance: float, t: int, n: int, delta: float, scale: float = 1.0, kind: str = "bernstein") -> float:
    """Excess loss that a cut `distance` candidates away may have; kind "uniform" has no mass term."""
    b = beta(t + 1, n, delta, scale)
    return b if kind == "uniform" else b * b / 2 + b * math.sqrt(distance / t)


def completed(unlabelled: str, lo: Column, hi: Column, margin: Column, label: Column) -> Column:
    """The label that counts: the bought one; else by side of the band (implied), or null."""
    side = F.when(margin < lo, F.lit(0)).when(margin > hi, F.lit(1))
    return F.coalesce(label, side) if unlabelled == "implied" else label


def loss_curve(scored: DataFrame, unlabelled: str = "implied", cut: str = "margin_micro", label: str = "label") -> DataFrame:
    """(cut, n0, n1, n1_le, n0_gt, loss) for the candidate 0 and each distinct score of scored(cut, label).

    A null label: an error on either side (constant), or not counted (labelled_only); completed labels have none. Rows
    are aggregated to distinct scores first, and sums run in two levels: see `running_sums`.
    """
    counts = scored.groupBy(F.col(cut).alias("cut")).agg(
        F.coalesce(F.sum((F.col(label) == 0).cast("bigint")), F.lit(0)).alias("n0"), F.coalesce(F.sum((F.col(label) == 1).cast("bigint")), F.lit(0)).alias("n1"), F.sum(F.col(label).isNull().cast("bigint")).alias("nn")
    )
    zero = scored.sparkSession.range(1).select(F.lit(ZERO).alias("cut"), *(F.lit(0).cast("bigint").alias(c) for c in ("n0", "n1", "nn")))
    rows = running_sums(counts.union(zero), "cut", ["n0", "n1"], BIN, ["n0", "n1", "nn"])
    total = F.col("n0_all") + F.col("n1_all") + F.col("nn_all")
    rows = rows.select("cut", "n0", "n1", F.col("n1_upto").alias("n1_le"), (F.col("n0_all") - F.col("n0_upto")).alias("n0_gt"), F.col("nn_all").alias("unknown"), total.alias("total"))
    wrong, of = F.col("n1_le") + F.col("n0_gt"), F.col("total")
    if unlabelled == "constant":
        wrong = wrong + F.col("unknown")
    if unlabelled == "labelled_only":
        of = F.col("total") - F.col("unknown")
    return rows.select("cut", "n0", "n1", "n1_le", "n0_gt", F.try_divide(wrong.cast("double"), of).alias("loss"))


def running_sums(df: DataFrame, order: str, columns: list[str], width: float, totals: list[str] | None = None) -> DataFrame:
    """df with c_upto for each column: sums over all rows with `order` up to the row's, in two levels; c_all for totals.

    Rows fall in bins of `width` values; bin totals are summed up in one small window and broadcast, and each bin has a
    window of its own. Nothing needs all rows in one task. The bins' number is the range of `order` over width: choose it.
    """
    totals = totals or []
    binned = df.withColumn("__bin", F.floor(F.col(order) / F.lit(width)).cast("bigint"))
    sums = binned.groupBy("__bin").agg(*(F.sum(c).alias(f"__{c}") for c in dict.fromkeys([*columns, *totals])))
    earlier, all_ = Window.orderBy("__bin").rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    before = sums.select("__bin", *(F.coalesce(F.sum(f"__{c}").over(earlier), F.lit(0)).alias(f"__{c}") for c in columns), *(F.sum(f"__{c}").over(all_).alias(f"{c}_all") for c in totals))
    inside = Window.partitionBy("__bin").orderBy(order).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    rows = binned.join(F.broadcast(before), "__bin")
    for c in columns:
        rows = rows.withColumn(f"{c}_upto", F.sum(c).over(inside) + F.col(f"__{c}"))
    return rows.drop("__bin", *(f"__{c}" for c in columns))


def empirical_cut(curve: DataFrame) -> DataFrame:
    """(s_hat, loss): the cut of least loss, the smallest of equals."""
    best = F.min(F.struct("loss", "cut"))
    return curve.agg(best.alias("b")).select(F.col("b.cut").alias("s_hat"), F.col("b.loss").alias("loss"))


def band(curve: DataFrame, t: int, n: int, delta: float, scale: float = 1.0, kind: str = "bernstein") -> DataFrame:
    """(lo, hi, s_hat, loss): the smallest and largest cut whose excess loss is within the slack of its distance in candidates."""
    best = empirical_cut(curve)
    ranked = running_sums(curve.select("cut", F.col("loss").alias("own"), F.lit(1).cast("bigint").alias("one")), "cut", ["one"], BIN).withColumnRenamed("one_upto", "place")
    rows = ranked.crossJoin(F.broadcast(best))
    at = rows.where("cut = s_hat").select(F.col("place").alias("home"))
    rows = rows.crossJoin(F.broadcast(at))
    b = beta(t + 1, n, delta, scale)
    bound = F.lit(b) if kind == "uniform" else F.lit(b * b / 2) + F.lit(b) * F.sqrt(F.abs(F.col("place") - F.col("home")) / F.lit(float(t)))
    good = rows.where(F.col("own") - F.col("loss") <= bound + CLOSE)
    return good.agg(F.min("cut").alias("lo"), F.max("cut").alias("hi"), F.first("s_hat").alias("s_hat"), F.first("loss").alias("loss"))


def true_cut(df: DataFrame, score: str = "score", eta: str = "eta", width: float = 1 / 4096) -> DataFrame:
    """(cut, risk) at the candidate 0 and each score, where eta is the probability of class 0; scores in bins of `width`."""
    counts = df.groupBy(F.col(score).alias("cut")).agg(F.sum(1 - F.col(eta)).alias("c1"), F.sum(eta).alias("c0"), F.count("*").alias("n"))
    rows = counts.union(df.sparkSession.range(1).selectExpr("cast(0 as double)", "0.0D", "0.0D", "0L"))
    rows = running_sums(rows, "cut", ["c1", "c0"], width, ["c0", "n"])
    return rows.select("cut", ((F.col("c1_upto") + F.col("c0_all") - F.col("c0_upto")) / F.col("n_all")).alias("risk"))


class Counts:
    """The same update on arrays: for a round whose scores fit in the driver as numbers, never text."""

    def __init__(self, unlabelled: str = "implied"):
        self.unlabelled, self.top = unlabelled, ZERO
        #: Distinct (margin, label) pairs, as 3 * margin + label + 1, and how often each was added.
        self.pairs, self.times = np.zeros(0, np.int64), np.zeros(0, np.int64)

    def add(self, margins: np.ndarray, labels: np.ndarray) -> None:
        """labels: 0, 1, or -1 for unknown."""
        pairs, times = np.unique(margins * 3 + labels + 1, return_counts=True)
        self.pairs, place = np.unique(np.concatenate([self.pairs, pairs]), return_inverse=True)
        self.times = np.bincount(place, np.concatenate([self.times, times]), len(self.pairs)).astype(np.int64)
        self.top = max(self.top, int(margins.max())) if len(margins) else self.top

    def update(self, t: int, n: int, delta: float, scale: float, kind: str = "bernstein") -> tuple[int, int, int, float]:
        """(lo, hi, s_hat, loss) over all that was added."""
        y = self.pairs % 3 - 1
        cuts, place = np.unique((self.pairs - y - 1) // 3, return_inverse=True)
        n0, n1, unknown = (np.bincount(place, self.times * (y == k), len(cuts)) for k in (0, 1, -1))
        cuts = np.concatenate([[ZERO], cuts])
        wrong = np.concatenate([[0], np.cumsum(n1)]) + n0.sum() - np.concatenate([[0], np.cumsum(n0)])
        total = self.times.sum()
        wrong = wrong + unknown.sum() * (self.unlabelled == "constant")
        loss = wrong / max(1, total - unknown.sum() if self.unlabelled == "labelled_only" else total)
        home = int(np.argmin(loss))
        b = beta(t + 1, n, delta, scale)
        distance = np.abs(np.arange(len(cuts)) - home)
        bound = b if kind == "uniform" else b * b / 2 + b * np.sqrt(distance / t)
        good = np.flatnonzero(loss - loss[home] <= bound + CLOSE)
        return int(cuts[good[0]]), int(cuts[good[-1]]), int(cuts[home]), float(loss[home])
