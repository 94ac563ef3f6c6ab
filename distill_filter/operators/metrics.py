"""Accuracy and balance measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import hash_int
from .threshold import running_sums


def confusion(df: DataFrame, truth: str, pred: str, by: list[str] | None = None) -> DataFrame:
    """tp, fp, tn, fn, accuracy, precision, recall, f1 and balanced accuracy, by group; ratios of nothing are null."""
    t, p = F.col(truth) == 1, F.col(pred) == 1
    out = df.groupBy(*(by or [])).agg(*(F.count_if(c).alias(n) for n, c in (("tp", t & p), ("fp", ~t & p), ("tn", ~t & ~p), ("fn", t & ~p))))
    ratio = lambda a, b: F.try_divide(a.cast("double"), b)
    tp, fp, tn, fn = (F.col(c) for c in ("tp", "fp", "tn", "fn"))
    out = out.withColumn("accuracy", ratio(tp + tn, tp + fp + tn + fn)).withColumn("precision", ratio(tp, tp + fp)).withColumn("recall", ratio(tp, tp + fn))
    out = out.withColumn("f1", ratio(2 * tp, 2 * tp + fp + fn))
    return out.withColumn("balanced_accuracy", (ratio(tp, tp + fn) + ratio(tn, tn + fp)) / 2)


def balanced_accuracy(df: DataFrame, truth: str, pred: str, by: list[str] | None = None) -> DataFrame:
    return confusion(df, truth, pred, by).select(*(by or []), "balanced_accuracy")


def auc(df: DataFrame, score: str, truth: str, width: float = 1 / 4096) -> DataFrame:
    """(auc): the share of pass-fail pairs in right order, ties one half; from counts by distinct score, in bins of `width`, no pairs."""
    counts = df.groupBy(score).agg(F.sum(F.col(truth)).alias("n1"), F.sum(1 - F.col(truth)).alias("n0"))
    rows = running_sums(counts, score, ["n0"], width)
    rows = rows.select("n1", "n0", (F.col("n1") * (F.col("n0_upto") - F.col("n0") / 2)).alias("u"))
    return rows.agg(F.try_divide(F.sum("u"), (F.sum("n1") * F.sum("n0")).cast("double")).alias("auc"))


def imbalance(labels: DataFrame, by: list[str], order: str = "ord") -> DataFrame:
    """labels with running counts of both classes and minority / majority by number of calls."""
    upto = Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ones, n = F.sum("verdict").over(upto), F.count("*").over(upto)
    out = labels.withColumn("n_pass", ones.cast("bigint")).withColumn("n_fail", (n - ones).cast("bigint"))
    return out.withColumn("imbalance", F.try_divide(F.least("n_pass", "n_fail").cast("double"), F.greatest("n_pass", "n_fail")))


def panel_votes(rows: DataFrame, truth: str, spec: str, annotators: int = 13, groups: int = 2, error: float = 0.1) -> DataFrame:
    """(.., group_no, annotator, vote): simulated people who err with a fixed probability, each repeatably."""
    out = rows.withColumn("group_no", F.explode(F.sequence(F.lit(1), F.lit(groups)))).withColumn("annotator", F.explode(F.sequence(F.lit(1), F.lit(annotators))))
    wrong = hash_int("vote", spec, F.col("group_no"), F.col("annotator"), F.col("snippet_id")) < int(error * (1 << 32))
    return out.withColumn("vote", F.when(wrong, 1 - F.col(truth)).otherwise(F.col(truth)).cast("int"))


def human_preference(rows: DataFrame, teacher: str, student: str, truth: str, spec: str, n: int = 100, annotators: int = 13, groups: int = 2, error: float = 0.1) -> DataFrame:
    """(group_no, n_snippets, student_wins, preference): of up to n disagreements, how often a panel's majority sides with the student."""
    apart = rows.where(F.col(teacher) != F.col(student)).withColumn("__h", hash_int("panel", spec, F.col("snippet_id"))).orderBy("__h", "snippet_id").limit(n)
    votes = panel_votes(apart.drop("__h"), truth, spec, annotators, groups, error)
    majority = votes.groupBy("group_no", "snippet_id").agg((2 * F.sum("vote") > F.count("*")).cast("int").alias("said"), F.first(student).alias("s"))
    out = majority.groupBy("group_no").agg(F.count("*").alias("n_snippets"), F.count_if(F.col("said") == F.col("s")).alias("student_wins"))
    return out.withColumn("preference", F.col("student_wins") / F.col("n_snippets"))


def savings(curve: DataFrame, target: Column | float, against: str = "random", mine: str = "band") -> DataFrame:
    """(target, calls_<mine>, calls_<against>, factor): the fewest calls at which each policy reaches the target accuracy."""
    goal = F.lit(target) if isinstance(target, float) else target
    reach = curve.where(F.col("balanced_accuracy") >= goal)
    out = reach.agg(F.min(F.when(F.col("policy") == mine, F.col("calls"))).alias(f"calls_{mine}"), F.min(F.when(F.col("policy") == against, F.col("calls"))).alias(f"calls_{against}"))
    return out.select(goal.alias("target"), "*", F.try_divide(F.col(f"calls_{against}").cast("double"), F.col(f"calls_{mine}")).alias("factor"))
