"""Whole-corpus filtering with a distilled student: one scan, no exchange."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import students, threshold


def decision_cut(labelled: DataFrame, model: students.Student, cut: str | float = "half") -> int:
    """The margin above which a snippet passes: score one half, the empirical equal-odds cut, the cut of least balanced
    error, or the one that passes a share of labelled(text, verdict)."""
    if cut == "half":
        return 0
    scored = students.score(labelled.withColumnRenamed("verdict", "label"), model).select("margin_micro", "label")
    if isinstance(cut, float):
        return int(scored.agg(F.percentile_approx("margin_micro", 1 - cut, 10_000)).first()[0])
    curve = threshold.loss_curve(scored)
    if cut == "eot":
        return int(threshold.empirical_cut(curve).first().s_hat)
    totals = scored.agg(F.sum("label").alias("t1"), F.sum(1 - F.col("label")).alias("t0"))
    error = F.coalesce(F.try_divide(F.col("n1_le"), F.col("t1")), F.lit(0.0)) + F.coalesce(F.try_divide(F.col("n0_gt"), F.col("t0")), F.lit(0.0))
    return int(curve.crossJoin(F.broadcast(totals)).agg(F.min(F.struct(error.alias("e"), "cut")).alias("b")).first().b.cut)


def passes(margin: Column, cut: int = 0) -> Column:
    """A margin that equals the cut is class 0."""
    return (margin > cut).cast("int")


def filter_corpus(snippets: DataFrame, model: students.Student, cut: int = 0) -> DataFrame:
    """The snippets that pass, with their margins and scores."""
    return students.score(snippets, model).where(F.col("margin_micro") > cut)


def filter_many(snippets: DataFrame, models: dict[str, tuple[students.Student, int]]) -> DataFrame:
    """snippets with a pass_<name> column for each filter: one scan and one hand-over of the text for all of them."""
    for name, (model, cut) in models.items():
        snippets = snippets.withColumn(f"pass_{name}", passes(model.margin(F.col("text")), cut))
    return snippets


def roll_up(verdicts: DataFrame, how: str = "share", min_share: float = 0.5, column: str = "verdict") -> DataFrame:
    """(doc_id, n_snippets, n_pass, doc_pass): a document passes if any, all, or a share of its snippets do."""
    rows = verdicts.groupBy("doc_id").agg(F.count("*").alias("n_snippets"), F.sum(column).cast("bigint").alias("n_pass"))
    ok = {"any": F.col("n_pass") > 0, "all": F.col("n_pass") == F.col("n_snippets"), "share": F.col("n_pass") >= min_share * F.col("n_snippets")}[how]
    return rows.withColumn("doc_pass", ok.cast("int"))
