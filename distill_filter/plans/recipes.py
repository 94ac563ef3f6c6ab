"""Selection recipes to compare with, and proxies for the quality of a selection."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..config import StudentConfig
from ..functions.hashing import hash_int
from ..functions.text import tokens
from ..operators import students
from ..operators.teacher import HOSTILE, evidence


def trusted_sources(docs: DataFrame, allow: list[str]) -> DataFrame:
    """Documents of trusted sources; the list is short and goes into the scan's filter."""
    return docs.where(F.col("source").isin(*allow))


def preset_detectors(text: Column) -> Column:
    """1 where preset rules find nothing wrong: length, symbol share, repetition, hostile words."""
    toks = tokens(text)
    symbols = F.length(F.regexp_replace(text, "[^#*$%&|<>]", ""))
    varied = F.size(F.array_distinct(F.transform(toks, F.lower))) >= 0.3 * F.size(toks)
    fine = (F.size(toks) >= 20) & (symbols <= 0.02 * F.length(text)) & varied & (evidence("topic_hostile", text) == 0)
    return fine.cast("int")


def ngram_classifier(docs: DataFrame, positives: DataFrame, negatives: DataFrame, keep_share: float, config: StudentConfig = StudentConfig(prior=False)) -> DataFrame:
    """docs(doc_id, text) with margin_micro and kept: a linear classifier of reference texts against random ones, whose
    highest share is kept. The cut is an exact order statistic over scores, so ties at the cut are all kept; margins are
    not clipped, as over half of long texts could tie at the clip."""
    labels = positives.select("text", F.lit(1).alias("verdict")).union(negatives.select("text", F.lit(0).alias("verdict")))
    model = students.fit(labels, config)
    if isinstance(model, students.LogOdds):
        model = replace(model, clip=1 << 62)
    scored = students.score(docs, model)
    cut = scored.agg(F.percentile_approx("margin_micro", 1 - keep_share, 100_000).alias("cut"))
    return scored.crossJoin(F.broadcast(cut)).withColumn("kept", (F.col("margin_micro") >= F.col("cut")).cast("int")).drop("cut")


def grade(text: Column) -> Column:
    """A teacher's quality grade from 0 to 5: five, less one for each sign of junk and for hostility."""
    return F.greatest(F.lit(0), F.lit(5) - evidence("quality", text) * 2 - F.least(evidence("topic_hostile", text), F.lit(2))).cast("int")


def annotated_score(docs: DataFrame, graded: DataFrame, threshold: float = 3.0) -> DataFrame:
    """docs with a predicted grade and kept: a linear fit of graded(text, grade) on a student's margin, cut at threshold."""
    model = students.fit(graded.select("text", (F.col("grade") >= threshold).cast("int").alias("verdict")))
    line = students.score(graded, model).agg(F.regr_slope("grade", F.col("margin_micro").cast("double")).alias("b"), F.regr_intercept("grade", F.col("margin_micro").cast("double")).alias("a"))
    scored = students.score(docs, model).crossJoin(F.broadcast(line))
    predicted = F.coalesce(F.col("a"), F.lit(0.0)) + F.coalesce(F.col("b"), F.lit(0.0)) * F.col("margin_micro")
    return scored.withColumn("grade", predicted).withColumn("kept", (F.col("grade") >= threshold).cast("int")).drop("a", "b")


def take_tokens(docs: DataFrame, budget: int, seed: int = 0, bins: int = 1024) -> DataFrame:
    """docs(doc_id, n_tokens) in the order of a hash, as long as their running sum stays within budget.

    The running sum goes in two levels: totals by hash bin, a window over those, and a window inside each bin.
    """
    rows = docs.withColumn("__h", hash_int(f"take{seed}", F.col("doc_id"))).withColumn("__bin", F.floor(F.col("__h") / ((1 << 32) // bins)))
    sums = rows.groupBy("__bin").agg(F.sum("n_tokens").alias("s"))
    before = sums.select("__bin", F.coalesce(F.sum("s").over(Window.orderBy("__bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.sum("n_tokens").over(Window.partitionBy("__bin").orderBy("__h", "doc_id").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    out = rows.withColumn("upto", inside).join(F.broadcast(before), "__bin")
    return out.where(F.col("upto") + F.col("before") <= budget).drop("__h", "__bin", "upto", "before")


def unigram_cross_entropy(selected: DataFrame, texts: DataFrame) -> DataFrame:
    """(nats): mean negative log-probability of the texts' tokens under add-one unigram counts of a selection."""
    counts = selected.select(F.explode(tokens(F.lower("text"))).alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    size = counts.agg(F.sum("n").alias("total"), F.count("*").alias("kinds"))
    asked = texts.select(F.explode(tokens(F.lower("text"))).alias("token")).groupBy("token").agg(F.count("*").alias("m"))
    rows = asked.join(counts, "token", "left").crossJoin(F.broadcast(size))
    nats = -F.ln((F.coalesce("n", F.lit(0)) + 1.0) / (F.coalesce("total", F.lit(0)) + F.col("kinds") + 1.0))
    return rows.agg((F.sum(F.col("m") * nats) / F.sum("m")).alias("nats"))


def pairs(texts: DataFrame, *names: str) -> DataFrame:
    """A row (names, a, b) for each two neighbouring tokens of a text, in lower case."""
    rows = texts.select(*names, tokens(F.lower("text")).alias("__w"))
    inner = F.transform(F.slice("__w", 1, F.greatest(F.size("__w") - 1, F.lit(0))), lambda t, i: F.struct(t.alias("a"), F.get("__w", i + 1).alias("b")))
    return rows.select(*names, F.explode(inner).alias("__p")).select(*names, "__p.a", "__p.b")


def bigram_cross_entropy(selected: DataFrame, texts: DataFrame) -> DataFrame:
    """(nats): mean negative log-probability of a token of the texts after the one before it, under add-one counts of a
    selection's pairs. Texts of under two tokens have none; no pairs asked: null."""
    seen = pairs(selected).groupBy("a", "b").agg(F.count("*").alias("n"))
    heads = seen.groupBy("a").agg(F.sum("n").alias("total"))
    kinds = seen.select(F.col("b").alias("t")).distinct().agg(F.count("*").alias("kinds"))
    asked = pairs(texts).groupBy("a", "b").agg(F.count("*").alias("m"))
    rows = asked.join(seen, ["a", "b"], "left").join(heads, "a", "left").crossJoin(F.broadcast(kinds))
    nats = -F.ln((F.coalesce("n", F.lit(0)) + 1.0) / (F.coalesce("total", F.lit(0)) + F.col("kinds") + 1.0))
    return rows.agg((F.sum(F.col("m") * nats) / F.sum("m")).alias("nats"))


def runs(texts: DataFrame, width: int, *names: str) -> DataFrame:
    """A row (names, run) for each run of `width` tokens of a text, in lower case; shorter texts have none."""
    rows = texts.select(*names, tokens(F.lower("text")).alias("__w"))
    starts = F.when(F.size("__w") >= width, F.sequence(F.lit(1), F.size("__w") - width + 1))
    return rows.select(*names, F.explode(starts).alias("__i"), "__w").select(*names, F.array_join(F.slice("__w", F.col("__i"), width), " ").alias("run"))


def contaminated(docs: DataFrame, items: DataFrame, width: int = 8) -> DataFrame:
    """(doc_id) of docs that hold a run of `width` tokens of an item. The items' side goes to all tasks where Catalyst
    finds it small enough, and is joined by a shuffle of runs beyond that."""
    known = runs(items, width).distinct()
    return runs(docs, width, "doc_id").join(known, "run", "left_semi").select("doc_id").distinct()
