"""Lightweight students. Each fit starts from the base state and depends on the labels alone."""

from __future__ import annotations

import zlib
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import StudentConfig
from ..functions.losses import balanced_weights, focal_gradient
from ..functions.text import feature_line, features

MICRO = 1_000_000
#: Margins are clipped here, in micro-units, so that scores stay inside (0, 1).
CLIP = 30 * MICRO
#: Labelled rows that a driver-side fit takes: budgets are some 10^5 calls whatever the corpus holds.
MOST_LABELS = 200_000


class Student(Protocol):
    """What a policy needs of a student: a margin column, exact and ordered, in micro-units."""

    def margin(self, text: Column) -> Column: ...


def score_of(margin_micro: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-(margin_micro / MICRO)))


def score(df: DataFrame, model: Student, text_col: str = "text") -> DataFrame:
    """df with margin_micro bigint and score double; narrow, one Arrow pass over the text."""
    out = df.withColumn("margin_micro", model.margin(F.col(text_col)))
    return out.withColumn("score", score_of(F.col("margin_micro")))


@dataclass(frozen=True)
class LogOdds:
    """Integer weights of words and shapes; the margin is their exact sum over the set a snippet holds."""

    weights: dict[str, int]
    prior: int = 0
    clip: int = CLIP

    def margin(self, text: Column) -> Column:
        weights, prior, clip = self.weights, self.prior, self.clip

        def run(lines: pa.Array) -> pa.Array:
            get = weights.get
            sums = [prior + sum(get(t, 0) for t in set((x or "").split(" "))) for x in lines.to_pylist()]
            return pa.array(np.clip(sums, -clip, clip) if sums else [], pa.int64())

        run.__annotations__ = {"lines": pa.Array, "return": pa.Array}
        return F.arrow_udf(run, "bigint")(feature_line(text))


def logodds_weights(labels: DataFrame, config: StudentConfig = StudentConfig()) -> DataFrame:
    """(token, df1, df0, w_micro) of labels(text, verdict): kept where frequent and significant enough.

    Counts shuffle by token over the labelled rows only; the prior row has the token ''.
    """
    a = F.lit(config.smoothing)
    n = labels.agg(F.sum("verdict").cast("bigint").alias("n1"), F.sum(1 - F.col("verdict")).cast("bigint").alias("n0"))
    seen = labels.select("verdict", F.explode(features(F.col("text"))).alias("token"))
    counts = seen.groupBy("token").agg(F.sum("verdict").cast("bigint").alias("df1"), F.sum(1 - F.col("verdict")).cast("bigint").alias("df0"))
    odds = F.ln((F.col("df1") + a) / (F.col("n1") + 2 * a)) - F.ln((F.col("df0") + a) / (F.col("n0") + 2 * a))
    error = F.sqrt(1.0 / (F.col("df1") + a) + 1.0 / (F.col("df0") + a))
    rows = counts.crossJoin(F.broadcast(n)).where(F.col("df1") + F.col("df0") >= config.min_df).select("token", "df1", "df0", odds.alias("odds"), error.alias("error"))
    rows = rows.where(F.abs("odds") >= config.z_min * F.col("error")).select("token", "df1", "df0", F.round(F.col("odds") * MICRO).cast("bigint").alias("w_micro"))
    prior = F.round(F.ln((F.col("n1") + a) / (F.col("n0") + a)) * MICRO * float(config.prior)).cast("bigint")
    return rows.union(n.select(F.lit("").alias("token"), F.col("n1").alias("df1"), F.col("n0").alias("df0"), prior.alias("w_micro")))


def score_by_join(df: DataFrame, weights: DataFrame) -> DataFrame:
    """The same margins by a broadcast join and a sum: for weights that live in a table. Rows without any known token keep the prior."""
    prior = weights.where("token = ''").agg(F.coalesce(F.max("w_micro"), F.lit(0)).alias("prior"))
    known = df.select("snippet_id", F.explode(features(F.col("text"))).alias("token")).join(F.broadcast(weights.where("token <> ''").select("token", "w_micro")), "token")
    sums = known.groupBy("snippet_id").agg(F.sum("w_micro").alias("w"))
    out = df.join(sums, "snippet_id", "left").crossJoin(F.broadcast(prior))
    margin = F.greatest(F.lit(-CLIP), F.least(F.lit(CLIP), F.coalesce("w", F.lit(0)) + F.col("prior"))).cast("bigint")
    return out.withColumn("margin_micro", margin).withColumn("score", score_of(F.col("margin_micro"))).drop("w", "prior")


@dataclass(frozen=True)
class Hashed:
    """A linear head over hashed words and word pairs."""

    weights: np.ndarray
    bias: float

    def margin(self, text: Column) -> Column:
        model = self

        def run(texts: pa.Array) -> pa.Array:
            found = [model.value(t) for t in texts.to_pylist()]
            return pa.array(np.clip(np.round(np.array(found) * MICRO), -CLIP, CLIP).astype(np.int64) if found else [], pa.int64())

        run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
        return F.arrow_udf(run, "bigint")(text)

    def value(self, text: str | None) -> float:
        places = hashed_features(text, len(self.weights))
        return float(self.weights[places].sum() / max(1.0, np.sqrt(len(places))) + self.bias)


def hashed_features(text: str | None, size: int) -> np.ndarray:
    words = (text or "").lower().split()
    forms = ["#" + "".join("9" if c.isdigit() else c for c in w if not c.isalpha()) for w in words]
    return np.unique([zlib.crc32(x.encode()) % size for x in [*words, *forms, *map("_".join, zip(words, words[1:]))]]).astype(np.int64)


def fit_focal(labels: DataFrame, config: StudentConfig = StudentConfig(), start: Hashed | None = None) -> Hashed:
    """From zero, or from `start`: a linear head by full-batch gradient descent with focal loss. Labels come to the driver: MOST_LABELS at most, or it raises."""
    rows = labels.select("text", "verdict").limit(MOST_LABELS + 1).collect()
    if len(rows) > MOST_LABELS:
        raise ValueError(f"more than {MOST_LABELS} labels; fit on fewer")
    rows.sort(key=lambda r: r.text or "")
    size = 1 << config.bits
    places = [hashed_features(r.text, size) for r in rows]
    y = np.array([r.verdict for r in rows])
    lengths = np.array([len(p) for p in places])
    flat, owner = (np.concatenate(places) if places else np.zeros(0, np.int64)), np.repeat(np.arange(len(rows)), lengths)
    scale = 1 / np.maximum(1.0, np.sqrt(lengths))
    weight = balanced_weights(y) if config.class_weight else np.ones(len(y))
    w, bias = (start.weights.copy(), start.bias) if start else (np.zeros(size), 0.0)
    for _ in range(config.epochs):
        margin = np.bincount(owner, w[flat], len(rows)) * scale + bias
        g = focal_gradient(margin, y, config.focal_gamma, weight) / max(1, len(rows))
        w -= config.rate * 100 * np.bincount(flat, (g * scale)[owner], size)
        bias -= config.rate * g.sum()
    return Hashed(w, bias)


@dataclass(frozen=True)
class Pipeline:
    """The alternative student: a library pipeline of hashed term counts and logistic regression."""

    model: object

    def apply(self, df: DataFrame) -> DataFrame:
        from pyspark.ml.functions import vector_to_array

        keep = df.columns
        out = self.model.transform(df)
        margin = F.round(F.greatest(F.lit(-30.0), F.least(F.lit(30.0), vector_to_array("rawPrediction")[1])) * MICRO).cast("bigint")
        return out.select(*keep, margin.alias("margin_micro")).withColumn("score", score_of(F.col("margin_micro")))


def fit_library(labels: DataFrame, config: StudentConfig = StudentConfig()) -> Pipeline:
    from pyspark.ml import Pipeline as Stages
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import IDF, HashingTF, Tokenizer

    rows = labels.select("text", F.col("verdict").cast("double").alias("label"))
    share = rows.agg(F.avg("label")).first()[0] or 0.5
    rows = rows.withColumn("weight", F.when(F.col("label") == 1, 0.5 / max(share, 1e-6)).otherwise(0.5 / max(1 - share, 1e-6)) if config.class_weight else F.lit(1.0))
    stages = [Tokenizer(inputCol="text", outputCol="__words"), HashingTF(inputCol="__words", outputCol="__tf", numFeatures=1 << 14), IDF(inputCol="__tf", outputCol="__x")]
    return Pipeline(Stages(stages=[*stages, LogisticRegression(featuresCol="__x", weightCol="weight", regParam=0.01, maxIter=30)]).fit(rows))


@dataclass(frozen=True)
class VectorHead:
    """A linear head over frozen vectors; the dot product runs in the JVM."""

    weights: tuple[float, ...]
    bias: float

    def margin(self, vector: Column) -> Column:
        products = F.zip_with(vector, F.array(*(F.lit(float(w)) for w in self.weights)), lambda x, w: x.cast("double") * w)
        value = F.aggregate(products, F.lit(0.0), lambda a, b: a + b) + F.lit(self.bias)
        return F.round(F.greatest(F.lit(-30.0), F.least(F.lit(30.0), value)) * MICRO).cast("bigint")


def fit_vectors(labels: DataFrame, config: StudentConfig = StudentConfig(class_weight=True)) -> VectorHead:
    """labels(embedding, verdict) to a head by focal gradient descent on the driver, MOST_LABELS rows at most."""
    rows = labels.select("embedding", "verdict").limit(MOST_LABELS + 1).collect()
    if len(rows) > MOST_LABELS:
        raise ValueError(f"more than {MOST_LABELS} labels; fit on fewer")
    rows.sort(key=lambda r: list(r.embedding))
    x, y = np.array([r.embedding for r in rows], float), np.array([r.verdict for r in rows])
    weight = balanced_weights(y) if config.class_weight else np.ones(len(y))
    w, bias = np.zeros(x.shape[1]), 0.0
    for _ in range(config.epochs * 5):
        g = focal_gradient(x @ w + bias, y, config.focal_gamma, weight) / len(y)
        w, bias = w - config.rate * 5 * (x.T @ g), bias - config.rate * 5 * g.sum()
    return VectorHead(tuple(w), float(bias))


def fit(labels: DataFrame, config: StudentConfig = StudentConfig(), start: Student | None = None) -> Student:
    """labels(text, verdict) to a student of config.kind. The weights table is bounded by the labels' tokens."""
    if config.kind == "focal":
        return fit_focal(labels, config, start)
    if config.kind != "logodds":
        raise ValueError(f"{config.kind}: use fit_library or fit_vectors")
    found = {r.token: r.w_micro for r in logodds_weights(labels, config).select("token", "w_micro").collect()}
    return LogOdds({t: w for t, w in found.items() if t}, found.get("") or 0)
