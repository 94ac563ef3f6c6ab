"""The corpus pipeline: five stages over `documents`, each on all that the one before it kept."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from distill_filter.llm.bpe import bpe_codec
from distill_filter.llm.decontaminate import without_contaminated
from distill_filter.llm.pii import redact
from distill_filter.llm.quality import keep_good
from distill_filter.llm.shared import materialise
from distill_filter.llm.simhash import drop_near_duplicates


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or lie far from their language's histograms go."""
    return keep_good(docs)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents whose SimHash fingerprints link, at 3 or fewer differing bits, the one with the smallest id stays."""
    return drop_near_duplicates(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, edited by a fifth of its words at most, go."""
    return without_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data is replaced by its kind; n_chars follows the text."""
    return redact(docs)


def bpe_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, and whether they decode to it."""
    coded = docs.select("doc_id", bpe_codec(public_tokenizers.path("byte_bpe_50k.json"), with_text=False)(F.col("text")).alias("c"))
    return coded.select("doc_id", (F.octet_length("c.ids") / 4).cast("long").alias("n_tokens"), "c.ids", F.sha2("c.ids", 256).alias("ids_sha256"), "c.decodes")


STAGES = [
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", simhash_near_dedup),
    ("benchmark_decontamination", benchmark_decontamination),
    ("pii", pii),
    ("bpe_encoding", bpe_encoding),
]

#: Fingerprints, edit distances and merges are not expressible in SQL; a test holds run() against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's result is written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
