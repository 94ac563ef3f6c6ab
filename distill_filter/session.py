"""A session with the settings that the engine's plans assume, for those who start their own."""

from __future__ import annotations

from pyspark.sql import SparkSession


def build_session(name: str = "distill_filter", master: str | None = None, shuffle_partitions: int | None = None) -> SparkSession:
    build = SparkSession.builder.appName(name)
    if master:
        build = build.master(master)
    build = build.config("spark.sql.adaptive.enabled", "true").config("spark.sql.session.timeZone", "UTC").config("spark.sql.execution.arrow.pyspark.enabled", "true")
    if shuffle_partitions:
        build = build.config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    return build.getOrCreate()
