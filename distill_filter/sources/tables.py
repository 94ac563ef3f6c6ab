"""Reading the given tables, and a shared place for derived ones."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One of the given Parquet tables; columns prune the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which driver and executors share. Where it is unset, a folder of this machine if all runs on it; else an error."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="distill-work-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def materialise(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write df as Parquet in the shared place and read it again: lineage ends here, whatever executor is lost."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    write = df.write.partitionBy(*partition_by) if partition_by else df.write
    write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared place, if it is there, through Spark's own file system layer."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


_KEPT: dict[tuple, DataFrame] = {}


def kept(spark: SparkSession, sf_dir: str, name: str, build) -> DataFrame:
    """A derived table that several queries of one session share, written once for each state of the input folder's files."""
    key = (spark.sparkContext.applicationId, sf_dir, name, folder_state(spark, sf_dir))
    if key not in _KEPT:
        _KEPT[key] = materialise(build(), name)
    return _KEPT[key]


def folder_state(spark: SparkSession, path: str) -> int:
    """A hash of the names, sizes and times of a folder's files: it changes when the data does."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = where.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(where)
    return hash(tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in files)))
