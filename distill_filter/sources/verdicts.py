"""The verdict cache as a data source, a remote annotator in batches, and imported human labels."""

from __future__ import annotations

import random
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Protocol

import pandas as pd
import pyarrow as pa
import pyarrow.fs
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

CACHE = "spec string, teacher_id string, snippet_id string, call_no int, verdict int"


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _CacheReader(DataSourceReader):
    """One task for each file of a spec's folder; only that folder is listed."""

    def __init__(self, options: dict):
        self.root, self.spec = options["path"], options["spec"]

    def partitions(self) -> list[_File]:
        fs, base = pa.fs.FileSystem.from_uri(self.root)
        found = fs.get_file_info(pa.fs.FileSelector(f"{base}/spec={self.spec}", allow_not_found=True))
        return [_File(f.path) for f in found if f.path.endswith(".parquet")] or [_File("")]

    def read(self, partition: _File) -> Iterator[pa.RecordBatch]:
        names = ["spec", "teacher_id", "snippet_id", "call_no", "verdict"]
        if not partition.path:
            return
        fs, _ = pa.fs.FileSystem.from_uri(self.root)
        for b in pq.ParquetFile(fs.open_input_file(partition.path)).iter_batches(columns=names[1:]):
            columns = [pa.array([self.spec] * b.num_rows), b.column("teacher_id"), b.column("snippet_id"), b.column("call_no").cast(pa.int32()), b.column("verdict").cast(pa.int32())]
            yield pa.RecordBatch.from_arrays(columns, names=names)


class VerdictCache(DataSource):
    """spark.read.format("verdict_cache").option("spec", ..).load(path): the cached calls of one spec."""

    @classmethod
    def name(cls) -> str:
        return "verdict_cache"

    def schema(self) -> str:
        return CACHE

    def reader(self, schema) -> DataSourceReader:
        return _CacheReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VerdictCache)


def append(calls: DataFrame, path: str) -> None:
    """Add calls to the cache; a call written twice after a retry is dropped on read by `distinct_calls`."""
    calls.write.mode("append").partitionBy("spec").parquet(path)


def distinct_calls(cache: DataFrame) -> DataFrame:
    return cache.dropDuplicates(["spec", "teacher_id", "snippet_id", "call_no"])


class Teacher(Protocol):
    """What a remote annotator must offer: verdicts, 0 or 1, for a list of texts; it may raise."""

    def __call__(self, texts: list[str]) -> list[int]: ...


def annotate_remote(requests: DataFrame, call: Teacher, batch: int = 32, retries: int = 3, per_second: float | None = None, pause: Callable[[float], None] = time.sleep) -> DataFrame:
    """requests(snippet_id, text) to (snippet_id, verdict, tries): batched calls inside tasks, with waits that double
    after a failure and a rate for each task. What fails to the end has a null verdict and is counted, not dropped.
    Parallelism is the number of partitions: blocks of the loop are bought at once."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for at in range(0, len(frame), batch):
                some = frame.iloc[at : at + batch]
                verdicts, tries = [None] * len(some), 0
                for tries in range(1, retries + 2):
                    try:
                        verdicts = call(some.text.tolist())
                        break
                    except Exception:  # an annotator's failure of whatever kind is a null verdict in the end
                        pause(min(60.0, 0.05 * 2**tries) * (0.5 + random.random()))
                if per_second:
                    pause(len(some) / per_second)
                yield pd.DataFrame({"snippet_id": some.snippet_id, "verdict": pd.array(verdicts, dtype="Int32"), "tries": tries})

    return requests.select("snippet_id", "text").mapInPandas(run, "snippet_id string, verdict int, tries int")


@dataclass(frozen=True)
class CachedAnnotator:
    """A remote annotator for the loop whose calls are paid once: verdicts go to a cache below `path` as they come, and
    only what the cache lacks is asked for, also by a run that begins anew after a failure.

    A call that fails to the end stops the run with an error, after all that was answered is in the cache.
    """

    call: Teacher
    path: str
    spec: str
    teacher_id: str = "teacher"
    call_no: int = 0
    batch: int = 32
    retries: int = 3
    parallel: int = 8
    per_second: float | None = None
    pause: Callable[[float], None] = time.sleep

    def column(self, text: Column, snippet_id: Column) -> None:
        return None

    def known(self, spark: SparkSession) -> DataFrame:
        """(snippet_id, verdict) of the calls in the cache; its files are listed anew each time."""
        append(spark.createDataFrame([], CACHE), self.path)  # makes the folder where it is not there yet
        mine = (F.col("spec") == self.spec) & (F.col("teacher_id") == self.teacher_id) & (F.col("call_no") == self.call_no)
        return distinct_calls(spark.read.schema(CACHE).parquet(self.path).where(mine)).select("snippet_id", "verdict")

    def ask(self, requests: DataFrame) -> DataFrame:
        spark = requests.sparkSession
        missing = requests.dropDuplicates(["snippet_id"]).join(self.known(spark).select("snippet_id"), "snippet_id", "left_anti")
        said = annotate_remote(missing.repartition(self.parallel), self.call, self.batch, self.retries, self.per_second, self.pause).where("verdict is not null")
        append(said.select(F.lit(self.spec).alias("spec"), F.lit(self.teacher_id).alias("teacher_id"), "snippet_id", F.lit(self.call_no).alias("call_no"), "verdict"), self.path)
        out = requests.select("snippet_id", "stream_pos").join(self.known(spark), "snippet_id", "left")
        if failed := out.where("verdict is null").count():
            raise RuntimeError(f"{failed} calls got no answer; run again to ask for them")
        return out


def human_labels(spark: SparkSession, path: str) -> DataFrame:
    """Votes from a labelling tool's CSV export (snippet_id, annotator, vote): declared schema, bad rows kept apart as nulls."""
    rows = spark.read.schema("snippet_id string, annotator int, vote string").option("header", True).csv(path)
    return rows.withColumn("vote", F.expr("try_cast(vote AS int)")).withColumn("vote", F.when(F.col("vote").isin(0, 1), F.col("vote")))


def call_latency(trace: DataFrame, parallel: int, seconds_per_call: float) -> DataFrame:
    """trace(round, t, bought): a row for each block with the calls it made and the time they take side by side."""
    from pyspark.sql.window import Window

    earlier = F.coalesce(F.lag("bought").over(Window.partitionBy("round").orderBy("t")), F.lit(0))
    return trace.select("round", "t", (F.col("bought") - earlier).alias("calls")).withColumn("seconds", F.ceil(F.col("calls") / parallel) * seconds_per_call)
