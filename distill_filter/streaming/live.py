"""The engine on live arrivals, and stream forms of the monitors.

Live snippets arrive in micro-batches in stream order (stream_pos rises). The collector keeps what a round needs as
numbers: the band, the place in the round and counts by margin. A batch is cut where the band may change (after 2, 4,
8, ... snippets), so the labels bought do not hang on how arrivals fall into batches.
"""

from __future__ import annotations

import copy
import json
import pickle
import uuid
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import RunConfig, StudentConfig
from ..operators import students, threshold
from ..operators.teacher import verdict
from ..plans.active import LABELS, Annotator, Collector, asked, numbers
from ..sources.tables import remove, shared_dir


#: State that grows with the keys of a stream lies on the executors' disks, not in their heaps.
STATE_STORE = "spark.sql.streaming.stateStore.providerClass"
ON_DISK = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


#: Rows of a batch of which the driver takes (position, margin, label) at a time, about.
PIECE_ROWS = 1 << 20


def pieces(rows: DataFrame, size: int | None = None) -> list[tuple[int, int]]:
    """(first, last) stream_pos of pieces of about `size` rows, in order, that hold all rows; positions may have gaps."""
    n, lo, hi = rows.agg(F.count("stream_pos"), F.min("stream_pos"), F.max("stream_pos")).first()
    if not n:
        return []
    parts = -(-n // (size or PIECE_ROWS))
    inner = rows.agg(F.percentile_approx("stream_pos", [k / parts for k in range(1, parts)], 10_000)).first()[0] if parts > 1 else []
    edges = sorted({lo - 1, *inner, hi})
    return [(a + 1, b) for a, b in zip(edges, edges[1:])]


def collect_live(arrivals: DataFrame, model: students.Student, spec: str, n: int, need: int, config: RunConfig, state_dir: str | None = None) -> DataFrame:
    """Run one round over a stream of (snippet_id, stream_pos, text) to its present end; returns the labels bought.

    Each batch's labels are appended under its batch_id and the collector's numbers are kept with them; a batch that is
    run again after a failure overwrites its own files, and the state it starts from is that of the batch before. A batch
    is scored once, into files; the driver gets numbers of a piece at a time, and ids of what is bought alone.
    """
    spark = arrivals.sparkSession
    base = state_dir or f"{shared_dir(spark)}/live-{uuid.uuid4().hex}"
    held: dict[int, Collector] = {}

    def state_of(batch_id: int) -> Collector:
        if batch_id < 0:
            return Collector(n, need, config, counts=threshold.Counts(config.unlabelled))
        if batch_id not in held:  # the driver was started anew
            held[batch_id] = pickle.loads(spark.read.parquet(f"{base}/state/batch={batch_id}").first().state)
        return held[batch_id]

    def take(batch: DataFrame, batch_id: int) -> None:
        now = copy.deepcopy(state_of(batch_id - 1))
        own, schema = f"{base}/scored/batch={batch_id}", "stream_pos bigint, snippet_id string, margin_micro bigint, label int"
        rows = students.score(batch, model).withColumn("label", verdict(spec, F.col("text"), F.col("snippet_id")))
        rows.select(*(c.split()[0] for c in schema.split(", "))).write.mode("overwrite").parquet(own)
        rows, at = spark.read.schema(schema).parquet(own), []
        for lo, hi in pieces(rows):
            if now.bought == now.need:
                break
            pos, margin, label = numbers(rows.where(F.col("stream_pos").between(lo, hi)), "label")
            at += pos[now.feed(margin, label)].tolist()
        places = spark.createDataFrame([(p,) for p in at], "stream_pos bigint")
        bought = rows.join(F.broadcast(places), "stream_pos").orderBy("stream_pos").collect() if at else []
        out = [(r.snippet_id, int(r.stream_pos), int(r.label), int(batch_id)) for r in bought]
        remove(spark, own)
        spark.createDataFrame(out, "snippet_id string, stream_pos bigint, verdict int, batch_id bigint").write.mode("overwrite").parquet(f"{base}/labels/batch={batch_id}")
        spark.createDataFrame([(bytearray(pickle.dumps(now)),)], "state binary").coalesce(1).write.mode("overwrite").parquet(f"{base}/state/batch={batch_id}")
        held[batch_id] = now
        held.pop(batch_id - 2, None)

    query = arrivals.writeStream.foreachBatch(take).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{base}/labels").select("snippet_id", "stream_pos", "verdict", "batch_id")


@dataclass
class LiveState:
    """What a live run carries from batch to batch: numbers alone. The student is fitted anew from its labels."""

    bought: int = 0
    head: int = -(1 << 62)
    fitted_on: int = 0
    collector: Collector | None = None

    def dump(self) -> str:
        c = self.collector
        held = None if c is None else {**{k: getattr(c, k) for k in ("n", "need", "seen", "lo", "hi", "bought", "round_no")}, "top": c.counts.top, "pairs": c.counts.pairs.tolist(), "times": c.counts.times.tolist()}
        return json.dumps({"bought": self.bought, "head": self.head, "fitted_on": self.fitted_on, "collector": held})

    @staticmethod
    def load(text: str, config: RunConfig) -> LiveState:
        found = json.loads(text)
        if held := found["collector"]:
            counts = threshold.Counts(config.unlabelled)
            counts.top, counts.pairs, counts.times = held.pop("top"), np.array(held.pop("pairs"), np.int64), np.array(held.pop("times"), np.int64)
            found["collector"] = Collector(config=config, counts=counts, **held)
        return LiveState(**found)


def run_live(arrivals: DataFrame, annotator: Annotator, n: int, config: RunConfig, student: StudentConfig = StudentConfig(), state_dir: str | None = None) -> DataFrame:
    """The whole loop over a stream of (snippet_id, stream_pos, text), stream_pos rising: seed, rounds, a refit after each
    `batch` labels, the next round from the row after. Returns the labels (ord, round, snippet_id, stream_pos, verdict).

    They are those of a batch run over the same rows, wherever batches are cut. Margins are computed in tasks; the driver
    gets positions and margins of a batch, and asks for what is bought alone. A batch's labels and the state after it are
    files of that batch: one that is run again after a failure replaces them, from the state of the batch before.
    """
    spark = arrivals.sparkSession
    base = state_dir or f"{shared_dir(spark)}/live-{uuid.uuid4().hex}"
    most = config.budget + config.batch * (config.budget_mode == "extra")
    models: dict[int, students.Student] = {}

    def labels(upto: int) -> DataFrame:
        return spark.read.schema(LABELS).parquet(f"{base}/labels/batch=*").where(F.col("ord") < upto)

    def model_of(fitted_on: int) -> students.Student:
        if fitted_on not in models:  # a new round, or the driver was started anew
            models.clear()
            models[fitted_on] = students.fit(labels(fitted_on).select("text", "verdict"), student)
        return models[fitted_on]

    def take(batch: DataFrame, batch_id: int) -> None:
        now = LiveState.load(spark.read.text(f"{base}/state/batch={batch_id - 1}", wholetext=True).first()[0], config) if batch_id else LiveState()
        own = f"{base}/labels/batch={batch_id}"
        remove(spark, own)
        spark.createDataFrame([], LABELS).write.parquet(own)
        rows = batch.select("snippet_id", "stream_pos", "text").persist()
        ends = [b for _, b in pieces(rows)]  # all of a batch is read, also where the budget is spent: state before it must be committed whole

        def buy(positions: list[int], round_no: int) -> None:
            order = spark.createDataFrame([(p, now.bought + i) for i, p in enumerate(positions)], "stream_pos bigint, ord bigint")
            mine = rows.join(F.broadcast(order), "stream_pos")
            said = annotator.ask(mine.select("snippet_id", "stream_pos", "text")).select("stream_pos", "verdict")
            mine.join(said, "stream_pos").select("ord", F.lit(round_no).alias("round"), "snippet_id", "stream_pos", "text", "verdict").coalesce(1).write.mode("append").parquet(own)
            now.bought += len(positions)

        def next_round() -> None:
            now.fitted_on, round_no = now.bought, 1 + (now.collector.round_no if now.collector else 0)
            now.collector = Collector(n, min(config.batch, most - now.bought), config, round_no=round_no)

        while now.bought < most and (now.collector is None or now.collector.round_no <= config.rounds):
            rest = rows.where(F.col("stream_pos") >= now.head)
            if now.collector is None:  # the seed
                got = [r.stream_pos for r in rest.select("stream_pos").orderBy("stream_pos").limit(config.batch - now.bought).collect()]
                if not got:
                    break
                buy(got, 0)
                now.head = got[-1] + 1
                if now.bought == config.batch:
                    next_round()
                continue
            end = next((b for b in ends if b >= now.head), None)
            if end is None:
                break
            pos, margin = numbers(students.score(rest.where(F.col("stream_pos") <= end), model_of(now.fitted_on)))
            if not len(pos):
                now.head = end + 1
                continue
            places = pos[now.collector.feed(margin, lambda at, pos=pos: asked(rows, annotator, pos[at]))].tolist()
            if places:
                buy(places, now.collector.round_no)
            done = now.collector.bought == now.collector.need
            now.head = (places[-1] if done else int(pos[-1])) + 1
            if done:
                next_round()
        rows.unpersist()
        spark.createDataFrame([(now.dump(),)], "state string").coalesce(1).write.mode("overwrite").text(f"{base}/state/batch={batch_id}")

    arrivals.writeStream.foreachBatch(take).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(LABELS).parquet(f"{base}/labels/batch=*").drop("text")


def score_live(arrivals: DataFrame, weights: DataFrame) -> DataFrame:
    """A stream joined with a static table of weights: the margin of each arrival's tokens, exploded and summed by a batch twin elsewhere."""
    from ..functions.text import features

    return arrivals.select("snippet_id", F.explode(features(F.col("text"))).alias("token")).join(F.broadcast(weights), "token").select("snippet_id", "token", "w_micro")


#: Bytes of files that a batch takes where their number does not matter: a file at least, and many where they are small.
BATCH_BYTES = 128 << 20


def file_stream(spark: SparkSession, path: str, schema, files_per_batch: int | None = 1) -> DataFrame:
    """Files as a stream, so many to a batch; None: as many as BATCH_BYTES hold, so that batches go by size, however it is cut."""
    size = ("maxFilesPerTrigger", files_per_batch) if files_per_batch else ("maxBytesPerTrigger", BATCH_BYTES)
    return spark.readStream.schema(schema).option(*size).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream to its present end into files, a folder for each batch, and give the rows: the driver gets none.

    A batch that is run again replaces its own folder. With mode "complete" each batch has all rows, so the last one stays.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/live-{uuid.uuid4().hex}"
    spark.createDataFrame([], stream.schema).write.parquet(f"{base}/rows/batch=none")

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/batch={batch_id}")
        if mode == "complete":
            remove(spark, f"{base}/rows/batch={batch_id - 1}")

    was = spark.conf.get(STATE_STORE)
    spark.conf.set(STATE_STORE, ON_DISK)  # a query has the settings of its start
    try:
        query = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    finally:
        spark.conf.set(STATE_STORE, was)
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows/batch=*")


def hourly(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


def sliding(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))


def on_time(arrivals: DataFrame, time: str, delay: str, key: str) -> DataFrame:
    """Arrivals, each once, without those that come later than the watermark allows."""
    return arrivals.withWatermark(time, delay).dropDuplicatesWithinWatermark([key])


def sessions(events: DataFrame) -> DataFrame:
    return events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))


def keyed_counts(events: DataFrame) -> DataFrame:
    """A count and a largest value for each user, kept as arbitrary state; late in the stream it equals the batch result."""

    def step(key, frames, state):
        n, top = state.get if state.exists else (0, float("-inf"))
        for f in frames:
            n, top = n + len(f), max(top, float(f["value"].max()))
        state.update((n, top))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "top": [top]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, n bigint, top double", "n bigint, top double", "update", "NoTimeout")


def save_model(model: students.LogOdds, path: str, spark: SparkSession) -> None:
    spark.createDataFrame([(json.dumps({"prior": model.prior, "weights": model.weights}),)], "model string").coalesce(1).write.mode("overwrite").text(path)


def load_model(path: str, spark: SparkSession) -> students.LogOdds:
    found = json.loads(spark.read.text(path, wholetext=True).first()[0])
    return students.LogOdds(found["weights"], found["prior"])
