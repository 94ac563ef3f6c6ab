"""Stream-based distillation: buy labels inside a band of scores, refit, go on at the stream's head.

Within a round the student is fixed and the band changes only after 2, 4, 8, ... snippets. So a round is a sequence of
blocks of the stream in which the band is constant, and the only thing that hangs on order inside a block is where the
cap falls: the first rows in the band, by position. The stream is read from its head in pieces, each as long as what is
still to be bought or as all that the round has read so far, whichever is more: the rows scored are at most twice the
rows read. Of a piece the driver gets positions and margins, PIECE_ROWS at most, never text; of a round it keeps counts
by distinct margin, which the student's clip bounds. The same steps run at every size, in batches and on live arrivals.
"""

from __future__ import annotations

import bisect
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import RunConfig, StudentConfig, TeacherConfig
from ..operators import students, threshold
from ..operators.teacher import verdict
from ..sources.tables import shared_dir

#: Rows of which the driver takes (position, margin) at a time: 16 bytes each.
PIECE_ROWS = 1 << 22
OPEN_LO, OPEN_HI = -(1 << 61), 1 << 61
LABELS = "ord bigint, round int, snippet_id string, stream_pos bigint, text string, verdict int"


class Annotator(Protocol):
    """What the loop asks: requests(snippet_id, stream_pos, text) to (snippet_id, stream_pos, verdict), a row for each.

    `column` may give the verdict as an expression where it costs nothing to compute it before it is known what is
    bought; else None, and only what is bought is asked for.
    """

    def column(self, text: Column, snippet_id: Column) -> Column | None: ...

    def ask(self, requests: DataFrame) -> DataFrame: ...


@dataclass(frozen=True)
class RuleAnnotator:
    """A simulated teacher: its verdict is an expression over the text."""

    spec: str
    teacher: TeacherConfig = TeacherConfig()
    common: tuple[str, ...] | None = None

    def column(self, text: Column, snippet_id: Column) -> Column:
        return verdict(self.spec, text, snippet_id, self.teacher, 0, list(self.common) if self.common else None)

    def ask(self, requests: DataFrame) -> DataFrame:
        return requests.select("snippet_id", "stream_pos", self.column(F.col("text"), F.col("snippet_id")).alias("verdict"))


def blocks(cap: int) -> Iterator[tuple[int, int]]:
    """(first, last) places of each block, counted from the head: 0-2, 3-4, 5-8, ... up to cap."""
    first, last = 0, 2
    while first < cap:
        yield first, last
        first, last = last + 1, last * 2


@dataclass
class Run:
    """What a run leaves: labels bought in order, a trace row for each band update, a student for each round, counters.

    seen: the stream's rows up to the last one read; scored: rows that a student scored on the way; passes: those of
    whole-pool scans; calls: verdicts asked for. The labels' texts lie in tables below `paths`.
    """

    config: RunConfig
    labels: list[tuple[int, int, str, int, int]] = field(default_factory=list)
    trace: list[tuple] = field(default_factory=list)
    models: list[tuple[int, students.Student]] = field(default_factory=list)
    seen: int = 0
    exhausted: bool = False
    passes: int = 0
    scored: int = 0
    calls: int = 0
    paths: list[str] = field(default_factory=list)

    @property
    def model(self) -> students.Student:
        return self.models[-1][1]

    def labels_df(self, spark: SparkSession) -> DataFrame:
        rows = [(self.config.policy, r, i, s, p, v) for i, (r, _, s, p, v) in enumerate(self.labels)]
        return spark.createDataFrame(rows, "policy string, round int, ord int, snippet_id string, stream_pos bigint, verdict int")

    def trace_df(self, spark: SparkSession) -> DataFrame:
        rows = [(self.config.policy, self.config.radius_scale, *t) for t in self.trace]
        return spark.createDataFrame(rows, "policy string, radius_scale double, round int, t bigint, lo bigint, hi bigint, s_hat bigint, loss double, beta double, bought int")

    def labelled(self, spark: SparkSession, upto: int | None = None) -> DataFrame:
        """(text, verdict) of the first `upto` labels, from the tables that were written as they were bought."""
        rows = spark.read.schema(LABELS).parquet(*self.paths)
        return (rows if upto is None else rows.where(F.col("ord") < upto)).select("text", "verdict")


@dataclass
class Band:
    lo: int = OPEN_LO
    hi: int = OPEN_HI


def narrowed(lo: int, hi: int, band: Band, top: int, nested: bool) -> Band:
    """The band after an update that found [lo, hi] among scores up to top: those two ends.

    Nested bands never widen, so an upper end at the highest score seen must not close the band to scores not seen yet:
    cuts from there on up say the same of what was seen, and the end stays where it was.
    """
    return Band(max(band.lo, lo), band.hi if hi == top else min(band.hi, hi)) if nested else Band(lo, hi)


@dataclass
class Collector:
    """One round, fed with margins in stream order, cut anywhere: labels are looked at only where bought."""

    n: int
    need: int
    config: RunConfig
    seen: int = 0
    lo: int = OPEN_LO
    hi: int = OPEN_HI
    bought: int = 0
    counts: threshold.Counts | None = None
    round_no: int = 1
    trace: list = field(default_factory=list)

    def __post_init__(self) -> None:
        self.counts = self.counts or threshold.Counts(self.config.unlabelled)

    def feed(self, margins: np.ndarray, labels: np.ndarray | Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
        """Places in this piece whose labels are bought; labels: one for each margin, or what says those of given places."""
        ask = labels if callable(labels) else lambda at: labels[at]
        out, at = [], 0
        while at < len(margins) and self.bought < self.need:
            update = 2 if self.seen <= 2 else 1 << (self.seen - 1).bit_length()
            end = min(len(margins), at + update - self.seen + 1)
            m = margins[at:end]
            inside = np.flatnonzero((m >= self.lo) & (m <= self.hi))[: self.need - self.bought]
            out += (at + inside).tolist()
            self.bought += len(inside)
            known = np.full(len(m), -1)
            if len(inside):
                known[inside] = ask(at + inside)
            if self.bought == self.need:
                self.seen += int(inside[-1]) + 1 if len(inside) else 0
                break
            if self.config.unlabelled == "implied":
                known = np.where(known >= 0, known, np.where(m < self.lo, 0, 1))
            self.counts.add(m, known)
            self.seen += len(m)
            if self.seen == update + 1:
                c = self.config
                lo, hi, s_hat, loss = self.counts.update(update, self.n, c.delta, c.radius_scale, c.radius)
                band = narrowed(lo, hi, Band(self.lo, self.hi), self.counts.top, c.nested)
                self.lo, self.hi = band.lo, band.hi
                self.trace.append((self.round_no, update, band.lo, band.hi, s_hat, loss, threshold.beta(update + 1, self.n, c.delta, c.radius_scale), self.bought))
            at = end
        return np.array(out, dtype=np.int64)


def local_round(pos: np.ndarray, margin: np.ndarray, label: np.ndarray, need: int, n: int, config: RunConfig, trace: list, round_no: int = 1) -> tuple[np.ndarray, int]:
    """(places bought, places read) of one round over arrays in stream order."""
    c = Collector(n, need, config, round_no=round_no, trace=trace)
    return c.feed(margin, label), c.seen if c.bought == need else len(pos)


def frame_round(scored: DataFrame, head: int, need: int, n: int, config: RunConfig, trace: list, round_no: int = 1, piece_rows: int = PIECE_ROWS) -> tuple[list, int]:
    """A round over a table scored(stream_pos, snippet_id, margin_micro, label). Returns the rows bought and the next head."""
    c, at, bought = Collector(n, need, config, round_no=round_no, trace=trace), head, {}
    while at < n and c.bought < need:
        size = min(piece_rows, max(need - c.bought, c.seen), n - at)
        pos, margin, label = numbers(scored.where(F.col("stream_pos").between(at, at + size - 1)), "label")
        bought |= {int(pos[i]): int(label[i]) for i in c.feed(margin, label)}
        at += size
    places = scored.sparkSession.createDataFrame([(p,) for p in bought], "stream_pos bigint")
    rows = scored.join(F.broadcast(places), "stream_pos").select("stream_pos", "snippet_id", "label").orderBy("stream_pos").collect()
    return rows, rows[-1].stream_pos + 1 if c.bought == need else n


def numbers(rows: DataFrame, *more: str) -> list[np.ndarray]:
    """stream_pos, margin_micro and other whole numbers of rows, in the order of stream_pos: a bounded piece."""
    table = rows.select(*(F.col(c).cast("bigint") for c in ("stream_pos", "margin_micro", *more))).toArrow().sort_by("stream_pos")
    return [table[c].to_numpy() for c in table.column_names]


class Places:
    """Ranks of rows that are not bought to positions in the stream, for a second way round it."""

    def __init__(self, bought: list[int], head: int):
        self.gaps, self.head = sorted(p for p in bought if p >= head), head

    def position(self, rank: int) -> int:
        """Where the row of this rank lies: the smallest p with rank rows before it that are not bought."""
        low, high = 0, len(self.gaps)
        while low < high:  # the number of gaps before it
            mid = (low + high) // 2
            low, high = (mid + 1, high) if self.gaps[mid] - self.head - mid <= rank else (low, mid)
        return self.head + rank + low

    def left(self, n: int) -> int:
        return max(0, n - self.head - bisect.bisect_left(self.gaps, n))


def _buy(stream: DataFrame, run: Run, annotator: Annotator, positions: list[int], verdicts: dict[int, int], round_no: int) -> int:
    """Write the rows at positions with their verdicts, asking for those that are not known yet; returns how many."""
    if not positions:
        return 0
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/labels-{uuid.uuid4().hex}"
    order = spark.createDataFrame([(p, len(run.labels) + i, verdicts.get(p)) for i, p in enumerate(positions)], "stream_pos bigint, ord bigint, known int")
    rows = stream.where(F.col("stream_pos").between(min(positions), max(positions))).join(F.broadcast(order), "stream_pos")
    rows = rows.select("ord", F.lit(round_no).alias("round"), "snippet_id", "stream_pos", "text", "known")
    if len(verdicts) < len(positions):
        said = annotator.ask(rows.select("snippet_id", "stream_pos", "text"))
        rows = rows.drop("known").join(said.select("stream_pos", "verdict"), "stream_pos")
    else:
        rows = rows.withColumnRenamed("known", "verdict")
    rows.select(*(c.split()[0] for c in LABELS.split(", "))).coalesce(1 + len(positions) // 50_000).write.parquet(path)
    run.paths.append(path)
    got = spark.read.schema(LABELS).parquet(path).select("ord", "snippet_id", "stream_pos", "verdict").orderBy("ord").collect()
    run.labels += [(round_no, int(g.ord), g.snippet_id, int(g.stream_pos), int(g.verdict)) for g in got]
    run.calls += len(got)
    return len(got)


def _band_round(stream: DataFrame, run: Run, model: students.Student, annotator: Annotator, places: Places, need: int, n: int, round_no: int) -> tuple[list[int], dict[int, int], int]:
    """(positions bought, their verdicts, next head) of one round of the band policy."""
    inline = annotator.column(F.col("text"), F.col("snippet_id"))
    c = Collector(n, need, run.config, round_no=round_no, trace=run.trace)
    rank, left, positions, verdicts = 0, places.left(n), [], {}
    taken = stream.sparkSession.createDataFrame([(p,) for p in places.gaps], "stream_pos bigint") if places.gaps else None
    while rank < left and c.bought < need:
        size = min(PIECE_ROWS, max(need - c.bought, c.seen), left - rank)
        piece = stream.where(F.col("stream_pos").between(places.position(rank), places.position(rank + size - 1)))
        if taken is not None:
            piece = piece.join(F.broadcast(taken), "stream_pos", "left_anti")
        if inline is not None:
            piece = piece.withColumn("label", inline)
        pos, margin, *label = numbers(students.score(piece, model), *(["label"] if inline is not None else []))
        run.scored += len(pos)

        def ask(at: np.ndarray) -> np.ndarray:
            """Blocks of a piece are asked one after the other, each at once: the next block's band hangs on the answers."""
            got = label[0][at] if label else asked(stream, annotator, pos[at])
            verdicts.update(zip(pos[at].tolist(), got.tolist(), strict=True))
            return got

        positions += pos[c.feed(margin, ask)].tolist()
        rank += size
    return positions, verdicts, positions[-1] + 1 if c.bought == need else n


def asked(stream: DataFrame, annotator: Annotator, positions: np.ndarray) -> np.ndarray:
    want = stream.sparkSession.createDataFrame([(int(p),) for p in positions], "stream_pos bigint")
    rows = stream.where(F.col("stream_pos").between(int(positions.min()), int(positions.max()))).join(F.broadcast(want), "stream_pos")
    got = {r.stream_pos: r.verdict for r in annotator.ask(rows.select("snippet_id", "stream_pos", "text")).select("stream_pos", "verdict").collect()}
    return np.array([got[int(p)] for p in positions], dtype=np.int64)


def _scanned(stream: DataFrame, run: Run, model: students.Student, need: int, n: int, head: int, wrapped: bool) -> tuple[list[int], int]:
    """(positions, next head) of one round of a policy other than the band. Verdicts are not looked at."""
    policy, mine = run.config.policy, stream.sparkSession.createDataFrame([(p,) for _, _, _, p, _ in run.labels], "stream_pos bigint")
    pool = policy.startswith("pool")
    rows = stream if pool else stream.where(F.col("stream_pos") >= head)
    if pool or wrapped:
        rows = rows.join(F.broadcast(mine), "stream_pos", "left_anti")
    if policy == "random":
        got = rows.select("stream_pos").orderBy("stream_pos").limit(need).collect()
        return [r.stream_pos for r in got], got[-1].stream_pos + 1 if len(got) == need else n
    scored, centre = students.score(rows, model).select("stream_pos", "snippet_id", "score"), F.lit(0.5)
    if policy == "pool_cut":
        curve = threshold.loss_curve(students.score(run.labelled(stream.sparkSession).withColumnRenamed("verdict", "label"), model))
        centre = students.score_of(F.greatest(F.lit(threshold.empirical_cut(curve).first().s_hat), F.lit(-students.CLIP)))
    apart = F.abs(F.col("score") - centre)
    if pool:
        run.passes += n
        run.scored += n - len(run.labels)
        return [r.stream_pos for r in scored.orderBy(apart, "snippet_id").limit(need).select("stream_pos").collect()], head
    positions, at = [], head
    while at < n and len(positions) < need:
        size = min(PIECE_ROWS, max(need - len(positions), at - head), n - at)
        near = scored.where(F.col("stream_pos").between(at, at + size - 1) & (apart <= run.config.uncertainty_width))
        positions += sorted(r.stream_pos for r in near.select("stream_pos").collect())
        run.scored += size
        at += size
    positions = positions[:need]
    return positions, positions[-1] + 1 if len(positions) == need else n


def distil(stream: DataFrame, spec: str, config: RunConfig = RunConfig(), student: StudentConfig = StudentConfig(), teacher: TeacherConfig = TeacherConfig(), common: list[str] | None = None, n: int | None = None, annotator: Annotator | None = None) -> Run:
    """Run a policy over stream(snippet_id, stream_pos, text) until the budget or the stream ends.

    Verdicts come from `annotator`, or from the simulated `teacher` of `spec`; a remote one is asked only for what is
    bought. The seed is the first `batch` snippets, bought whatever they are. Each round fits a student on all labels so
    far, from its base state (or the last round's, with warm_start), then buys `batch` more. A stream that ends stops
    the run, or with on_exhausted="wrap" goes round once more over what was not bought. If the seed holds one class only
    the student scores all alike and the band policies read on in order; on_single_class="grow_seed" buys more in order
    of the stream first, until both classes are there.
    """
    n = stream.count() if n is None else n
    run = Run(config)
    stream = stream.select("snippet_id", "stream_pos", "text")
    annotator = annotator or RuleAnnotator(spec, teacher, tuple(common) if common else None)
    most = config.budget + config.batch * (config.budget_mode == "extra")
    head = run.seen = min(config.batch, n)
    _buy(stream, run, annotator, list(range(head)), {}, 0)
    while config.on_single_class == "grow_seed" and len({v for *_, v in run.labels}) == 1 and head < min(n, most):
        upto = min(head + config.batch, n, most)
        _buy(stream, run, annotator, list(range(head, upto)), {}, 0)
        head = run.seen = upto
    wrapped, spark, model = False, stream.sparkSession, None
    for round_no in range(1, config.rounds + 1):
        if not run.paths:
            break
        model = students.fit(run.labelled(spark), student, model if student.warm_start else None)
        run.models.append((len(run.labels), model))
        need = min(config.batch, most - len(run.labels))
        if need <= 0:
            break
        if config.policy == "band":
            bought = [p for _, _, _, p, _ in run.labels] if wrapped else []
            positions, verdicts, head = _band_round(stream, run, model, annotator, Places(bought, head), need, n, round_no)
        else:
            positions, head = _scanned(stream, run, model, need, n, head, wrapped)
            verdicts = {}
        _buy(stream, run, annotator, positions, verdicts, round_no)
        run.seen = max(run.seen, head)
        if len(positions) < need:
            run.exhausted = True
            if config.on_exhausted != "wrap" or wrapped:
                break
            wrapped, head = True, 0
    if run.paths:
        run.models.append((len(run.labels), students.fit(run.labelled(spark), student, model if student.warm_start else None)))
    return run
