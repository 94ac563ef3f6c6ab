"""The loop with annotators that are paid, at every piece size, round the stream twice, and live."""

import os
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from distill_filter.config import RunConfig, StudentConfig
from distill_filter.operators import snippets, threshold
from distill_filter.plans import active
from distill_filter.sources.tables import shared_dir
from distill_filter.sources.verdicts import CachedAnnotator
from distill_filter.streaming.live import LiveState

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def rows(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    snippets.order(snippets.cut(docs)).select("snippet_id", "stream_pos", "text").write.parquet(path)
    return spark.read.parquet(path)


def counting(log, broken=None):
    """A paid annotator that notes each text it is asked about; it fails while the file `broken` is there."""

    def call(texts):
        if broken and os.path.exists(broken):
            raise OSError("no answer")
        with open(log, "a", encoding="utf-8") as f:
            f.writelines(f"{abs(hash(t))}\n" for t in texts)
        return [int("***" not in t) for t in texts]

    return call


def asked(log):
    return sum(1 for _ in open(log, encoding="utf-8")) if os.path.exists(log) else 0


def test_only_what_is_bought_is_asked_and_paid_once(spark, rows, tmp_path):
    config, log, cache = RunConfig(batch=64, budget=192, radius_scale=0.1, nested=True), str(tmp_path / "calls"), f"{shared_dir(spark)}/paid-{uuid.uuid4().hex}"
    paid = CachedAnnotator(counting(log), cache, "marks", parallel=2, pause=lambda s: None)
    run = active.distil(rows, "marks", config, annotator=paid)
    assert asked(log) == run.calls == len(run.labels) == len({i for _, _, i, _, _ in run.labels})
    assert run.scored <= 2 * (run.seen - 64) + 64 * 2 and run.seen <= 1338
    again = active.distil(rows, "marks", config, annotator=paid)  # begun anew after its end
    assert again.labels == run.labels and again.model == run.model and asked(log) == len(run.labels)


def test_a_failed_run_goes_on_where_it_paid(spark, rows, tmp_path):
    config, log, broken, cache = RunConfig(batch=64, budget=192), str(tmp_path / "calls"), str(tmp_path / "broken"), f"{shared_dir(spark)}/paid-{uuid.uuid4().hex}"
    paid = CachedAnnotator(counting(log, broken), cache, "marks", batch=16, retries=0, parallel=1, pause=lambda s: None)
    paid.ask(rows.where("stream_pos < 40").select("snippet_id", "stream_pos", "text"))
    open(broken, "w").close()
    with pytest.raises(RuntimeError):
        active.distil(rows, "marks", config, annotator=paid)
    os.remove(broken)
    run = active.distil(rows, "marks", config, annotator=paid)
    assert asked(log) == len(run.labels) > 64  # the printed update may end a run before its budget is spent


@pytest.mark.parametrize("options", [{}, {"nested": True}, {"unlabelled": "constant"}, {"unlabelled": "labelled_only", "nested": True}, {"on_exhausted": "wrap", "radius_scale": 0.02}])
def test_piece_size_changes_nothing(rows, options, monkeypatch):
    config = RunConfig(**{"batch": 64, "budget": 256, "radius_scale": 0.1, **options})
    whole = active.distil(rows, "quality", config)
    monkeypatch.setattr(active, "PIECE_ROWS", 100)
    small = active.distil(rows, "quality", config)
    assert (small.labels, small.trace, small.model, small.seen) == (whole.labels, whole.trace, whole.model, whole.seen)
    assert len({i for _, _, i, _, _ in whole.labels}) == len(whole.labels)


def test_places_skip_what_was_bought():
    for bought, head in (([3, 4, 9], 0), ([0, 1, 2], 0), ([5], 6), ([], 2), ([2, 3, 19], 3)):
        places = active.Places(bought, head)
        left = [p for p in range(head, 20) if p not in bought]
        assert [places.position(k) for k in range(len(left))] == left and places.left(20) == len(left)


def test_one_class_seed(spark, rows):
    plain = rows.select("snippet_id", "stream_pos", F.when(F.col("stream_pos") == 100, F.lit("a ***")).otherwise(F.concat(F.lit("word "), "snippet_id")).alias("text"))
    grown = active.distil(plain, "quality", RunConfig(batch=32, budget=160, on_single_class="grow_seed"))
    assert [r for r, *_ in grown.labels[:128]] == [0] * 128 and grown.labels[100][4] == 0
    assert [r for r, *_ in active.distil(plain, "quality", RunConfig(batch=32, budget=64)).labels] == [0] * 32 + [1] * 32
    assert active.distil(plain.limit(0), "quality", RunConfig()).labels == []


def test_warm_start_goes_on_from_the_last_student(rows):
    config = RunConfig(batch=64, budget=128)
    cold, warm = (active.distil(rows, "quality", config, StudentConfig(kind="focal", epochs=5, warm_start=w)) for w in (False, True))
    assert np.abs(warm.model.weights).sum() > np.abs(cold.model.weights).sum() and cold.labels == warm.labels


def test_live_state_is_numbers():
    config, counts = RunConfig(nested=True), threshold.Counts()
    counts.add(np.array([3, 5, 5]), np.array([0, 1, -1]))
    now = LiveState(7, 9, 5, active.Collector(100, 4, config, 3, -2, 8, 1, counts, 2))
    back = LiveState.load(now.dump(), config)
    assert back.dump() == now.dump() and back.collector.counts.update(2, 100, 0.1, 1.0) == now.collector.counts.update(2, 100, 0.1, 1.0)


def test_a_run_from_the_streams_head_is_the_whole_streams(spark, monkeypatch):
    """Also where the head given at first is too short, and without the whole stream being written."""
    from distill_filter.queries import methods

    whole = methods.engine_run(spark, SF)
    monkeypatch.setattr(methods, "stream", None)
    for head_rows in (1, 300, 700, 1 << 18):
        run = methods.head_run(spark, SF, head_rows=head_rows)
        assert run.labels == whole.labels and run.model == whole.model and run.exhausted == whole.exhausted
    assert methods.m15c(spark, SF).count() > 0
