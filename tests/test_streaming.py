"""Ingestion in rounds and live operators against their batch twins."""

from __future__ import annotations

import time

import pytest
from pyspark.sql import functions as F

from tracegraph.model import DAY_US, HOUR_US, Thresholds
from tracegraph.operators import queries as ops
from tracegraph.operators.layouts import located
from tracegraph.plans import mapping as mp
from tracegraph.sources import tables as t
from tracegraph.sources.files import stream_edges
from tracegraph.streaming import live
from tracegraph.streaming.ingest import IngestStore, ingest_batch, ingest_stream

CORE = ["edge_id", "object_id", "ts_us", "location_id"]


@pytest.fixture(scope="module")
def replay(spark, sf, tmp_path_factory):
    """Events as files in time order."""
    path = tmp_path_factory.mktemp("replay")
    e = t.event_edges(spark, sf).select(*CORE)
    for i in range(5):
        lo = t.EVENTS_START_US + 6 * i * DAY_US
        part = e.where((F.col("ts_us") >= lo) & (F.col("ts_us") < lo + 6 * DAY_US))
        part.coalesce(1).write.mode("append").parquet(str(path))
        time.sleep(1.1)  # the source orders files by their modification times
    return str(path), e.cache()


@pytest.fixture
def store(spark, tmp_path):
    spec = t.EVENTS_SPEC.with_(n_workers=4)
    places = t.event_places(spark)
    m = mp.map_regions_bounded(mp.collect_weights(mp.region_weights(places, spec)), 4, 8, spec)
    return IngestStore(spark, str(tmp_path / "store"), spec, places, m.df(spark), m=6, groups=4)


def rows(df):
    return sorted(tuple(r) for r in df.select(*CORE).collect())


def test_stream_equals_batch(spark, replay, store, tmp_path):
    path, e = replay
    q = ingest_stream(store, stream_edges(spark, path, files_per_trigger=1), str(tmp_path / "cp"))
    q.awaitTermination()
    assert store.closed() and rows(store.edges()) == rows(e)
    open_before = store.staged()
    assert open_before is not None and open_before.count() > 0
    store.close_all()
    assert rows(store.layout("kt")) == rows(store.layout("st")) == rows(e)
    log = store.log
    assert sum(x.edges for x in log) == e.count()
    extra = store.layout("extra")
    assert extra.where("w_s <> w_k").count() == 0
    assert sum(x.copies for x in log) == 2 * e.count() + extra.count()


def test_replayed_batch_changes_nothing_and_late_edges_merge(spark, replay, store):
    _, e = replay
    first = e.where(F.col("ts_us") < t.EVENTS_START_US + 12 * DAY_US)
    store.stage(first, 0)
    store.stage(first, 0)
    assert store.staged().count() == first.count()
    ingest_batch(store, e.where(F.col("ts_us") >= t.EVENTS_START_US + 12 * DAY_US), 1)
    late = first.limit(5).withColumn("edge_id", F.col("edge_id") + 10**9)
    store.stage(late, 2)
    assert store.late().count() == 5
    assert store.merge_late() == 5
    store.close_all()
    assert rows(store.edges()) == rows(e.unionByName(late))


def _again(store):
    """The same store as a restarted process sees it."""
    return IngestStore(store.spark, store.path, store.spec, store.locations, store.mapping, m=store.m, groups=store.groups, rows_per_file=store.rows_per_file)


def test_replay_after_a_closed_round_changes_nothing(replay, store):
    _, e = replay
    store.stage(e, 0)
    assert store.close_due()
    closed = store.closed()
    store.stage(e, 0)  # the same micro-batch again: the stream had not committed it
    assert store.late() is None and store.merge_late() == 0 and not (store.closed() - closed)
    again = _again(store)
    again.stage(e, 0)
    again.close_all()
    assert rows(again.edges()) == rows(again.layout("kt")) == rows(again.layout("st")) == rows(e)


def test_crash_between_commit_and_sweep_counts_nothing_twice(replay, store, monkeypatch):
    _, e = replay
    store.stage(e, 0)

    def crash(self, round_id):
        raise RuntimeError("lost driver")

    with monkeypatch.context() as m:
        m.setattr(IngestStore, "sweep", crash)
        with pytest.raises(RuntimeError):
            store.close_due()
    again = _again(store)
    assert len(again.closed()) == 1 and again.max_ts == e.agg(F.max("ts_us")).first()[0]
    assert rows(again.edges()) == rows(e)
    again.close_all()
    assert rows(again.edges()) == rows(again.layout("st")) == rows(e)


@pytest.mark.parametrize("step", ["_write_layouts", "_commit", "sweep"])
def test_interrupted_merge_of_late_edges(replay, store, monkeypatch, step):
    _, e = replay
    store.stage(e, 0)
    store.close_all()
    late = e.where(F.col("edge_id") % 50 == 0).withColumn("edge_id", F.col("edge_id") + 10**9)
    store.stage(late, 1)
    assert store.late().count() == late.count()
    real, calls = getattr(IngestStore, step), []

    def crash(self, *args):
        calls.append(args)
        if len(calls) == 2:
            if step == "_write_layouts":  # half of the new version is there
                real(self, args[0].limit(3), *args[1:])
            raise RuntimeError("lost driver")
        return real(self, *args)

    with monkeypatch.context() as m:
        m.setattr(IngestStore, step, crash)
        with pytest.raises(RuntimeError):
            store.merge_late()
    again = _again(store)
    again.merge_late()
    assert again.late() is None and again.merge_late() == 0
    assert rows(again.layout("kt")) == rows(again.layout("st")) == rows(e.unionByName(late))
    again.stage(late, 1)
    assert again.merge_late() == 0


def test_edges_with_nulls_are_rejected_and_unknown_places_kept(spark, store):
    day = t.EVENTS_START_US
    df = spark.createDataFrame([(1, 1, day, 5), (2, None, day, 5), (3, 1, None, 5), (4, 1, day, None), (5, 1, day, 10**6)], "edge_id long, object_id long, ts_us long, location_id long")
    store.stage(df, 0)
    store.stage(df.limit(0), 1)
    store.close_all()
    assert sorted(r["edge_id"] for r in store.rejected().collect()) == [2, 3, 4]
    assert [r[0] for r in rows(store.layout("kt"))] == [r[0] for r in rows(store.layout("st"))] == [1, 5]


def test_a_hot_object_is_split_over_files(spark, store):
    store.rows_per_file = 1000
    day = t.EVENTS_START_US
    hot = spark.range(8000).selectExpr("id as edge_id", "cast(if(id % 2 = 0, 7, id) as bigint) as object_id", f"{day} + id * 1000000 as ts_us", "cast(if(id % 2 = 0, 3, id % 500) as bigint) as location_id")
    store.stage(hot, 0)
    store.close_all()
    for name in ("kt", "st"):
        sizes = [r["count"] for r in store.layout(name).groupBy("_metadata.file_path").count().collect()]
        assert sum(sizes) == 8000 and max(sizes) <= 2 * 1000  # a half of all rows is one object at one place


def _run(df, mode, name):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def test_live_windows_match_batch(spark, replay):
    path, e = replay
    places = t.event_places(spark)
    out = _run(live.visits_per_region(stream_edges(spark, path, files_per_trigger=1), places, t.EVENTS_SPEC), "complete", "visits")
    twin = live.visits_per_region(e, places, t.EVENTS_SPEC)
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, twin.collect()))
    slide = _run(live.visits_per_region(stream_edges(spark, path), places, t.EVENTS_SPEC, width="2 days", slide="1 day"), "complete", "slides")
    assert slide.agg(F.sum("visits")).first()[0] == 2 * e.count()


def test_live_trips_and_repeats(spark, replay):
    path, e = replay
    trips = _run(live.trips(stream_edges(spark, path, files_per_trigger=1)), "append", "trips")
    twin = {tuple(r) for r in live.trips(e).collect()}
    got = {tuple(r) for r in trips.collect()}
    assert got and got <= twin
    fresh = _run(live.without_repeats(stream_edges(spark, path).union(stream_edges(spark, path))), "append", "fresh")
    assert fresh.count() == e.count()


def test_live_similar_and_trace(spark, replay):
    path, e = replay
    places, th = t.event_places(spark), Thresholds(10 * HOUR_US, 1000)
    trace = located(e.where("object_id = 7"), places)
    got = _run(live.live_similar(stream_edges(spark, path), places, trace, th, t.EVENTS_SPEC), "complete", "similar")
    from tracegraph.model import TraceGraph

    twin = ops.similar_objects(TraceGraph(places, e, None, t.EVENTS_SPEC), 7, None, th, plan="kt", include_self=True)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, twin.collect()))
    mine = _run(live.live_trace(stream_edges(spark, path), spark.createDataFrame([(7,)], "object_id long")), "append", "mine")
    assert mine.count() == e.where("object_id = 7").count()


def test_clone_alarm_matches_batch(spark, replay):
    path, e = replay
    places = t.event_places(spark)
    out = _run(live.clone_alarm(stream_edges(spark, path, files_per_trigger=1), places, 9000.0), "append", "alarms")
    from tracegraph.model import TraceGraph

    twin = ops.clone_objects(TraceGraph(places, e, None, t.EVENTS_SPEC), None, 9000.0)
    assert {r[0] for r in out.select("object_id").collect()} == {r[0] for r in twin.collect()}


def test_copresence_of_streams(spark, replay):
    path, e = replay
    places, th = t.event_places(spark), Thresholds(HOUR_US, 1000)
    out = _run(live.copresence(stream_edges(spark, path), stream_edges(spark, path), places, th), "append", "met")
    twin = live.copresence(e, e, places, th)
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, twin.collect()))
