"""Stored layouts: what queries read of them, their writers, statistics, and the measures."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from tracegraph import measures as ms
from tracegraph.model import DAY_US, HOUR_US, QuerySpec, Thresholds, TraceGraph
from tracegraph.operators import baselines as base
from tracegraph.operators import locations as loc
from tracegraph.operators import queries as ops
from tracegraph.operators import store
from tracegraph.operators.catalog import layout_catalog
from tracegraph.operators.layouts import build_kt, build_st, groups_for, layout_info
from tracegraph.operators.prune import row_bytes, small
from tracegraph.plans import cost as cm
from tracegraph.plans import mapping as mp
from tracegraph.plans.choose import LayoutStatistics, choose_plan
from tracegraph.sources import tables as t

TH = Thresholds(7 * HOUR_US, 100)


@pytest.fixture(scope="module")
def lay(spark, sf, tmp_path_factory):
    path = tmp_path_factory.mktemp("layouts")
    g = t.event_graph(spark, sf)
    build_kt(g, f"{path}/kt", 8)
    build_st(g, f"{path}/st", 32)
    made = ops.Layouts.stored(g, f"{path}/kt", f"{path}/st")
    made.path = str(path)
    return made


def test_bytes_read_keep_the_published_order(lay):
    week = t.events_days(7)
    q1 = {p: ms.measure(ops.object_trace(lay, 7, week, p)) for p in ("kt", "st")}
    assert 0 < 3 * q1["kt"].bytes_read < q1["st"].bytes_read
    day = t.events_days(2)
    q3 = {p: ms.measure(ops.similar_objects(lay, 7, day, TH, plan=p)).bytes_read for p in ("st", "kt", "kt+st")}
    assert q3["kt+st"] < q3["kt"] < q3["st"]


def test_long_traces_stay_off_the_driver(lay, monkeypatch):
    month = t.events_days(30)
    want = ops.similar_objects(lay, 7, month, TH).collect()
    monkeypatch.setattr(ops, "TRACE_ROWS", 3)
    assert ops.similar_objects(lay, 7, month, TH).collect() == want


def test_hot_cells_of_all_pairs_are_dealt_out(lay, monkeypatch):
    key = lambda df: sorted(map(tuple, df.collect()))
    want = key(ops.all_similar_pairs(lay, t.events_days(10), Thresholds(7 * HOUR_US, 1000)))
    monkeypatch.setattr(ops, "HOT_ROWS", 2)
    assert key(ops.all_similar_pairs(lay, t.events_days(10), Thresholds(7 * HOUR_US, 1000))) == want and want


def test_groups_follow_the_rows():
    assert groups_for(1000, 10, 64) == 1
    assert groups_for(10**12, 30, 1 << 14) == 1 << 13
    assert groups_for(10**15, 30, 1 << 14) == 1 << 14


def test_unknown_places_stay_in_both_layouts(spark, tmp_path):
    g = TraceGraph(t.event_places(spark), spark.createDataFrame([(1, 1, t.EVENTS_START_US, 5), (2, 1, t.EVENTS_START_US, 10**6)], "edge_id long, object_id long, ts_us long, location_id long"), None, t.EVENTS_SPEC)
    build_kt(g, f"{tmp_path}/kt")
    build_st(g, f"{tmp_path}/st")
    assert spark.read.parquet(f"{tmp_path}/kt").count() == spark.read.parquet(f"{tmp_path}/st").count() == 2
    assert layout_info(spark, f"{tmp_path}/st").groups == 1


def test_empty_graph_is_stored(spark, tmp_path):
    g = TraceGraph(t.event_places(spark), spark.createDataFrame([], "edge_id long, object_id long, ts_us long, location_id long"), None, t.EVENTS_SPEC)
    assert build_kt(g, f"{tmp_path}/kt").rows == 0


def test_choice_from_statistics(spark, lay):
    stats = LayoutStatistics.of(layout_catalog(spark, f"{lay.path}/kt", "kt", "slot_group").unionByName(layout_catalog(spark, f"{lay.path}/st", "st", "unit_group")))
    lo, hi = t.events_days(30).buckets(DAY_US)
    mb, files = stats.of_range("kt", lo, hi)
    assert files >= 30 and mb > 0 and stats.of_range("kt", lo, lo)[0] < mb
    for q, want in (("Q1", "kt"), ("Q2", "kt"), ("Q3", "kt+st"), ("Q4", "kt")):
        assert choose_plan(QuerySpec(q, (7, 1), t.events_days(7)), lay, statistics=stats).plan == want


def test_calibration_gives_positive_constants(spark, lay):
    c = cm.calibrate(spark, f"{lay.path}/kt", cm.CostParams(), repeat=1)
    assert c.c_r > 0 and c.c_a > 0 and c.c_0 > 0


def test_refreshed_locations(spark, sf, tmp_path):
    g = t.event_graph(spark, sf)
    moved = g.locations.where("location_id = 3").withColumn("x", F.lit(1).cast("long"))
    fresh = loc.refresh_locations(g, moved, str(tmp_path / "places"))
    assert fresh.locations.count() == 500 and fresh.locations.where("location_id = 3").first()["x"] == 1
    with pytest.raises(ValueError):
        loc.refresh_locations(g, moved.union(moved), str(tmp_path / "twice"))


def test_wide_rows_are_not_broadcast(spark):
    wide = spark.range(10).select("id", F.array_repeat(F.lit(1.0), 4).alias("v"))
    assert row_bytes(wide.schema) > 1000
    big = spark.range(5_000_000).select("id", F.array_repeat(F.col("id").cast("double"), 4).alias("v")).where("id % 2 = 0")
    assert "hint" not in small(big)._jdf.queryExecution().analyzed().toString().lower().split("project")[0]


def test_greedy_partition_cuts_fewer_edges(spark):
    # two communities that a hash cannot see
    rows = [(i, (i * 7919) % 500 * 10 + (i % 2), 0, (i * 104729) % 50 * 10 + (i % 2)) for i in range(4000)]
    e = spark.createDataFrame(rows, "edge_id long, object_id long, ts_us long, location_id long")
    cut = lambda p: base.cut_edges(e, *p).first()["cut"]
    hashed, greedy = cut(base.vertex_partition(e, 2)), cut(base.vertex_partition_greedy(e, 2))
    assert greedy <= hashed


def test_baselines_from_their_own_tables(spark, sf, tmp_path):
    g = t.event_graph(spark, sf)
    month = t.events_days(30)
    want = sorted(map(tuple, ops.similar_objects(g, 7, month, TH).collect()))
    for cls in (base.Relational, base.Scan, base.ZIndex):
        made = cls(g).build(f"{tmp_path}/{cls.__name__}")
        assert sorted(map(tuple, made.q3(7, month, TH).collect())) == want
        assert "Scan parquet" in made.q3(7, month, TH)._jdf.queryExecution().executedPlan().toString()


def test_measures(spark, lay):
    assert ms.standard_error([1.0, 3.0]) == 1.0 and ms.standard_error([2.0]) == 0.0
    assert ms.load_skew([1, 1, 4]) == 1.0 and ms.load_skew([]) == 0.0
    disk = ms.disk_space(spark, {"kt": f"{lay.path}/kt", "st": f"{lay.path}/st"}, {"st": 2})
    assert disk["st"] > disk["kt"] > 0
    found, truth = spark.createDataFrame([(1,), (2,)], "object_id long"), spark.createDataFrame([(2,), (3,)], "object_id long")
    assert ms.clone_accuracy(found, truth) == {"precision": 0.5, "recall": 0.5}
    assert ms.progress_rates([{"timestamp": "a", "processedRowsPerSecond": 2.0}, {"timestamp": "b"}]) == [("a", 2.0), ("b", 0.0)]
    assert ms.throughput(10, 2.0)["edges_s"] == 5


def test_grid_rules():
    assert mp.choose_width(1_024_000, 100, 10) >= 1000
    with pytest.warns(UserWarning):
        assert mp.check_grid(t.EVENTS_SPEC, 500, 10)
    assert mp.check_grid(t.EVENTS_SPEC, 100, 10) == []


def test_busy_keys_of_the_split_store_are_cut(spark, sf, tmp_path, monkeypatch):
    monkeypatch.setattr(store, "ROWS_PER_VALUE", 100, raising=False)
    columns = ["object_id", "ts_us", "location_id", "l_quantity", "l_linestatus"]
    e = t.shop_edges(spark, sf).select(*columns[:3], F.expr("nullif(l_quantity, 7)").alias("l_quantity"), "l_linestatus").cache()
    for name, key in (("one", F.lit("k")), ("many", F.expr("cast(object_id % 7 as string)"))):
        store.write_split(e, f"{tmp_path}/{name}", key, ["l_quantity", "l_linestatus"])
        for c in columns:
            kept = spark.read.parquet(f"{tmp_path}/{name}/{c}")
            assert kept.agg(F.max(F.size(c))).first()[0] <= 100  # a key's values in one row: 6,000 at the smallest size, 36 M over 448 keys at 60 x sf0.1
        rows = store.read_split(spark, f"{tmp_path}/{name}", columns)
        # arrays of repeated values are small in files and large on the driver
        assert "BroadcastHashJoin" not in rows._jdf.queryExecution().executedPlan().toString()
        assert sorted(map(str, rows.drop("row_key").collect())) == sorted(map(str, e.collect()))
        if name == "many":
            assert rows.where("row_key <> cast(object_id % 7 as string)").count() == 0
            some = store.read_split(spark, f"{tmp_path}/{name}", ["l_linestatus", "ts_us"], F.col("row_key").isin("2", "5"))
            assert some.count() == e.where("object_id % 7 in (2, 5)").count() > 0
    assert not (tmp_path / "one" / "_rows").exists()
    store.write_split(e.limit(0), f"{tmp_path}/none", F.lit("k"), ["l_quantity"])
    assert store.read_split(spark, f"{tmp_path}/none", ["ts_us", "l_quantity"]).count() == 0
