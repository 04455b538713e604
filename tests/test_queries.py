"""The four queries on built edge cases, and equality of all plans, prune levels and stores."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from tracegraph.model import DAY_US, HOUR_US, GraphSpec, QuerySpec, Thresholds, TimeRange, TraceGraph, edges_from, validate_graph
from tracegraph.operators import queries as ops
from tracegraph.operators import store
from tracegraph.operators.catalog import layout_catalog
from tracegraph.operators.layouts import build_kt, build_st, kt_columns, row_key
from tracegraph.plans import mapping as mp
from tracegraph.plans.choose import explain_plan, run
from tracegraph.sources import tables as t
from tracegraph.sources.files import read_edges, write_edges

TH = Thresholds(7 * HOUR_US, 100, 120.0)
ALL = TimeRange(0, 10 * DAY_US)
SPEC = GraphSpec(a=1000, p=4, n_workers=3, eta=30)


def graph(spark, edges, places=((1, 0, 0), (2, 100, 0), (3, 101, 0), (4, 999, 0), (5, 1001, 0), (6, 500_000, 0))):
    e = spark.createDataFrame([(i, *x) for i, x in enumerate(edges)], "edge_id long, object_id long, ts_us long, location_id long")
    return TraceGraph(spark.createDataFrame(list(places), "location_id long, x long, y long"), e, None, SPEC)


def similar(g, o, plan, prune, **kw):
    return [(r[0], r[1]) for r in ops.similar_objects(g, o, ALL, TH, plan=plan, prune=prune, **kw).collect()]


EDGES = [
    (7, 1000, 1), (7, 5 * HOUR_US, 4),
    (1, 1000 + 7 * HOUR_US, 2),  # both thresholds exactly met
    (2, 1001 + 7 * HOUR_US, 2),  # a microsecond too late
    (3, 1000, 3),  # a metre too far
    (4, 5 * HOUR_US, 5), (4, 5 * HOUR_US, 5),  # across a region border, twice
    (-5, DAY_US, 4), (1 << 40, 5 * HOUR_US, 4),
]
EXPECTED = [(4, 2), (1, 1), (1 << 40, 1)]


@pytest.mark.parametrize("plan", ops.PLANS)
@pytest.mark.parametrize("prune", ["none", "time", "both", "cell"])
def test_similar_objects_borders(spark, plan, prune):
    assert similar(graph(spark, EDGES), 7, plan, prune) == EXPECTED


def test_similar_objects_options(spark):
    g = graph(spark, EDGES)
    assert similar(g, 7, "kt+st", "cell", min_sim=2) == [(4, 2)]
    assert similar(g, 7, "kt+st", "cell", limit=1) == [(4, 2)]
    assert (7, 2) in similar(g, 7, "st", "cell", include_self=True)
    assert similar(g, 999, "kt+st", "cell") == []
    with pytest.raises(ValueError):
        similar(g, 7, "zt", "cell")


def test_duplicates_multiply(spark):
    g = graph(spark, EDGES + EDGES)
    assert similar(g, 7, "kt", "cell") == [(o, 4 * n) for o, n in EXPECTED]


def test_shift_and_translate_change_nothing(spark):
    moved = [(o, ts + 3 * DAY_US, p) for o, ts, p in EDGES]
    places = [(p, x + 5000, y + 7000) for p, x, y in ((1, 0, 0), (2, 100, 0), (3, 101, 0), (4, 999, 0), (5, 1001, 0), (6, 500_000, 0))]
    assert similar(graph(spark, moved, places), 7, "kt+st", "cell") == EXPECTED


@pytest.mark.parametrize("prune", ["none", "time", "both", "cell"])
def test_trace_similarity(spark, prune):
    g = graph(spark, EDGES)
    value = lambda a, b: ops.trace_similarity(g, a, b, ALL, TH, prune=prune).collect()[0]["similarity"]
    assert value(7, 4) == 2 and value(4, 7) == 2 and value(7, 3) == 0 and value(7, 7) == 2 and value(8, 9) == 0


def test_clipping_half_open_and_closed(spark):
    g = graph(spark, [(1, 0, 1), (1, DAY_US, 2)])
    n = lambda r: ops.object_trace(g, 1, r).count()
    assert n(TimeRange(0, DAY_US)) == 1 and n(TimeRange(0, DAY_US, closed=True)) == 2 and n(TimeRange(1, 1)) == 0


@pytest.mark.parametrize("method", ["lag", "stitched", "pairs"])
def test_clones(spark, method):
    edges = [
        (1, 10, 1), (1, 10, 1),  # the same place twice at once: no clone
        (2, 10, 1), (2, 10, 6),  # two places at once
        (3, DAY_US - 1, 1), (3, DAY_US + HOUR_US, 6),  # across a bucket border
        (4, 0, 1), (4, 5 * HOUR_US, 6),  # 100 km/h
        (5, 0, 1),
    ]
    found = sorted(r[0] for r in ops.clone_objects(graph(spark, edges), ALL, 120.0, method).collect())
    assert found == [2, 3]


def test_methods_agree_on_events(spark, sf):
    g = t.event_graph(spark, sf, t.events_days(7))
    sets = [{r[0] for r in ops.clone_objects(g, t.events_days(7), 9000.0, m).collect()} for m in ("lag", "stitched", "pairs")]
    assert sets[0] == sets[1] == sets[2] and len(sets[0]) == 2


def test_stored_layouts_give_the_same(spark, sf, tmp_path):
    g = t.event_graph(spark, sf)
    build_kt(g, f"{tmp_path}/kt", 4)
    build_st(g, f"{tmp_path}/st", 4)
    stored = ops.Layouts.stored(g, f"{tmp_path}/kt", f"{tmp_path}/st")
    r = t.events_days(30)
    expected = similar_rows(ops.similar_objects(g, 7, r, TH))
    for plan in ops.PLANS:
        assert similar_rows(ops.similar_objects(stored, 7, r, TH, plan=plan)) == expected
    assert ops.object_trace(stored, 7, r).collect() == ops.object_trace(g, 7, r).collect()
    plan = ops.object_trace(stored, 7, t.events_days(1))._jdf.queryExecution().executedPlan().toString()
    assert "slot_group" in plan.split("PartitionFilters")[1].split("PushedFilters")[0]
    cat = layout_catalog(spark, f"{tmp_path}/kt", "kt", "slot_group")
    assert cat.agg(F.sum("rows")).first()[0] == g.edges.count()


def similar_rows(df):
    return [(r[0], r[1]) for r in df.collect()]


def test_no_nested_loop_and_no_python(spark, sf):
    g = t.event_graph(spark, sf)
    for prune in ("time", "both", "cell"):
        plan = ops.similar_objects(g, 7, t.events_days(7), TH, prune=prune)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Python" not in plan and "Cartesian" not in plan


@pytest.mark.parametrize("codec", ["snappy", "zstd", "gzip"])
def test_split_and_packed_stores(spark, sf, tmp_path, codec):
    e = kt_columns(t.shop_edges(spark, sf).limit(500), t.SHOP_SPEC)
    e = e.select("object_id", "ts_us", "location_id", "l_quantity", "l_returnflag", "slot", "tru", "worker").cache()
    key = row_key(F.lit("B"), "slot", F.expr("tru div 400"), "worker")
    want = sorted((r[0], r[1], r[2], r[3]) for r in e.select("object_id", "ts_us", "l_quantity", "l_returnflag").collect())
    store.write_split(e, f"{tmp_path}/c", key, ["l_quantity", "l_returnflag"], codec)
    got = store.read_split(spark, f"{tmp_path}/c", ["object_id", "ts_us", "l_quantity", "l_returnflag"])
    assert sorted(tuple(r)[1:] for r in got.collect()) == want
    store.write_packed(e, f"{tmp_path}/r", key, ["l_quantity", "l_returnflag"])
    back = store.read_packed(spark, f"{tmp_path}/r", "row_key string, object_id long, ts_us long, l_quantity double, l_returnflag string")
    assert sorted(tuple(r)[1:] for r in back.collect()) == want
    with pytest.raises(ValueError):
        store.write_split(e, f"{tmp_path}/x", key, [], "rar")


def test_integrity_finds_violations(spark):
    g = graph(spark, [(1, 0, 99), (None, 0, 1)])
    got = {r["check"]: r["violations"] for r in validate_graph(g).collect()}
    assert got == {"duplicate_location": 0, "dangling_location": 1, "null_in_edge": 1, "location_off_grid": 0}


def test_edges_from_keeps_properties(spark):
    df = spark.createDataFrame([(1, 2, 3, "x")], "who long, when_us long, place long, note string")
    assert edges_from(df, {"object_id": "who", "ts_us": "when_us", "location_id": "place"}).columns == ["object_id", "ts_us", "location_id", "note"]
    with pytest.raises(ValueError):
        edges_from(df, {"object_id": "nobody"})


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_readers_round_trip(spark, tmp_path, fmt):
    e = graph(spark, EDGES).edges
    write_edges(e, f"{tmp_path}/e", fmt)
    assert sorted(read_edges(spark, f"{tmp_path}/e", fmt).collect()) == sorted(e.collect())


def test_requests_run_with_chosen_plan(spark, sf):
    g = t.event_graph(spark, sf)
    r = t.events_days(7)
    for q in (QuerySpec("Q1", (7,), r), QuerySpec("Q2", (7, 1), r), QuerySpec("Q3", (7,), r), QuerySpec("Q4", (), r)):
        assert run(q, g).count() >= 0
    text = explain_plan(QuerySpec("Q1", (7,), r), g)
    assert "chosen: kt" in text and "Physical Plan" in text
