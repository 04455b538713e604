"""Mappings, theorems, cost model, capacity, bounds: against brute force, closed forms and simulation."""

from __future__ import annotations

import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tracegraph.functions.geometry import z_code_int, z_decode_int
from tracegraph.functions.slots import slot_of_int
from tracegraph.model import DAY_US, HOUR_US, GraphSpec, QuerySpec, TimeRange, TraceGraph
from tracegraph.operators.groups import rebalance
from tracegraph.operators.prune import bucket_reach, intervals, regions_touching
from tracegraph.plans import cost as cm
from tracegraph.plans import mapping as mp
from tracegraph.plans.capacity import capacity
from tracegraph.plans.choose import choose_plan
from tracegraph.sources import tables as t

WEIGHTS = st.lists(st.tuples(st.integers(0, 4095), st.integers(1, 50)), min_size=1, max_size=60, unique_by=lambda x: x[0])


@given(st.integers(0, 65535), st.integers(0, 65535))
def test_z_code_round_trip(x, y):
    assert z_decode_int(z_code_int(x, y)) == (x, y)


@given(st.integers(-(1 << 40), 1 << 40), st.integers(1, 14))
def test_slots_in_range(i, p):
    assert 0 <= slot_of_int(i, p) < 1 << p


@given(WEIGHTS, st.integers(1, 12))
def test_unbounded_mapping_bound(weights, workers):
    """A bin ends below the mean plus its last region's weight; all regions are placed, along the curve."""
    m = mp.map_regions_unbounded(sorted(weights), workers)
    assert sum(m.loads()) == sum(w for _, w in weights)
    assert len(m.loads()) == workers
    mean, heaviest = sum(m.loads()) / workers, max(w for _, w in weights)
    assert all(load < mean + heaviest for load in m.loads()[:-1])
    order = [w for _, _, w, _ in m.rows]
    assert order == sorted(order)


@given(WEIGHTS, st.integers(1, 12), st.sampled_from([1, 2, 4, 8]))
def test_bounded_mapping_bound(weights, workers, b):
    spec = GraphSpec()
    m = mp.map_regions_bounded(weights, workers, b, spec)
    units: dict[int, int] = {}
    for r, w in weights:
        units[mp.unit_of(r, b, spec)] = units.get(mp.unit_of(r, b, spec), 0) + w
    assert max(m.loads()) <= sum(m.loads()) / workers + max(units.values())
    assert len({(u, w) for _, u, w, _ in m.rows}) == len(units)


def test_fixture_skews(spark):
    """Published fixture values: skew by unit width for 4 and 10 workers, bins of the unbounded mapping."""
    weights = mp.collect_weights(mp.region_weights(t.event_places(spark), t.EVENTS_SPEC))
    assert len(weights) == 121 and max(w for _, w in weights) == 5
    assert mp.map_regions_unbounded(weights, 4).loads() == [125] * 4
    assert sorted(mp.map_regions_unbounded(weights, 10).loads()) == sorted([52, 53, *[50] * 7, 45])
    skew = {b: round(mp.map_regions_bounded(weights, 10, b, t.EVENTS_SPEC).skew(), 3) for b in (1, 4, 8, 16)}
    assert skew == {1: 0.0, 4: 0.02, 8: 0.04, 16: 1.0}


def test_spatial_factor_values_and_simulation():
    assert [round(mp.spatial_factor(b, 1000, 1000), 4) for b in (8, 4, 2)] == [0.8789, 0.7656, 0.5625]
    rnd, side, d, hits, n = random.Random(7), 4000.0, 1000.0, 0, 40_000
    for _ in range(n):
        x, y = rnd.uniform(0, side), rnd.uniform(0, side)
        u, v = x + rnd.uniform(-d, d), y + rnd.uniform(-d, d)
        hits += 0 <= u < side and 0 <= v < side
    p = mp.spatial_factor(4, 1000, 1000)
    assert abs(hits / n - p) < 4 * math.sqrt(p * (1 - p) / n)


def test_nine_parts_add_up():
    parts = mp.nine_parts(4, 1000, 1000)
    assert math.isclose(sum(s for s, _ in parts.values()), 1)
    assert math.isclose(1 - sum(s * e for s, e in parts.values()), mp.spatial_factor(4, 1000, 1000))


def test_b_bounds():
    low, high, feasible = mp.b_bounds(100, 1000, 0.9, 0.001, 0.4)
    assert feasible and low <= high and math.isclose(high, 20)
    assert mp.spatial_factor(low, 1000, 100) >= 0.9 - 1e-9


def test_cost_orders_and_values():
    c = cm.CostParams()
    total = {(q, p): cm.cost(q, p, 1, c, 100).total for q in cm.QUERIES for p in cm.plans_of(q)}
    for q in ("Q1", "Q2", "Q4"):
        assert total[q, "kt"] < total[q, "st"]
    assert total["Q3", "kt+st"] < total["Q3", "kt"] < total["Q3", "st"]
    assert math.isclose(total["Q2", "kt"], total["Q1", "kt"])
    assert [round(total[k], 2) for k in (("Q1", "st"), ("Q3", "st"), ("Q3", "kt"), ("Q4", "kt"))] == [14.29, 26.17, 13.27, 1.39]
    assert 834_000 < cm.break_even_regions(1, c) < 835_000
    assert cm.cost("Q3", "kt+st", 2, c, 100).total > total["Q3", "kt+st"]
    assert cm.cost("Q3", "kt+st", 1, c, 200).total > total["Q3", "kt+st"]


def test_choice_falls_back_beyond_break_even():
    g, day = TraceGraph(None, None, None, GraphSpec()), TimeRange.days(t.EVENTS_START_US, 1)
    assert choose_plan(QuerySpec("Q3", (7,), day), g, cm.CostParams(), 100).plan == "kt+st"
    assert choose_plan(QuerySpec("Q3", (7,), day), g, cm.CostParams(), 900_000).plan == "kt"


def test_capacity():
    c = capacity()
    assert c["edge_pb"] == 2.4 and c["stored_pb"] == 7.2 and c["day_tb"] == 24 and c["ingest_workers"] == 15


@pytest.mark.parametrize("th", [HOUR_US, DAY_US, DAY_US + 1, 3 * DAY_US])
def test_bucket_rule_loses_no_pair(th):
    reach, rnd = bucket_reach(th, DAY_US), random.Random(1)
    for _ in range(2000):
        a = rnd.randrange(10 * DAY_US)
        b = a + rnd.choice([-th, th, rnd.randint(-th, th)])
        assert abs(a // DAY_US - b // DAY_US) <= reach


def test_time_range_counts():
    r = TimeRange(DAY_US, 3 * DAY_US)
    assert r.n_tru(DAY_US) == 2 and TimeRange(DAY_US, 3 * DAY_US, closed=True).n_tru(DAY_US) == 3
    assert r.n_tru(DAY_US, "paper") == 2


@settings(max_examples=50)
@given(st.lists(st.integers(0, 100_000), min_size=1, max_size=200, unique=True), st.integers(1, 20))
def test_intervals_cover(codes, most):
    spans = intervals(sorted(codes), most)
    assert len(spans) <= most and all(any(a <= c <= b for a, b in spans) for c in codes)


def test_regions_touching_crosses_borders():
    spec = GraphSpec()
    assert len(regions_touching([(1500, 1500)], 100, spec)) == 1
    assert len(regions_touching([(1950, 1500)], 100, spec)) == 2
    assert len(regions_touching([(2000, 2000)], 100, spec)) == 4
    assert len(regions_touching([(0, 0)], 100, spec)) == 1


@given(st.lists(st.integers(1, 30), min_size=1, max_size=60), st.integers(2, 6))
def test_rebalance_never_worsens(loads, workers):
    placed = [(f"g{i}", i % workers, n) for i, n in enumerate(loads)]
    moves = rebalance(placed, workers)
    at = {g: w for g, w, _ in placed}
    for m in moves:
        assert at[m.group_id] == m.source
        at[m.group_id] = m.target
    size = {g: n for g, _, n in placed}
    before, after = [0] * workers, [0] * workers
    for g, w, n in placed:
        before[w] += n
        after[at[g]] += n
    assert max(after) <= max(before) and sum(size.values()) == sum(after)
