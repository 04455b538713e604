"""Queries over whole tables against brute force."""

from __future__ import annotations

import math
from collections import Counter, defaultdict

from tests.oracle import connect
from tracegraph import registry
from tracegraph.sources import tables as t

QUERIES = registry.queries()


def _visits(spark, sf):
    places = {r["location_id"]: r["embedding"] for r in t.vector_locations(spark, sf).collect()}
    edges = t.event_edges(spark, sf, t.events_days(30)).collect()
    return [(r["object_id"], r["ts_us"], r["edge_id"] % len(places)) for r in edges], places


def test_sort_covers_all_edges(spark, sf):
    rows = [tuple(r) for r in QUERIES["op_sort_trace"](spark, sf).collect()]
    assert rows == sorted(rows) and len(rows) == t.shop_edges(spark, sf).count()
    assert any(r[0] >= 20 for r in rows)


def test_all_pairs_of_a_month(spark, sf):
    sql = registry.oracle_sql()["q3_all_pairs"]
    assert sql.count(str(1704067200000000 + 30 * 86400000000)) == 2
    want = connect(sf).execute(sql).fetchall()
    got = QUERIES["q3_all_pairs"](spark, sf).select("object_a", "object_b", "similarity").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_near_places_of_all_queries(spark, sf):
    _, places = _visits(spark, sf)
    want = {(a, b) for a in places if a % 100 == 0 for b in places if a != b and round(math.dist(places[a], places[b]), 6) <= 9}
    assert {(r["a"], r["b"]) for r in QUERIES["vector_near_places"](spark, sf).collect()} == want


def test_similar_objects_of_a_month(spark, sf):
    visits, places = _visits(spark, sf)
    mine, want = [v for v in visits if v[0] == 7], Counter()
    for o, ts, place in visits:
        for _, ta, pa in mine:
            if o != 7 and abs(ta - ts) <= 36_000_000_000 and round(math.dist(places[pa], places[place]), 9) <= 10:
                want[o] += 1
    assert {r["object_id"]: r["similarity"] for r in QUERIES["vector_similar_objects"](spark, sf).collect()} == want


def test_cosine_clones_of_a_month(spark, sf):
    visits, places = _visits(spark, sf)
    norm = {k: math.hypot(*v) for k, v in places.items()}
    by, want = defaultdict(list), set()
    for o, ts, place in visits:
        by[o].append((ts, place))
    for o, rows in by.items():
        for i, (ta, a) in enumerate(rows):
            for tb, b in rows[:i]:
                far = 1 - sum(x * y for x, y in zip(places[a], places[b], strict=True)) / norm[a] / norm[b]
                if a != b and far * 3.6e6 > 1e-4 * abs(ta - tb):
                    want.add(o)
    assert {r["object_id"] for r in QUERIES["vector_clones_cosine"](spark, sf).collect()} == want
