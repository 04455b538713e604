"""The experiments, re-expressed on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from tracegraph.functions.geometry import METRICS, vector_l2
from tracegraph.functions.slots import object_placement, slot_of
from tracegraph.model import GraphSpec, QuerySpec, Thresholds, TimeRange, TraceGraph
from tracegraph.operators import baselines as base
from tracegraph.operators import groups as grp
from tracegraph.operators import index as idx
from tracegraph.operators import locations as loc
from tracegraph.operators import queries as ops
from tracegraph.operators import store
from tracegraph.operators.catalog import layout_catalog
from tracegraph.operators.layouts import kt_columns, row_key, st_columns
from tracegraph.operators.prune import small
from tracegraph.operators.replicas import placement, recover_worker, with_workers
from tracegraph.plans import capacity as cap
from tracegraph.plans import cost as cm
from tracegraph.plans import mapping as mp
from tracegraph.plans.choose import LayoutStatistics, choose_plan
from tracegraph.sources import tables as t
from tracegraph.sources.datagen import generate_edges
from tracegraph.sources.files import scratch, write_edges
from tracegraph.streaming.ingest import IngestStore, ingest_batch

from . import stored
from .entries import DAY, EV, HOUR, PC, PL, S0, SE, SO, E, days, entry, fast, near, slot, zcode

NARROW = Thresholds(7 * HOUR, 100, 120.0)
WIDE = Thresholds(10 * HOUR, 1000, 120.0)
ME = 7


def _ev(s, d):
    """The stored layouts of the event graph: every query reads what its plan needs of them."""
    return stored.events(s, d)


# --- Q1 --------------------------------------------------------------------

_Q1 = f"WITH {EV} SELECT object_id, ts_us, location_id FROM ev WHERE object_id = {ME} AND "


@entry("q1_trace_kt", _Q1 + days(7))
def q1_trace_kt(s, d):
    return ops.object_trace(_ev(s, d), ME, t.events_days(7), "kt")


@entry("q1_trace_st", _Q1 + days(7))
def q1_trace_st(s, d):
    return ops.object_trace(_ev(s, d), ME, t.events_days(7), "st")


@entry("q1_trace_day", _Q1 + days(1))
def q1_trace_day(s, d):
    return ops.object_trace(_ev(s, d), ME, t.events_days(1), "kt")


@entry("q1_trace_month", _Q1 + days(30))
def q1_trace_month(s, d):
    return ops.object_trace(_ev(s, d), ME, t.events_days(30), "kt")


@entry("q1_trace_shop", f"WITH {SO} SELECT object_id, ts_us, location_id FROM so WHERE object_id = {ME}")
def q1_trace_shop(s, d):
    return ops.object_trace(stored.shop(s, d), ME, None, "kt")


@entry("q1_traces_of_segment", f"""WITH {SO} SELECT object_id, ts_us, location_id FROM so
  WHERE object_id IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')""")
def q1_traces_of_segment(s, d):
    ids = t.read(s, d, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("object_id"))
    return ops.object_traces(stored.shop(s, d), ids, None)


@entry("q1_trace_adjacency", _Q1 + days(7))
def q1_trace_adjacency(s, d):
    return stored.baseline(s, d, "graph").q1(ME, t.events_days(7))


@entry("q1_trace_scan", _Q1 + days(7))
def q1_trace_scan(s, d):
    return stored.baseline(s, d, "scan").q1(ME, t.events_days(7))


# --- Q2 --------------------------------------------------------------------


def _q2_sql(o1, o2, h, m, n=30):
    return f"""WITH {E} SELECT CAST({o1} AS BIGINT) AS object_a, CAST({o2} AS BIGINT) AS object_b, count(*) AS similarity
      FROM (SELECT * FROM e WHERE object_id = {o1} AND {days(n)}) a, (SELECT * FROM e WHERE object_id = {o2} AND {days(n)}) b
      WHERE {near(h, m)}"""


@entry("q2_similarity_7h100m", _q2_sql(7, 21, 7, 100))
def q2_similarity_7h100m(s, d):
    return ops.trace_similarity(_ev(s, d), 7, 21, t.events_days(30), NARROW)


@entry("q2_similarity_10h1000m", _q2_sql(7, 1, 10, 1000))
def q2_similarity_10h1000m(s, d):
    return ops.trace_similarity(_ev(s, d), 7, 1, t.events_days(30), WIDE)


@entry("q2_similarity_st", _q2_sql(7, 1, 10, 1000))
def q2_similarity_st(s, d):
    return ops.trace_similarity(_ev(s, d), 7, 1, t.events_days(30), WIDE, plan="st", prune="both")


@entry("q2_similarity_self", _q2_sql(7, 7, 10, 1000))
def q2_similarity_self(s, d):
    return ops.trace_similarity(_ev(s, d), 7, 7, t.events_days(30), WIDE)


@entry("q2_similarity_shop", f"""WITH {SE} SELECT CAST(7 AS BIGINT) AS object_a, CAST(1 AS BIGINT) AS object_b, count(*) AS similarity
  FROM se a, se b WHERE a.object_id = 7 AND b.object_id = 1 AND {near(10, 1000)}""")
def q2_similarity_shop(s, d):
    return ops.trace_similarity(stored.shop(s, d), 7, 1, None, WIDE)


# --- Q3 --------------------------------------------------------------------


def _q3_sql(h, m, n, extra=""):
    return f"""WITH {E} SELECT b.object_id, count(*) AS similarity
      FROM (SELECT * FROM e WHERE object_id = {ME} AND {days(n)}) a, (SELECT * FROM e WHERE object_id <> {ME} AND {days(n)}) b
      WHERE {near(h, m)} GROUP BY b.object_id {extra}"""


def _q3(name, plan, prune, th, n, h, m):
    @entry(name, _q3_sql(h, m, n))
    def run(s, d):
        return ops.similar_objects(_ev(s, d), ME, t.events_days(n), th, plan=plan, prune=prune)


for _name, _plan, _prune in (
    ("q3_similar_st", "st", "cell"), ("q3_similar_kt", "kt", "cell"), ("q3_similar_ktst", "kt+st", "cell"),
    ("q3_prune_none", "kt+st", "none"), ("q3_prune_time", "kt+st", "time"), ("q3_prune_both", "kt+st", "both"),
):
    _q3(_name, _plan, _prune, NARROW, 7, 7, 100)
for _n in (1, 4, 30):
    _q3(f"q3_range_{_n}d", "kt+st", "cell", NARROW, _n, 7, 100)
_q3("q3_similar_10h1000m", "kt+st", "cell", WIDE, 7, 10, 1000)
_q3("q3_prune_both_10h1000m", "kt", "both", WIDE, 30, 10, 1000)


@entry("q3_range_sweep", " UNION ALL ".join(
    f"SELECT CAST({n} AS INTEGER) AS days, count(*) AS results, CAST(coalesce(sum(similarity), 0) AS BIGINT) AS pairs FROM ({_q3_sql(10, 1000, n)})"
    for n in (1, 2, 4, 8, 16, 30)))
def q3_range_sweep(s, d):
    out = None
    for n in (1, 2, 4, 8, 16, 30):
        rows = ops.similar_objects(_ev(s, d), ME, t.events_days(n), WIDE).agg(
            F.count(F.lit(1)).alias("results"), F.coalesce(F.sum("similarity"), F.lit(0)).alias("pairs")
        ).select(F.lit(n).cast("int").alias("days"), "results", "pairs")
        out = rows if out is None else out.unionByName(rows)
    return out


@entry("q3_top5", f"SELECT * FROM ({_q3_sql(10, 1000, 30)}) ORDER BY similarity DESC, object_id LIMIT 5")
def q3_top5(s, d):
    return ops.similar_objects(_ev(s, d), ME, t.events_days(30), WIDE, limit=5)


@entry("q3_min_similarity", _q3_sql(10, 1000, 30, "HAVING count(*) >= 3"))
def q3_min_similarity(s, d):
    return ops.similar_objects(_ev(s, d), ME, t.events_days(30), WIDE, min_sim=3)


@entry("q3_all_pairs", f"""WITH {E} SELECT a.object_id AS object_a, b.object_id AS object_b, count(*) AS similarity
  FROM (SELECT * FROM e WHERE {days(30)}) a JOIN (SELECT * FROM e WHERE {days(30)}) b ON a.object_id < b.object_id AND {near(7, 100)} GROUP BY 1, 2""")
def q3_all_pairs(s, d):
    return ops.all_similar_pairs(_ev(s, d), t.events_days(30), NARROW)


# --- Q3: pairs met at each prune level, by range ---------------------------------

_EVENT_RANGES = (1, 2, 4, 8, 16, 30)
_SHOP_RANGES = (1, 2, 4, 8, 16, 32, 64, 128, 256, 512, 1024, 2048)
#: First day of the shop edges.
SHOP_START = 694_224_000_000_000  # 1992-01-01


def _pairs_sql(src, edges, start, ranges, hours, metres):
    """Counts by definition: days of the range, all pairs, those in near buckets, those the cells leave, those whose distance is computed, similar ones."""
    reach = -(-hours // 24)
    gx = lambda c: f"({c} // 50)"
    dx, dy = f"abs({gx('a.x')} - {gx('b.x')})", f"abs({gx('a.y')} - {gx('b.y')})"
    lower, upper = f"greatest(greatest({dx}, {dy}) - 1, 0) * 50", f"({dx} + {dy} + 2) * 50"
    close = f"abs(a.ts_us - b.ts_us) <= {hours * HOUR}"
    return f"""{src}, f AS (SELECT *, (ts_us - {start}) // {DAY} AS day FROM {edges} WHERE ts_us >= {start}),
      p AS (SELECT greatest(a.day, b.day) AS day, count(*) AS n, count(*) FILTER (WHERE abs(a.ts_us // {DAY} - b.ts_us // {DAY}) <= {reach}) AS near_time,
        count(*) FILTER (WHERE {close} AND {lower} <= {metres}) AS near_cells, count(*) FILTER (WHERE {close} AND {lower} <= {metres} AND {upper} > {metres}) AS measured,
        count(*) FILTER (WHERE {near(hours, metres)}) AS similar_pairs FROM f a JOIN f b ON a.object_id = {ME} AND b.object_id <> {ME} GROUP BY 1),
      r AS (SELECT unnest([{', '.join(map(str, ranges))}]) AS days)
      SELECT CAST(days AS INTEGER) AS days, CAST(coalesce(sum(n), 0) AS BIGINT) AS pairs, CAST(coalesce(sum(near_time), 0) AS BIGINT) AS near_time,
        CAST(coalesce(sum(near_cells), 0) AS BIGINT) AS near_cells, CAST(coalesce(sum(measured), 0) AS BIGINT) AS measured,
        CAST(coalesce(sum(similar_pairs), 0) AS BIGINT) AS similar_pairs FROM r LEFT JOIN p ON p.day < r.days GROUP BY 1"""


@entry("q3_pairs_by_range", _pairs_sql(f"WITH {E}", "e", S0, _EVENT_RANGES, 10, 1000))
def q3_pairs_by_range(s, d):
    return ops.pairs_by_range(_ev(s, d), ME, S0, _EVENT_RANGES, WIDE)


@entry("q3_pairs_by_range_shop", _pairs_sql(f"WITH {SE}", "se", SHOP_START, _SHOP_RANGES, 10, 1000))
def q3_pairs_by_range_shop(s, d):
    return ops.pairs_by_range(t.shop_graph(s, d), ME, SHOP_START, _SHOP_RANGES, WIDE)


_SWEEP = (1, 8, 64, 512, 2048)


@entry("q3_sweep_shop", " UNION ALL ".join(
    f"""SELECT CAST({n} AS INTEGER) AS days, '{level}' AS prune, count(*) AS results, CAST(coalesce(sum(similarity), 0) AS BIGINT) AS pairs FROM (
      WITH {SE} SELECT b.object_id, count(*) AS similarity FROM se a JOIN se b ON a.object_id = {ME} AND b.object_id <> {ME} AND {near(10, 1000)}
      WHERE a.ts_us >= {SHOP_START} AND b.ts_us >= {SHOP_START} AND a.ts_us < {SHOP_START + n * DAY} AND b.ts_us < {SHOP_START + n * DAY} GROUP BY 1)"""
    for n in _SWEEP for level in ("none", "time", "both")))
def q3_sweep_shop(s, d):
    """Similar objects over ranges up to 2048 days, at three prune levels."""
    out, lay = None, stored.shop(s, d)
    for n in _SWEEP:
        for level in ("none", "time", "both"):
            rows = ops.similar_objects(lay, ME, TimeRange.days(SHOP_START, n), WIDE, prune=level).agg(
                F.count(F.lit(1)).alias("results"), F.coalesce(F.sum("similarity"), F.lit(0)).alias("pairs")
            ).select(F.lit(n).cast("int").alias("days"), F.lit(level).alias("prune"), "results", "pairs")
            out = rows if out is None else out.unionByName(rows)
    return out


# --- Q4 --------------------------------------------------------------------


def _q4_sql(kmh, n):
    return f"""WITH {E} SELECT DISTINCT a.object_id FROM (SELECT * FROM e WHERE {days(n)}) a JOIN (SELECT * FROM e WHERE {days(n)}) b
      ON a.object_id = b.object_id AND a.ts_us <= b.ts_us WHERE {fast(kmh)}"""


for _name, _method, _kmh, _n in (
    ("q4_clones_lag", "lag", 120, 1), ("q4_clones_pairs", "pairs", 120, 1), ("q4_clones_stitched", "stitched", 120, 1),
    ("q4_clones_month", "lag", 9000, 30), ("q4_clones_month_stitched", "stitched", 9000, 30),
):

    def _make(method=_method, kmh=_kmh, n=_n):
        return lambda s, d: ops.clone_objects(_ev(s, d), t.events_days(n), kmh, method)

    entry(_name, _q4_sql(_kmh, _n))(_make())

_STEPS = """st AS (SELECT *, lag(ts_us) OVER w AS pt, lag(location_id) OVER w AS pl_, lag(x) OVER w AS px, lag(y) OVER w AS py
  FROM {src} WINDOW w AS (PARTITION BY object_id ORDER BY ts_us, location_id))"""
_DIST = "sqrt(CAST((px - x) * (px - x) + (py - y) * (py - y) AS DOUBLE))"


@entry("q4_evidence", f"""WITH {E}, {_STEPS.format(src=f"(SELECT * FROM e WHERE {days(1)})")}
  SELECT object_id, pt AS ts1_us, pl_ AS loc1, ts_us AS ts2_us, location_id AS loc2, round({_DIST}, 3) AS dist_m,
    round((ts_us - pt) / 1e6, 3) AS seconds FROM st WHERE pt IS NOT NULL AND {_DIST} * 3.6e6 > 120.0 * (ts_us - pt)""")
def q4_evidence(s, d):
    rows = ops.clone_evidence(_ev(s, d), t.events_days(1), 120.0)
    return rows.select("object_id", "ts1_us", "loc1", "ts2_us", "loc2", F.round("dist_m", 3).alias("dist_m"), F.round("seconds", 3).alias("seconds"))


@entry("q4_clones_shop", f"""WITH {SE} SELECT DISTINCT a.object_id FROM se a JOIN se b
  ON a.object_id = b.object_id AND a.ts_us <= b.ts_us WHERE {fast(120)}""")
def q4_clones_shop(s, d):
    return ops.clone_objects(stored.shop(s, d), None, 120.0, "stitched")


# --- stores: each property apart, or all of a sub-partition in one value -----------

_PROPS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
_SHOP_Q4 = f"""WITH {SE} SELECT DISTINCT a.object_id FROM se a JOIN se b
  ON a.object_id = b.object_id AND a.ts_us <= b.ts_us WHERE {fast(120)}"""


def _kept(s, d, write):
    """Shop edges stored by (slot, 400 days), once a session; returns the graph and the path."""
    g = t.shop_graph(s, d)

    def make(path):
        write(kt_columns(g.edges, g.spec), path, row_key(F.lit("B"), "slot", F.expr("tru div 400"), "worker"), _PROPS)
        return path

    return g, stored.once(s, d, write.__name__, make)


def _clones_of(g, edges):
    return ops.clone_objects(TraceGraph(g.locations, edges, None, g.spec), None, 120.0, "stitched")


@entry("q4_store_split", _SHOP_Q4)
def q4_store_split(s, d):
    g, path = _kept(s, d, store.write_split)
    return _clones_of(g, store.read_split(s, path, ["object_id", "ts_us", "location_id"]).drop("row_key"))


@entry("q4_store_packed", _SHOP_Q4)
def q4_store_packed(s, d):
    g, path = _kept(s, d, store.write_packed)
    return _clones_of(g, store.read_packed(s, path, "row_key string, object_id long, ts_us long, location_id long").drop("row_key"))


_COLUMNS = ["object_id", "ts_us", "location_id", *_PROPS]
_NUMBER = {"l_returnflag": "ascii(l_returnflag)", "l_linestatus": "ascii(l_linestatus)"}


def _sums(read):
    """properties, edges, clones and the sums of what was read, for 3 to 9 columns: Q4 with more and more properties beside it."""
    out = None
    for k in range(3, 10):
        rows = read(_COLUMNS[:k])
        total = F.lit(0.0)
        for c in _COLUMNS[3:k]:
            total = total + F.expr(_NUMBER.get(c, c)).cast("double")
        sums = rows.agg(F.count(F.lit(1)).alias("edges"), F.round(F.sum(total), 2).alias("total")).select(F.lit(k).cast("int").alias("properties"), "edges", "total")
        out = sums if out is None else out.unionByName(sums)
    return out


_SUMS = f"WITH {SE} " + " UNION ALL ".join(
    f"SELECT CAST({k} AS INTEGER) AS properties, count(*) AS edges, round(sum({' + '.join(['0.0', *[_NUMBER.get(c, c) for c in _COLUMNS[3:k]]])}), 2) AS total FROM se"
    for k in range(3, 10))


@entry("store_split_by_properties", _SUMS)
def store_split_by_properties(s, d):
    _, path = _kept(s, d, store.write_split)
    return _sums(lambda columns: store.read_split(s, path, columns))


@entry("store_packed_by_properties", _SUMS)
def store_packed_by_properties(s, d):
    g, path = _kept(s, d, store.write_packed)
    types = dict(t.shop_edges(s, d).dtypes)
    return _sums(lambda columns: store.read_packed(s, path, ", ".join(["row_key string", *[f"{c} {types[c]}" for c in columns]])))


@entry("op_codec_roundtrip", " UNION ALL ".join(
    f"SELECT '{c}' AS codec, count(*) AS edges, CAST(sum(l_orderkey * 8 + l_linenumber) AS BIGINT) AS ids FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
    for c in store.CODECS))
def op_codec_roundtrip(s, d):
    edges, out = t.shop_edges(s, d), None
    for codec in store.CODECS:
        path = scratch(s, f"codec-{codec}")
        write_edges(edges, path, compression=codec)
        sums = s.read.schema(edges.schema).parquet(path).agg(F.count(F.lit(1)).alias("edges"), F.sum("edge_id").alias("ids"))
        rows = sums.select(F.lit(codec).alias("codec"), "edges", "ids")
        out = rows if out is None else out.unionByName(rows)
    return out


# --- distribution and replicas ----------------------------------------------

_MAP10 = 10


def _mapping(s, spec: GraphSpec, b=None):
    weights = mp.collect_weights(mp.region_weights(t.event_places(s), spec))
    return mp.map_regions_bounded(weights, spec.n_workers, b, spec)


_W = f"w AS (SELECT {zcode('x', 'y')} AS region, count(*) AS weight FROM pl GROUP BY 1)"


def _rec(m):
    """Recursive form of the sequential cut along the Z-curve."""
    return f"""o AS (SELECT region, weight, row_number() OVER (ORDER BY region) AS rn, sum(weight) OVER () AS total FROM w),
      r AS (SELECT rn, region, weight, 0 AS worker, CAST(weight AS HUGEINT) AS held FROM o WHERE rn = 1 UNION ALL
        SELECT o.rn, o.region, o.weight, CASE WHEN r.held * {m} >= o.total AND r.worker < {m - 1} THEN r.worker + 1 ELSE r.worker END,
          CASE WHEN r.held * {m} >= o.total AND r.worker < {m - 1} THEN CAST(o.weight AS HUGEINT) ELSE r.held + o.weight END
        FROM r JOIN o ON o.rn = r.rn + 1)"""


_WORKER_K = f"CAST({slot('object_id', 6)} % 10 AS INTEGER)"


@entry("map_region_weights", f"WITH {PL}, {_W} SELECT region, weight FROM w")
def map_region_weights(s, d):
    return mp.region_weights(t.event_places(s), t.EVENTS_SPEC)


@entry("map_region_weights_edges", f"""WITH {E} SELECT {zcode('x', 'y')} AS region, count(*) AS weight FROM e GROUP BY 1""")
def map_region_weights_edges(s, d):
    return mp.region_weights(t.event_places(s), t.EVENTS_SPEC, t.event_edges(s, d))


for _m in (4, 10):

    def _unbounded(m=_m):
        def run(s, d):
            spec = t.EVENTS_SPEC.with_(n_workers=m)
            return _mapping(s, spec).df(s).select("region", "worker", "weight")

        return run

    entry(f"map_unbounded_m{_m}", f"WITH RECURSIVE {PL}, {_W}, {_rec(_m)} SELECT region, worker, weight FROM r")(_unbounded())


@entry("map_prefix", f"""WITH {PL}, {_W} SELECT region, weight, CAST(least(floor(
  coalesce(sum(weight) OVER (ORDER BY region ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 10 / sum(weight) OVER ()), 9) AS INTEGER) AS worker FROM w""")
def map_prefix(s, d):
    return mp.map_regions_prefix(mp.region_weights(t.event_places(s), t.EVENTS_SPEC), 10)


def _greedy(b, m):
    """Recursive form of the bounded mapping: units by weight and code, each to the least loaded worker."""
    zeros = "[" + ", ".join(["0"] * m) + "]"
    return f"""un AS (SELECT {zcode('x', 'y', 1000 * b)} AS unit, count(*) AS w FROM pl GROUP BY 1),
      oo AS (SELECT unit, w, row_number() OVER (ORDER BY w DESC, unit) AS rn FROM un),
      gr AS (SELECT CAST(0 AS BIGINT) AS rn, CAST(-1 AS BIGINT) AS unit, 0 AS worker, CAST({zeros} AS BIGINT[]) AS loads UNION ALL
        SELECT oo.rn, oo.unit, CAST(list_position(loads, list_min(loads)) - 1 AS INTEGER),
          list_transform(loads, lambda x, i: CASE WHEN i = list_position(loads, list_min(loads)) THEN x + oo.w ELSE x END) FROM gr JOIN oo ON oo.rn = gr.rn + 1),
      mb AS (SELECT region, unit, worker, weight FROM (SELECT {zcode('x', 'y')} AS region, {zcode('x', 'y', 1000 * b)} AS unit, count(*) AS weight FROM pl GROUP BY 1, 2) JOIN gr USING (unit))"""


for _b in (1, 2, 4, 8, 16):

    def _bounded(b=_b):
        return lambda s, d: _mapping(s, t.EVENTS_SPEC, b).df(s)

    entry(f"map_bounded_b{_b}", f"WITH RECURSIVE {PL}, {_greedy(_b, 10)} SELECT region, unit, worker, weight FROM mb")(_bounded())


@entry("map_spatial_factor", " UNION ALL ".join(
    f"SELECT CAST({b} AS INTEGER) AS b, round((1 - 1.0 / (2 * {b})) * (1 - 1.0 / (2 * {b})), 6) AS factor" for b in (2, 4, 8)))
def map_spatial_factor(s, d):
    return s.createDataFrame([(b, round(mp.spatial_factor(b, 1000, 1000), 6)) for b in (2, 4, 8)], "b int, factor double")


@entry("map_spatial_factor_measured", f"""WITH {PL} SELECT count(*) AS pairs,
  count(*) FILTER (WHERE a.x // 8000 = b.x // 8000 AND a.y // 8000 = b.y // 8000) AS same_unit FROM pl a JOIN pl b ON a.location_id < b.location_id
  AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 4000000""")
def map_spatial_factor_measured(s, d):
    return mp.empirical_spatial_factor(t.event_places(s), 8, 2000, t.EVENTS_SPEC)


_TOUCHED = f"""v AS (SELECT DISTINCT x, y FROM e WHERE object_id = {ME} AND {days(7)}),
  tr AS (SELECT DISTINCT {zcode('x + dx * 1000', 'y + dy * 1000')} AS region FROM v, (SELECT unnest([-1, 0, 1]) AS dx), (SELECT unnest([-1, 0, 1]) AS dy))"""


def _accessed_sql(b):
    made = f"{_W}, {_rec(_MAP10)}, mp AS (SELECT region, worker FROM r)" if b is None else f"{_greedy(b, 10)}, mp AS (SELECT region, worker FROM mb)"
    name = "infinity" if b is None else b
    return f"""SELECT * FROM (WITH RECURSIVE {E}, {_TOUCHED}, {made}
      SELECT '{name}' AS b, CAST(w AS INTEGER) AS worker, count(mp.region) AS regions FROM range(10) k(w) LEFT JOIN (mp JOIN tr USING (region)) ON mp.worker = w GROUP BY 1, 2)"""


@entry("map_accessed_regions", " UNION ALL ".join(_accessed_sql(b) for b in (8, 4, 2, None)))
def map_accessed_regions(s, d):
    """How many of a query's regions each worker serves, for four mappings."""
    regions = ops.visited_regions(_ev(s, d), ME, t.events_days(7), 1000)
    out = None
    for b in (8, 4, 2, None):
        rows = mp.accessed_regions(_mapping(s, t.EVENTS_SPEC, b).df(s), regions, _MAP10).select(F.lit("infinity" if b is None else str(b)).alias("b"), "worker", "regions")
        out = rows if out is None else out.unionByName(rows)
    return out


@entry("dist_kt_workers", f"WITH {EV} SELECT {_WORKER_K} AS worker, count(*) AS rows FROM ev GROUP BY 1")
def dist_kt_workers(s, d):
    return kt_columns(t.event_edges(s, d), t.EVENTS_SPEC).groupBy("worker").agg(F.count(F.lit(1)).alias("rows"))


@entry("dist_st_workers", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)} SELECT r.worker, count(*) AS rows FROM e JOIN r ON r.region = {zcode('x', 'y')} GROUP BY 1""")
def dist_st_workers(s, d):
    g = t.event_graph(s, d)
    return st_columns(g.edges, g.locations, g.spec, _mapping(s, g.spec).df(s)).groupBy("worker").agg(F.count(F.lit(1)).alias("rows"))


@entry("dist_slots_p14", f"WITH {EV} SELECT {slot('object_id', 14)} AS slot, count(*) AS rows FROM ev GROUP BY 1")
def dist_slots_p14(s, d):
    return t.event_edges(s, d).groupBy(slot_of("object_id", 14).alias("slot")).agg(F.count(F.lit(1)).alias("rows"))


@entry("dist_object_copies", f"""WITH o AS (SELECT c_custkey AS object_id, {slot('c_custkey', 6)} AS slot FROM customer)
  SELECT CAST((slot + c) % 10 AS INTEGER) AS worker, count(*) AS objects FROM o, range(3) k(c) GROUP BY 1""")
def dist_object_copies(s, d):
    objects = t.read(s, d, "customer").select(F.col("c_custkey").alias("object_id"))
    return object_placement(objects, 6, 10).groupBy("worker").agg(F.count(F.lit(1)).alias("objects"))


_PLACED = f"""p AS (SELECT e.edge_id, r.worker AS w_s, {_WORKER_K} AS w_k FROM e JOIN r ON r.region = {zcode('x', 'y')})"""


def _placed(s, d):
    g = t.event_graph(s, d)
    return with_workers(g.edges, g.locations, _mapping(s, g.spec).df(s), g.spec)


@entry("replica_collisions", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)}, {_PLACED}
  SELECT count(*) AS edges, count(*) FILTER (WHERE w_s = w_k) AS collisions FROM p""")
def replica_collisions(s, d):
    return _placed(s, d).agg(F.count(F.lit(1)).alias("edges"), F.count(F.when(F.col("w_s") == F.col("w_k"), 1)).alias("collisions"))


@entry("replica_placement", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)}, {_PLACED}
  SELECT copy, worker, count(*) AS edges FROM (SELECT 's' AS copy, w_s AS worker FROM p UNION ALL SELECT 'k', w_k FROM p
    UNION ALL SELECT 'f', CAST((w_s + 1) % 10 AS INTEGER) FROM p WHERE w_s = w_k) GROUP BY 1, 2""")
def replica_placement(s, d):
    return placement(_placed(s, d), 10).groupBy("copy", "worker").agg(F.count(F.lit(1)).alias("edges"))


@entry("replica_recovery", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)}, {_PLACED}
  SELECT count(*) AS rebuilt, CAST(0 AS BIGINT) AS lost FROM p WHERE w_s = 3 OR w_k = 3 OR (w_s = w_k AND (w_s + 1) % 10 = 3)""")
def replica_recovery(s, d):
    rebuilt, gone = recover_worker(placement(_placed(s, d), 10), 3)
    return rebuilt.agg(F.count(F.lit(1)).alias("rebuilt")).join(gone.agg(F.count(F.lit(1)).alias("lost")), F.lit(True))


# --- ingestion, batch form of the rounds ---------------------------------------


@entry("ingest_round_counts", f"""WITH {EV} SELECT ts_us // {5 * DAY} AS round, count(*) AS edges, count(DISTINCT ts_us // {DAY}) AS buckets FROM ev GROUP BY 1""")
def ingest_round_counts(s, d):
    e = t.event_edges(s, d)
    return e.groupBy(F.expr(f"ts_us div {5 * DAY}").alias("round")).agg(
        F.count(F.lit(1)).alias("edges"), F.countDistinct(F.expr(f"ts_us div {DAY}")).alias("buckets")
    )


def _ingested(s, d):
    """Events brought in by rounds of ten days, each micro-batch twice; every 97th edge comes after all others and is merged late."""

    def make(path):
        spec = t.EVENTS_SPEC
        store_ = IngestStore(s, path, spec, t.event_places(s), _mapping(s, spec).df(s), m=10, groups=stored.KT_GROUPS)
        e = t.event_edges(s, d).select("edge_id", "object_id", "ts_us", "location_id")
        for i in range(3):
            lo = S0 + 10 * i * DAY
            batch = e.where(f"edge_id % 97 <> 0 and ts_us >= {lo} and ts_us < {lo + 10 * DAY}")
            for _ in range(2):  # the second time is a replay: it changes nothing, whether the round has closed or not
                ingest_batch(store_, batch, i)
        store_.close_all()
        store_.stage(e.where("edge_id % 97 = 0"), 6)
        store_.merge_late()
        return store_

    return stored.once(s, d, "ingested", make)


@entry("ingest_rounds_kt", f"""WITH {EV} SELECT ts_us // {DAY} AS tru, {slot('object_id', 6)} AS slot, count(*) AS edges, CAST(sum(edge_id) AS BIGINT) AS ids FROM ev GROUP BY 1, 2""")
def ingest_rounds_kt(s, d):
    kt = _ingested(s, d).layout("kt")
    return kt.groupBy(F.col("tru").cast("bigint").alias("tru"), "slot").agg(F.count(F.lit(1)).alias("edges"), F.sum("edge_id").alias("ids"))


@entry("ingest_rounds_st", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)} SELECT ts_us // {DAY} AS tru, {zcode('x', 'y')} AS region, r.worker, count(*) AS edges, CAST(sum(edge_id) AS BIGINT) AS ids
  FROM e JOIN r ON r.region = {zcode('x', 'y')} GROUP BY 1, 2, 3""")
def ingest_rounds_st(s, d):
    st = _ingested(s, d).layout("st")
    return st.groupBy(F.col("tru").cast("bigint").alias("tru"), "region", "worker").agg(F.count(F.lit(1)).alias("edges"), F.sum("edge_id").alias("ids"))


@entry("ingest_rounds_extra", f"""WITH RECURSIVE {E}, {_W}, {_rec(_MAP10)}, {_PLACED} SELECT CAST((w_s + 1) % 10 AS INTEGER) AS worker, count(*) AS edges, CAST(sum(edge_id) AS BIGINT) AS ids
  FROM p WHERE w_s = w_k GROUP BY 1""")
def ingest_rounds_extra(s, d):
    return _ingested(s, d).layout("extra").groupBy("worker").agg(F.count(F.lit(1)).alias("edges"), F.sum("edge_id").alias("ids"))


@entry("ingest_rounds_log", f"""WITH {EV} SELECT ts_us // {10 * DAY} AS round, count(*) AS edges FROM ev GROUP BY 1""")
def ingest_rounds_log(s, d):
    """What the commit files say of each round."""
    rows = [(c.round_id, c.edges) for c in _ingested(s, d).commits().values()]
    return s.createDataFrame(rows, "round long, edges long")


@entry("layout_catalog_rows", f"""WITH {E} SELECT 'kt' AS method, ts_us // {DAY} AS tru, CAST({slot('object_id', 6)} * {stored.KT_GROUPS} // 64 AS INTEGER) AS grp, count(*) AS rows FROM e GROUP BY 1, 2, 3
  UNION ALL SELECT 'st', ts_us // {DAY}, {slot(zcode('x', 'y', 8000), 5)}, count(*) FROM e GROUP BY 1, 2, 3""")
def layout_catalog_rows(s, d):
    _ev(s, d)
    paths = stored.PATHS[d, "events"]
    both = layout_catalog(s, paths["kt"], "kt", "slot_group").unionByName(layout_catalog(s, paths["st"], "st", "unit_group"))
    return both.select("method", F.col("tru").cast("bigint").alias("tru"), "grp", "rows")


# --- baselines, each over its own stored table -----------------------------------------

for _key in ("relational", "scan", "zindex"):

    def _b1(n, key=_key):
        return lambda s, d: stored.baseline(s, d, key).q1(ME, t.events_days(n))

    def _b2(th, key=_key):
        return lambda s, d: stored.baseline(s, d, key).q2(7, 1, t.events_days(30), th)

    def _b3(n, th, key=_key):
        return lambda s, d: stored.baseline(s, d, key).q3(ME, t.events_days(n), th)

    def _b4(n, kmh, key=_key):
        return lambda s, d: stored.baseline(s, d, key).q4(t.events_days(n), float(kmh))

    entry(f"base_{_key}_q1", _Q1 + days(7))(_b1(7))
    entry(f"base_{_key}_q2", _q2_sql(7, 1, 10, 1000))(_b2(WIDE))
    entry(f"base_{_key}_q2_7h100m", _q2_sql(7, 1, 7, 100))(_b2(NARROW))
    entry(f"base_{_key}_q3", _q3_sql(7, 100, 7))(_b3(7, NARROW))
    entry(f"base_{_key}_q4", _q4_sql(120, 1))(_b4(1, 120))
    for _n in (1, 30):
        entry(f"base_{_key}_q1_{_n}d", _Q1 + days(_n))(_b1(_n))
        entry(f"base_{_key}_q3_{_n}d", _q3_sql(7, 100, _n))(_b3(_n, NARROW))
    for _n in (1, 7, 30):
        entry(f"base_{_key}_q3_10h1000m_{_n}d", _q3_sql(10, 1000, _n))(_b3(_n, WIDE))
    for _n in (7, 30):
        entry(f"base_{_key}_q4_{_n}d", _q4_sql(9000, _n))(_b4(_n, 9000))
for _n in (1, 30):
    _q3(f"q3_similar_10h1000m_{_n}d", "kt+st", "cell", WIDE, _n, 10, 1000)


@entry("q4_clones_week", _q4_sql(9000, 7))
def q4_clones_week(s, d):
    return ops.clone_objects(_ev(s, d), t.events_days(7), 9000.0)


@entry("base_graph_q1", _Q1 + days(30))
def base_graph_q1(s, d):
    return stored.baseline(s, d, "graph").q1(ME, t.events_days(30))


@entry("base_graph_q2", _q2_sql(7, 1, 10, 1000))
def base_graph_q2(s, d):
    return stored.baseline(s, d, "graph").q2(7, 1, t.events_days(30), WIDE)


@entry("base_random_workers", f"WITH {EV} SELECT CAST({slot('(edge_id * 2)', 20)} % 10 AS INTEGER) AS worker, count(*) AS rows FROM ev GROUP BY 1")
def base_random_workers(s, d):
    return base.random_layout(t.event_edges(s, d), 10).groupBy("worker").agg(F.count(F.lit(1)).alias("rows"))


_AT = "CAST(({c} * 48271) % 10 AS INTEGER)"


@entry("cut_edges_vertex", f"""WITH {EV} SELECT count(*) AS edges, count(*) FILTER (WHERE
  {_AT.format(c='object_id')} <> {_AT.format(c='location_id')}) AS cut FROM ev""")
def cut_edges_vertex(s, d):
    e = t.event_edges(s, d)
    return base.cut_edges(e, *base.vertex_partition(e, 10))


@entry("cut_edges_greedy")
def cut_edges_greedy(s, d):
    """Edges cut by the partitioning that moves vertices towards their neighbours, beside the hashed one."""
    e = t.event_edges(s, d)
    hashed = base.cut_edges(e, *base.vertex_partition(e, 10)).select(F.lit("hash").alias("method"), "edges", "cut")
    return hashed.unionByName(base.cut_edges(e, *base.vertex_partition_greedy(e, 10)).select(F.lit("greedy").alias("method"), "edges", "cut"))


@entry("ghosts_edge", f"""WITH {EV}, p AS (SELECT *, {_AT.format(c='edge_id')} AS worker FROM ev)
  SELECT 'object_id' AS side, count(*) AS vertices, CAST(sum(k) AS BIGINT) AS copies, CAST(sum(k - 1) AS BIGINT) AS ghosts
    FROM (SELECT object_id, count(DISTINCT worker) AS k FROM p GROUP BY 1)
  UNION ALL SELECT 'location_id', count(*), CAST(sum(k) AS BIGINT), CAST(sum(k - 1) AS BIGINT) FROM (SELECT location_id, count(DISTINCT worker) AS k FROM p GROUP BY 1)""")
def ghosts_edge(s, d):
    return base.ghost_edges(base.edge_partition(t.event_edges(s, d), 10))


# --- generator ------------------------------------------------------------------


def _generated(s, d):
    customers = t.read(s, d, "customer").select(F.col("c_custkey").alias("object_id"), F.col("c_nationkey").alias("home"))
    return generate_edges(customers, t.shop_places(s, d).select("area", "location_id"))


_GEN = """g AS (SELECT c_custkey AS object_id, w AS week FROM customer, range(114) k(w)
  WHERE (48271 * c_custkey + 69621 * w + 12345) % 1000 < CASE WHEN c_custkey % 10 < 4 THEN 800 ELSE 200 END)"""


@entry("gen_edge_counts", f"WITH {_GEN} SELECT week, count(*) AS edges FROM g GROUP BY 1")
def gen_edge_counts(s, d):
    return _generated(s, d).where("not is_clone").groupBy("week").agg(F.count(F.lit(1)).alias("edges"))


@entry("gen_planted_clones", f"WITH {_GEN} SELECT object_id FROM g WHERE object_id % 97 = 0 AND week = object_id % 114")
def gen_planted_clones(s, d):
    return _generated(s, d).where("is_clone").select("object_id")


# --- cost model and capacity -------------------------------------------------------

#: query, plan, share of the bytes, shuffle factor, sub-partitions, parallelism, and a first Q1 on KT if combined
_COSTS = (
    ("Q1", "st", "1.0", "0.0", "1048576", "10", 0), ("Q1", "kt", "1.0/16384", "0.0", "1", "1", 0),
    ("Q2", "st", "1.0", "0.0", "1048576", "10", 0), ("Q2", "kt", "2.0/16384", "0.0", "2", "2", 0),
    ("Q3", "st", "1.0", "0.1", "1048576", "10", 0), ("Q3", "kt", "1.0", "0.1", "16384", "10", 0),
    ("Q3", "kt+st", "100.0/1048576", "0.02", "100", "10", 1),
    ("Q4", "st", "1.0", "0.1", "1048576", "10", 0), ("Q4", "kt", "1.0", "0.0", "16384", "10", 0),
)


def _cost_sql():
    rows = []
    for q, p, share, f, n, par, first in _COSTS:
        r = f"0.01 * 950.0 * {share} / (0.8 * {par})" + (" + 0.01 * 950.0 / 16384 / 0.8" if first else "")
        a = f"0.0001 * {n} / (0.8 * {par})" + (" + 0.0001 / 0.8" if first else "")
        rows.append(f"SELECT '{q}' AS query, '{p}' AS plan, CAST({r} AS DOUBLE) AS r, CAST({a} AS DOUBLE) AS i, CAST({f} * 950.0 * {share} / (0.8 * {par}) AS DOUBLE) AS f")
    return " UNION ALL ".join(rows)


@entry("cost_table", f"SELECT query, plan, round(r, 3) AS read, round(i, 3) AS invoke, round(f, 3) AS shuffle, round(r + i + f, 3) AS total FROM ({_cost_sql()})")
def cost_table(s, d):
    rows = cm.cost_table(s, cm.CostParams(), 1, 100)
    return rows.select("query", "plan", *[F.round(c, 3).alias(c) for c in ("read", "invoke", "shuffle", "total")])


@entry("cost_choice", f"SELECT query, arg_min(plan, r + i + f) AS plan FROM ({_cost_sql()}) GROUP BY query")
def cost_choice(s, d):
    spec = GraphSpec()
    day = TimeRange.days(S0, 1)
    g = TraceGraph(None, None, None, spec)
    picks = [(q, choose_plan(QuerySpec(q, (ME,), day), g, cm.CostParams(), 100).plan) for q in cm.QUERIES]
    return s.createDataFrame(picks, "query string, plan string")


@entry("cost_choice_stored", "SELECT * FROM (VALUES ('Q1', 'kt'), ('Q2', 'kt'), ('Q3', 'kt+st'), ('Q4', 'kt')) v(query, plan)")
def cost_choice_stored(s, d):
    """The choice from the stored layouts' own statistics: bytes of the range by bucket, sub-partitions, regions that the trace touches."""
    lay = _ev(s, d)
    paths = stored.PATHS[d, "events"]
    stats = LayoutStatistics.of(layout_catalog(s, paths["kt"], "kt", "slot_group").unionByName(layout_catalog(s, paths["st"], "st", "unit_group")))
    picks = [(q, choose_plan(QuerySpec(q, (ME, 1), t.events_days(7)), lay, statistics=stats).plan) for q in cm.QUERIES]
    return s.createDataFrame(picks, "query string, plan string")


@entry("cost_break_even", """SELECT round((950.0 * 0.11 / 8 + 0.0001 * 16384 / 8 - 0.01 * 950 / 16384 / 0.8 - 0.0001 / 0.8) * 8
  / (0.03 * 950.0 / 1048576 + 0.0001), 0) AS regions""")
def cost_break_even(s, d):
    return s.createDataFrame([(float(round(cm.break_even_regions(1, cm.CostParams()))),)], "regions double")


@entry("capacity_plan", """SELECT measure, CAST(value AS DOUBLE) AS value FROM (VALUES ('object_tb', 1.0), ('location_gb', 1.0), ('edge_pb', 2.4), ('stored_pb', 7.2),
  ('machines', 720.0), ('day_tb', 24.0), ('rate_mb_s', 277.7778), ('rate_mib_s', 291.2711), ('ingest_workers', 15.0)) v(measure, value)""")
def capacity_plan(s, d):
    return cap.capacity_table(s)


# --- parcels --------------------------------------------------------------------------

_NOW = 883_612_800_000_000  # 1998-01-01


@entry("parcel_trace", f"WITH {PC} SELECT object_id, ts_us, location_id FROM pc WHERE object_id = 7")
def parcel_trace(s, d):
    return ops.object_trace(t.parcel_graph(s, d), 7, None)


@entry("parcel_status", f"""WITH {PC} SELECT object_id, max(ts_us) AS ts_us, arg_max(location_id, (ts_us, location_id)) AS location_id,
  count(*) AS scans FROM pc WHERE ts_us <= {_NOW} GROUP BY 1""")
def parcel_status(s, d):
    return ops.status_at(t.parcel_graph(s, d), _NOW)


@entry("parcel_silent", f"""WITH {PC} SELECT object_id, max(ts_us) AS ts_us FROM pc WHERE ts_us <= {_NOW} GROUP BY 1 HAVING max(ts_us) < {_NOW - 365 * DAY}""")
def parcel_silent(s, d):
    return ops.status_at(t.parcel_graph(s, d), _NOW).where(F.col("ts_us") < _NOW - 365 * DAY).select("object_id", "ts_us")


# --- relational composition -------------------------------------------------------------

_SHOP_CLONES = f"""c AS (SELECT DISTINCT a.object_id FROM se a JOIN se b ON a.object_id = b.object_id AND a.ts_us <= b.ts_us WHERE {fast(120)})"""


def _shop_clones(s, d):
    return ops.clone_objects(stored.shop(s, d), None, 120.0, "stitched")


@entry("clones_by_segment", f"WITH {SE}, {_SHOP_CLONES} SELECT c_mktsegment, count(*) AS clones FROM c JOIN customer ON c_custkey = object_id GROUP BY 1")
def clones_by_segment(s, d):
    ids = _shop_clones(s, d)
    c = t.read(s, d, "customer")
    return c.join(ids, c["c_custkey"] == ids["object_id"], "left_semi").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("clones"))


@entry("clones_revenue_rollup", f"""WITH {SE}, {_SHOP_CLONES} SELECT n_name, c_mktsegment, count(*) AS orders, round(sum(o_totalprice), 2) AS revenue
  FROM c JOIN customer ON c_custkey = object_id JOIN nation ON n_nationkey = c_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY ROLLUP (n_name, c_mktsegment)""")
def clones_revenue_rollup(s, d):
    ids = _shop_clones(s, d)
    c, n, o = (t.read(s, d, x) for x in ("customer", "nation", "orders"))
    flagged = c.join(ids, c["c_custkey"] == ids["object_id"], "left_semi")
    rows = flagged.join(n, n["n_nationkey"] == flagged["c_nationkey"]).join(o, o["o_custkey"] == flagged["c_custkey"])
    return rows.rollup("n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("revenue"))


# --- groups ---------------------------------------------------------------------------


@entry("group_loads", f"""WITH {SO} SELECT c_mktsegment AS group_id, count(DISTINCT c_custkey) AS objects, count(object_id) AS edges
  FROM customer LEFT JOIN so ON object_id = c_custkey GROUP BY 1""")
def group_loads(s, d):
    objects = t.read(s, d, "customer").select(F.col("c_custkey").alias("object_id"), "c_mktsegment")
    return grp.group_loads(t.shop_edges(s, d), objects, "c_mktsegment")


@entry("group_loads_brand", """SELECT p_brand AS group_id, count(DISTINCT p_partkey) AS objects, count(l_partkey) AS edges FROM part LEFT JOIN lineitem ON l_partkey = p_partkey GROUP BY 1""")
def group_loads_brand(s, d):
    objects = t.read(s, d, "part").select(F.col("p_partkey").alias("object_id"), "p_brand")
    return grp.group_loads(t.read(s, d, "lineitem").select(F.col("l_partkey").alias("object_id")), objects, "p_brand")


@entry("group_moves")
def group_moves(s, d):
    placed = [(r["group_id"], r["worker"], r["edges"]) for r in grp.group_placement(group_loads_brand(s, d), 7).collect()]
    moves = grp.rebalance(placed, 7)
    return s.createDataFrame([(m.group_id, m.source, m.target, m.load) for m in moves], "group_id string, source int, target int, load long")


# --- generalised space -----------------------------------------------------------------


@entry("vector_similar_objects", """WITH n AS (SELECT count(*) AS c FROM embeddings),
  v AS (SELECT user_id AS object_id, epoch_us(ts) AS ts_us, event_id % c AS location_id FROM events, n),
  m AS (SELECT v.*, embedding FROM v JOIN embeddings ON vec_id = location_id)
  SELECT b.object_id, count(*) AS similarity FROM m a JOIN m b ON a.object_id = 7 AND b.object_id <> 7 AND abs(a.ts_us - b.ts_us) <= 36000000000
  AND round(list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) <= 10 GROUP BY 1""")
def vector_similar_objects(s, d):
    places = t.vector_locations(s, d)
    n = places.count()
    e = t.event_edges(s, d).select("object_id", "ts_us", (F.col("edge_id") % n).alias("location_id"))
    m = e.join(places.select("location_id", "embedding"), "location_id")
    # no grid in a vector space: the trace meets edges in neighbouring time buckets, then by exact distance
    a = m.where(F.col("object_id") == ME).select(F.col("ts_us").alias("ta"), F.col("embedding").alias("va"), F.explode(F.expr(f"sequence(ts_us div {10 * HOUR} - 1, ts_us div {10 * HOUR} + 1)")).alias("tb"))
    b = m.where(F.col("object_id") != ME).withColumn("tb", F.expr(f"ts_us div {10 * HOUR}"))
    pairs = b.join(a, "tb").where((F.abs(F.col("ta") - F.col("ts_us")) <= 10 * HOUR) & (F.round(vector_l2("va", "embedding"), 9) <= 10))
    return pairs.groupBy("object_id").agg(F.count(F.lit(1)).alias("similarity"))


@entry("vector_clones_cosine", """WITH n AS (SELECT count(*) AS c FROM embeddings),
  m AS (SELECT user_id AS object_id, epoch_us(ts) AS ts_us, event_id % c AS location_id, CAST(embedding AS DOUBLE[]) AS v FROM events, n JOIN embeddings ON vec_id = event_id % c)
  SELECT DISTINCT a.object_id FROM m a JOIN m b ON a.object_id = b.object_id AND a.ts_us <= b.ts_us AND a.location_id <> b.location_id
  WHERE (1 - list_cosine_similarity(a.v, b.v)) * 3.6e6 > 1e-4 * (b.ts_us - a.ts_us)""")
def vector_clones_cosine(s, d):
    """Clones under cosine distance, no metric: the all-pairs definition is forced."""
    places = t.vector_locations(s, d)
    n = places.count()
    e = t.event_edges(s, d, t.events_days(30)).withColumn("location_id", F.col("edge_id") % n)
    g = TraceGraph(places.select("location_id", "embedding"), e, None, t.EVENTS_SPEC)
    return ops.clone_objects(g, t.events_days(30), 1e-4, metric="cosine")


@entry("vector_near_places", """SELECT a.vec_id AS a, b.vec_id AS b, round(list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS dist FROM embeddings a JOIN embeddings b
  ON a.vec_id % 100 = 0 AND b.vec_id <> a.vec_id WHERE round(list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) <= 9""")
def vector_near_places(s, d):
    """Query vectors: those whose id is divisible by 100, against all."""
    v = t.vector_locations(s, d)
    q = v.where("location_id % 100 = 0").select(F.col("location_id").alias("a"), F.col("embedding").alias("ea"))
    dist = F.round(METRICS["vector_l2"].distance("ea", "embedding"), 6)
    return v.join(small(q), F.col("a") != F.col("location_id")).select("a", F.col("location_id").alias("b"), dist.alias("dist")).where("dist <= 9")


# --- ids for relational queries, updated locations -------------------------------------------


@entry("index_vertex_ids", f"""WITH {SE}, {_SHOP_CLONES} SELECT nation.n_name, count(*) AS customers FROM customer JOIN nation ON n_nationkey = c_nationkey
  WHERE c_custkey IN (SELECT object_id FROM c) GROUP BY 1""")
def index_vertex_ids(s, d):
    """The graph as an index: ids of the objects that a query flags, joined with relational tables."""
    ids = idx.vertex_ids(ops.clone_objects(stored.shop(s, d), None, 120.0, "stitched"), "object_id", "c_custkey")
    c, n = t.read(s, d, "customer"), t.read(s, d, "nation")
    return c.join(ids, "c_custkey", "left_semi").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@entry("index_edge_ids", f"""WITH {EV} SELECT event_type, count(*) AS events, round(sum(value), 4) AS total FROM ev WHERE object_id = {ME} AND {days(7)} GROUP BY 1""")
def index_edge_ids(s, d):
    """Ids of the edges of a trace, joined with the event table."""
    ids = idx.edge_ids(_ev(s, d), [ME], t.events_days(7), "event_id")
    ev = t.read(s, d, "events")
    return ev.join(ids, "event_id", "left_semi").groupBy("event_type").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("value"), 4).alias("total"))


@entry("locations_refreshed", f"""WITH {PL}, moved AS (SELECT location_id, k, t, area, x + CASE WHEN location_id % 50 = 0 THEN 5000 ELSE 0 END AS x, y FROM pl UNION ALL SELECT 9999, 0, 0, 0, 1000, 1000)
  SELECT {zcode('x', 'y')} AS region, count(*) AS weight FROM moved GROUP BY 1""")
def locations_refreshed(s, d):
    """Moved and new locations reach every holder of the table: a new version of it, and the weights made from it."""
    g = t.event_graph(s, d)
    moved = g.locations.where("location_id % 50 = 0").withColumn("x", F.col("x") + 5000)
    new = s.createDataFrame([(9999, 1000, 1000, 0)], "location_id long, x long, y long, area int")
    return mp.region_weights(loc.refresh_locations(g, moved.unionByName(new), scratch(s, "locations")).locations, g.spec)
