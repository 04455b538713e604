"""Operators that users of the trace methods need around them, one entry each."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from tracegraph.functions import sql as sqlfuncs
from tracegraph.functions.geometry import METRICS, cell, grid_bounds, region_of, sq_dist, vector_cosine, vector_l2, z_code
from tracegraph.functions.slots import slot_of
from tracegraph.model import Thresholds, validate_graph
from tracegraph.operators.layouts import located, parse_row_key, row_key
from tracegraph.operators.prune import distance_join, interval_join, near
from tracegraph.operators.queries import status_at
from tracegraph.sources import tables as t

from .entries import DAY, EV, HOUR, PC, PL, S0, SE, SO, E, days, entry, slot, zcode


def count_rows():
    return F.count(F.lit(1))



def _edges(s, d):
    g = t.event_graph(s, d)
    return located(g.edges, g.locations.select("location_id", "x", "y"))


def _with_area(s, d):
    g = t.event_graph(s, d)
    return g.edges.join(F.broadcast(g.locations), "location_id")  # 500 places by construction


# --- scans, integrity, degrees ---------------------------------------------------------


@entry("op_scan_edges_f1", f"WITH {EV} SELECT count(*) AS edges, CAST(sum(edge_id) AS BIGINT) AS ids, min(ts_us) AS first_us, max(ts_us) AS last_us FROM ev")
def op_scan_edges_f1(s, d):
    return t.event_edges(s, d).agg(count_rows().alias("edges"), F.sum("edge_id").alias("ids"), F.min("ts_us").alias("first_us"), F.max("ts_us").alias("last_us"))


@entry("op_scan_edges_f2", f"WITH {SO} SELECT count(*) AS edges, CAST(sum(object_id) AS BIGINT) AS ids, min(ts_us) AS first_us, max(ts_us) AS last_us FROM so")
def op_scan_edges_f2(s, d):
    return t.shop_edges(s, d).agg(count_rows().alias("edges"), F.sum("object_id").alias("ids"), F.min("ts_us").alias("first_us"), F.max("ts_us").alias("last_us"))


_CHECKS = ("duplicate_location", "dangling_location", "null_in_edge", "location_off_grid", "duplicate_object", "dangling_object")
_ZERO = " UNION ALL ".join(f"SELECT '{c}' AS \"check\", CAST(0 AS BIGINT) AS violations" for c in _CHECKS)


@entry("op_graph_integrity_f1", _ZERO)
def op_graph_integrity_f1(s, d):
    return validate_graph(t.event_graph(s, d))


@entry("op_graph_integrity_f2", _ZERO)
def op_graph_integrity_f2(s, d):
    return validate_graph(t.shop_graph(s, d))


@entry("op_degree_objects", f"WITH {EV} SELECT object_id, count(*) AS degree FROM ev GROUP BY 1")
def op_degree_objects(s, d):
    return t.event_edges(s, d).groupBy("object_id").agg(count_rows().alias("degree"))


@entry("op_degree_locations", f"WITH {E} SELECT pl.location_id, count(ev.edge_id) AS degree FROM pl LEFT JOIN ev USING (location_id) GROUP BY 1")
def op_degree_locations(s, d):
    per = t.event_edges(s, d).groupBy("location_id").agg(count_rows().alias("n"))
    return t.event_places(s).join(per, "location_id", "left").select("location_id", F.coalesce("n", F.lit(0)).alias("degree"))


@entry("op_filter_box", f"WITH {E} SELECT edge_id, object_id FROM e WHERE {days(7)} AND x BETWEEN 100000 AND 330000 AND y BETWEEN 100000 AND 120000")
def op_filter_box(s, d):
    e = t.event_edges(s, d, t.events_days(7))
    e = located(e, t.event_places(s)).where((F.col("ts_us") >= S0) & (F.col("ts_us") < S0 + 7 * DAY))
    return e.where(F.col("x").between(100000, 330000) & F.col("y").between(100000, 120000)).select("edge_id", "object_id")


@entry("op_filter_property", f"WITH {EV} SELECT edge_id, object_id, value FROM ev WHERE event_type = 'purchase' AND value > 100")
def op_filter_property(s, d):
    return t.event_edges(s, d).where((F.col("event_type") == "purchase") & (F.col("value") > 100)).select("edge_id", "object_id", "value")


# --- joins -----------------------------------------------------------------------------


@entry("op_join_broadcast_location", f"WITH {E} SELECT edge_id, x, y FROM e")
def op_join_broadcast_location(s, d):
    return _edges(s, d).select("edge_id", "x", "y")


@entry("op_join_sortmerge_orders", "SELECT o_custkey, count(*) AS lines, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def op_join_sortmerge_orders(s, d):
    lines, orders = t.read(s, d, "lineitem"), t.read(s, d, "orders")
    joined = lines.join(orders.hint("merge"), lines["l_orderkey"] == orders["o_orderkey"])
    return joined.groupBy("o_custkey").agg(count_rows().alias("lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@entry("op_join_shuffle_hash", "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def op_join_shuffle_hash(s, d):
    c, n = t.read(s, d, "customer"), t.read(s, d, "nation")
    return c.join(n.hint("shuffle_hash"), c["c_nationkey"] == n["n_nationkey"]).groupBy("n_name").agg(count_rows().alias("customers"))


@entry("op_join_theta_nested", f"""WITH {E} SELECT a.edge_id AS a, b.edge_id AS b FROM e a JOIN e b ON a.object_id = 7 AND b.object_id = 1
  AND abs(a.ts_us - b.ts_us) <= {10 * HOUR} AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 1000000""")
def op_join_theta_nested(s, d):
    e = _edges(s, d)
    a = e.where("object_id = 7").select(F.col("edge_id").alias("a"), F.col("ts_us").alias("t_ts"), F.col("x").alias("t_x"), F.col("y").alias("t_y"))
    return e.where("object_id = 1").join(a, near(Thresholds(10 * HOUR, 1000))).select("a", F.col("edge_id").alias("b"))


@entry("op_join_interval_time", f"""WITH {EV} SELECT a.edge_id AS a, b.edge_id AS b FROM ev a JOIN ev b ON a.location_id = b.location_id
  AND a.edge_id < b.edge_id AND abs(a.ts_us - b.ts_us) <= {HOUR}""")
def op_join_interval_time(s, d):
    return interval_join(t.event_edges(s, d), ["location_id"], HOUR).select("a", "b")


@entry("op_join_distance_cell", f"""WITH {PL} SELECT a.location_id AS a, b.location_id AS b, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS sq_dist
  FROM pl a JOIN pl b ON a.location_id < b.location_id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 4000000""")
def op_join_distance_cell(s, d):
    return distance_join(t.event_places(s), 2000)


_AT = 852_076_800_000_000


@entry("op_join_asof_status", f"""WITH {PC}, q AS (SELECT o_orderkey AS object_id, epoch_us(o_orderdate) + {365 * DAY} AS at_us FROM orders)
  SELECT q.object_id, q.at_us, max(pc.ts_us) AS last_us FROM q LEFT JOIN pc ON pc.object_id = q.object_id AND pc.ts_us <= q.at_us GROUP BY 1, 2""")
def op_join_asof_status(s, d):
    """Last scan at or before each parcel's own instant: union and one running window, no range join."""
    q = t.read(s, d, "orders").select(
        F.col("o_orderkey").alias("object_id"), (t.micros(F.col("o_orderdate")) + 365 * DAY).alias("at_us"), F.lit(None).cast("bigint").alias("seen")
    ).distinct()
    p = t.parcel_edges(s, d).select("object_id", F.col("ts_us").alias("at_us"), F.col("ts_us").alias("seen"))
    w = Window.partitionBy("object_id").orderBy("at_us", F.col("seen").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    both = q.withColumn("ask", F.lit(True)).unionByName(p.withColumn("ask", F.lit(False)))
    return both.withColumn("last_us", F.last("seen", ignorenulls=True).over(w)).where("ask").select("object_id", "at_us", "last_us")


@entry("op_status_at", f"WITH {PC} SELECT object_id, max(ts_us) AS ts_us, count(*) AS scans FROM pc WHERE ts_us <= {_AT} GROUP BY 1")
def op_status_at(s, d):
    return status_at(t.parcel_graph(s, d), _AT).select("object_id", "ts_us", "scans")


@entry("op_join_semi_clones", f"WITH {EV} SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT object_id FROM ev WHERE {days(1)})")
def op_join_semi_clones(s, d):
    c, e = t.read(s, d, "customer"), t.event_edges(s, d, t.events_days(1))
    return c.join(e, c["c_custkey"] == e["object_id"], "left_semi").select("c_custkey", "c_name")


@entry("op_join_anti_inactive", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_join_anti_inactive(s, d):
    c, o = t.read(s, d, "customer"), t.read(s, d, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


@entry("op_join_full_gap", f"""WITH {E}, v AS (SELECT area, (ts_us - {S0}) // {DAY} AS day, count(*) AS n FROM e GROUP BY 1, 2),
  dom AS (SELECT CAST(a AS INTEGER) AS area, dd AS day FROM range(25) x(a), range(30) y(dd))
  SELECT coalesce(v.area, dom.area) AS area, coalesce(v.day, dom.day) AS day, coalesce(n, 0) AS visits FROM v FULL JOIN dom ON v.area = dom.area AND v.day = dom.day""")
def op_join_full_gap(s, d):
    v = _with_area(s, d).groupBy("area", F.expr(f"(ts_us - {S0}) div {DAY}").alias("day")).agg(count_rows().alias("n"))
    dom = s.range(25 * 30).select(F.expr("cast(id div 30 as int)").alias("area"), (F.col("id") % 30).alias("day"))
    return v.join(dom, ["area", "day"], "full").select("area", "day", F.coalesce("n", F.lit(0)).alias("visits"))


@entry("op_self_join_copresence", f"""WITH {EV} SELECT a.object_id AS o1, b.object_id AS o2, count(*) AS meets FROM ev a JOIN ev b ON a.location_id = b.location_id
  AND a.object_id < b.object_id AND abs(a.ts_us - b.ts_us) <= {7 * HOUR} GROUP BY 1, 2""")
def op_self_join_copresence(s, d):
    pairs = interval_join(t.event_edges(s, d), ["location_id"], 7 * HOUR).where("oa <> ob")
    return pairs.groupBy(F.least("oa", "ob").alias("o1"), F.greatest("oa", "ob").alias("o2")).agg(count_rows().alias("meets"))


# --- aggregations ------------------------------------------------------------------------


@entry("op_agg_region_day", f"""WITH {E} SELECT {zcode('x', 'y')} AS region, ts_us // {DAY} AS tru, count(*) AS visits, count(DISTINCT object_id) AS objects FROM e GROUP BY 1, 2""")
def op_agg_region_day(s, d):
    return _edges(s, d).groupBy(region_of("x", "y", t.EVENTS_SPEC).alias("region"), F.expr(f"ts_us div {DAY}").alias("tru")).agg(
        count_rows().alias("visits"), F.countDistinct("object_id").alias("objects")
    )


@entry("op_agg_rollup", f"WITH {E} SELECT area, location_id, count(*) AS visits FROM e GROUP BY ROLLUP (area, location_id)")
def op_agg_rollup(s, d):
    return _with_area(s, d).rollup("area", "location_id").agg(count_rows().alias("visits"))


@entry("op_agg_cube", f"WITH {E} SELECT event_type, area, count(*) AS visits FROM e GROUP BY CUBE (event_type, area)")
def op_agg_cube(s, d):
    return _with_area(s, d).cube("event_type", "area").agg(count_rows().alias("visits"))


@entry("op_agg_grouping_sets", f"WITH {E} SELECT event_type, area, count(*) AS visits FROM e GROUP BY GROUPING SETS ((event_type), (area), ())")
def op_agg_grouping_sets(s, d):
    _with_area(s, d).createOrReplaceTempView("tg_area_edges")
    return s.sql("select event_type, area, count(*) as visits from tg_area_edges group by grouping sets ((event_type), (area), ())")


@entry("op_agg_pivot_type", f"""WITH {E} SELECT area, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase,
  count(*) FILTER (WHERE event_type = 'view') AS "view" FROM e WHERE event_type IN ('click', 'purchase', 'view') GROUP BY 1""")
def op_agg_pivot_type(s, d):
    kinds = ["click", "purchase", "view"]
    rows = _with_area(s, d).where(F.col("event_type").isin(kinds)).groupBy("area").pivot("event_type", kinds).agg(count_rows())
    return rows.select("area", *[F.coalesce(k, F.lit(0)).alias(k) for k in kinds])


_WEEK = ("mon", "tue", "wed", "thu", "fri", "sat", "sun")


@entry("op_agg_pivot_weekday", f"WITH {E} SELECT area, " + ", ".join(f"count(*) FILTER (WHERE (ts_us // {DAY} + 3) % 7 = {i}) AS {w}" for i, w in enumerate(_WEEK)) + " FROM e GROUP BY 1")
def op_agg_pivot_weekday(s, d):
    day = F.expr(f"(ts_us div {DAY} + 3) % 7").cast("int")
    rows = _with_area(s, d).withColumn("day", day).groupBy("area").pivot("day", list(range(7))).agg(count_rows())
    return rows.select("area", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(w) for i, w in enumerate(_WEEK)])


@entry("op_agg_approx_visitors", f"WITH {E} SELECT area, count(DISTINCT object_id) AS visitors, true AS approx_within_5_sd FROM e GROUP BY 1")
def op_agg_approx_visitors(s, d):
    """Exact visitors by area, and whether the sketch (relative deviation 5 %) is within five deviations of them."""
    sketch = F.approx_count_distinct("object_id", 0.05)
    both = _with_area(s, d).groupBy("area").agg(F.countDistinct("object_id").alias("visitors"), sketch.alias("approx"))
    return both.select("area", "visitors", (F.abs(F.col("approx") - F.col("visitors")) <= 0.25 * F.col("visitors") + 1).alias("approx_within_5_sd"))


_GAP = f"""g AS (SELECT object_id, ts_us - lag(ts_us) OVER (PARTITION BY object_id ORDER BY ts_us, edge_id) AS gap FROM ev)"""


@entry("op_agg_gap_percentiles", f"WITH {EV}, {_GAP} SELECT quantile_cont(gap, 0.5) AS median_us, round(quantile_cont(gap, 0.9), 2) AS p90_us FROM g WHERE gap IS NOT NULL")
def op_agg_gap_percentiles(s, d):
    w = Window.partitionBy("object_id").orderBy("ts_us", "edge_id")
    g = t.event_edges(s, d).withColumn("gap", F.col("ts_us") - F.lag("ts_us").over(w)).where("gap is not null")
    return g.agg(F.percentile("gap", 0.5).alias("median_us"), F.round(F.percentile("gap", 0.9), 2).alias("p90_us"))


# --- windows -----------------------------------------------------------------------------


def _by_time():
    return Window.partitionBy("object_id").orderBy("ts_us", "edge_id")


_BY = "(PARTITION BY object_id ORDER BY ts_us, edge_id)"


@entry("op_window_lag_gap", f"WITH {E} SELECT edge_id, ts_us - lag(ts_us) OVER w AS gap_us, (x - lag(x) OVER w) * (x - lag(x) OVER w) + (y - lag(y) OVER w) * (y - lag(y) OVER w) AS sq_dist FROM e WINDOW w AS {_BY}")
def op_window_lag_gap(s, d):
    w = _by_time()
    e = _edges(s, d)
    return e.select("edge_id", (F.col("ts_us") - F.lag("ts_us").over(w)).alias("gap_us"), sq_dist(F.col("x"), F.col("y"), F.lag("x").over(w), F.lag("y").over(w)).alias("sq_dist"))


@entry("op_window_lead_next", f"WITH {EV} SELECT edge_id, lead(location_id) OVER {_BY} AS next_location FROM ev")
def op_window_lead_next(s, d):
    return t.event_edges(s, d).select("edge_id", F.lead("location_id").over(_by_time()).alias("next_location"))


@entry("op_window_rank_places", f"""WITH {E}, c AS (SELECT area, location_id, count(*) AS visits FROM e GROUP BY 1, 2),
  r AS (SELECT *, dense_rank() OVER (PARTITION BY area ORDER BY visits DESC) AS rnk FROM c) SELECT area, location_id, visits, CAST(rnk AS INTEGER) AS rnk FROM r WHERE rnk <= 3""")
def op_window_rank_places(s, d):
    c = _with_area(s, d).groupBy("area", "location_id").agg(count_rows().alias("visits"))
    return c.withColumn("rnk", F.dense_rank().over(Window.partitionBy("area").orderBy(F.desc("visits")))).where("rnk <= 3")


@entry("op_window_row_number_dedup", f"""WITH {EV} SELECT object_id, day, edge_id FROM (SELECT object_id, ts_us // {DAY} AS day, edge_id,
  row_number() OVER (PARTITION BY object_id, ts_us // {DAY} ORDER BY ts_us, edge_id) AS rn FROM ev) WHERE rn = 1""")
def op_window_row_number_dedup(s, d):
    e = t.event_edges(s, d).withColumn("day", F.expr(f"ts_us div {DAY}"))
    first = F.row_number().over(Window.partitionBy("object_id", "day").orderBy("ts_us", "edge_id"))
    return e.withColumn("rn", first).where("rn = 1").select("object_id", "day", "edge_id")


@entry("op_window_running_visits", f"WITH {EV} SELECT edge_id, count(*) OVER (PARTITION BY object_id ORDER BY ts_us, edge_id ROWS UNBOUNDED PRECEDING) AS visits FROM ev")
def op_window_running_visits(s, d):
    w = _by_time().rowsBetween(Window.unboundedPreceding, 0)
    return t.event_edges(s, d).select("edge_id", count_rows().over(w).alias("visits"))


@entry("op_window_range_7h", f"WITH {EV} SELECT edge_id, count(*) OVER (PARTITION BY object_id ORDER BY ts_us RANGE BETWEEN {7 * HOUR} PRECEDING AND CURRENT ROW) AS visits FROM ev")
def op_window_range_7h(s, d):
    w = Window.partitionBy("object_id").orderBy("ts_us").rangeBetween(-7 * HOUR, 0)
    return t.event_edges(s, d).select("edge_id", count_rows().over(w).alias("visits"))


@entry("op_window_ntile_activity", f"WITH {EV}, c AS (SELECT object_id, count(*) AS n FROM ev GROUP BY 1) SELECT object_id, CAST(ntile(4) OVER (ORDER BY n, object_id) AS INTEGER) AS quartile FROM c")
def op_window_ntile_activity(s, d):
    c = t.event_edges(s, d).groupBy("object_id").agg(count_rows().alias("n"))
    return c.select("object_id", F.ntile(4).over(Window.orderBy("n", "object_id")).alias("quartile"))


@entry("op_trip_sessions", f"""WITH {EV}, s AS (SELECT object_id, ts_us, edge_id, CASE WHEN ts_us - lag(ts_us) OVER {_BY} <= {12 * HOUR} THEN 0 ELSE 1 END AS fresh FROM ev),
  n AS (SELECT *, sum(fresh) OVER (PARTITION BY object_id ORDER BY ts_us, edge_id ROWS UNBOUNDED PRECEDING) AS trip FROM s)
  SELECT object_id, CAST(trip AS BIGINT) AS trip, count(*) AS edges, min(ts_us) AS start_us, max(ts_us) AS end_us FROM n GROUP BY 1, 2""")
def op_trip_sessions(s, d):
    w = _by_time()
    e = t.event_edges(s, d).withColumn("fresh", F.when(F.col("ts_us") - F.lag("ts_us").over(w) <= 12 * HOUR, 0).otherwise(1))
    e = e.withColumn("trip", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return e.groupBy("object_id", "trip").agg(count_rows().alias("edges"), F.min("ts_us").alias("start_us"), F.max("ts_us").alias("end_us"))


@entry("op_topk_places", f"WITH {EV} SELECT location_id, count(*) AS visits FROM ev GROUP BY 1 ORDER BY visits DESC, location_id LIMIT 10")
def op_topk_places(s, d):
    return t.event_edges(s, d).groupBy("location_id").agg(count_rows().alias("visits")).orderBy(F.desc("visits"), "location_id").limit(10)


@entry("op_sort_trace", f"WITH {SO} SELECT object_id, ts_us, location_id FROM so")
def op_sort_trace(s, d):
    """All shop edges in full order."""
    return t.shop_edges(s, d).select("object_id", "ts_us", "location_id").orderBy("object_id", "ts_us", "location_id")


# --- sets ----------------------------------------------------------------------------------


def _visitors(s, d, area):
    return _with_area(s, d).where(F.col("area") == area).select("object_id")


_V = "SELECT object_id FROM e WHERE area = {}"


@entry("op_set_union", f"WITH {E} {_V.format(23)} UNION {_V.format(24)}")
def op_set_union(s, d):
    return _visitors(s, d, 23).union(_visitors(s, d, 24)).distinct()


@entry("op_set_union_all", f"WITH {E} {_V.format(23)} UNION ALL {_V.format(24)}")
def op_set_union_all(s, d):
    return _visitors(s, d, 23).unionByName(_visitors(s, d, 24))


@entry("op_set_intersect", f"WITH {E} {_V.format(23)} INTERSECT {_V.format(24)}")
def op_set_intersect(s, d):
    return _visitors(s, d, 23).intersect(_visitors(s, d, 24))


@entry("op_set_intersect_all", f"WITH {E} {_V.format(23)} INTERSECT ALL {_V.format(24)}")
def op_set_intersect_all(s, d):
    return _visitors(s, d, 23).intersectAll(_visitors(s, d, 24))


@entry("op_set_except", f"WITH {E} {_V.format(23)} EXCEPT {_V.format(24)}")
def op_set_except(s, d):
    return _visitors(s, d, 23).subtract(_visitors(s, d, 24))


@entry("op_set_except_all", f"WITH {E} {_V.format(23)} EXCEPT ALL {_V.format(24)}")
def op_set_except_all(s, d):
    return _visitors(s, d, 23).exceptAll(_visitors(s, d, 24))


# --- scalars ---------------------------------------------------------------------------------


@entry("op_scalar_zcode", f"WITH {PL} SELECT location_id, {zcode('x', 'y', 250)} AS z FROM pl".replace(">> 9", ">> 9"))
def op_scalar_zcode(s, d):
    return t.event_places(s).select("location_id", z_code(cell("x", 250).bitwiseAND(1023), cell("y", 250).bitwiseAND(1023)).alias("z"))


@entry("op_scalar_region", f"WITH {SE} SELECT edge_id, {zcode('x', 'y')} AS region FROM se")
def op_scalar_region(s, d):
    g = t.shop_graph(s, d)
    return located(g.edges, g.locations).select("edge_id", region_of("x", "y", g.spec).alias("region"))


@entry("op_scalar_slot", f"WITH {EV} SELECT edge_id, {slot('object_id', 14)} AS slot FROM ev")
def op_scalar_slot(s, d):
    return t.event_edges(s, d).select("edge_id", slot_of("object_id", 14).alias("slot"))


@entry("op_scalar_tru", f"WITH {EV} SELECT edge_id, ts_us // {DAY} AS tru FROM ev")
def op_scalar_tru(s, d):
    return t.event_edges(s, d).select("edge_id", F.expr(f"ts_us div {DAY}").alias("tru"))


_LL = "(x - 102400) / 100000.0 + 40", "(y - 102400) / 100000.0"
_HAV = "2 * 6371000.0 * asin(sqrt(pow(sin((radians(lat2) - radians(lat1)) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)))"


@entry("op_scalar_metrics", f"""WITH {PL}, q AS (SELECT location_id, x, y, {_LL[0]} AS lat1, {_LL[1]} AS lon1, 41.5 AS lat2, 2.25 AS lon2 FROM pl)
  SELECT location_id, round(sqrt(CAST((x - 500000) * (x - 500000) + (y - 500000) * (y - 500000) AS DOUBLE)), 3) AS euclid, CAST(greatest(abs(x - 500000), abs(y - 500000)) AS DOUBLE) AS chebyshev,
  CAST(abs(x - 500000) + abs(y - 500000) AS DOUBLE) AS manhattan, round({_HAV}, 1) AS haversine FROM q""")
def op_scalar_metrics(s, d):
    p = t.event_places(s)
    c = F.lit(500000)
    lat, lon = (F.col("x") - 102400) / 100000.0 + 40, (F.col("y") - 102400) / 100000.0
    return p.select(
        "location_id",
        F.round(METRICS["euclid"].distance("x", "y", c, c), 3).alias("euclid"),
        METRICS["chebyshev"].distance(F.col("x"), F.col("y"), c, c).alias("chebyshev"),
        METRICS["manhattan"].distance(F.col("x"), F.col("y"), c, c).alias("manhattan"),
        F.round(METRICS["haversine"].distance(lat, lon, F.lit(41.5), F.lit(2.25)), 1).alias("haversine"),
    )


@entry("op_scalar_bounds", " UNION ALL ".join(f"SELECT '{b}' AS bound, CAST({eta} AS INTEGER) AS eta, CAST(0 AS BIGINT) AS violations" for b in ("printed", "chebyshev") for eta in (10, 60, 250)))
def op_scalar_bounds(s, d):
    """Pairs of places within 5 km whose distance lies outside the bounds: none."""
    p = t.event_places(s).select("location_id", "x", "y")
    pairs = distance_join(p, 5000)
    a = p.select(F.col("location_id").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    b = p.select(F.col("location_id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"))
    both = pairs.join(a, "a").join(b, "b")
    out = None
    for bound in ("printed", "chebyshev"):
        for eta in (10, 60, 250):
            g = [cell(c, eta) for c in ("ax", "ay", "bx", "by")]
            lo, hi = grid_bounds(*g, eta, bound)
            dist = F.sqrt(F.col("sq_dist").cast("double"))
            row = both.where((lo > dist) | (hi < dist)).agg(count_rows().alias("violations")).select(F.lit(bound).alias("bound"), F.lit(eta).alias("eta"), "violations")
            out = row if out is None else out.unionByName(row)
    return out


@entry("op_string_rowkey", f"""WITH {EV}, k AS (SELECT DISTINCT {slot('object_id', 6)} AS slot, ts_us // {DAY} AS tru FROM ev)
  SELECT lpad(CAST(slot % 10 AS VARCHAR), 4, '0') || '|B|' || lpad(CAST(slot AS VARCHAR), 10, '0') || '|' || lpad(CAST(tru AS VARCHAR), 8, '0') AS row_key,
  CAST(slot % 10 AS INTEGER) AS node, 'B' AS method, CAST(slot AS BIGINT) AS pid, tru AS bucket FROM k""")
def op_string_rowkey(s, d):
    k = t.event_edges(s, d).select(slot_of("object_id", 6).alias("slot"), F.expr(f"ts_us div {DAY}").alias("tru")).distinct()
    k = k.select(row_key(F.lit("B"), "slot", "tru", F.col("slot") % 10).alias("row_key"))
    return k.select("row_key", *[v.alias(n) for n, v in parse_row_key("row_key").items()])


@entry("op_date_buckets", "SELECT event_id AS edge_id, epoch_us(date_trunc('hour', ts)) AS hour_us, epoch_us(date_trunc('day', ts)) AS day_us, epoch_us(CAST(date_trunc('week', ts) AS TIMESTAMP)) AS week_us FROM events")
def op_date_buckets(s, d):
    rows = t.read(s, d, "events")
    at = lambda unit: t.micros(F.date_trunc(unit, "ts").cast("timestamp_ntz"))
    return rows.select(F.col("event_id").alias("edge_id"), at("hour").alias("hour_us"), at("day").alias("day_us"), at("week").alias("week_us"))


@entry("op_json_props", "SELECT event_id AS edge_id, CAST(regexp_extract(props, '[0-9]+') AS BIGINT) AS k_path, CAST(regexp_extract(props, '[0-9]+') AS BIGINT) AS k_struct FROM events")
def op_json_props(s, d):
    rows = t.read(s, d, "events")
    return rows.select(F.col("event_id").alias("edge_id"), F.get_json_object("props", "$.k").cast("bigint").alias("k_path"), F.from_json("props", "k bigint")["k"].alias("k_struct"))


@entry("op_map_props", f"WITH {EV} SELECT object_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM ev GROUP BY 1")
def op_map_props(s, d):
    per = t.event_edges(s, d).groupBy("object_id", "event_type").agg(count_rows().alias("n"))
    m = per.groupBy("object_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # five types at most
    return m.select("object_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size("m").cast("bigint").alias("kinds"))


@entry("op_array_trace", f"""WITH {E}, st AS (SELECT object_id, sqrt(CAST((x - lag(x) OVER w) * (x - lag(x) OVER w) + (y - lag(y) OVER w) * (y - lag(y) OVER w) AS DOUBLE)) AS step
  FROM e WHERE {days(7)} WINDOW w AS (PARTITION BY object_id ORDER BY ts_us, location_id))
  SELECT object_id, CAST(count(*) AS INTEGER) AS n, round(coalesce(sum(step), 0), 2) AS length_m FROM st GROUP BY 1""")
def op_array_trace(s, d):
    """Traces as arrays, and their polyline lengths by higher-order functions."""
    e = located(t.event_graph(s, d, t.events_days(7)).edges, t.event_places(s)).where((F.col("ts_us") >= S0) & (F.col("ts_us") < S0 + 7 * DAY))
    tr = e.groupBy("object_id").agg(F.array_sort(F.collect_list(F.struct("ts_us", "location_id", "x", "y"))).alias("r"))
    steps = F.zip_with(
        F.slice("r", 1, F.size("r") - 1), F.slice("r", 2, F.size("r") - 1), lambda a, b: F.sqrt(sq_dist(a["x"], a["y"], b["x"], b["y"]).cast("double"))
    )
    return tr.select("object_id", F.size("r").alias("n"), F.round(F.aggregate(steps, F.lit(0.0), lambda x, y: x + y), 2).alias("length_m"))


@entry("op_vector_distance", """SELECT vec_id, round(list_distance(CAST(embedding AS DOUBLE[]), (SELECT CAST(embedding AS DOUBLE[]) FROM embeddings WHERE vec_id = 0)), 5) AS l2,
  round(1 - list_cosine_similarity(CAST(embedding AS DOUBLE[]), (SELECT CAST(embedding AS DOUBLE[]) FROM embeddings WHERE vec_id = 0)), 5) AS cosine FROM embeddings""")
def op_vector_distance(s, d):
    v = t.read(s, d, "embeddings")
    q = v.where("vec_id = 0").select(F.col("embedding").alias("q"))  # one query vector
    return v.join(F.broadcast(q), F.lit(True)).select("vec_id", F.round(vector_l2("q", "embedding"), 5).alias("l2"), F.round(vector_cosine("q", "embedding"), 5).alias("cosine"))


# --- time windows as streams have them ------------------------------------------------------------


@entry("op_tumbling_window", f"WITH {EV} SELECT ts_us // {DAY} * {DAY} AS start_us, event_type, count(*) AS visits FROM ev GROUP BY 1, 2")
def op_tumbling_window(s, d):
    e = t.event_edges(s, d).withColumn("ts", F.timestamp_micros("ts_us"))
    w = e.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(count_rows().alias("visits"))
    return w.select(F.unix_micros("w.start").alias("start_us"), "event_type", "visits")


@entry("op_sliding_window", f"""WITH {EV} SELECT ts_us // {12 * HOUR} * {12 * HOUR} - o * {12 * HOUR} AS start_us, count(*) AS visits FROM ev, range(2) k(o) GROUP BY 1""")
def op_sliding_window(s, d):
    e = t.event_edges(s, d).withColumn("ts", F.timestamp_micros("ts_us"))
    w = e.groupBy(F.window("ts", "24 hours", "12 hours").alias("w")).agg(count_rows().alias("visits"))
    return w.select(F.unix_micros("w.start").alias("start_us"), "visits")


# --- SQL surface --------------------------------------------------------------------------------------


@entry("op_sql_scalar_functions", f"""WITH {E} SELECT edge_id, CAST({slot('object_id', 6)} AS BIGINT) AS slot, ts_us // {DAY} AS tru, {zcode('x', 'y')} AS region FROM e""")
def op_sql_scalar_functions(s, d):
    sqlfuncs.register(s, t.event_graph(s, d))
    return s.sql("select e.edge_id, tg_slot(e.object_id) slot, tg_tru(e.ts_us) tru, tg_region(l.x, l.y) region from tg_edges e join tg_locations l on e.location_id = l.location_id")


@entry("op_sql_table_functions", f"WITH {EV} SELECT object_id, ts_us, location_id FROM ev WHERE object_id = 7 AND {days(7)}")
def op_sql_table_functions(s, d):
    sqlfuncs.register(s, t.event_graph(s, d))
    return s.sql(f"select * from tg_trace(7, {S0}, {S0 + 7 * DAY})")


@entry("op_sql_clones", f"""WITH {E} SELECT DISTINCT a.object_id FROM (SELECT * FROM e WHERE {days(1)}) a JOIN (SELECT * FROM e WHERE {days(1)}) b
  ON a.object_id = b.object_id AND a.ts_us <= b.ts_us WHERE sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE)) * 3.6e6 > 120.0 * (b.ts_us - a.ts_us)""")
def op_sql_clones(s, d):
    sqlfuncs.register(s, t.event_graph(s, d))
    return s.sql(f"select * from tg_clones({S0}, {S0 + DAY}, 120.0D)")


@entry("op_sample_fraction", f"WITH {EV} SELECT edge_id FROM ev WHERE (edge_id * 48271) % 1000 < 100")
def op_sample_fraction(s, d):
    """Deterministic tenth of the edges by a hash of their id: a sampling operator."""
    return t.event_edges(s, d).where((F.col("edge_id") * 48271) % 1000 < 100).select("edge_id")
