"""SQL surface: scalar functions and table functions over registered views; all are inlined by Catalyst."""

from __future__ import annotations

from pyspark.sql import SparkSession

from tracegraph.functions.slots import MULTIPLIER
from tracegraph.model import Thresholds, TraceGraph


def _spread(x: str, bits: int = 16) -> str:
    return " + ".join(f"shiftleft(shiftright({x}, {i}) & 1L, {2 * i})" for i in range(bits))


def register(spark: SparkSession, g: TraceGraph, th: Thresholds = Thresholds()) -> None:
    """Views locations and edges, functions tg_slot, tg_tru, tg_region, tg_dist, tg_spatial_factor, and table functions
    tg_trace, tg_similarity, tg_similar, tg_clones."""
    s = g.spec
    g.locations.createOrReplaceTempView("tg_locations")
    g.edges.createOrReplaceTempView("tg_edges")
    if g.objects is not None:
        g.objects.createOrReplaceTempView("tg_objects")
    scalar = {
        "tg_slot(id bigint) returns bigint": f"shiftright(pmod(pmod(id, 4294967296L) * {MULTIPLIER}L, 4294967296L), {32 - s.p})",
        "tg_tru(ts_us bigint) returns bigint": f"ts_us div {s.tru_us}L",
        "tg_spread(v bigint) returns bigint": _spread("v"),
        "tg_zcode(cx bigint, cy bigint) returns bigint": "tg_spread(cx) | shiftleft(tg_spread(cy), 1)",
        "tg_region(x bigint, y bigint) returns bigint": f"tg_zcode((x - {s.origin_x}) div {s.a}, (y - {s.origin_y}) div {s.a})",
        "tg_dist(x1 bigint, y1 bigint, x2 bigint, y2 bigint) returns double": "sqrt(cast((x1-x2)*(x1-x2)+(y1-y2)*(y1-y2) as double))",
        "tg_spatial_factor(b double, a double, d double) returns double": "(1 - d / (2 * b * a)) * (1 - d / (2 * b * a))",
    }
    for head, body in scalar.items():
        spark.sql(f"create or replace temporary function {head} return {body}")
    clip = "ts_us >= from_us and ts_us < to_us"
    near = f"abs(p.ts_us - q.ts_us) <= {th.time_us} and tg_dist(p.x, p.y, q.x, q.y) <= {th.dist_m}"
    at = "select e.object_id, e.ts_us, e.location_id, l.x, l.y from tg_edges e join tg_locations l on e.location_id = l.location_id"
    tables = {
        "tg_trace(id bigint, from_us bigint, to_us bigint) returns table (object_id bigint, ts_us bigint, location_id bigint)":
            f"select object_id, ts_us, location_id from tg_edges where object_id = id and {clip}",
        "tg_similarity(id1 bigint, id2 bigint, from_us bigint, to_us bigint) returns table (similarity bigint)":
            f"select count(*) from (select * from ({at}) where object_id = id1 and {clip}) p"
            f" join (select * from ({at}) where object_id = id2 and {clip}) q on {near}",
        "tg_similar(id bigint, from_us bigint, to_us bigint) returns table (object_id bigint, similarity bigint)":
            f"select q.object_id, count(*) from (select * from ({at}) where object_id = id and {clip}) p"
            f" join (select * from ({at}) where object_id <> id and {clip}) q on {near} group by q.object_id",
        "tg_clones(from_us bigint, to_us bigint, kmh double) returns table (object_id bigint)":
            "select distinct object_id from (select object_id, ts_us, x, y, lag(ts_us) over w pt, lag(x) over w px, lag(y) over w py"
            f" from ({at}) where {clip} window w as (partition by object_id order by ts_us, location_id))"
            " where pt is not null and tg_dist(px, py, x, y) * 3.6e6D > kmh * (ts_us - pt)",
    }
    for head, body in tables.items():
        spark.sql(f"create or replace temporary function {head} return {body}")
