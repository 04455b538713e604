"""Live operators: traces, similar objects, clone alarms, windows, sessions, joins of streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tracegraph.functions.geometry import cell, region_of
from tracegraph.model import GraphSpec, Thresholds
from tracegraph.operators.prune import candidate_join, small


def timed(edges: DataFrame, delay: str) -> DataFrame:
    """Edges with a timestamp column ``ts`` under a watermark."""
    return edges.withColumn("ts", F.timestamp_micros("ts_us")).withWatermark("ts", delay)


def live_trace(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges of a watched set of objects: stream-static join."""
    return edges.join(small(ids.select("object_id").distinct()), "object_id", "left_semi")


def live_similar(edges: DataFrame, locations: DataFrame, trace: DataFrame, th: Thresholds, spec: GraphSpec) -> DataFrame:
    """Running similarity of every object with one fixed trace (update mode)."""
    located = edges.join(small(locations.select("location_id", "x", "y")), "location_id")
    return candidate_join(trace, located, th, spec, "cell").groupBy("object_id").agg(F.count(F.lit(1)).alias("similarity"))


def visits_per_region(edges: DataFrame, locations: DataFrame, spec: GraphSpec, delay: str = "1 hour", width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Visits by region in tumbling windows, or sliding ones if ``slide`` is given."""
    at = locations.select("location_id", region_of("x", "y", spec).alias("region"))
    windows = F.window("ts", width, slide) if slide else F.window("ts", width)
    return timed(edges, delay).join(small(at), "location_id").groupBy(windows.alias("w"), "region").agg(F.count(F.lit(1)).alias("visits")).select(
        F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "region", "visits"
    )


def trips(edges: DataFrame, gap: str = "12 hours", delay: str = "1 hour") -> DataFrame:
    """Sessions of an object: edges less than ``gap`` apart."""
    return timed(edges, delay).groupBy(F.session_window("ts", gap).alias("w"), "object_id").agg(F.count(F.lit(1)).alias("edges")).select(
        "object_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "edges"
    )


def without_repeats(edges: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Scans that come again within the delay are dropped."""
    return timed(edges, delay).dropDuplicatesWithinWatermark(["edge_id"]).drop("ts")


def copresence(left: DataFrame, right: DataFrame, locations: DataFrame, th: Thresholds, delay: str = "1 hour") -> DataFrame:
    """Pairs of edges of two streams in one cell of width ``dist_m`` and at most ``time_us`` apart; state ends with the time bound."""
    seconds = -(-th.time_us // 1_000_000)
    at = locations.select("location_id", cell("x", th.dist_m).alias("cx"), cell("y", th.dist_m).alias("cy"))
    a = timed(left, delay).join(small(at), "location_id").select(F.col("object_id").alias("a"), F.col("ts").alias("ta"), "cx", "cy")
    b = timed(right, delay).join(small(at), "location_id").select(
        F.col("object_id").alias("b"), F.col("ts").alias("tb"), F.col("cx").alias("bx"), F.col("cy").alias("by")
    )
    near = F.expr(f"cx = bx and cy = by and tb between ta - interval {seconds} seconds and ta + interval {seconds} seconds")
    return a.join(b, near).select("a", "b", F.unix_micros("ta").alias("ta_us"), F.unix_micros("tb").alias("tb_us"), "cx", "cy")


ALARM = "object_id long, ts1_us long, loc1 long, ts2_us long, loc2 long, dist_m double"


def clone_alarm(
    edges: DataFrame, locations: DataFrame, kmh: float = 120.0, idle_ms: int = 30 * 86_400_000, delay: str = "1 hour"
) -> DataFrame:
    """Alarm when an object moves faster than ``kmh`` from its last edge.

    State: the latest edge of each object, forgotten ``idle_ms`` of event time after it. The edges of a micro-batch are sorted first;
    one that is older than the state is compared with it and leaves it as it is.
    """
    located = timed(edges, delay).join(small(locations.select("location_id", "x", "y")), "location_id")

    def watch(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = sorted(r for p in parts for r in zip(p["ts_us"], p["location_id"], p["x"], p["y"], strict=True))
        last = state.get if state.exists else None
        out = []
        for row in rows:
            row = tuple(int(v) for v in row)
            if last is not None:
                dist = ((row[2] - last[2]) ** 2 + (row[3] - last[3]) ** 2) ** 0.5
                if dist * 3.6e6 > kmh * abs(row[0] - last[0]):
                    first, second = sorted((tuple(last), row))
                    out.append((key[0], first[0], first[1], second[0], second[1], dist))
            if last is None or row[:2] >= tuple(last[:2]):
                last = row
        if last is not None:
            state.update(tuple(last))
            state.setTimeoutTimestamp(max(last[0] // 1000, state.getCurrentWatermarkMs()) + idle_ms)
        yield pd.DataFrame(out, columns=[c.split()[0] for c in ALARM.split(", ")])

    return located.groupBy("object_id").applyInPandasWithState(
        watch, ALARM, "ts_us long, location_id long, x long, y long", "append", GroupStateTimeout.EventTimeTimeout
    )


def group_statistics(edges: DataFrame, groups: DataFrame, placement: DataFrame) -> DataFrame:
    """Edges per group and worker, complete mode: what the rebalancer reads at each trigger."""
    return edges.join(small(groups.select("object_id", "group_id")), "object_id").join(small(placement.select("group_id", "worker")), "group_id").groupBy(
        "worker", "group_id"
    ).agg(F.count(F.lit(1)).alias("edges"))
