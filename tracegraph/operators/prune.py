"""Similarity joins: time buckets, cell joins, bounds; range predicates become equi-joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracegraph.functions.geometry import cell, grid_bounds, sq_dist, z_code, z_code_int, z_decode_int
from tracegraph.model import GraphSpec, Thresholds

#: Rows of a side that is broadcast at most, and their bytes by the schema (``row_bytes``).
BROADCAST_ROWS, BROADCAST_BYTES = 2_000_000, 256 << 20
#: Numbers that an array column is taken to hold.
VECTOR = 128
#: Estimated bytes below which a side is broadcast without counting it; an expansion to neighbour keys adds a factor of 27.
SURELY_SMALL = 4 << 20
LEVELS = ("none", "time", "both", "cell")


def row_bytes(schema: T.StructType) -> int:
    """Bytes of a row in memory, about: fixed types by their size, arrays as vectors of ``VECTOR`` numbers, strings as short ones."""

    def of(t: T.DataType) -> int:
        if isinstance(t, T.ArrayType):
            return 16 + VECTOR * of(t.elementType)
        if isinstance(t, T.StructType):
            return 8 + sum(of(f.dataType) for f in t)
        if isinstance(t, T.MapType):
            return 16 + VECTOR * (of(t.keyType) + of(t.valueType))
        return 32 if isinstance(t, T.StringType | T.BinaryType) else 8

    return 16 + sum(of(f.dataType) for f in schema)


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``limit`` rows and BROADCAST_BYTES bytes, else as it is: the join then shuffles.

    Catalyst's own bound on the size settles the clear cases without a job. Otherwise the rows are counted, up to the limit
    only; a side that is costly to make should be stored first.
    """
    if int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) <= SURELY_SMALL:
        return F.broadcast(df)
    limit = min(limit, BROADCAST_BYTES // row_bytes(df.schema))
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


def bucket_reach(th_time_us: int, tru_us: int) -> int:
    """How many time buckets away a similar edge can be."""
    return -(-th_time_us // tru_us)


def neighbours(col: Column, reach: int) -> Column:
    return F.explode(F.sequence(col - reach, col + reach))


def near(th: Thresholds) -> Column:
    """Exact predicate on the columns of a candidate join (t: trace side, e: edge side)."""
    d = sq_dist(F.col("t_x"), F.col("t_y"), F.col("x"), F.col("y")) <= th.dist_m * th.dist_m
    return (F.abs(F.col("ts_us") - F.col("t_ts")) <= th.time_us) & d


def candidate_join(trace: DataFrame, edges: DataFrame, th: Thresholds, spec: GraphSpec, prune: str, hint=small) -> DataFrame:
    """Pairs of a trace edge (ts_us, location_id, x, y) and an edge that are similar; one row per pair.

    ``none``: every pair meets (nested loop); ``time``: pairs in neighbouring buckets; ``both``: of those, the
    fine cells' lower bound rejects and the upper bound accepts before the distance is computed; ``cell``: pairs
    meet only in neighbouring buckets and cells, by hash join. The trace side is expanded to
    distinct keys, each edge has one, so a pair meets once and bags keep their multiplicity.
    """
    t = trace.select(
        F.col("ts_us").alias("t_ts"), F.col("location_id").alias("t_loc"), F.col("x").alias("t_x"), F.col("y").alias("t_y")
    )
    if prune == "none":
        return edges.join(hint(t), near(th))
    reach = bucket_reach(th.time_us, spec.tru_us)
    t = t.withColumn("tru", neighbours(F.expr(f"t_ts div {spec.tru_us}"), reach))
    e = edges.withColumn("tru", F.expr(f"ts_us div {spec.tru_us}"))
    if prune == "time":
        return e.join(hint(t), "tru").where(near(th))
    if prune == "both":
        g = {c: cell(c, spec.eta) for c in ("t_x", "t_y", "x", "y")}
        lower, upper = grid_bounds(g["t_x"], g["t_y"], g["x"], g["y"], spec.eta, "chebyshev")
        exact = sq_dist(F.col("t_x"), F.col("t_y"), F.col("x"), F.col("y")) <= th.dist_m * th.dist_m
        close = F.when(lower > th.dist_m, False).when(upper <= th.dist_m, True).otherwise(exact)
        return e.join(hint(t), "tru").where((F.abs(F.col("ts_us") - F.col("t_ts")) <= th.time_us) & close)
    if prune == "cell":
        width = max(1, th.dist_m)
        t = t.withColumn("cx", neighbours(cell("t_x", width), 1)).withColumn("cy", neighbours(cell("t_y", width), 1))
        e = e.withColumns({"cx": cell("x", width), "cy": cell("y", width)})
        return e.join(hint(t), ["tru", "cx", "cy"]).where(near(th))
    raise ValueError(f"prune level {prune!r}: choose one of {LEVELS}")


def regions_touching(points: list[tuple[int, int]], dist: int, spec: GraphSpec) -> list[int]:
    """Z-codes of all regions within ``dist`` of a point: a similar edge may lie across a region's border."""
    found = set()
    for x, y in points:
        x0, x1 = (x - dist - spec.origin_x) // spec.a, (x + dist - spec.origin_x) // spec.a
        y0, y1 = (y - dist - spec.origin_y) // spec.a, (y + dist - spec.origin_y) // spec.a
        for cx in range(max(0, x0), min(spec.grid_w - 1, x1) + 1):
            for cy in range(max(0, y0), min(spec.grid_h - 1, y1) + 1):
                found.add(z_code_int(cx, cy))
    return sorted(found)


def near_regions(points: list[tuple[int, int, int]], th: Thresholds, spec: GraphSpec) -> set[tuple[int, int]]:
    """(time bucket, region) pairs that can hold an edge similar to one at (ts, x, y)."""
    found, regions = set(), {}
    for ts, x, y in points:
        if (x, y) not in regions:
            regions[x, y] = regions_touching([(x, y)], th.dist_m, spec)
        for bucket in range((ts - th.time_us) // spec.tru_us, (ts + th.time_us) // spec.tru_us + 1):
            found.update((bucket, r) for r in regions[x, y])
    return found


def touched_regions(trace: DataFrame, th: Thresholds, spec: GraphSpec) -> DataFrame:
    """``near_regions`` without the driver: distinct tru and region for a trace (ts_us, x, y) of any length."""

    def cells(c: str, origin: int, most: int) -> Column:
        low, high = cell(F.col(c) - th.dist_m, spec.a, origin), cell(F.col(c) + th.dist_m, spec.a, origin)
        low, high = F.greatest(low, F.lit(0)), F.least(high, F.lit(most - 1))
        return F.explode(F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<bigint>")))

    places = trace.select("x", "y").distinct().withColumn("cx", cells("x", spec.origin_x, spec.grid_w)).withColumn("cy", cells("y", spec.origin_y, spec.grid_h))
    regions = places.select("x", "y", z_code("cx", "cy").alias("region"))
    buckets = F.expr(f"sequence((ts_us - {th.time_us}) div {spec.tru_us}, (ts_us + {th.time_us}) div {spec.tru_us})")
    at = trace.select("x", "y", F.explode(buckets).alias("tru")).distinct()
    return at.join(regions, ["x", "y"]).select("tru", "region").distinct()


def intervals(codes: list[int], most: int = 64) -> list[tuple[int, int]]:
    """Sorted codes as at most ``most`` closed intervals; the smallest gaps are closed first.

    Long IN lists are not pushed to row groups, a few ranges are.
    """
    if not codes:
        return []
    gaps = sorted(range(1, len(codes)), key=lambda i: codes[i - 1] - codes[i])[: most - 1]
    cuts = [0, *sorted(i for i in gaps if codes[i] - codes[i - 1] > 1), len(codes)]
    return [(codes[a], codes[b - 1]) for a, b in zip(cuts, cuts[1:], strict=False)]


def in_intervals(col: str, spans: list[tuple[int, int]]) -> Column:
    out = F.lit(False)
    for a, b in spans:
        out = out | F.col(col).between(a, b)
    return out


def decode_regions(codes: list[int]) -> list[tuple[int, int]]:
    return [z_decode_int(z) for z in codes]


def distance_join(places: DataFrame, dist: int) -> DataFrame:
    """Pairs (a < b) of places (location_id, x, y) within ``dist``: equi-join on cells of that width."""
    width = max(1, dist)
    keyed = places.select("location_id", "x", "y", cell("x", width).alias("cx"), cell("y", width).alias("cy"))
    spread_ = keyed.select(
        F.col("location_id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"),
        neighbours(F.col("cx"), 1).alias("cx"), "cy",
    ).withColumn("cy", neighbours(F.col("cy"), 1))
    pairs = keyed.withColumnRenamed("location_id", "a").join(spread_, ["cx", "cy"])
    return pairs.where((F.col("a") < F.col("b")) & (sq_dist("x", "y", "bx", "by") <= dist * dist)).select(
        "a", "b", sq_dist("x", "y", "bx", "by").alias("sq_dist")
    )


def interval_join(edges: DataFrame, keys: list[str], reach_us: int) -> DataFrame:
    """Pairs of edges (a.edge_id < b.edge_id) with equal keys and times at most ``reach_us`` apart.

    Buckets of that width: only the same and the next one can hold a partner.
    """
    width = max(1, reach_us)
    left = edges.select(*keys, F.col("edge_id").alias("a"), F.col("object_id").alias("oa"), F.col("ts_us").alias("ta"), F.expr(f"ts_us div {width}").alias("tb"))
    right = edges.select(*keys, F.col("edge_id").alias("b"), F.col("object_id").alias("ob"), F.col("ts_us").alias("tz"), F.explode(F.expr(f"sequence(ts_us div {width} - 1, ts_us div {width} + 1)")).alias("tb"))
    return left.join(right, [*keys, "tb"]).where((F.col("a") < F.col("b")) & (F.abs(F.col("ta") - F.col("tz")) <= reach_us)).drop("tb")
