"""The four exact queries: object trace, trace similarity, similar objects, clone detection.

Each builds one DataFrame from derived predicates; all plans and prune levels of a query give the same rows.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tracegraph.functions.geometry import METRICS, cell, grid_bounds, sq_dist
from tracegraph.functions.slots import slot_of_int
from tracegraph.model import DAY_US, Thresholds, TimeRange, TraceGraph, in_range

from .layouts import LayoutInfo, kt_columns, layout_info, located, st_columns, unit_group_of_region
from .prune import bucket_reach, candidate_join, in_intervals, intervals, near_regions, neighbours, small, touched_regions

PLANS = ("st", "kt", "kt+st")
#: Edges of a trace that the driver takes in at most.
TRACE_ROWS = 20_000
#: Rows of a (bucket, cell) key beyond which it is dealt over several tasks, and such keys that are broadcast at most.
HOT_ROWS, HOT_KEYS = 20_000, 500_000


class Layouts:
    """Where a graph's edges are read from: stored tables if given, else derived columns over the edge table."""

    def __init__(
        self, g: TraceGraph, kt: DataFrame | None = None, st: DataFrame | None = None, kt_info: LayoutInfo | None = None, st_info: LayoutInfo | None = None
    ):
        self.g, self._kt, self._st, self.kt_info, self.st_info = g, kt, st, kt_info, st_info

    @classmethod
    def stored(cls, g: TraceGraph, kt_path: str, st_path: str) -> Layouts:
        """The layouts that ``build_kt`` and ``build_st`` wrote."""
        spark = g.locations.sparkSession
        return cls(g, spark.read.parquet(kt_path), spark.read.parquet(st_path), layout_info(spark, kt_path), layout_info(spark, st_path))

    @property
    def stored_st(self) -> bool:
        return self._st is not None

    def kt(self, rng: TimeRange | None) -> DataFrame:
        base = self._kt if self._kt is not None else kt_columns(self.g.between(rng), self.g.spec)
        return self._clip(base, rng)

    def st(self, rng: TimeRange | None) -> DataFrame:
        base = self._st if self._st is not None else st_columns(self.g.between(rng), self.g.locations, self.g.spec)
        return self._clip(base, rng)

    def of_slots(self, rng: TimeRange | None, slots: list[int]) -> DataFrame:
        """KT rows of some slots: their groups' files, of those the row groups that hold them."""
        kt = self.kt(rng).where(F.col("slot").isin(slots))
        if self.kt_info:
            kt = kt.where(F.col("slot_group").isin(sorted({s * self.kt_info.groups // self.g.spec.n_slots for s in slots})))
        return kt

    def of_regions(self, rng: TimeRange | None, near: set[tuple[int, int]]) -> DataFrame:
        """ST rows of (time bucket, region) pairs: only the files of (bucket, unit group) pairs that can hold one.

        Stored tables are then skipped by ranges of regions; derived columns are tested by one set lookup.
        """
        st, regions = self.st(rng), sorted({r for _, r in near})
        if not self.stored_st:
            return st.where(F.col("region").isin(regions))
        if self.st_info:
            n = self.st_info.groups
            pairs = sorted({b * n + unit_group_of_region(r, n, self.st_info.b) for b, r in near})
            st = st.where((F.col("tru") * n + F.col("unit_group")).isin(pairs))
        return st.where(in_intervals("region", intervals(regions)))

    def _clip(self, df: DataFrame, rng: TimeRange | None) -> DataFrame:
        if rng is None:
            return df
        lo, hi = rng.buckets(self.g.spec.tru_us)
        return in_range(df.where(F.col("tru").between(lo, hi)), rng)


def _layouts(g: TraceGraph | Layouts) -> Layouts:
    return g if isinstance(g, Layouts) else Layouts(g)


def _of_objects(lay: Layouts, ids: list[int], rng: TimeRange | None, plan: str) -> DataFrame:
    """Edges of a few objects: KT reads their slots only, ST reads all regions of the range."""
    if plan == "st":
        return lay.st(rng).where(F.col("object_id").isin(ids))
    spec = lay.g.spec
    kt = lay.of_slots(rng, sorted({slot_of_int(i, spec.p) for i in ids})) if spec.hash_kind == "mult" else lay.kt(rng)
    return kt.where(F.col("object_id").isin(ids))


def edges_of(g: TraceGraph | Layouts, ids: list[int], rng: TimeRange | None, plan: str = "kt") -> DataFrame:
    """All columns of the edges of a few objects."""
    return _of_objects(_layouts(g), ids, rng, plan)


def object_trace(g: TraceGraph | Layouts, object_id: int, rng: TimeRange | None, plan: str = "kt") -> DataFrame:
    """Q1: object_id, ts_us, location_id of one object, in time order."""
    rows = _of_objects(_layouts(g), [object_id], rng, plan)
    return rows.select("object_id", "ts_us", "location_id").orderBy("ts_us", "location_id")


def object_traces(g: TraceGraph | Layouts, ids: DataFrame, rng: TimeRange | None) -> DataFrame:
    """Q1 for every object of a table (object_id)."""
    return _layouts(g).kt(rng).join(small(ids.select("object_id").distinct()), "object_id", "left_semi").select(
        "object_id", "ts_us", "location_id"
    )


def status_at(g: TraceGraph | Layouts, at_us: int, ids: DataFrame | None = None) -> DataFrame:
    """Latest edge of each object at or before an instant: one combined aggregation, no sort."""
    lay = _layouts(g)
    rows = lay.g.edges.where(F.col("ts_us") <= at_us)
    if ids is not None:
        rows = rows.join(small(ids), "object_id", "left_semi")
    last = F.max(F.struct("ts_us", "location_id")).alias("m")
    return rows.groupBy("object_id").agg(last, F.count(F.lit(1)).alias("scans")).select(
        "object_id", F.col("m.ts_us").alias("ts_us"), F.col("m.location_id").alias("location_id"), "scans"
    )


def trace_similarity(
    g: TraceGraph | Layouts, o1: int, o2: int, rng: TimeRange | None, th: Thresholds, plan: str = "kt", prune: str = "cell"
) -> DataFrame:
    """Q2: number of similar edge pairs of two objects, both traces clipped to the range; always one row."""
    lay = _layouts(g)
    both = _of_objects(lay, sorted({o1, o2}), rng, plan)
    if "x" not in both.columns:
        both = located(both, lay.g.locations)
    pairs = candidate_join(both.where(F.col("object_id") == o1), both.where(F.col("object_id") == o2), th, lay.g.spec, prune)
    return pairs.agg(F.count(F.lit(1)).alias("similarity")).select(
        F.lit(o1).cast("bigint").alias("object_a"), F.lit(o2).cast("bigint").alias("object_b"), "similarity"
    )


def similar_objects(
    g: TraceGraph | Layouts,
    object_id: int,
    rng: TimeRange | None,
    th: Thresholds,
    plan: str = "kt+st",
    prune: str = "cell",
    min_sim: int = 1,
    limit: int | None = None,
    include_self: bool = False,
) -> DataFrame:
    """Q3: objects with edges similar to an object's trace, by descending number of similar pairs.

    ``kt+st`` takes the trace from KT and reads only the regions its discs touch from ST; ``st`` and ``kt`` read the whole range.
    """
    lay = _layouts(g)
    spec = lay.g.spec
    if plan not in PLANS:
        raise ValueError(f"plan {plan!r}: choose one of {PLANS}")
    mine = _of_objects(lay, [object_id], rng, "st" if plan == "st" else "kt")
    trace = mine if "x" in mine.columns else located(mine, lay.g.locations)
    if plan == "kt":
        edges = located(lay.kt(rng), lay.g.locations)
    else:
        edges = lay.st(rng)
    hint = small
    if plan == "kt+st":
        # the only trip to the driver: one object's trace, if it is short
        rows = trace.select("ts_us", "location_id", "x", "y").limit(TRACE_ROWS + 1).collect()
        if len(rows) <= TRACE_ROWS:
            columns = {c: pa.array([r[c] for r in rows], pa.int64()) for c in ("ts_us", "location_id", "x", "y")}
            trace = trace.sparkSession.createDataFrame(pa.table(columns))
            hint = F.broadcast
            edges = lay.of_regions(rng, near_regions([(r["ts_us"], r["x"], r["y"]) for r in rows], th, spec))
        else:
            edges = edges.join(small(touched_regions(trace, th, spec)), ["tru", "region"], "left_semi")
    if not include_self:
        edges = edges.where(F.col("object_id") != object_id)
    pairs = candidate_join(trace, edges.select("object_id", "ts_us", "location_id", "x", "y"), th, spec, prune, hint)
    counts = pairs.groupBy("object_id").agg(F.count(F.lit(1)).alias("similarity")).where(F.col("similarity") >= min_sim)
    ordered = counts.orderBy(F.desc("similarity"), "object_id")
    return ordered.limit(limit) if limit is not None else ordered


def pairs_by_range(g: TraceGraph | Layouts, object_id: int, start_us: int, ranges: tuple[int, ...], th: Thresholds) -> DataFrame:
    """What each prune level saves, for ranges of days from ``start_us``: days, pairs (all), near_time (in neighbouring buckets), near_cells (near in time
    and not rejected by the cells' lower bound), measured (of those, not accepted by the upper bound: distances computed), similar_pairs.

    One join in neighbouring buckets serves all ranges: a pair belongs to those that hold the later of its days.
    """
    lay = _layouts(g)
    spec, rng = lay.g.spec, TimeRange.days(start_us, max(ranges))
    day = F.expr(f"(ts_us - {start_us}) div {DAY_US}")
    e = located(lay.kt(rng).select("object_id", "ts_us", "location_id"), lay.g.locations).withColumn("day", day)
    mine = e.where(F.col("object_id") == object_id).select(F.col("ts_us").alias("ta"), F.col("x").alias("ax"), F.col("y").alias("ay"), F.col("day").alias("da"))
    other = e.where(F.col("object_id") != object_id)
    days = F.array(*[F.lit(n) for n in ranges])
    of = lambda last: F.explode(F.filter(days, lambda n: n > last)).alias("days")
    sizes = mine.select(of(F.col("da"))).groupBy("days").agg(F.count(F.lit(1)).alias("n"))
    others = other.select(of(F.col("day"))).groupBy("days").agg(F.count(F.lit(1)).alias("m"))
    bucket = lambda c: F.expr(f"{c} div {DAY_US}")
    near_rows = other.withColumn("tru", bucket("ts_us")).join(small(mine.withColumn("tru", neighbours(bucket("ta"), bucket_reach(th.time_us, DAY_US)))), "tru")
    lower, upper = grid_bounds(cell("ax", spec.eta), cell("ay", spec.eta), cell("x", spec.eta), cell("y", spec.eta), spec.eta, "chebyshev")
    close = F.abs(F.col("ta") - F.col("ts_us")) <= th.time_us
    left = close & (lower <= th.dist_m)
    marks = {"near_time": F.lit(True), "near_cells": left, "measured": left & (upper > th.dist_m), "similar_pairs": close & (sq_dist("ax", "ay", "x", "y") <= th.dist_m**2)}
    met = near_rows.select(of(F.greatest("da", "day")), *[c.alias(k) for k, c in marks.items()]).groupBy("days").agg(*[F.count_if(k).alias(k) for k in marks])
    every = lay.g.locations.sparkSession.createDataFrame([(n,) for n in ranges], "days int")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("bigint")
    return every.join(sizes, "days", "left").join(others, "days", "left").join(met, "days", "left").select(
        "days", (zero(F.col("n")) * zero(F.col("m"))).alias("pairs"), *[zero(F.col(k)).alias(k) for k in marks]
    )


def visited_regions(g: TraceGraph | Layouts, object_id: int, rng: TimeRange | None, dist_m: int) -> DataFrame:
    """region: those that the discs around an object's places touch."""
    lay = _layouts(g)
    trace = located(_of_objects(lay, [object_id], rng, "kt"), lay.g.locations)
    return touched_regions(trace, Thresholds(0, dist_m), lay.g.spec).select("region").distinct()


def all_similar_pairs(g: TraceGraph | Layouts, rng: TimeRange | None, th: Thresholds, min_sim: int = 1) -> DataFrame:
    """Pairs o1 < o2 of all objects with at least ``min_sim`` similar edge pairs: a self-join on cell and bucket.

    Edges equal in object, place and time are one row with a count. Each unordered pair of rows meets once: a row is sent to itself's cell and
    to half of its neighbours (those that follow it in bucket, column and row). Keys with more than ``HOT_ROWS`` rows are dealt
    over parts, so that a busy place is no single task.
    """
    lay = _layouts(g)
    spec = lay.g.spec
    e = located(lay.g.between(rng), lay.g.locations).groupBy("object_id", "ts_us", "x", "y").agg(F.count(F.lit(1)).alias("n"))
    width = max(1, th.dist_m)
    key = {"tru": F.expr(f"ts_us div {spec.tru_us}"), "cx": cell("x", width), "cy": cell("y", width)}
    home = e.withColumns(key)
    reach = bucket_reach(th.time_us, spec.tru_us)
    # the key itself and those that follow it in (tru, cx, cy) order: the other half is met from the other side
    steps = [(t, i, j) for t in range(0, reach + 1) for i in (-1, 0, 1) for j in (-1, 0, 1) if (t, i, j) >= (0, 0, 0)]
    there = F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.lit(i).alias("i"), F.lit(j).alias("j")) for t, i, j in steps])).alias("d")
    parts = home.groupBy("tru", "cx", "cy").agg(F.ceil(F.count(F.lit(1)) / HOT_ROWS).alias("parts"))
    left = home.join(small(parts.where("parts > 1"), HOT_KEYS), ["tru", "cx", "cy"], "left").withColumn("part", F.pmod(F.xxhash64("object_id", "ts_us"), F.coalesce("parts", F.lit(1))))
    right = home.select("object_id", "ts_us", "x", "y", "n", "tru", "cx", "cy", there).select(
        F.col("object_id").alias("o2"), F.col("ts_us").alias("t2"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.col("n").alias("n2"),
        (F.col("tru") - F.col("d.t")).alias("tru"), (F.col("cx") - F.col("d.i")).alias("cx"), (F.col("cy") - F.col("d.j")).alias("cy"),
        (F.struct("d.t", "d.i", "d.j") == F.struct(F.lit(0), F.lit(0), F.lit(0))).alias("same"),
    )
    right = right.join(small(parts.where("parts > 1"), HOT_KEYS), ["tru", "cx", "cy"], "left")
    right = right.withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.coalesce("parts", F.lit(1)) - 1)))
    met = left.select("object_id", "ts_us", "x", "y", "n", "tru", "cx", "cy", "part").join(right.drop("parts"), ["tru", "cx", "cy", "part"])
    # inside one key both orders meet: the one with the smaller object first is taken
    once = (F.col("object_id") != F.col("o2")) & (~F.col("same") | (F.col("object_id") < F.col("o2")))
    close = (F.abs(F.col("ts_us") - F.col("t2")) <= th.time_us) & (sq_dist("x", "y", "x2", "y2") <= th.dist_m * th.dist_m)
    pairs = met.where(once & close)
    return (
        pairs.groupBy(F.least("object_id", "o2").alias("object_a"), F.greatest("object_id", "o2").alias("object_b"))
        .agg(F.sum(F.col("n") * F.col("n2")).alias("similarity"))
        .where(F.col("similarity") >= min_sim)
    )


def too_fast(dist_m: Column, gap_us: Column, kmh: float) -> Column:
    """Speed above ``kmh``, without division: two places at one instant are too fast, one place never is."""
    return dist_m * F.lit(3.6e6) > F.lit(float(kmh)) * gap_us


def _steps(e: DataFrame, partition: list[str], metric: str) -> DataFrame:
    """Each edge with the edge before it in its partition (p_ columns)."""
    m = METRICS[metric]
    w = Window.partitionBy(*partition).orderBy("ts_us", "location_id")
    return e.withColumns({f"p_{c}": F.lag(c).over(w) for c in ("ts_us", "location_id", *m.columns)}).where("p_ts_us is not null")


def _violations(steps: DataFrame, kmh: float, metric: str) -> DataFrame:
    m = METRICS[metric]
    dist = m.distance(*[F.col(f"p_{c}") for c in m.columns], *[F.col(c) for c in m.columns])
    return steps.withColumn("dist_m", dist).where(too_fast(F.col("dist_m"), F.col("ts_us") - F.col("p_ts_us"), kmh))


def clone_evidence(g: TraceGraph | Layouts, rng: TimeRange | None, kmh: float = 120.0, metric: str = "euclid") -> DataFrame:
    """The consecutive edges that need more than ``kmh``: object, both edges, distance, seconds and speed (null for no time)."""
    lay = _layouts(g)
    e = _with_location(lay, rng, metric)
    bad = _violations(_steps(e, ["object_id"], metric), kmh, metric)
    gap = (F.col("ts_us") - F.col("p_ts_us")).cast("double")
    return bad.select(
        "object_id",
        F.col("p_ts_us").alias("ts1_us"),
        F.col("p_location_id").alias("loc1"),
        F.col("ts_us").alias("ts2_us"),
        F.col("location_id").alias("loc2"),
        "dist_m",
        (gap / 1e6).alias("seconds"),
        F.when(gap > 0, F.col("dist_m") * 3.6e6 / gap).alias("kmh"),
    )


def _with_location(lay: Layouts, rng: TimeRange | None, metric: str) -> DataFrame:
    columns = METRICS[metric].columns
    edges = lay.kt(rng).select("object_id", "ts_us", "location_id", "tru", "slot")
    return edges.join(small(lay.g.locations.select("location_id", *columns)), "location_id")


def clone_objects(
    g: TraceGraph | Layouts, rng: TimeRange | None, kmh: float = 120.0, method: str = "lag", metric: str = "euclid"
) -> DataFrame:
    """Q4: objects with two edges whose speed is above ``kmh``.

    For a metric distance a violating pair exists just when a violating pair of time neighbours does (``lag``);
    ``stitched`` looks inside buckets first and then only at each bucket's ends; ``pairs`` is the definition itself and
    is forced where the distance is no metric.
    """
    lay = _layouts(g)
    m = METRICS[metric]
    if not m.is_metric:
        method = "pairs"
    e = _with_location(lay, rng, metric)
    if method == "lag":
        return _violations(_steps(e, ["object_id"], metric), kmh, metric).select("object_id").distinct()
    if method == "stitched":
        inside = _violations(_steps(e, ["slot", "object_id", "tru"], metric), kmh, metric).select("object_id")
        row = F.struct("ts_us", "location_id", *m.columns)
        ends = e.groupBy("object_id", "tru").agg(F.min(row).alias("a"), F.max(row).alias("z"))
        edges = ends.select("object_id", F.explode(F.array_distinct(F.array("a", "z"))).alias("r")).select("object_id", "r.*")
        return inside.union(_violations(_steps(edges, ["object_id"], metric), kmh, metric).select("object_id")).distinct()
    if method == "pairs":
        left = e.select("object_id", F.col("ts_us").alias("p_ts_us"), *[F.col(c).alias(f"p_{c}") for c in m.columns])
        pairs = left.join(e, "object_id").where(F.col("p_ts_us") <= F.col("ts_us"))
        return _violations(pairs, kmh, metric).select("object_id").distinct()
    raise ValueError(f"method {method!r}: choose lag, stitched or pairs")
