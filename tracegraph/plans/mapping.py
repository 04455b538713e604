"""Skew-aware mappings of regions to workers, their bounds and their measures."""

from __future__ import annotations

import heapq
import math
import warnings
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracegraph.functions.geometry import region_of, z_code_int, z_decode_int
from tracegraph.model import GraphSpec
from tracegraph.operators.prune import distance_join

#: Weights are collected for the sequential mappings: at most one row per region of the grid.
MOST_REGIONS = 1 << 22


@dataclass
class Mapping:
    """region -> (unit, worker) with the weights it was made from."""

    rows: list[tuple[int, int, int, int]]  # region, unit, worker, weight
    n_workers: int
    b: int | None

    def loads(self) -> list[int]:
        out = [0] * self.n_workers
        for _, _, w, n in self.rows:
            out[w] += n
        return out

    def skew(self) -> float:
        """Largest worker's weight over the mean, less one."""
        loads = self.loads()
        return max(loads) * self.n_workers / sum(loads) - 1 if sum(loads) else 0.0

    def df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "region long, unit long, worker int, weight long")


def region_weights(locations: DataFrame, spec: GraphSpec, edges: DataFrame | None = None) -> DataFrame:
    """region and weight: its number of locations, or with edges its number of edges."""
    placed = locations.select("location_id", region_of("x", "y", spec).alias("region"))
    if edges is not None:
        placed = edges.groupBy("location_id").agg(F.count(F.lit(1)).alias("n")).join(placed, "location_id")
        return placed.groupBy("region").agg(F.sum("n").alias("weight"))
    return placed.groupBy("region").agg(F.count(F.lit(1)).alias("weight"))


def collect_weights(weights: DataFrame) -> list[tuple[int, int]]:
    rows = weights.limit(MOST_REGIONS + 1).collect()
    if len(rows) > MOST_REGIONS:
        raise ValueError("more regions than the driver should hold: use map_regions_prefix")
    return sorted((r["region"], r["weight"]) for r in rows)


def map_regions_unbounded(weights: list[tuple[int, int]], n_workers: int, clamp: bool = True) -> Mapping:
    """Along the Z-curve, a worker takes regions until its weight reaches the mean; then the next one does."""
    share = sum(w for _, w in weights) / n_workers
    rows, worker, held = [], 0, 0
    for region, weight in sorted(weights):
        if held >= share and (not clamp or worker < n_workers - 1):
            worker, held = worker + 1, 0
        rows.append((region, worker, worker, weight))
        held += weight
    return Mapping(rows, max(n_workers, worker + 1), None)


def map_regions_prefix(weights: DataFrame, n_workers: int) -> DataFrame:
    """Distributed form without resets: worker = prefix weight over the mean. region, weight, worker.

    Prefix sums inside range partitions, moved up by the sums of the partitions before.
    """
    from tracegraph.operators.prune import small

    ranged = weights.repartitionByRange("region").withColumn("part", F.spark_partition_id())
    sums = ranged.groupBy("part").agg(F.sum("weight").alias("s"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    offsets = sums.select("part", F.coalesce(F.sum("s").over(before), F.lit(0)).alias("off"))
    inside = Window.partitionBy("part").orderBy("region").rowsBetween(Window.unboundedPreceding, -1)
    total = weights.agg(F.sum("weight").alias("total"))
    pre = ranged.withColumn("pre", F.coalesce(F.sum("weight").over(inside), F.lit(0)))
    joined = pre.join(small(offsets), "part").join(F.broadcast(total), F.lit(True))
    worker = F.least(F.floor((F.col("off") + F.col("pre")) * n_workers / F.col("total")), F.lit(n_workers - 1)).cast("int")
    return joined.select("region", "weight", worker.alias("worker"))


def unit_of(region: int, b: int, spec: GraphSpec) -> int:
    cx, cy = z_decode_int(region)
    return z_code_int(cx // b, cy // b)


def map_regions_bounded(weights: list[tuple[int, int]], n_workers: int, b: int | None, spec: GraphSpec) -> Mapping:
    """Units of b x b regions, heaviest first, each to the least loaded worker; ties by Z-code and worker.

    b None is the unbounded mapping. Units without weight are dealt round robin by their code.
    """
    if b is None:
        return map_regions_unbounded(weights, n_workers)
    units: dict[int, int] = {}
    for region, weight in weights:
        u = unit_of(region, b, spec)
        units[u] = units.get(u, 0) + weight
    heap = [(0, w) for w in range(n_workers)]
    placed: dict[int, int] = {}
    for unit, weight in sorted(units.items(), key=lambda x: (-x[1], x[0])):
        if not weight:
            placed[unit] = unit % n_workers
            continue
        load, worker = heapq.heappop(heap)
        placed[unit] = worker
        heapq.heappush(heap, (load + weight, worker))
    return Mapping([(r, u := unit_of(r, b, spec), placed[u], w) for r, w in sorted(weights)], n_workers, b)


def check_grid(spec: GraphSpec, dist_m: float, n_workers: int, occupied: int | None = None) -> list[str]:
    """Warnings where the grid breaks its rules of thumb."""
    found = []
    if spec.a < 10 * dist_m:
        found.append(f"region width {spec.a} is not far above the distance {dist_m}: many queries cross borders")
    if spec.grid_w < 16 or spec.grid_h < 16:
        found.append("regions are large against the universe")
    if (occupied or spec.n_regions) < 10 * n_workers:
        found.append("few regions for each worker")
    for text in found:
        warnings.warn(text, stacklevel=2)
    return found


def choose_width(universe: int, dist_m: int, n_workers: int) -> int:
    """A region width far above the distance that leaves each worker a hundred regions at least."""
    return max(10 * dist_m, 1, min(universe // 16, int(universe / math.sqrt(100 * n_workers))))


def b_bounds(dist: float, a: float, alpha: float, eps1: float, eps2: float) -> tuple[float, float, bool]:
    """Unit widths that keep near locations together (from below) and loads even (from above), and whether there are any."""
    floor = max(alpha, ((2 * a - dist) / (2 * a)) ** 2)
    low = dist / (2 * a * (1 - math.sqrt(floor))) if floor < 1 else math.inf
    high = math.sqrt(eps2 / eps1)
    return low, high, math.ceil(low) <= math.floor(high) and high >= 1


def spatial_factor(b: float, a: float, dist: float) -> float:
    """Lower bound of the probability that a location within ``dist`` lies in the same unit."""
    if b * a < 2 * dist and b * a != dist:
        return max(0.0, 1 - dist / (2 * b * a)) ** 2
    return (1 - dist / (2 * b * a)) ** 2


def nine_parts(b: float, a: float, dist: float) -> dict[str, tuple[float, float]]:
    """(share of the unit, mean probability of leaving it) of its inner part, four sides and four corners."""
    side = b * a
    if side < 2 * dist:
        raise ValueError("the unit must be at least twice as wide as the distance")
    return {
        "inner": (((side - 2 * dist) / side) ** 2, 0.0),
        "sides": (4 * (side - 2 * dist) * dist / side**2, 0.25),
        "corners": (4 * dist**2 / side**2, 7 / 16),
    }


def empirical_spatial_factor(locations: DataFrame, b: int, dist: int, spec: GraphSpec) -> DataFrame:
    """Pairs of locations within ``dist``, and how many share a unit."""
    pairs = distance_join(locations, dist)
    at = locations.select("location_id", F.expr(f"(x - {spec.origin_x}) div {spec.a * b}").alias("ux"), F.expr(f"(y - {spec.origin_y}) div {spec.a * b}").alias("uy"))
    left = at.select(F.col("location_id").alias("a"), F.struct("ux", "uy").alias("ua"))
    right = at.select(F.col("location_id").alias("b"), F.struct("ux", "uy").alias("ub"))
    both = pairs.join(left, "a").join(right, "b")
    return both.agg(F.count(F.lit(1)).alias("pairs"), F.count(F.when(F.col("ua") == F.col("ub"), 1)).alias("same_unit"))


def accessed_regions(mapping: DataFrame, regions: DataFrame, n_workers: int) -> DataFrame:
    """worker and regions: how many of a query's regions (region) each worker serves; workers without one count zero."""
    met = mapping.select("region", "worker").join(regions.select("region").distinct(), "region").groupBy("worker").agg(F.count(F.lit(1)).alias("n"))
    every = mapping.sparkSession.range(n_workers).select(F.col("id").cast("int").alias("worker"))
    return every.join(met, "worker", "left").select("worker", F.coalesce("n", F.lit(0)).alias("regions"))
