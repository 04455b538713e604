"""Groups of vertices as the unit of placement, and rebalancing when a worker strays from the mean."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Groups that the driver plans for at most.
MOST_GROUPS = 1 << 20


@dataclass(frozen=True)
class Move:
    group_id: str
    source: int
    target: int
    load: int


def group_loads(edges: DataFrame, objects: DataFrame, group: Column | str) -> DataFrame:
    """group_id, objects and edges of each group; groups without edges count zero."""
    g = F.col(group) if isinstance(group, str) else group
    of = objects.select("object_id", g.alias("group_id"))
    per = edges.groupBy("object_id").agg(F.count(F.lit(1)).alias("n"))
    return of.join(per, "object_id", "left").groupBy("group_id").agg(
        F.count(F.lit(1)).alias("objects"), F.coalesce(F.sum("n"), F.lit(0)).alias("edges")
    )


def group_placement(loads: DataFrame, n_workers: int) -> DataFrame:
    """Groups to workers round robin by name: the start before any rebalancing."""
    rows = loads.limit(MOST_GROUPS + 1).collect()
    if len(rows) > MOST_GROUPS:
        raise ValueError("too many groups for the driver")
    placed = [(r["group_id"], i % n_workers, r["edges"]) for i, r in enumerate(sorted(rows, key=lambda r: str(r["group_id"])))]
    return loads.sparkSession.createDataFrame(placed, "group_id string, worker int, edges long")


def rebalance(placed: list[tuple[str, int, int]], n_workers: int, tolerance: float = 0.05) -> list[Move]:
    """Moves from the most to the least loaded worker while any is off the mean by more than the tolerance.

    Each move takes the group that brings the pair nearest to even; it stops when no move helps.
    """
    held: dict[int, dict[str, int]] = {w: {} for w in range(n_workers)}
    for name, worker, load in placed:
        held[worker][name] = load
    total = {w: sum(v.values()) for w, v in held.items()}
    mean = sum(total.values()) / n_workers
    moves: list[Move] = []
    while True:
        high, low = max(total, key=lambda w: (total[w], -w)), min(total, key=lambda w: (total[w], w))
        if max(total[high] - mean, mean - total[low]) <= tolerance * mean:
            return moves
        gap = total[high] - total[low]
        fit = [(abs(gap - 2 * load), name, load) for name, load in held[high].items() if 0 < load < gap]
        if not fit:
            return moves
        _, name, load = min(fit)
        held[low][name] = held[high].pop(name)
        total[high] -= load
        total[low] += load
        moves.append(Move(name, high, low, load))
