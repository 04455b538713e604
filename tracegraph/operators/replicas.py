"""Copies of an edge: one per layout, one more where both layouts put it on the same worker; recovery after a loss."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegraph.functions.geometry import region_of
from tracegraph.functions.slots import slot_of, worker_of_slot
from tracegraph.model import GraphSpec

from .prune import small


def with_workers(edges: DataFrame, locations: DataFrame, mapping: DataFrame, spec: GraphSpec) -> DataFrame:
    """Edges with w_s (ST worker), w_k (KT worker) and tru.

    Location -> worker is joined first, on the small side; edges at unmapped locations fall to worker 0.
    """
    at = locations.select("location_id", region_of("x", "y", spec).alias("region")).join(mapping.select("region", "worker"), "region", "left")
    at = at.select("location_id", F.coalesce("worker", F.lit(0)).cast("int").alias("w_s"))
    return edges.join(small(at), "location_id", "left").withColumns(
        {
            "w_s": F.coalesce("w_s", F.lit(0)),
            "w_k": worker_of_slot(slot_of("object_id", spec.p, spec.hash_kind), spec.n_workers),
            "tru": F.expr(f"ts_us div {spec.tru_us}"),
        }
    )


def _copies(n: int) -> Column:
    s = F.struct(F.lit("s").alias("copy"), F.col("w_s").alias("worker"))
    k = F.struct(F.lit("k").alias("copy"), F.col("w_k").alias("worker"))
    f = F.struct(F.lit("f").alias("copy"), ((F.col("w_s") + 1) % n).cast("int").alias("worker"))
    return F.when(F.col("w_s") == F.col("w_k"), F.array(s, k, f)).otherwise(F.array(s, k))


def placement(placed: DataFrame, n_workers: int) -> DataFrame:
    """One row per copy: ``s`` and ``k`` for the layouts, ``f`` on the next worker where both meet."""
    return placed.withColumn("c", F.explode(_copies(n_workers))).select(*placed.columns, "c.copy", "c.worker")


def collision_replicas(placed: DataFrame, n_workers: int) -> DataFrame:
    return placed.where("w_s = w_k").withColumn("worker", ((F.col("w_s") + 1) % n_workers).cast("int"))


def recover_worker(copies: DataFrame, lost: int, keys: tuple[str, ...] = ("edge_id",)) -> tuple[DataFrame, DataFrame]:
    """(edges that had a copy on the lost worker, rebuilt from the other workers' copies; those without any copy left)."""
    alive = copies.where(F.col("worker") != lost)
    needed = copies.where(F.col("worker") == lost).select(*keys).distinct()
    rebuilt = alive.join(needed, list(keys), "left_semi").dropDuplicates(list(keys))
    return rebuilt, needed.join(alive.select(*keys).distinct(), list(keys), "left_anti")
