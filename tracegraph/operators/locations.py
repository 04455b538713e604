"""The location table that every worker holds: sent whole while it is small, and replaced as a whole when places change."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from tracegraph.model import TraceGraph

from .prune import small


def broadcast_locations(locations: DataFrame, limit_rows: int = 2_000_000) -> DataFrame:
    """The columns that queries need, with a broadcast hint while rows and bytes allow; beyond that joins shuffle."""
    return small(locations.select("location_id", "x", "y"), limit_rows)


def refresh_locations(g: TraceGraph, changes: DataFrame, path: str) -> TraceGraph:
    """The graph with changed and new locations (all columns of the table): a new version of the table under ``path``.

    A location that is changed twice has no defined order: that is refused. Edges are not touched; layouts of rounds that are
    closed keep the places that held when they were written.
    """
    twice = changes.groupBy("location_id").count().where("count > 1").limit(1).count()
    if twice:
        raise ValueError("a location is changed more than once")
    kept = g.locations.join(changes.select("location_id"), "location_id", "left_anti")
    kept.unionByName(changes.select(*g.locations.columns)).write.mode("overwrite").parquet(path)
    return replace(g, locations=g.locations.sparkSession.read.parquet(path))
