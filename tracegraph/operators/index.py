"""The graph as an index beside relational tables: a trace query gives ids, a relational query semi-joins them."""

from __future__ import annotations

from pyspark.sql import DataFrame

from tracegraph.model import TimeRange, TraceGraph

from .queries import Layouts, edges_of


def vertex_ids(found: DataFrame, column: str = "object_id", name: str | None = None) -> DataFrame:
    """Distinct ids of the vertices that a query found, under the name of a relational key."""
    return found.select(found[column].alias(name or column)).distinct()


def edge_ids(g: TraceGraph | Layouts, objects: list[int], rng: TimeRange | None, name: str = "edge_id") -> DataFrame:
    """Ids of the edges of some objects in a range: read from their slots alone."""
    return edges_of(g, objects, rng).select("edge_id").withColumnRenamed("edge_id", name).distinct()
