"""Stored layouts and baseline tables of the given graphs: built once per session and folder, in the shared scratch folder."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import SparkSession

from tracegraph.model import TraceGraph
from tracegraph.operators import baselines as base
from tracegraph.operators.layouts import build_kt, build_st
from tracegraph.operators.queries import Layouts
from tracegraph.sources import tables as t
from tracegraph.sources.files import scratch

#: Groups of a day: the given tables are small, so they are set; ``groups_for`` chooses them from the rows elsewhere.
KT_GROUPS, ST_GROUPS = 8, 32

_built: dict[tuple, object] = {}
#: Paths and build times in seconds of what was stored, by (folder, name).
PATHS: dict[tuple[str, str], dict[str, str]] = {}
LOAD_SECONDS: dict[tuple[str, str], float] = {}


def once(spark: SparkSession, sf_dir: str, name: str, make: Callable[[str], object]):
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        began = time.perf_counter()
        path = scratch(spark, name)
        PATHS[sf_dir, name] = {name: path}
        _built[key] = make(path)
        LOAD_SECONDS[sf_dir, name] = time.perf_counter() - began
    return _built[key]


def layouts_of(spark: SparkSession, sf_dir: str, name: str, g: TraceGraph, kt_groups: int = KT_GROUPS, st_groups: int = ST_GROUPS) -> Layouts:
    def make(path: str) -> Layouts:
        PATHS[sf_dir, name] = {"kt": f"{path}/kt", "st": f"{path}/st"}
        build_kt(g, f"{path}/kt", kt_groups)
        build_st(g, f"{path}/st", st_groups)
        return Layouts.stored(g, f"{path}/kt", f"{path}/st")

    return once(spark, sf_dir, name, make)


def events(spark: SparkSession, sf_dir: str) -> Layouts:
    """Both layouts of the whole event graph."""
    return layouts_of(spark, sf_dir, "events", t.event_graph(spark, sf_dir))


def shop(spark: SparkSession, sf_dir: str) -> Layouts:
    """Both layouts of the whole shop graph; its seven years take buckets of thirty days."""
    return layouts_of(spark, sf_dir, "shop", t.shop_graph(spark, sf_dir, t.SHOP_SPEC.with_(tru_us=30 * t.SHOP_SPEC.tru_us)), 2, 2)


def baseline(spark: SparkSession, sf_dir: str, kind: str):
    """The stored table of a baseline system over the event graph."""
    made = {"relational": base.Relational, "scan": base.Scan, "zindex": base.ZIndex, "graph": base.Adjacency}[kind]
    return once(spark, sf_dir, kind, lambda path: made(t.event_graph(spark, sf_dir)).build(path))
