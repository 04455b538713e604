"""Graphs over the given tables: event edges, shop edges, parcel edges, vector locations."""

from __future__ import annotations

import datetime as dt

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegraph.model import DAY_US, GraphSpec, TimeRange, TraceGraph

#: 2024-01-01T00:00Z, where the events begin.
EVENTS_START_US = 1_704_067_200_000_000
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
#: Grid of the event places: 1,024 x 1,024 regions of 1,000 m.
EVENTS_SPEC = GraphSpec(a=1000, p=6)
SHOP_SPEC = GraphSpec(a=1000, p=6)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: Column) -> Column:
    """Microseconds of a zone-less timestamp read as UTC, whatever the session's zone."""
    return F.unix_micros(F.convert_timezone(F.lit("UTC"), F.current_timezone(), ts).cast("timestamp"))


def _ntz(us: int) -> Column:
    at = dt.datetime(1970, 1, 1) + dt.timedelta(microseconds=us)
    return F.lit(at.isoformat(sep=" ")).cast("timestamp_ntz")


def event_places(spark: SparkSession) -> DataFrame:
    """All 500 places, visited or not: five doors for each k, 20 k's in area 0 down to 2 in area 24.

    A local table: coordinates are plain columns for everything that is derived from them.
    """
    k = [i % 100 for i in range(500)]
    kind = [i // 100 for i in range(500)]
    area = [v * v // 400 for v in k]
    return spark.createDataFrame(
        pa.table(
            {
                "location_id": pa.array(range(500), pa.int64()),
                "x": pa.array([102400 + 204800 * (r % 5) + 1500 * (v % 7) + 60 * t for r, v, t in zip(area, k, kind, strict=True)], pa.int64()),
                "y": pa.array([102400 + 204800 * (r // 5) + 1500 * (v % 5) for r, v in zip(area, k, strict=True)], pa.int64()),
                "area": pa.array(area, pa.int32()),
            }
        )
    )


def event_edges(spark: SparkSession, sf_dir: str, rng: TimeRange | None = None) -> DataFrame:
    """edge_id, object_id, ts_us, location_id, event_type, value; a range is also pushed to the scan."""
    rows = read(spark, sf_dir, "events")
    if rng is not None:
        rows = rows.where((F.col("ts") >= _ntz(rng.start_us)) & (F.col("ts") <= _ntz(rng.last_us)))
    code = F.expr("case event_type " + " ".join(f"when '{t}' then {i}" for i, t in enumerate(EVENT_TYPES)) + " end")
    k = F.get_json_object("props", "$.k").cast("bigint")
    return rows.select(
        F.col("event_id").alias("edge_id"),
        F.col("user_id").alias("object_id"),
        micros(F.col("ts")).alias("ts_us"),
        (100 * code + k).cast("bigint").alias("location_id"),
        "event_type",
        "value",
    )


def event_graph(spark: SparkSession, sf_dir: str, rng: TimeRange | None = None, spec: GraphSpec = EVENTS_SPEC) -> TraceGraph:
    edges = event_edges(spark, sf_dir, rng)
    objects = read(spark, sf_dir, "events").select(F.col("user_id").alias("object_id")).distinct()
    return TraceGraph(event_places(spark), edges, objects, spec)


def shop_places(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n = F.col("s_suppkey"), F.col("s_nationkey").cast("bigint")
    return read(spark, sf_dir, "supplier").select(
        s.alias("location_id"),
        (102400 + 204800 * (n % 5) + 250 * ((37 * s) % 40)).alias("x"),
        (102400 + 204800 * F.expr("cast(s_nationkey as bigint) div 5") + 250 * ((61 * s) % 37)).alias("y"),
        F.col("s_nationkey").alias("area"),
    )


def _shipped() -> Column:
    second = (131 * F.col("l_orderkey") + 31 * F.col("l_partkey") + 7919 * F.col("l_linenumber").cast("bigint")) % 86400
    return micros(F.col("l_shipdate")) + 1_000_000 * second


def shop_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases: object is the customer, location the supplier; a bag, repeated lines are repeated edges."""
    lines, orders = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    props = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
    return lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]).select(
        (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("edge_id"),
        F.col("o_custkey").alias("object_id"),
        _shipped().alias("ts_us"),
        F.col("l_suppkey").alias("location_id"),
        *props,
    )


def shop_graph(spark: SparkSession, sf_dir: str, spec: GraphSpec = SHOP_SPEC) -> TraceGraph:
    objects = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("object_id"))
    return TraceGraph(shop_places(spark, sf_dir), shop_edges(spark, sf_dir), objects, spec)


def parcel_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scans: object is the parcel (order), location the scanner (supplier)."""
    return read(spark, sf_dir, "lineitem").select(
        (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("edge_id"),
        F.col("l_orderkey").alias("object_id"),
        _shipped().alias("ts_us"),
        F.col("l_suppkey").alias("location_id"),
    )


def parcel_graph(spark: SparkSession, sf_dir: str, spec: GraphSpec = SHOP_SPEC) -> TraceGraph:
    return TraceGraph(shop_places(spark, sf_dir), parcel_edges(spark, sf_dir), None, spec)


def vector_locations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("location_id"), "embedding", "label")


def events_days(n: int) -> TimeRange:
    return TimeRange.days(EVENTS_START_US, n)


def whole_shop_range() -> TimeRange:
    """Covers every shipment date of the given tables."""
    return TimeRange(0, 30_000 * DAY_US)
