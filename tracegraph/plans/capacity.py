"""Capacity arithmetic of a deployment: edges, bytes, machines, ingest rate."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession


def capacity(
    objects: int = 10**10,
    locations: int = 10**7,
    edges_per_day: int = 10**12,
    edges: int = 10**14,
    edge_bytes: int = 24,
    vertex_bytes: int = 100,
    replicas: int = 3,
    disk_tb: int = 10,
    worker_mb_s: float = 20.0,
) -> dict[str, float]:
    """Decimal units; ``rate_mib_s`` uses binary ones, which is how 24 TB a day become about 290 MB/s."""
    raw = edges * edge_bytes
    day = edges_per_day * edge_bytes
    return {
        "object_tb": objects * vertex_bytes / 1e12,
        "location_gb": locations * vertex_bytes / 1e9,
        "edge_pb": raw / 1e15,
        "stored_pb": raw * replicas / 1e15,
        "machines": float(math.ceil(raw * replicas / (disk_tb * 1e12))),
        "day_tb": day / 1e12,
        "rate_mb_s": day / 86_400 / 1e6,
        "rate_mib_s": (day / 1e12) * 2**20 / 86_400,
        "ingest_workers": float(math.ceil((day / 1e12) * 2**20 / 86_400 / worker_mb_s)),
    }


def capacity_table(spark: SparkSession, **options) -> DataFrame:
    return spark.createDataFrame([(k, round(v, 4)) for k, v in capacity(**options).items()], "measure string, value double")
