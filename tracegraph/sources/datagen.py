"""Trace generator: weekly shopping visits near home, frequent and rare shoppers, a few clones far away.

Arithmetic hashes instead of random numbers, so that any engine makes the same edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracegraph.model import DAY_US, HOUR_US

WEEK_US = 7 * DAY_US
#: 2022-01-03T00:00Z, a Monday.
START_US = 1_641_168_000_000_000
AREAS = 25


def _places_by_rank(places: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Places numbered within their area, and for each area the nearest following one that has places."""
    rank = F.row_number().over(Window.partitionBy("area").orderBy("location_id")) - 1
    ranked = places.select("area", "location_id").withColumn("rnk", rank.cast("bigint"))
    counts = places.groupBy("area").agg(F.count(F.lit(1)).alias("n"))
    wanted = places.sparkSession.range(AREAS).select(F.col("id").cast("int").alias("home"))
    step = F.pmod(F.col("area") - F.col("home"), F.lit(AREAS))
    use = (
        wanted.join(F.broadcast(counts), F.lit(True))  # 25 areas on either side
        .groupBy("home")
        .agg(F.min(F.struct(step.alias("step"), "area", "n")).alias("u"))
        .select("home", F.col("u.area").alias("area"), F.col("u.n").alias("n"))
    )
    return ranked, use


def generate_edges(
    customers: DataFrame,
    places: DataFrame,
    weeks: int = 114,
    p_frequent: int = 800,
    p_rare: int = 200,
    frequent_of_10: int = 4,
    clone_stride: int = 97,
    visits: int = 1,
) -> DataFrame:
    """object_id, ts_us, location_id, week, is_clone from customers (object_id, home) and places (location_id, area)."""
    ranked, use = _places_by_rank(places)
    c, w, v = F.col("object_id"), F.col("week"), F.col("visit")
    limit = F.when(c % 10 < frequent_of_10, p_frequent).otherwise(p_rare)
    base = (
        customers.select("object_id", "home")
        .withColumn("week", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(weeks - 1).cast("bigint"))))
        .withColumn("visit", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(visits - 1).cast("bigint"))))
        .where((48271 * c + 69621 * w + 12345 + 7717 * v) % 1000 < limit)
        .withColumn("ts_us", F.lit(START_US) + w * WEEK_US + ((31 * c + 17 * w + 5 * v) % (7 * 24)) * HOUR_US)
        .withColumn("pick", (7919 * c + 104729 * w + 13 * v) % 1_000_003)
        .withColumn("is_clone", F.lit(False))
    )
    copies = (
        base.where((c % clone_stride == 0) & (w == c % weeks) & (v == 0))
        .withColumn("home", ((F.col("home") + 12) % AREAS).cast("int"))
        .withColumn("ts_us", F.col("ts_us") + HOUR_US)
        .withColumn("is_clone", F.lit(True))
    )
    placed = base.unionByName(copies).join(F.broadcast(use), "home").withColumn("rnk", F.col("pick") % F.col("n"))
    return placed.join(ranked, ["area", "rnk"]).select("object_id", "ts_us", "location_id", "week", "is_clone")
