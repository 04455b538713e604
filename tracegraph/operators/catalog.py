"""What a stored layout consists of: files, bytes and rows by partition; the coordinator's view."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def layout_catalog(spark: SparkSession, path: str, method: str, group: str) -> DataFrame:
    """method, tru, grp, files, bytes, rows of a layout stored by (tru, group)."""
    files = spark.read.parquet(path).select("tru", F.col(group).alias("grp"), "_metadata.file_path", "_metadata.file_size")
    per_file = files.groupBy("tru", "grp", "file_path").agg(F.max("file_size").alias("bytes"), F.count(F.lit(1)).alias("rows"))
    return per_file.groupBy("tru", "grp").agg(
        F.count(F.lit(1)).alias("files"), F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows")
    ).select(F.lit(method).alias("method"), "tru", "grp", "files", "bytes", "rows")


def register_views(spark: SparkSession, views: dict[str, DataFrame]) -> None:
    for name, df in views.items():
        df.createOrReplaceTempView(name)
