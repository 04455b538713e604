"""Readers and sinks with explicit schemas; nothing is inferred at scale."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from tracegraph.model import EDGE_CORE

_scratch: list[tuple[SparkSession, str]] = []

FORMATS = ("parquet", "orc", "csv", "json")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType = EDGE_CORE, **options) -> DataFrame:
    """Batch source of edges."""
    if fmt not in FORMATS:
        raise ValueError(f"format {fmt!r}: choose one of {FORMATS}")
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_jdbc(spark: SparkSession, url: str, query: str, column: str, lower: int, upper: int, parts: int, **options) -> DataFrame:
    """Edges from a relational store, read in parallel by ranges of ``column``."""
    return (
        spark.read.format("jdbc")
        .options(url=url, dbtable=f"({query}) q", partitionColumn=column, lowerBound=lower, upperBound=upper, numPartitions=parts, **options)
        .load()
    )


def stream_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType = EDGE_CORE, files_per_trigger: int | None = None) -> DataFrame:
    """File stream; files are taken in the order of their modification times."""
    reader = spark.readStream.format(fmt).schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.load(path)


def stream_rate(spark: SparkSession, rows_per_second: int, n_objects: int, n_locations: int) -> DataFrame:
    """Load-test stream of made-up edges."""
    from pyspark.sql import functions as F

    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rate.select(
        F.col("value").alias("edge_id"),
        (F.col("value") * 48271 % n_objects).alias("object_id"),
        F.unix_micros("timestamp").alias("ts_us"),
        (F.col("value") * 69621 % n_locations).alias("location_id"),
    )


def stream_kafka(spark: SparkSession, servers: str, topic: str, schema: T.StructType = EDGE_CORE) -> DataFrame:
    """Edges as JSON values of a Kafka topic; needs the connector on the class path."""
    from pyspark.sql import functions as F

    raw = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).load()
    return raw.select(F.from_json(F.col("value").cast("string"), schema).alias("e")).select("e.*")


def write_edges(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "overwrite", **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def to_noop(df: DataFrame) -> None:
    """Runs a query without keeping its result: what timings use."""
    df.write.format("noop").mode("overwrite").save()


def _fs(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def exists(spark: SparkSession, path: str) -> bool:
    fs, where = _fs(spark, path)
    return fs.exists(where)


def delete(spark: SparkSession, path: str) -> None:
    fs, where = _fs(spark, path)
    fs.delete(where, True)


def names(spark: SparkSession, path: str) -> list[str]:
    """Names of the entries of a folder; none if it isn't there."""
    fs, where = _fs(spark, path)
    return sorted(s.getPath().getName() for s in fs.listStatus(where)) if fs.exists(where) else []


def touch(spark: SparkSession, path: str) -> None:
    fs, where = _fs(spark, path)
    fs.create(where, True).close()


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """A small file that is there whole or not at all: written aside, then renamed."""
    fs, where = _fs(spark, path)
    jvm = spark.sparkContext._jvm
    aside = jvm.org.apache.hadoop.fs.Path(f"{path}.{uuid.uuid4().hex}.tmp")
    out = fs.create(aside, True)
    try:
        out.write(bytearray(text.encode()))
    finally:
        out.close()
    if not fs.rename(aside, where):
        fs.delete(where, False)
        if not fs.rename(aside, where):
            raise OSError(f"could not write {path}")


def read_text(spark: SparkSession, path: str) -> str:
    fs, where = _fs(spark, path)
    stream = fs.open(where)
    try:
        return bytes(spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
    finally:
        stream.close()


def make_folder(spark: SparkSession, path: str) -> None:
    fs, where = _fs(spark, path)
    fs.mkdirs(where)


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes of all files under a path."""
    fs, where = _fs(spark, path)
    return fs.getContentSummary(where).getLength()


def scratch(spark: SparkSession, tag: str) -> str:
    """A fresh path in the folder that driver and executors share (spark.checkpoint.dir); removed when the process ends."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.match(r"local(\[|$)", sc.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = f"file://{tempfile.gettempdir()}/trace-scratch"
    path = f"{base.rstrip('/')}/{tag}-{uuid.uuid4().hex}"
    _scratch.append((spark, path))
    return path


@atexit.register
def _remove_scratch() -> None:
    for spark, path in _scratch:
        try:
            delete(spark, path)
        except Exception:  # the session may be gone already
            return
