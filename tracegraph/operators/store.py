"""Two stores of sub-partitions: each property's compressed column apart (split), or all of them in one value (packed)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracegraph.sources import files

CODECS = ("snappy", "lz4_raw", "zstd", "gzip", "none")
CORE = ("object_id", "ts_us", "location_id")
#: Values of a property that a row of the split store holds at most, and rows of a Parquet row group: readers unpack a group's arrays at once.
ROWS_PER_VALUE, ROWS_PER_GROUP = 4096, 128


def write_split(edges: DataFrame, path: str, key: Column, props: list[str], codec: str = "snappy") -> None:
    """One dataset per property: its values by ``row_key``, ``ROWS_PER_VALUE`` at most in a row; ``row_part`` names a row, the same in all datasets.

    Row order inside a key is by time. Ranges follow the whole order, so a busy key is dealt over several tasks. The rows are
    sorted and cut once, into ``_rows``; the datasets are its columns.
    """
    if codec not in CODECS:
        raise ValueError(f"codec {codec!r}: choose one of {CODECS}")
    columns, order = list(dict.fromkeys([*CORE, *props])), ["row_key", "ts_us", "object_id", "location_id"]
    rows = edges.withColumn("row_key", key).select("row_key", *columns)
    ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order).select(F.monotonically_increasing_id().alias("row_part"), "*")
    most = ROWS_PER_VALUE

    def cut(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            names = batch.column("row_key")
            new = pc.fill_null(pc.not_equal(names.slice(1), names.slice(0, len(names) - 1)), True).to_numpy(zero_copy_only=False)
            bounds = np.concatenate([[0], np.flatnonzero(new) + 1, [len(names)]])
            starts = np.concatenate([np.arange(a, b, most) for a, b in zip(bounds, bounds[1:])])
            offsets, at = pa.array(np.append(starts, len(names)), pa.int32()), pa.array(starts)
            lists = [pa.ListArray.from_arrays(offsets, batch.column(c)) for c in columns]
            yield pa.RecordBatch.from_arrays([names.take(at), batch.column("row_part").take(at), *lists], ["row_key", "row_part", *columns])

    types = {f.name: f.dataType for f in rows.schema}
    schema = T.StructType([T.StructField("row_key", types["row_key"]), T.StructField("row_part", T.LongType()), *[T.StructField(c, T.ArrayType(types[c])) for c in columns]])
    options = {"parquet.block.size": 64 << 20, "parquet.block.row.count.limit": ROWS_PER_GROUP}
    spark, whole = edges.sparkSession, f"{path}/_rows"
    ranged.mapInArrow(cut, schema).write.mode("overwrite").options(**options).parquet(whole)
    for c in columns:
        out = spark.read.schema(schema).parquet(whole).select("row_key", "row_part", c)
        out.write.mode("overwrite").options(compression=codec, **options).parquet(f"{path}/{c}")
    files.delete(spark, whole)


def read_split(spark: SparkSession, path: str, columns: list[str], keys: Column | None = None) -> DataFrame:
    """Only the datasets of ``columns`` are read; their rows are zipped.

    The join is always by merging: files of repeated values are tiny beside the arrays in them, so their size says nothing of a broadcast's.
    """
    out = None
    for c in columns:
        part = spark.read.parquet(f"{path}/{c}")
        part = part.where(keys) if keys is not None else part
        out = part if out is None else out.join(part.drop("row_key").hint("merge"), "row_part")
    first, *rest = columns
    at = out.select("row_key", *rest, F.posexplode(first).alias("row_pos", first))
    return at.select("row_key", *[F.col(c) if c == first else F.col(c)[F.col("row_pos")].alias(c) for c in columns])


def write_packed(edges: DataFrame, path: str, key: Column, props: list[str], codec: str = "lz4") -> None:
    """All columns of a sub-partition in one binary value: an Arrow stream with a compressed buffer for each column."""
    columns = list(dict.fromkeys([*CORE, *props]))

    def pack(group):
        name = group.column("row_key")[0].as_py()
        body = group.select(columns).sort_by("ts_us").combine_chunks()
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, body.schema, options=pa.ipc.IpcWriteOptions(compression=codec)) as writer:
            writer.write_table(body)
        return pa.table({"row_key": pa.array([name]), "n": pa.array([body.num_rows], pa.int64()), "packed": pa.array([sink.getvalue().to_pybytes()], pa.binary())})

    packed = edges.withColumn("row_key", key).select("row_key", *columns).groupBy("row_key").applyInArrow(pack, "row_key string, n long, packed binary")
    packed.write.mode("overwrite").option("compression", "none").parquet(path)


def read_packed(spark: SparkSession, path: str, schema: str, keys: Column | None = None) -> DataFrame:
    """Inverse of ``write_packed``; every column is read whatever ``schema`` keeps. ``schema``: row_key and wanted columns."""
    rows = spark.read.parquet(path)
    rows = rows.where(keys) if keys is not None else rows
    wanted = [c.split()[0] for c in schema.split(",")][1:]

    def unpack(batches):
        for batch in batches:
            for name, data in zip(batch.column("row_key").to_pylist(), batch.column("packed"), strict=True):
                body = pa.ipc.open_stream(data.as_buffer()).read_all()
                for part in body.select(wanted).to_batches():
                    yield pa.RecordBatch.from_arrays([pa.array([name] * part.num_rows, pa.string()), *part.columns], ["row_key", *wanted])

    return rows.select("row_key", "packed").mapInArrow(unpack, schema)
