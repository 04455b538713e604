"""Shared pieces of the corpus operators: words, shared-folder tables, gapless ranks."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from collections.abc import Iterable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Characters that separate words in the contracts: the space and U+0009 to U+000D.
SPACES = " \t\n\x0b\x0c\r"
SPACE_CLASS = r"[\x20\x09-\x0D]+"

_kept: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a local one only where that is unset."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if re.match(r"local(\[|$)", sc.master):
        return f"file://{tempfile.gettempdir()}/corpus-shared"
    raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")


def remove(spark: SparkSession, path: str) -> None:
    """Delete a table written by ``materialise``."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _remove_kept() -> None:
    for spark, path in _kept:
        try:
            remove(spark, path)
        except Exception:  # the session may be gone already
            return


class Stored:
    """A written table: ``df`` reads it, ``drop()`` deletes its files once nothing needs them."""

    def __init__(self, spark: SparkSession, path: str, schema):
        self.spark, self.path = spark, path
        self.df = spark.read.schema(schema).parquet(path)
        _kept.append((spark, path))

    def drop(self) -> None:
        remove(self.spark, self.path)
        _kept[:] = [x for x in _kept if x[1] != self.path]


def store(df: DataFrame, tag: str, parts: int | None = None) -> Stored:
    """Cut the lineage: write ``df`` as Parquet in the shared folder, so a lost executor costs no recomputation.

    ``parts``: number of files of a table that is small whatever the corpus (a row per group): many tiny
    files would make it look too large to broadcast.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
    (df.repartition(parts) if parts else df).write.option("compression", "zstd").parquet(path)
    return Stored(spark, path, df.schema)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """``store`` for a table that the result still reads; its files go when the process ends."""
    return store(df, tag).df


def words_of(text: Column) -> Column:
    """array<string> of the words of a text; none for null."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE_CLASS), lambda w: w != "")


def let(value: Column, use) -> Column:
    """``use(v)`` with ``value`` computed once: inside a lambda a plain reference would be computed for each element."""
    return F.element_at(F.transform(F.array(value), use), 1)


def gapless_rank(
    df: DataFrame, by: Sequence[str], bucket: Column, order: Iterable[Column], name: str, tag: str = "__"
) -> DataFrame:
    """0-based rank without gaps within ``by``, ordered by ``bucket`` and then ``order``.

    No task ever holds a whole ``by`` group: rows are numbered within (by, bucket)
    and moved up by the counts of the buckets before. ``bucket`` has a bounded number of
    values and should spread any hot group.
    """
    b, n, off, r = f"{tag}b", f"{tag}n", f"{tag}off", f"{tag}r"
    marked = df.withColumn(b, bucket)
    counts = marked.groupBy(*by, b).agg(F.count(F.lit(1)).alias(n))
    before = Window.partitionBy(*by).orderBy(b).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*by, b, F.coalesce(F.sum(n).over(before), F.lit(0)).alias(off))
    ranked = marked.withColumn(r, F.row_number().over(Window.partitionBy(*by, b).orderBy(*order)))
    return ranked.join(offsets, [*by, b]).withColumn(name, F.col(off) + F.col(r) - 1).drop(b, off, r)

