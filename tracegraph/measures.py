"""Measures of a run: time, files and bytes read, shuffled bytes, rows, skew, throughput, disk."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegraph.sources.files import size_of, to_noop


@dataclass(frozen=True)
class RunReport:
    seconds: float
    files: int
    bytes_read: int
    shuffle_bytes: int
    result_rows: int


def _number(text: str) -> int:
    """Value of a metric as Spark prints it: '1,234' or '12.5 MiB (..)' or a total followed by a breakdown."""
    units = {"B": 1, "KiB": 1 << 10, "MiB": 1 << 20, "GiB": 1 << 30, "TiB": 1 << 40}
    words = text.split("\n")[-1].replace(",", "").split()
    value = float(words[0])
    return int(value * units[words[1]]) if len(words) > 1 and words[1] in units else int(value)


def _metrics_of_last_execution(spark: SparkSession) -> dict[str, int]:
    """Sums of the SQL metrics of the latest finished execution, by name."""
    store = spark._jsparkSession.sharedState().statusStore()
    runs = store.executionsList()
    if runs.isEmpty():
        return {}
    last = runs.last()
    values, out = store.executionMetrics(last.executionId()), {}
    it = last.metrics().iterator()
    while it.hasNext():
        m = it.next()
        got = values.get(m.accumulatorId())
        if got.isDefined():
            try:
                out[m.name()] = out.get(m.name(), 0) + _number(got.get())
            except (ValueError, IndexError):
                continue
    return out


def measure(df: DataFrame, repeat: int = 1) -> RunReport:
    """Runs a query to a sink that keeps nothing; median time and the metrics of the last run."""
    spent = []
    for _ in range(repeat):
        t = time.perf_counter()
        to_noop(df)
        spent.append(time.perf_counter() - t)
    m = _metrics_of_last_execution(df.sparkSession)
    return RunReport(
        statistics.median(spent),
        m.get("number of files read", 0),
        m.get("size of files read", 0),
        m.get("shuffle bytes written", 0),
        df.count(),
    )


def speed_up(a: RunReport, b: RunReport) -> float:
    return b.seconds / a.seconds


def distribution(copies: DataFrame) -> DataFrame:
    """rows by worker of any table with a worker column."""
    return copies.groupBy("worker").agg(F.count(F.lit(1)).alias("rows"))


def load_skew(loads: list[int]) -> float:
    return max(loads) * len(loads) / sum(loads) - 1 if sum(loads) else 0.0


def standard_error(values: list[float]) -> float:
    return statistics.stdev(values) / math.sqrt(len(values)) if len(values) > 1 else 0.0


def throughput(edges: int, seconds: float, edge_bytes: int = 24) -> dict[str, float]:
    return {"edges_s": edges / seconds, "mb_s": edges * edge_bytes / seconds / 1e6}


def progress_rates(progress: list[dict]) -> list[tuple[str, float]]:
    """(time, rows per second) of a streaming query's progress events."""
    return [(p["timestamp"], float(p.get("processedRowsPerSecond") or 0.0)) for p in progress]


def disk_space(spark: SparkSession, paths: dict[str, str], replicas: dict[str, int] | None = None) -> dict[str, float]:
    """MB of each stored table times its replicas."""
    return {k: size_of(spark, p) / 1e6 * (replicas or {}).get(k, 1) for k, p in paths.items()}


def clone_accuracy(found: DataFrame, truth: DataFrame) -> dict[str, float]:
    """Precision and recall of clone detection against planted clones (object_id)."""
    f, t = found.select("object_id").distinct(), truth.select("object_id").distinct()
    both, n, m = f.join(t, "object_id", "left_semi").count(), f.count(), t.count()
    return {"precision": both / n if n else 1.0, "recall": both / m if m else 1.0}


def timed(run: Callable[[], object]) -> float:
    t = time.perf_counter()
    run()
    return time.perf_counter() - t
