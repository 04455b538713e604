"""The two edge layouts: clustered by region then time (ST), and by key slot then time (KT).

A layout is a table plus derived columns that Catalyst can prune on. Slots and regions are sort keys
inside groups, not directories: millions of paths would defeat any store. Writes are partitioned by ranges of the whole
sort key with as many ranges as the rows need, so a hot slot, region or object is dealt over several files and tasks.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegraph.functions.geometry import cell, region_of, z_code, z_code_int, z_decode_int
from tracegraph.functions.slots import slot_of, slot_of_int, worker_of_slot
from tracegraph.model import GraphSpec, TraceGraph
from tracegraph.sources import files

from .prune import small

#: Edges in a file of a stored layout, about: some 128 MB of compressed columns.
ROWS_PER_FILE = 8_000_000


def tru(spec: GraphSpec, ts: str = "ts_us") -> Column:
    return F.expr(f"{ts} div {spec.tru_us}")


def kt_columns(edges: DataFrame, spec: GraphSpec) -> DataFrame:
    """Edges with slot, tru and worker."""
    return edges.withColumns({"slot": slot_of("object_id", spec.p, spec.hash_kind), "tru": tru(spec)}).withColumn(
        "worker", worker_of_slot("slot", spec.n_workers)
    )


def located(edges: DataFrame, locations: DataFrame) -> DataFrame:
    """Edges with x, y of their location: the location table is small and goes to every task, behind a check of its size."""
    return edges.join(small(locations.select("location_id", "x", "y")), "location_id")


def st_columns(edges: DataFrame, locations: DataFrame, spec: GraphSpec, mapping: DataFrame | None = None, how: str = "inner", **extra: Column) -> DataFrame:
    """Edges with x, y, region, gx, gy, tru; with a mapping (region, unit, worker) also unit and worker.

    ``how`` left keeps edges whose location is unknown, without coordinates. ``extra``: further columns made from a place's x and y.
    """
    places = locations.select(
        "location_id", "x", "y", region_of("x", "y", spec).alias("region"), cell("x", spec.eta).alias("gx"), cell("y", spec.eta).alias("gy"),
        *[c.alias(name) for name, c in extra.items()],
    )
    e = edges.join(small(places), "location_id", how).withColumn("tru", tru(spec))
    if mapping is None:
        return e
    return e.join(small(mapping.select("region", "unit", "worker")), "region", "left")


def row_key(method: Column | str, pid: Column | str, bucket: Column | str, node: Column | str) -> Column:
    """Key of a sub-partition: node, method letter, padded partition id, padded bucket; sorts as its parts do."""
    c = lambda v: F.col(v) if isinstance(v, str) else v
    return F.concat_ws(
        "|", F.lpad(c(node).cast("string"), 4, "0"), c(method), F.lpad(c(pid).cast("string"), 10, "0"), F.lpad(c(bucket).cast("string"), 8, "0")
    )


def parse_row_key(key: Column | str) -> dict[str, Column]:
    parts = F.split(F.col(key) if isinstance(key, str) else key, r"\|")
    return {
        "node": parts[0].cast("int"),
        "method": parts[1],
        "pid": parts[2].cast("bigint"),
        "bucket": parts[3].cast("bigint"),
    }


@dataclass(frozen=True)
class LayoutInfo:
    """How a stored layout is grouped; kept beside its files."""

    method: str
    groups: int
    rows: int
    b: int = 8


def groups_for(rows: int, buckets: int, most: int, rows_per_file: int = ROWS_PER_FILE) -> int:
    """A power of two of groups, so that a group of one time bucket fills a file or so."""
    want = rows / max(1, buckets) / rows_per_file
    return min(most, 1 << max(0, math.ceil(math.log2(max(1.0, want)))))


def slot_group(spec: GraphSpec, groups: int, slot: str = "slot") -> Column:
    return F.expr(f"{slot} * {groups} div {spec.n_slots}").cast("int")


def unit_column(spec: GraphSpec, b: int) -> Column:
    """Z-code of the unit of b x b regions that x, y lie in."""
    width = spec.a * b
    return z_code(F.expr(f"(x - {spec.origin_x}) div {width}"), F.expr(f"(y - {spec.origin_y}) div {width}"))


def unit_group(spec: GraphSpec, groups: int, b: int) -> Column:
    """Group of a unit, by hash: neighbouring units, which are busy together, fall into different groups."""
    return slot_of(unit_column(spec, b), groups.bit_length() - 1)


def unit_group_of_region(region: int, groups: int, b: int) -> int:
    cx, cy = z_decode_int(region)
    return slot_of_int(z_code_int(cx // b, cy // b), groups.bit_length() - 1)


def write_clustered(
    df: DataFrame, path: str, order: list[str], by: list[str], rows: int, rows_per_file: int = ROWS_PER_FILE, mode: str = "overwrite", **options
) -> None:
    """Write sorted by ``order`` in directories ``by``, its first columns: one range shuffle, ranges of ``rows_per_file`` rows or so.

    Ranges follow the whole order, so one busy key is split like any other; a task never holds more than its range.
    """
    sc = df.sparkSession.sparkContext
    ranges = max(math.ceil(rows / rows_per_file), min(sc.defaultParallelism, rows // 1000), 1)
    ranged = df.repartitionByRange(ranges, *order) if ranges > 1 else df.coalesce(1)
    ranged.sortWithinPartitions(*order).write.mode(mode).options(**options).partitionBy(*by).parquet(path)


KT_ORDER = ["tru", "slot_group", "slot", "object_id", "ts_us"]
ST_ORDER = ["tru", "unit_group", "region", "ts_us", "object_id"]


def build_kt(g: TraceGraph, path: str, groups: int | None = None, codec: str = "snappy", rows_per_file: int = ROWS_PER_FILE) -> LayoutInfo:
    """Write KT: files by (tru, slot group), sorted by slot, object, time; bloom filter on the object."""
    rows, buckets = _extent(g)
    info = LayoutInfo("kt", groups or groups_for(rows, buckets, g.spec.n_slots, rows_per_file), rows)
    e = kt_columns(g.edges, g.spec).withColumn("slot_group", slot_group(g.spec, info.groups))
    # the filter is sized for the objects that a group of a bucket can hold: the default takes a megabyte a file
    distinct = max(16, min(rows_per_file, rows // (buckets * info.groups)))
    bloom = {"parquet.bloom.filter.enabled#object_id": "true", "parquet.bloom.filter.expected.ndv#object_id": str(distinct)}
    options = {"compression": codec, "parquet.block.size": 64 << 20, **bloom}
    write_clustered(e, path, KT_ORDER, ["tru", "slot_group"], rows, rows_per_file, **options)
    _note(g.edges.sparkSession, path, info)
    return info


def build_st(g: TraceGraph, path: str, groups: int | None = None, codec: str = "snappy", rows_per_file: int = ROWS_PER_FILE) -> LayoutInfo:
    """Write ST: files by (tru, unit group), sorted by region and time, x and y kept with the edge."""
    rows, buckets = _extent(g)
    b = g.spec.b or 8
    info = LayoutInfo("st", groups or groups_for(rows, buckets, 1 << 14, rows_per_file), rows, b)
    e = st_columns(g.edges, g.locations, g.spec, how="left", unit_group=unit_group(g.spec, info.groups, b))
    e = e.withColumn("unit_group", F.coalesce("unit_group", F.lit(0)))  # unknown places
    write_clustered(e, path, ST_ORDER, ["tru", "unit_group"], rows, rows_per_file, compression=codec)
    _note(g.edges.sparkSession, path, info)
    return info


def _extent(g: TraceGraph) -> tuple[int, int]:
    """Edges, and how many time buckets they span."""
    t = F.expr(f"ts_us div {g.spec.tru_us}")
    n, lo, hi = g.edges.agg(F.count(F.lit(1)), F.min(t), F.max(t)).first()
    return n, (hi - lo + 1) if n and lo is not None else 1


def _note(spark: SparkSession, path: str, info: LayoutInfo) -> None:
    files.write_text(spark, f"{path}/_layout.json", json.dumps(info.__dict__))


def layout_info(spark: SparkSession, path: str) -> LayoutInfo:
    return LayoutInfo(**json.loads(files.read_text(spark, f"{path}/_layout.json")))
