"""The systems that the layouts are compared with: adjacency lists, relational SQL, full scans, a Z-order index, partitioners.

Each keeps its own stored table, written once by ``build`` and read by every query, as the layouts do: bytes read can be set side by side.
Without ``build`` the queries run over the edge table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracegraph.functions.geometry import sq_dist
from tracegraph.functions.slots import slot_of, slot_of_int
from tracegraph.model import Thresholds, TimeRange, TraceGraph, in_range
from tracegraph.sources.files import scratch

from .layouts import ROWS_PER_FILE, located, st_columns, write_clustered
from .prune import bucket_reach, in_intervals, intervals, neighbours, regions_touching, small
from .queries import TRACE_ROWS, too_fast

#: Edges in one adjacency row at most, about: a busy place has many rows.
CHUNK = 10_000


class Adjacency:
    """Property graph: each edge is kept at both of its ends, twice the bytes; simple traversals only."""

    def __init__(self, g: TraceGraph):
        self.g = g
        self.by_object = self._lists("object_id", "location_id")
        self.by_location = self._lists("location_id", "object_id")

    def _lists(self, vertex: str, other: str) -> DataFrame:
        """vertex, tru, chunk and edges: the list of a vertex is cut by time bucket, and a long one by hash."""
        e = self.g.edges.select(vertex, other, "ts_us", F.expr(f"ts_us div {self.g.spec.tru_us}").alias("tru"))
        long_ = e.groupBy(vertex, "tru").agg(F.ceil(F.count(F.lit(1)) / CHUNK).alias("chunks")).where("chunks > 1")
        dealt = e.join(small(long_), [vertex, "tru"], "left")
        chunk = F.pmod(F.xxhash64(other, "ts_us"), F.coalesce("chunks", F.lit(1)))
        return dealt.groupBy(vertex, "tru", chunk.alias("chunk")).agg(F.collect_list(F.struct("ts_us", other)).alias("edges"))

    def build(self, path: str) -> Adjacency:
        spark, rows = self.g.edges.sparkSession, self.g.edges.count()
        for name, vertex in (("by_object", "object_id"), ("by_location", "location_id")):
            lists = getattr(self, name)
            lists.repartitionByRange(max(1, rows // ROWS_PER_FILE), vertex, "tru").sortWithinPartitions(vertex, "tru").write.mode("overwrite").parquet(f"{path}/{name}")
            setattr(self, name, spark.read.parquet(f"{path}/{name}"))
        return self

    def q1(self, object_id: int, rng: TimeRange) -> DataFrame:
        lo, hi = rng.buckets(self.g.spec.tru_us)
        lists = self.by_object.where((F.col("object_id") == object_id) & F.col("tru").between(lo, hi))
        mine = lists.select("object_id", F.explode("edges").alias("e")).select("object_id", "e.*")
        return in_range(mine, rng).orderBy("ts_us", "location_id")

    def q2(self, o1: int, o2: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        a, b = (located(self.q1(o, rng), self.g.locations) for o in (o1, o2))
        return _count_pairs(a, b, o1, o2, th)


def _count_pairs(a: DataFrame, b: DataFrame, o1: int, o2: int, th: Thresholds) -> DataFrame:
    t = a.select(F.col("ts_us").alias("ta"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    near = (F.abs(F.col("ta") - F.col("ts_us")) <= th.time_us) & (sq_dist("ax", "ay", "x", "y") <= th.dist_m**2)
    return b.join(small(t), near).agg(F.count(F.lit(1)).alias("similarity")).select(
        F.lit(o1).cast("bigint").alias("object_a"), F.lit(o2).cast("bigint").alias("object_b"), "similarity"
    )


class Relational:
    """Edge table joined with the location table in plain SQL; clones by all pairs of an object's edges.

    The stored table is partitioned by a hash of the vertex, then by day, and not compressed.
    """

    PARTS = 3  # 2^3 hash partitions

    def __init__(self, g: TraceGraph, tag: str = "rel"):
        self.spark: SparkSession = g.edges.sparkSession
        self.g, self.tag, self.stored = g, tag, False
        g.edges.createOrReplaceTempView(f"{tag}_edges")
        g.locations.createOrReplaceTempView(f"{tag}_locations")

    def build(self, path: str) -> Relational:
        e = self.g.edges.withColumns({"part": slot_of("object_id", self.PARTS), "day": F.expr(f"ts_us div {self.g.spec.tru_us}")})
        write_clustered(e, path, ["part", "day", "object_id", "ts_us"], ["part", "day"], e.count(), compression="uncompressed")
        self.spark.read.parquet(path).createOrReplaceTempView(f"{self.tag}_edges")
        self.stored = True
        return self

    def _view(self, rng: TimeRange, object_id: int | None = None) -> str:
        where = [f"e.ts_us >= {rng.start_us}", f"e.ts_us <= {rng.last_us}"]
        if self.stored:
            lo, hi = rng.buckets(self.g.spec.tru_us)
            where.append(f"e.day between {lo} and {hi}")
            if object_id is not None:
                where.append(f"e.part = {slot_of_int(object_id, self.PARTS)}")
        return (
            f"(select e.object_id, e.ts_us, e.location_id, l.x, l.y from {self.tag}_edges e join {self.tag}_locations l"
            f" on e.location_id = l.location_id where {' and '.join(where)})"
        )

    def q1(self, object_id: int, rng: TimeRange) -> DataFrame:
        return self.spark.sql(
            f"select object_id, ts_us, location_id from {self._view(rng, object_id)} where object_id = {object_id} order by ts_us, location_id"
        )

    def q2(self, o1: int, o2: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        return self.spark.sql(
            f"select cast({o1} as bigint) object_a, cast({o2} as bigint) object_b, count(*) similarity from {self._view(rng, o1)} a, {self._view(rng, o2)} b"
            f" where a.object_id = {o1} and b.object_id = {o2} and {_close(th)}"
        )

    def q3(self, object_id: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        v = self._view(rng)
        return self.spark.sql(
            f"select b.object_id, count(*) similarity from {self._view(rng, object_id)} a, {v} b where a.object_id = {object_id}"
            f" and b.object_id <> {object_id} and {_close(th)} group by b.object_id order by similarity desc, object_id"
        )

    def q4(self, rng: TimeRange, kmh: float) -> DataFrame:
        v = self._view(rng)
        return self.spark.sql(
            f"select distinct a.object_id from {v} a join {v} b on a.object_id = b.object_id and a.ts_us <= b.ts_us where"
            f" sqrt(cast((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) as double)) * 3.6e6 > {float(kmh)}D * (b.ts_us - a.ts_us)"
        )


def _close(th: Thresholds) -> str:
    return (
        f"abs(a.ts_us - b.ts_us) <= {th.time_us} and (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {th.dist_m**2}"
    )


class Scan:
    """Unclustered edges, locations preloaded: every query reads the table and shuffles for itself."""

    def __init__(self, g: TraceGraph):
        self.g = g
        self.edges = g.edges

    def build(self, path: str) -> Scan:
        """Files in order of arrival, here that of the edge numbers dealt by hash: no file is about one day or place."""
        self.edges.repartition(max(1, self.edges.count() // ROWS_PER_FILE, 8), "edge_id").write.mode("overwrite").parquet(path)
        self.edges = self.edges.sparkSession.read.parquet(path)
        return self

    def _rows(self, rng: TimeRange) -> DataFrame:
        return located(in_range(self.edges, rng), self.g.locations)

    def q1(self, object_id: int, rng: TimeRange) -> DataFrame:
        return self._rows(rng).where(F.col("object_id") == object_id).select("object_id", "ts_us", "location_id").orderBy("ts_us", "location_id")

    def q2(self, o1: int, o2: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        rows = self._rows(rng)
        return _count_pairs(rows.where(F.col("object_id") == o1), rows.where(F.col("object_id") == o2), o1, o2, th)

    def q3(self, object_id: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        rows = self._rows(rng)
        t = rows.where(F.col("object_id") == object_id).select(F.col("ts_us").alias("ta"), F.col("x").alias("ax"), F.col("y").alias("ay"))
        near = (F.abs(F.col("ta") - F.col("ts_us")) <= th.time_us) & (sq_dist("ax", "ay", "x", "y") <= th.dist_m**2)
        pairs = rows.where(F.col("object_id") != object_id).join(small(t), near)
        return pairs.groupBy("object_id").agg(F.count(F.lit(1)).alias("similarity")).orderBy(F.desc("similarity"), "object_id")

    def q4(self, rng: TimeRange, kmh: float) -> DataFrame:
        w = Window.partitionBy("object_id").orderBy("ts_us", "location_id")
        steps = self._rows(rng).withColumns({f"p_{c}": F.lag(c).over(w) for c in ("ts_us", "x", "y")}).where("p_ts_us is not null")
        dist = F.sqrt(sq_dist("p_x", "p_y", "x", "y").cast("double"))
        return steps.where(too_fast(dist, F.col("ts_us") - F.col("p_ts_us"), kmh)).select("object_id").distinct()


class ZIndex(Scan):
    """Edges sorted by (day, Z-code of the region): days can be skipped, and regions for Q3; objects cannot."""

    def __init__(self, g: TraceGraph):
        super().__init__(g)
        self.edges = st_columns(g.edges, g.locations, g.spec)

    def build(self, path: str) -> ZIndex:
        write_clustered(self.edges, path, ["tru", "region", "ts_us"], ["tru"], self.edges.count())
        self.edges = self.edges.sparkSession.read.parquet(path)
        return self

    def _rows(self, rng: TimeRange) -> DataFrame:
        lo, hi = rng.buckets(self.g.spec.tru_us)
        return in_range(self.edges.where(F.col("tru").between(lo, hi)), rng)

    def q3(self, object_id: int, rng: TimeRange, th: Thresholds) -> DataFrame:
        """The trace is found by reading the days whole; its regions then bound what is joined with it, day by day."""
        spec = self.g.spec
        trace = self._rows(rng).where(F.col("object_id") == object_id).select("ts_us", "x", "y")
        rows = self._rows(rng).where(F.col("object_id") != object_id)
        places = trace.select("x", "y").distinct().limit(TRACE_ROWS + 1).collect()
        if len(places) <= TRACE_ROWS:
            rows = rows.where(in_intervals("region", intervals(regions_touching([(r["x"], r["y"]) for r in places], th.dist_m, spec))))
        day = neighbours(F.expr(f"ts_us div {spec.tru_us}"), bucket_reach(th.time_us, spec.tru_us))
        t = trace.select(F.col("ts_us").alias("ta"), F.col("x").alias("ax"), F.col("y").alias("ay"), day.alias("tru"))
        near = (F.abs(F.col("ta") - F.col("ts_us")) <= th.time_us) & (sq_dist("ax", "ay", "x", "y") <= th.dist_m**2)
        pairs = rows.join(small(t), "tru").where(near)
        return pairs.groupBy("object_id").agg(F.count(F.lit(1)).alias("similarity")).orderBy(F.desc("similarity"), "object_id")


def random_layout(edges: DataFrame, n_workers: int, seed: int = 0) -> DataFrame:
    """Edges with a worker by portable hash of the edge: every query has to ask every worker."""
    mixed = slot_of(F.col("edge_id") * 2 + seed, 20)
    return edges.withColumn("worker", (mixed % n_workers).cast("int"))


def vertex_partition(edges: DataFrame, n_workers: int) -> tuple[DataFrame, DataFrame]:
    """Workers of objects and of locations, by portable hash: a vertex with its edges is the unit."""
    at = lambda c: F.pmod(F.col(c) * 48271, F.lit(n_workers)).cast("int")
    objects = edges.select("object_id").distinct().withColumn("worker", at("object_id"))
    places = edges.select("location_id").distinct().withColumn("worker", at("location_id"))
    return objects, places


def vertex_partition_greedy(edges: DataFrame, n_workers: int, rounds: int = 3, slack: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """Workers of objects and of locations that cut fewer edges, sizes kept even.

    Locations start by hash. In turn, each side moves to the worker that holds most of its neighbours; a worker takes the
    vertices that gain most, up to its share of the side's edges and a slack, the others stay where they are. Counts are combined before
    every shuffle; each move is written, which cuts the lineage.
    """

    def kept(df: DataFrame, tag: str) -> DataFrame:
        path = scratch(df.sparkSession, tag)
        df.write.parquet(path)
        return df.sparkSession.read.parquet(path)

    pairs = kept(edges.groupBy("object_id", "location_id").agg(F.count(F.lit(1)).alias("n")), "pairs")
    objects, places = (kept(x, "side") for x in vertex_partition(edges, n_workers))

    def move(side: str, other: str, at_other: DataFrame, before: DataFrame) -> DataFrame:
        votes = pairs.join(at_other, other).groupBy(side, "worker").agg(F.sum("n").alias("v"))
        best = votes.groupBy(side).agg(F.max(F.struct("v", (-F.col("worker")).alias("w"))).alias("b"), F.sum("v").alias("w"))
        best = best.select(side, (-F.col("b.w")).cast("int").alias("wish"), F.col("b.v").alias("gain"), "w")
        whole = best.agg(F.sum("w").alias("total"))
        # a worker's room, filled in order of gain: running sums inside (worker, gain octave), moved up by the octaves before
        octave = F.floor(F.log2("gain")).cast("int")
        sums = best.groupBy("wish", octave.alias("octave")).agg(F.sum("w").alias("s"))
        above = Window.partitionBy("wish").orderBy(F.desc("octave")).rowsBetween(Window.unboundedPreceding, 0)
        upto = sums.select("wish", "octave", F.sum("s").over(above).alias("upto"))
        room = best.withColumn("octave", octave).join(F.broadcast(upto), ["wish", "octave"]).join(F.broadcast(whole), F.lit(True))
        fits = F.col("upto") <= (1 + slack) * F.col("total") / n_workers
        return room.join(before.withColumnRenamed("worker", "old"), side).select(side, F.when(fits, F.col("wish")).otherwise(F.col("old")).alias("worker"))

    for _ in range(rounds):
        objects = kept(move("object_id", "location_id", places, objects), "objects")
        places = kept(move("location_id", "object_id", objects, places), "places")
    return objects, places


def cut_edges(edges: DataFrame, objects: DataFrame, places: DataFrame) -> DataFrame:
    """edges, and how many have their ends on different workers."""
    o = objects.select("object_id", F.col("worker").alias("wo"))
    p = places.select("location_id", F.col("worker").alias("wl"))
    both = edges.select("object_id", "location_id").join(small(o), "object_id").join(small(p), "location_id")
    return both.agg(F.count(F.lit(1)).alias("edges"), F.count(F.when(F.col("wo") != F.col("wl"), 1)).alias("cut"))


def edge_partition(edges: DataFrame, n_workers: int) -> DataFrame:
    return edges.withColumn("worker", F.pmod(F.col("edge_id") * 48271, F.lit(n_workers)).cast("int"))


def ghost_edges(placed: DataFrame) -> DataFrame:
    """side, vertices, copies and ghosts of an edge partitioning: a vertex on k workers has k - 1 ghosts."""

    def side(column: str) -> DataFrame:
        spread = placed.groupBy(column).agg(F.countDistinct("worker").alias("k"))
        return spread.agg(F.count(F.lit(1)).alias("vertices"), F.sum("k").alias("copies"), F.sum(F.col("k") - 1).alias("ghosts")).select(
            F.lit(column).alias("side"), "vertices", "copies", "ghosts"
        )

    return side("object_id").unionByName(side("location_id"))
