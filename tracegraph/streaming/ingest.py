"""Ingestion in rounds: edges are staged as they come; a round of m time buckets is shuffled into both layouts once it is over.

A round is closed when the largest event time seen, less the delay, has passed its end. Closing writes both
layouts and the extra copies as a new version of the round, then a commit file that names the version and the batches it holds.
Everything follows from the commit files, so each step can be repeated and none counts twice:

- a batch's edges of a round are *held* once a commit of the round names the batch; replaying the batch stages them anew, where they are ignored;
- staged edges that no commit holds are *open* while their round is, and *late* once it is closed by other batches;
- ``merge_late`` writes a new version of a round from the current one and its late edges, and commits it with their batches:
  a crash before the commit leaves the old version in force, one after it leaves nothing to merge;
- leftovers (held staging folders, versions not in force) are swept whenever a round is committed, and never read.
"""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from tracegraph.functions.slots import slot_of
from tracegraph.model import HOUR_US, TRIPLET, GraphSpec
from tracegraph.operators.layouts import ROWS_PER_FILE, slot_group, st_columns, unit_group, write_clustered
from tracegraph.operators.replicas import placement, with_workers
from tracegraph.sources import files

#: Round of edges that no round can take: a null in the triplet.
REJECTED = -1
LAYOUTS = ("kt", "st", "extra")


@dataclass
class RoundLog:
    """What closing a round took."""

    round_id: int
    edges: int
    copies: int
    seconds: float


@dataclass(frozen=True)
class Commit:
    """The version of a round in force, and the batches whose edges it holds."""

    round_id: int
    version: int
    batches: frozenset[int]
    edges: int
    extra: int


@dataclass
class IngestStore:
    """Staged, stored and late edges under one path."""

    spark: SparkSession
    path: str
    spec: GraphSpec
    locations: DataFrame
    mapping: DataFrame
    m: int = 10
    t_delay_us: int = HOUR_US
    groups: int = 16
    rows_per_file: int = ROWS_PER_FILE
    max_ts: int = -1
    log: list[RoundLog] = field(default_factory=list)
    staged_log: list[tuple[int, int, float]] = field(default_factory=list)  # batch, edges, seconds
    _commits: dict[int, Commit] = field(default_factory=dict)

    def __post_init__(self) -> None:
        """Takes up where an earlier run stopped: the largest event time and the schema are kept beside the edges."""
        files.make_folder(self.spark, self._at("inbox"))
        self.schema: T.StructType | None = None
        if files.exists(self.spark, self._at("state.json")):
            state = json.loads(files.read_text(self.spark, self._at("state.json")))
            self.max_ts, self.schema = max(self.max_ts, state["max_ts"]), T.StructType.fromJson(state["schema"])

    @property
    def round_us(self) -> int:
        return self.m * self.spec.tru_us

    def _at(self, *parts: object) -> str:
        return "/".join([self.path, *map(str, parts)])

    # --- commits -------------------------------------------------------------------

    def commits(self) -> dict[int, Commit]:
        """The commit in force of each closed round: the one with the highest version."""
        newest: dict[int, int] = {}
        for name in files.names(self.spark, self._at("commits")):
            if name.endswith(".json"):
                r, v = (int(x) for x in name.removesuffix(".json").split("."))
                newest[r] = max(v, newest.get(r, 0))
        for r, v in newest.items():
            if r not in self._commits or self._commits[r].version != v:
                c = json.loads(files.read_text(self.spark, self._at("commits", f"{r}.{v}.json")))
                self._commits[r] = Commit(r, v, frozenset(c["batches"]), c["edges"], c["extra"])
        return self._commits

    def closed(self) -> set[int]:
        return set(self.commits())

    def _commit(self, c: Commit) -> None:
        text = json.dumps({"batches": sorted(c.batches), "edges": c.edges, "extra": c.extra})
        files.write_text(self.spark, self._at("commits", f"{c.round_id}.{c.version}.json"), text)

    # --- staging -------------------------------------------------------------------

    def stage(self, batch: DataFrame, batch_id: int) -> None:
        """Keep a micro-batch by round under its id: writing it again replaces it. One pass over the batch."""
        began = time.perf_counter()
        if self.schema is None:
            self.schema = T.StructType([T.StructField(f.name, f.dataType) for f in batch.schema])
        bad = F.lit(False)
        for c in TRIPLET:
            bad = bad | F.col(c).isNull()
        seen = Observation()
        marked = batch.withColumn("round", F.when(bad, REJECTED).otherwise(F.expr(f"ts_us div {self.round_us}")).cast("bigint"))
        marked = marked.observe(seen, F.max("ts_us").alias("top"), F.count(F.lit(1)).alias("n"))
        marked.write.mode("overwrite").partitionBy("round").parquet(self._at("inbox", f"batch={batch_id}"))
        got = seen.get
        if got.get("top") is not None and got["top"] > self.max_ts:
            self.max_ts = got["top"]
        files.write_text(self.spark, self._at("state.json"), json.dumps({"max_ts": self.max_ts, "schema": json.loads(self.schema.json())}))
        self.staged_log.append((batch_id, got.get("n") or 0, time.perf_counter() - began))

    def _waiting(self) -> dict[int, set[int]]:
        """round -> batches with staged edges of it that no commit holds."""
        commits, out = self.commits(), {}
        for name in files.names(self.spark, self._at("inbox")):
            if not name.startswith("batch="):
                continue
            for part in files.names(self.spark, self._at("inbox", name)):
                if part.startswith("round="):
                    r, b = int(part[6:]), int(name[6:])
                    if r not in commits or b not in commits[r].batches:
                        out.setdefault(r, set()).add(b)
        return out

    def _read(self, waiting: dict[int, set[int]]) -> DataFrame | None:
        """Staged edges of (round, batches): one relation, whatever their number."""
        paths = [self._at("inbox", f"batch={b}", f"round={r}") for r, batches in waiting.items() for b in sorted(batches)]
        if not paths:
            return None
        schema = T.StructType([*self.schema, T.StructField("round", T.LongType())])
        return self.spark.read.schema(schema).option("basePath", self._at("inbox")).parquet(*paths)

    def staged(self, round_id: int | None = None) -> DataFrame | None:
        """Edges that wait for their round to close, of one round or of all."""
        closed = self.closed()
        return self._read({r: b for r, b in self._waiting().items() if r not in closed and r != REJECTED and round_id in (None, r)})

    def late(self) -> DataFrame | None:
        """Edges that came after their round was closed and are not merged yet."""
        closed = self.closed()
        return self._read({r: b for r, b in self._waiting().items() if r in closed})

    def rejected(self) -> DataFrame | None:
        """Edges with a null in their triplet: kept aside, in no layout."""
        return self._read({r: b for r, b in self._waiting().items() if r == REJECTED})

    def due(self) -> list[int]:
        """Open rounds whose end lies before the largest event time less the delay."""
        rounds = set(self._waiting()) - self.closed() - {REJECTED}
        return sorted(r for r in rounds if (r + 1) * self.round_us <= self.max_ts - self.t_delay_us)

    # --- closing -------------------------------------------------------------------

    def destinations(self, edges: DataFrame) -> DataFrame:
        """One row per copy of each edge, with the layout it belongs to (s, k, f) and its worker."""
        return placement(with_workers(edges, self.locations, self.mapping, self.spec), self.spec.n_workers)

    def close_round(self, round_id: int) -> RoundLog:
        if round_id in self.closed():
            raise ValueError(f"round {round_id} is closed: merge_late takes what came after")
        batches = self._waiting().get(round_id)
        if not batches:
            raise ValueError(f"round {round_id} has no staged edges")
        return self._write_version(self._read({round_id: batches}).drop("round"), round_id, 1, batches)

    def _write_version(self, edges: DataFrame, round_id: int, version: int, batches: set[int] | frozenset[int]) -> RoundLog:
        began = time.perf_counter()
        n, extra = self._write_layouts(edges, round_id, version)
        self._commit(Commit(round_id, version, frozenset(batches), n, extra))
        self.sweep(round_id)
        entry = RoundLog(round_id, n, 2 * n + extra, time.perf_counter() - began)
        self.log.append(entry)
        return entry

    def _write_layouts(self, edges: DataFrame, round_id: int, version: int) -> tuple[int, int]:
        """Both layouts and the extra copies of a round's edges; returns how many edges and extra copies there are."""
        at = lambda name: self._at(name, f"round={round_id}", f"v={version}")
        rows = edges.count()  # of Parquet files: their footers
        placed = with_workers(edges, self.locations, self.mapping, self.spec)
        slot = slot_of("object_id", self.spec.p, self.spec.hash_kind)
        kt = placed.withColumns({"slot": slot, "worker": F.col("w_k")}).withColumn("slot_group", slot_group(self.spec, self.groups))
        write_clustered(kt, at("kt"), ["tru", "slot_group", "slot", "object_id", "ts_us"], ["tru", "slot_group"], rows, self.rows_per_file)
        group = unit_group(self.spec, self.groups, self.spec.b or 8)
        st = st_columns(placed.drop("tru"), self.locations, self.spec, how="left", unit_group=group)
        st = st.withColumn("worker", F.col("w_s")).withColumn("unit_group", F.coalesce("unit_group", F.lit(0)))
        write_clustered(st, at("st"), ["tru", "unit_group", "region", "ts_us", "object_id"], ["tru", "unit_group"], rows, self.rows_per_file)
        seen = Observation()
        extra = placed.where("w_s = w_k").withColumn("worker", ((F.col("w_s") + 1) % self.spec.n_workers).cast("int"))
        extra.observe(seen, F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(at("extra"))
        return rows, seen.get.get("n") or 0

    def sweep(self, round_id: int) -> None:
        """Deletes what a round's commit has made useless: staged folders that it holds, other versions of its layouts."""
        c = self.commits()[round_id]
        for b in c.batches:
            files.delete(self.spark, self._at("inbox", f"batch={b}", f"round={round_id}"))
        for name in LAYOUTS:
            for v in files.names(self.spark, self._at(name, f"round={round_id}")):
                if v.startswith("v=") and v != f"v={c.version}":
                    files.delete(self.spark, self._at(name, f"round={round_id}", v))

    def close_due(self) -> list[RoundLog]:
        return [self.close_round(r) for r in self.due()]

    def close_all(self) -> list[RoundLog]:
        """Closes every staged round, at the end of a finite source."""
        return [self.close_round(r) for r in sorted(set(self._waiting()) - self.closed() - {REJECTED})]

    def merge_late(self) -> int:
        """Brings late edges into the closed rounds that they belong to; returns how many edges were merged."""
        merged, commits = 0, dict(self.commits())
        for r, batches in sorted(self._waiting().items()):
            if r not in commits:
                continue
            old, fresh = commits[r], self._read({r: batches}).drop("round")
            held = self.spark.read.parquet(self._at("kt", f"round={r}", f"v={old.version}")).select(*fresh.columns)
            self._write_version(held.unionByName(fresh), r, old.version + 1, old.batches | batches)
            merged += self.commits()[r].edges - old.edges
        return merged

    # --- reading -------------------------------------------------------------------

    def layout(self, name: str) -> DataFrame | None:
        """``kt``, ``st`` or ``extra``: the versions in force of the committed rounds only."""
        paths = [self._at(name, f"round={r}", f"v={c.version}") for r, c in sorted(self.commits().items())]
        return self.spark.read.option("basePath", self._at(name)).parquet(*paths).drop("round", "v") if paths else None

    def edges(self, include_staged: bool = True) -> DataFrame | None:
        """Edges of closed rounds, and those of open ones too: new edges can be queried before their round is over."""
        columns = ["edge_id", "object_id", "ts_us", "location_id"]
        parts = [self.layout("kt"), self.staged() if include_staged else None]
        out = None
        for p in parts:
            if p is not None:
                out = p.select(*columns) if out is None else out.unionByName(p.select(*columns))
        return out


def ingest_batch(store: IngestStore, edges: DataFrame, batch_id: int = 0) -> list[RoundLog]:
    store.stage(edges, batch_id)
    return store.close_due()


def ingest_stream(store: IngestStore, source: DataFrame, checkpoint: str, available_now: bool = True) -> StreamingQuery:
    """Stages every micro-batch and closes the rounds that fall due; the checkpoint makes restarts resume."""

    def each(batch: DataFrame, batch_id: int) -> None:
        store.stage(batch, batch_id)
        store.close_due()

    writer = source.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer.trigger(processingTime="30 seconds")).start()
