"""Graph model: specification, ranges, thresholds, query requests and integrity checks."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

HOUR_US = 3_600_000_000
DAY_US = 24 * HOUR_US

#: An edge: one visit of an object to a location; further columns are properties.
EDGE_CORE = T.StructType(
    [
        T.StructField("edge_id", T.LongType()),
        T.StructField("object_id", T.LongType()),
        T.StructField("ts_us", T.LongType()),
        T.StructField("location_id", T.LongType()),
    ]
)
TRIPLET = ("object_id", "ts_us", "location_id")


@dataclass(frozen=True)
class TimeRange:
    """Query range in microseconds; half-open unless ``closed``."""

    start_us: int
    end_us: int
    closed: bool = False

    @property
    def last_us(self) -> int:
        return self.end_us if self.closed else self.end_us - 1

    def buckets(self, tru_us: int) -> tuple[int, int]:
        """First and last time bucket that the range touches."""
        return self.start_us // tru_us, self.last_us // tru_us

    def n_tru(self, tru_us: int, rule: str = "exact") -> int:
        """Buckets covered: ``exact`` counts floors, ``paper`` the printed difference of ceilings."""
        if rule == "paper":
            return -(-self.end_us // tru_us) - -(-self.start_us // tru_us)
        lo, hi = self.buckets(tru_us)
        return max(0, hi - lo + 1)

    @classmethod
    def days(cls, start_us: int, n: int) -> TimeRange:
        return cls(start_us, start_us + n * DAY_US)


@dataclass(frozen=True)
class Thresholds:
    """Closeness in time and space (inclusive) and the speed beyond which an object must be a clone."""

    time_us: int = 7 * HOUR_US
    dist_m: int = 100
    kmh: float = 120.0


@dataclass(frozen=True)
class GraphSpec:
    """Everything that places an edge: grid, slots, time buckets, workers, unit width."""

    origin_x: int = 0
    origin_y: int = 0
    a: int = 1000
    grid_w: int = 1024
    grid_h: int = 1024
    p: int = 14
    tru_us: int = DAY_US
    eta: int = 50
    n_workers: int = 10
    b: int | None = 8
    metric: str = "euclid"
    hash_kind: str = "mult"
    replicas: dict = field(default_factory=lambda: {"st": 2, "kt": 1})

    @property
    def n_slots(self) -> int:
        return 1 << self.p

    @property
    def n_regions(self) -> int:
        return self.grid_w * self.grid_h

    def with_(self, **changes) -> GraphSpec:
        return replace(self, **changes)


@dataclass(frozen=True)
class QuerySpec:
    """A request before planning."""

    kind: str
    ids: tuple[int, ...]
    range: TimeRange
    thresholds: Thresholds = Thresholds()
    plan: str = "auto"
    prune: str = "cell"
    method: str = "lag"
    limit: int | None = None
    include_self: bool = False


@dataclass
class TraceGraph:
    """Bipartite graph of objects and located places with timestamped edges between them."""

    locations: DataFrame
    edges: DataFrame
    objects: DataFrame | None = None
    spec: GraphSpec = field(default_factory=GraphSpec)

    def between(self, rng: TimeRange | None) -> DataFrame:
        return self.edges if rng is None else in_range(self.edges, rng)


def in_range(edges: DataFrame, rng: TimeRange) -> DataFrame:
    return edges.where((F.col("ts_us") >= rng.start_us) & (F.col("ts_us") <= rng.last_us))


def edges_from(df: DataFrame, mapping: dict[str, str]) -> DataFrame:
    """Rename user columns into the edge triplet (and edge_id); all other columns stay as properties."""
    missing = [v for v in mapping.values() if v not in df.columns]
    if missing:
        raise ValueError(f"no such columns: {missing}")
    back = {v: k for k, v in mapping.items()}
    return df.select(*[F.col(c).alias(back.get(c, c)) for c in df.columns])


def validate_graph(g: TraceGraph) -> DataFrame:
    """check and number of violations: unique vertices, no dangling edge end, no null in the triplet, coordinates in the plane."""
    s = g.spec

    def count(name: str, bad: DataFrame) -> DataFrame:
        return bad.agg(F.count(F.lit(1)).alias("violations")).select(F.lit(name).alias("check"), "violations")

    nulls = F.lit(False)
    for c in TRIPLET:
        nulls = nulls | F.col(c).isNull()
    outside = (F.col("x") < s.origin_x) | (F.col("y") < s.origin_y) | F.col("x").isNull() | F.col("y").isNull()
    checks = [
        count("duplicate_location", g.locations.groupBy("location_id").count().where("count > 1")),
        count("dangling_location", g.edges.where("location_id is not null").join(g.locations, "location_id", "left_anti")),
        count("null_in_edge", g.edges.where(nulls)),
        count("location_off_grid", g.locations.where(outside)),
    ]
    if g.objects is not None:
        checks += [
            count("duplicate_object", g.objects.groupBy("object_id").count().where("count > 1")),
            count("dangling_object", g.edges.where("object_id is not null").join(g.objects, "object_id", "left_anti")),
        ]
    out = checks[0]
    for c in checks[1:]:
        out = out.unionByName(c)
    return out
