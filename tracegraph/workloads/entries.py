"""Registry of named queries and shared SQL fragments of their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tracegraph.sources.tables import EVENT_TYPES, EVENTS_START_US

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

DAY = 86_400_000_000
HOUR = 3_600_000_000
S0 = EVENTS_START_US


def entry(name: str, sql: str | None = None):
    """Registers a query; ``sql`` gives the same rows in DuckDB."""

    def add(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


_CODE = "CASE event_type " + " ".join(f"WHEN '{t}' THEN {i}" for i, t in enumerate(EVENT_TYPES)) + " END"
EV = f"""ev AS (SELECT event_id AS edge_id, user_id AS object_id, epoch_us(ts) AS ts_us,
  100 * CAST({_CODE} AS BIGINT) + CAST(regexp_extract(props, '[0-9]+') AS BIGINT) AS location_id, event_type, value FROM events)"""
PL = """pl AS (SELECT 100 * t + k AS location_id, k, t, CAST((k * k) // 400 AS INTEGER) AS area,
  102400 + 204800 * (((k * k) // 400) % 5) + 1500 * (k % 7) + 60 * t AS x,
  102400 + 204800 * (((k * k) // 400) // 5) + 1500 * (k % 5) AS y FROM range(5) a(t), range(100) b(k))"""
E = f"""{EV}, {PL}, e AS (SELECT ev.*, pl.x, pl.y, pl.area FROM ev JOIN pl USING (location_id))"""
_SEC = "((131 * l_orderkey + 31 * l_partkey + 7919 * CAST(l_linenumber AS BIGINT)) % 86400)"
SO = f"""so AS (SELECT l_orderkey * 8 + l_linenumber AS edge_id, o_custkey AS object_id,
  epoch_us(l_shipdate) + 1000000 * {_SEC} AS ts_us, l_suppkey AS location_id,
  l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"""
SP = """sp AS (SELECT s_suppkey AS location_id, 102400 + 204800 * (CAST(s_nationkey AS BIGINT) % 5) + 250 * ((37 * s_suppkey) % 40) AS x,
  102400 + 204800 * (CAST(s_nationkey AS BIGINT) // 5) + 250 * ((61 * s_suppkey) % 37) AS y, s_nationkey AS area FROM supplier)"""
SE = f"""{SO}, {SP}, se AS (SELECT so.*, sp.x, sp.y, sp.area FROM so JOIN sp USING (location_id))"""
PC = f"""pc AS (SELECT l_orderkey AS object_id, epoch_us(l_shipdate) + 1000000 * {_SEC} AS ts_us, l_suppkey AS location_id FROM lineitem)"""


def days(n: int, col: str = "ts_us") -> str:
    return f"{col} >= {S0} AND {col} < {S0 + n * DAY}"


def near(hours: int, metres: int, a: str = "a", b: str = "b") -> str:
    return (
        f"abs({a}.ts_us - {b}.ts_us) <= {hours * HOUR} AND"
        f" ({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y) <= {metres * metres}"
    )


def fast(kmh: int, a: str = "a", b: str = "b") -> str:
    return (
        f"sqrt(CAST(({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y) AS DOUBLE)) * 3.6e6"
        f" > {kmh}.0 * ({b}.ts_us - {a}.ts_us)"
    )


def _spread(v: str, bits: int = 10) -> str:
    return " + ".join(f"((({v}) >> {i}) & 1) * {1 << 2 * i}" for i in range(bits))


def zcode(x: str, y: str, a: int = 1000) -> str:
    """Z-code of the region of a point."""
    cx, cy = f"({x}) // {a}", f"({y}) // {a}"
    return f"(({_spread(cx)}) + 2 * ({_spread(cy)}))"


def slot(v: str, p: int) -> str:
    return f"CAST(((({v} % 4294967296) * 1327217885) % 4294967296) >> {32 - p} AS INTEGER)"
