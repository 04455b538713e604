"""Comparison of a query with its DuckDB oracle: names, types and values, whatever the order."""

from __future__ import annotations

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
TYPES = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}


def connect(sf: str) -> duckdb.DuckDBPyConnection:
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    return c


def _value(v):
    if v is None:
        return "null"
    if isinstance(v, float):
        return "null" if math.isnan(v) else f"{v:.6g}"
    return str(v)


def rows(records, names) -> list[tuple]:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(_value(r[i]) for i in order) for r in records)


def check(df, c, sql: str) -> None:
    described = {r[0]: r[1] for r in c.execute(f"describe {sql}").fetchall()}
    assert sorted(df.columns) == sorted(described)
    for name, kind in df.dtypes:
        assert described[name] == TYPES.get(kind, described[name]), name
    found = c.execute(sql)
    names = [d[0] for d in found.description]
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(found.fetchall(), names)
