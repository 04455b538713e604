"""All engine queries and their oracles."""

from __future__ import annotations

from tracegraph.workloads import experiments, surface  # noqa: F401  they register themselves
from tracegraph.workloads.entries import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
