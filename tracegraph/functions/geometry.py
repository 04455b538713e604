"""Grid, Z-order codes, distances and their bounds, as native column expressions."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from tracegraph.model import GraphSpec

EARTH_M = 6_371_000.0


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def cell(v, width: int, origin: int = 0) -> Column:
    """Index of the cell of ``width`` that holds a coordinate (floor, also below the origin); exact below 2^53."""
    return F.floor((_c(v) - origin) / F.lit(width)).cast("bigint")


def spread(v: Column, bits: int = 16) -> Column:
    """The low ``bits`` of a number with a zero between each two.

    A sum over bits: nested shifts would double the expression at every step.
    """
    out = F.lit(0).cast("bigint")
    for i in range(bits):
        out = out + F.shiftleft(F.shiftright(v, i).bitwiseAND(F.lit(1).cast("bigint")), 2 * i)
    return out


def z_code(cx, cy, bits: int = 16) -> Column:
    """Z-order code: bits of cx and cy in turn."""
    return spread(_c(cx), bits).bitwiseOR(F.shiftleft(spread(_c(cy), bits), 1))


def region_of(x, y, spec: GraphSpec) -> Column:
    """Z-code of the region that holds a point."""
    return z_code(cell(x, spec.a, spec.origin_x), cell(y, spec.a, spec.origin_y))


def z_code_int(cx: int, cy: int, bits: int = 16) -> int:
    return sum(((cx >> i & 1) << 2 * i) | ((cy >> i & 1) << 2 * i + 1) for i in range(bits))


def z_decode_int(z: int, bits: int = 16) -> tuple[int, int]:
    return sum((z >> 2 * i & 1) << i for i in range(bits)), sum((z >> 2 * i + 1 & 1) << i for i in range(bits))


def sq_dist(x1, y1, x2, y2) -> Column:
    """Squared Euclidean distance; exact on integers."""
    dx, dy = _c(x1) - _c(x2), _c(y1) - _c(y2)
    return dx * dx + dy * dy


def grid_bounds(gx1, gy1, gx2, gy2, eta: int, bound: str = "printed") -> tuple[Column, Column]:
    """Lower and upper bound of the distance of two points from their fine cells of width eta.

    ``printed``: from the difference of the cell distances; ``chebyshev``: from the larger one, never below it.
    """
    dx, dy = F.abs(_c(gx1) - _c(gx2)), F.abs(_c(gy1) - _c(gy2))
    gap = F.abs(dx - dy) - 2 if bound == "printed" else F.greatest(dx, dy) - 1
    return F.greatest(gap, F.lit(0)) * eta, (dx + dy + 2) * eta


def haversine(lat1, lon1, lat2, lon2) -> Column:
    p1, p2 = F.radians(_c(lat1)), F.radians(_c(lat2))
    h = F.pow(F.sin((p2 - p1) / 2), 2) + F.cos(p1) * F.cos(p2) * F.pow(F.sin(F.radians(_c(lon2) - _c(lon1)) / 2), 2)
    return 2 * EARTH_M * F.asin(F.sqrt(F.least(h, F.lit(1.0))))


def vector_dot(a, b) -> Column:
    products = F.zip_with(_c(a), _c(b), lambda p, q: p.cast("double") * q.cast("double"))
    return F.aggregate(products, F.lit(0.0), lambda s, v: s + v)


def vector_l2(a, b) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(_c(a), _c(b), lambda p, q: F.pow(p.cast("double") - q.cast("double"), 2)), F.lit(0.0), lambda s, v: s + v))


def vector_l1(a, b) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda p, q: F.abs(p.cast("double") - q.cast("double"))), F.lit(0.0), lambda s, v: s + v)


def vector_chebyshev(a, b) -> Column:
    return F.array_max(F.zip_with(_c(a), _c(b), lambda p, q: F.abs(p.cast("double") - q.cast("double"))))


def vector_cosine(a, b) -> Column:
    """Cosine distance; not a metric."""
    return 1.0 - vector_dot(a, b) / F.sqrt(vector_dot(a, a) * vector_dot(b, b))


@dataclass(frozen=True)
class Metric:
    """A distance between location properties; ``is_metric`` allows the neighbour method for clones."""

    name: str
    columns: tuple[str, ...]
    is_metric: bool
    distance: Callable[..., Column]

    def between(self, left: str, right: str) -> Column:
        return self.distance(*[F.col(f"{s}{c}") for s in (left, right) for c in self.columns])


METRICS = {
    m.name: m
    for m in (
        Metric("euclid", ("x", "y"), True, lambda a, b, c, d: F.sqrt(sq_dist(a, b, c, d).cast("double"))),
        Metric("chebyshev", ("x", "y"), True, lambda a, b, c, d: F.greatest(F.abs(a - c), F.abs(b - d)).cast("double")),
        Metric("manhattan", ("x", "y"), True, lambda a, b, c, d: (F.abs(a - c) + F.abs(b - d)).cast("double")),
        Metric("haversine", ("lat", "lon"), True, haversine),
        Metric("vector_l2", ("embedding",), True, vector_l2),
        Metric("vector_l1", ("embedding",), True, vector_l1),
        Metric("vector_chebyshev", ("embedding",), True, vector_chebyshev),
        Metric("cosine", ("embedding",), False, vector_cosine),
    )
}


def degree_cells(lat: float, metres: float) -> tuple[float, float]:
    """Latitude and longitude widths in degrees that cover ``metres`` at a latitude, rounded up."""
    dlat = math.degrees(metres / EARTH_M)
    edge = min(89.999, abs(lat) + dlat)
    return dlat, min(360.0, math.degrees(metres / (EARTH_M * math.cos(math.radians(edge)))))
