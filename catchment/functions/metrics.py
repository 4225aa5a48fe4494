"""Metrics as column expressions, and the turn that makes L1 an L-infinity problem."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

METRICS = ("linf", "l1", "l2")


def distance(metric: str, x1, y1, x2, y2):
    """Exact LONG distance of columns or column names; squared for L2."""
    x1, y1, x2, y2 = (F.col(c) if isinstance(c, str) else c for c in (x1, y1, x2, y2))
    return reach(metric, F.abs(x1 - x2), F.abs(y1 - y2))


def reach(metric: str, dx, dy):
    """The distance of two places that lie dx and dy (neither negative) apart along the axes."""
    if metric == "linf":
        return F.greatest(dx, dy)
    if metric == "l1":
        return dx + dy
    if metric == "l2":
        return dx * dx + dy * dy
    raise ValueError(f"no metric {metric!r}")


def turned(points: DataFrame, x: str = "x", y: str = "y") -> DataFrame:
    """(u, v) = (x - y, x + y) in place of (x, y): L-infinity there is L1 here, still on integers."""
    return points.withColumns({x: F.col(x) - F.col(y), y: F.col(x) + F.col(y)})


def register_sql(spark) -> None:
    """linf_dist, l1_dist, l2_dist2 as SQL functions (expressions, no Python)."""
    for name, body in (("linf_dist", "greatest(abs(a - c), abs(b - d))"), ("l1_dist", "abs(a - c) + abs(b - d)"), ("l2_dist2", "(a - c) * (a - c) + (b - d) * (b - d)")):
        spark.sql(f"create or replace temporary function {name}(a bigint, b bigint, c bigint, d bigint) returns bigint return {body}")
