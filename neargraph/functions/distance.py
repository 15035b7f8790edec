"""Distances as column expressions over array columns, computed in double precision."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2", "sql2", "cosine", "ip")


def _doubles(a) -> Column:
    return (F.col(a) if isinstance(a, str) else a).cast("array<double>")


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(_doubles(a), _doubles(b), lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def norm(a) -> Column:
    return F.sqrt(F.aggregate(_doubles(a), F.lit(0.0), lambda s, v: s + v * v))


def sql2(a, b) -> Column:
    return F.aggregate(F.zip_with(_doubles(a), _doubles(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)


def l2(a, b) -> Column:
    return F.sqrt(sql2(a, b))


def cosine(a, b) -> Column:
    """1 - cosine; 1 where a vector is zero."""
    size = norm(a) * norm(b)
    return F.when(size > 0, 1.0 - dot(a, b) / size).otherwise(F.lit(1.0))


def neg_ip(a, b) -> Column:
    return -dot(a, b)


def distance(metric: str, a, b) -> Column:
    if metric not in METRICS:
        raise ValueError(f"unknown metric {metric}")
    return {"l2": l2, "sql2": sql2, "cosine": cosine, "ip": neg_ip}[metric](a, b)


def unit(a) -> Column:
    """The vector at unit length; a zero vector stays."""
    n = norm(a)
    return F.when(n > 0, F.transform(_doubles(a), lambda v: v / n)).otherwise(_doubles(a))
