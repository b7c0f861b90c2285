"""Hausdorff distance of point arrays, as expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _square(p: Column, q: Column) -> Column:
    dx, dy = p["x"] - q["x"], p["y"] - q["y"]
    return dx * dx + dy * dy


def _one_way(a: Column, b: Column) -> Column:
    return F.array_max(F.transform(a, lambda p: F.array_min(F.transform(b, lambda q: _square(p, q)))))


def distance(a: Column, b: Column) -> Column:
    """The distance of two arrays of ``(x, y)``."""
    return F.sqrt(F.greatest(_one_way(a, b), _one_way(b, a)))


def within(a: Column, b: Column, limit: Column) -> Column:
    """Whether the distance is at most ``limit``; stops at the first point without a partner."""
    bound = limit * limit
    covers = lambda u, v: F.forall(u, lambda p: F.exists(v, lambda q: _square(p, q) <= bound))
    return covers(a, b) & covers(b, a)
