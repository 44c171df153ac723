"""Distances and geometric predicates as Spark columns; small vectors and reference plans."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EXACT_COSINES = {0.0: 1.0, 60.0: 0.5, 90.0: 0.0}


def cos_degrees(alpha: float) -> float:
    """The shared literal of an angle; 0, 60 and 90 degrees are exact."""
    if not 0 <= alpha <= 90:
        raise ValueError("alpha must be from 0 to 90 degrees")
    return EXACT_COSINES.get(float(alpha), math.cos(math.radians(alpha)))


def _fold(a, b, term) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: term(x.cast("double"), y.cast("double"))), F.lit(0.0), lambda s, x: s + x)


def l2_sq(a, b) -> Column:
    return _fold(a, b, lambda x, y: (x - y) * (x - y))


def l2(a, b) -> Column:
    return F.sqrt(l2_sq(a, b))


def l1(a, b) -> Column:
    return _fold(a, b, lambda x, y: F.abs(x - y))


def linf(a, b) -> Column:
    return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x.cast("double") - y.cast("double"))))


def dot(a, b) -> Column:
    return _fold(a, b, lambda x, y: x * y)


def norm(a) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


def cosine_distance(a, b) -> Column:
    return 1 - dot(a, b) / (norm(a) * norm(b))


def angle_at(dpr, dpq, drq) -> Column:
    """Degrees at p between r and q, from three distances."""
    c = (F.col(dpr) ** 2 + F.col(dpq) ** 2 - F.col(drq) ** 2) / (2 * F.col(dpr) * F.col(dpq))
    return F.degrees(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), c))))


def angle_conflict(dpr2, dpq2, drq2, cos_alpha: float) -> Column:
    """Whether q stands within the angle of the kept r, seen from p; arguments are squared distances."""
    return F.col(dpr2) + F.col(dpq2) - F.col(drq2) > 2 * F.sqrt(F.col(dpr2)) * F.sqrt(F.col(dpq2)) * F.lit(float(cos_alpha))


def lune_conflict(dpr2, dpq2, drq2) -> Column:
    """Whether r is closer to both p and q than they are to each other."""
    return (F.col(dpr2) < F.col(dpq2)) & (F.col(drq2) < F.col(dpq2))


def in_ball(dist, radius) -> Column:
    return F.col(dist) < radius


def in_cone(dpr2, dpq2, drq2, cos_alpha: float) -> Column:
    return angle_conflict(dpr2, dpq2, drq2, cos_alpha)


def portable_hash(column, seed: int = 0) -> Column:
    """The same 31-bit value in Spark and in SQL engines, without overflow."""
    return ((F.col(column) % 2147483648) * 1103515245 + 12345 + seed * 7919) % 2147483648
