"""Affinity functions as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

LN2 = math.log(2.0)


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def squared_distance(a, b) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def phi(a, b, alpha: float = LN2) -> Column:
    """Gaussian affinity; one half at unit squared distance."""
    return F.exp(-alpha * squared_distance(a, b))


def l2_affinity(a, b) -> Column:
    return 1 / (1 + F.sqrt(squared_distance(a, b)))


def jensen_shannon(p, q) -> Column:
    """Base-2 divergence of two distributions, 0 (same) to 1 (disjoint)."""
    part = lambda x, m: F.when(x > 0, x * F.log2(x / m)).otherwise(F.lit(0.0))
    both = F.zip_with(_col(p), _col(q), lambda x, y: part(x, (x + y) / 2) + part(y, (x + y) / 2))
    return F.aggregate(both, F.lit(0.0), lambda s, x: s + x) / 2


def js_affinity(p, q, mode: str = "similarity") -> Column:
    d = jensen_shannon(p, q)
    if mode == "similarity":
        return 1 - d
    if mode == "sqrt_similarity":
        return 1 - F.sqrt(F.greatest(d, F.lit(0.0)))
    if mode == "raw":
        return d
    raise ValueError(mode)


def group_affinity(sem_a, sem_b, emb_a, emb_b, alpha: float = LN2, mode: str = "similarity") -> Column:
    return js_affinity(sem_a, sem_b, mode) * phi(emb_a, emb_b, alpha)


def damping(u: dict[str, Column], v: dict[str, Column], beta: float = 0.5) -> Column:
    """Positional damping of two boxes given by y0, y1, x0, x1 (inclusive):
    1 in an axis where centres agree."""
    out = F.lit(1.0)
    for lo, hi in (("y0", "y1"), ("x0", "x1")):
        size = F.greatest(u[hi] - u[lo] + 1, v[hi] - v[lo] + 1)
        gap = F.abs((u[lo] + u[hi]) / 2 - (v[lo] + v[hi]) / 2)
        out = out * F.when(gap == 0, F.lit(1.0)).otherwise(F.pow(F.least(F.lit(1.0), 0.5 * size / gap), F.lit(float(beta))))
    return out


def box(prefix: str = "", suffix: str = "") -> dict[str, Column]:
    return {c: F.col(f"{prefix}{c}{suffix}") for c in ("y0", "y1", "x0", "x1")}


def to_cost(a, t: float = 0.5, how: str = "linear", eps: float = 1e-7) -> Column:
    """Signed cost, positive where an edge attracts."""
    a = _col(a)
    if how == "linear":
        return a - t
    a = F.least(F.greatest(a, F.lit(eps)), F.lit(1 - eps))
    return F.ln(a / (1 - a)) - math.log(t / (1 - t))
