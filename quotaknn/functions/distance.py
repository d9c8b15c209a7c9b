"""Distances between vector columns, as expressions that stay in the JVM, and the same for numpy blocks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2", "l1", "cosine", "lp")


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _total(a: Column, b: Column, step) -> Column:
    return F.aggregate(F.zip_with(a, b, step), F.lit(0.0), lambda s, x: s + x)


def dot(a, b) -> Column:
    return _total(_col(a), _col(b), lambda x, y: x.cast("double") * y.cast("double"))


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def angle(a, b) -> Column:
    """Radians between two vectors; null where one has no length."""
    cos = dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cos)))


def distance(metric: str, a, b, p: float = 2.0) -> Column:
    """The distance of two array columns. Cosine distance to a vector without length is 1."""
    a, b = _col(a), _col(b)
    gap = lambda x, y: x.cast("double") - y.cast("double")
    if metric == "l2":
        return F.sqrt(_total(a, b, lambda x, y: gap(x, y) * gap(x, y)))
    if metric == "l1":
        return _total(a, b, lambda x, y: F.abs(gap(x, y)))
    if metric == "cosine":
        return F.coalesce(1 - dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0)), F.lit(1.0))
    if metric == "lp":
        if p < 1:
            raise ValueError("p must be 1 at least")
        return F.pow(_total(a, b, lambda x, y: F.pow(F.abs(gap(x, y)), F.lit(float(p)))), F.lit(1.0 / p))
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")


def distance_block(metric: str, queries: np.ndarray, rows: np.ndarray, p: float = 2.0) -> np.ndarray:
    """(queries, rows) distances in double precision."""
    q, x = np.asarray(queries, float), np.asarray(rows, float)
    if metric == "l2":
        return np.sqrt(np.maximum((q**2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * q @ x.T, 0))
    if metric == "cosine":
        size = np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :]
        return 1 - np.divide(q @ x.T, size, out=np.zeros_like(size), where=size > 0)
    gaps = np.abs(q[:, None, :] - x[None, :, :])
    if metric == "l1":
        return gaps.sum(2)
    if metric == "lp":
        return (gaps**p).sum(2) ** (1 / p)
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")


def distance_pairs(metric: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances of rows of `a` and `b` (either may be one vector), summed in the order of distance(), so equal to its bits."""
    a, b = np.atleast_2d(np.asarray(a, float)), np.atleast_2d(np.asarray(b, float))
    total = lambda x: np.cumsum(x, axis=1)[:, -1] if x.shape[1] else np.zeros(len(x))
    if metric == "l2":
        return np.sqrt(total((a - b) ** 2))
    if metric == "l1":
        return total(np.abs(a - b))
    if metric == "cosine":
        size = np.sqrt(total(a * a)) * np.sqrt(total(b * b))
        near = total(a * b)
        return np.where(size > 0, 1 - np.divide(near, size, out=np.zeros_like(near), where=size > 0), 1.0)
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS[:3]}")


def near_bound(metric: str, queries: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(queries, rows) numbers in the order of the distances up to rounding, and for each query more than twice that rounding."""
    q, x = np.asarray(queries, float), np.asarray(rows, float)
    if metric == "l2":
        q2, x2 = (q**2).sum(1), (x**2).sum(1)
        size = q2 + (x2.max() if len(x2) else 0)
        # single precision is twice as fast; its error is bounded by the length of the sums
        kind, unit = (np.float32, 1.2e-7) if len(q) and 1e-15 < size.max() < 1e15 else (np.float64, 2.3e-16)
        out = q.astype(kind) @ (-2 * x.T).astype(kind)
        out += x2.astype(kind)[None, :]
        return out, (4 * (q.shape[1] + 8) * unit * size).astype(kind)
    if metric == "l1":
        out = np.zeros((len(q), len(x)))
        for i in range(q.shape[1]):
            out += np.abs(q[:, i, None] - x[None, :, i])
        return out, 1e-12 * (np.abs(q).sum(1) + (np.abs(x).sum(1).max() if len(x) else 0))
    return distance_block(metric, q, x), np.full(len(q), 1e-12)
