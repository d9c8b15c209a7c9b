"""Locality-sensitive hash families, compound keys and the numbers that plan an index.

The projections come from (family, dimension, seed) alone, table by table, so a family of more tables or longer keys holds
the smaller one as its beginning, and the way rows are dealt over tasks cannot change a key.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

BASE = 1_000_003


@dataclass(frozen=True)
class Family:
    """kind: pstable (Gaussian, l2), cauchy (l1) or sign (angle); `tables` keys of `hashes` hashes, width w."""

    kind: str
    dim: int
    tables: int = 16
    hashes: int = 2
    width: float = 1.0
    seed: int = 42

    def prefix(self, hashes: int) -> "Family":
        """The family whose keys join only the first hashes of each table."""
        return replace(self, hashes=min(hashes, self.hashes))

    def projections(self) -> tuple[np.ndarray, np.ndarray]:
        """(tables, hashes, dim) directions and (tables, hashes) offsets."""
        a, b = np.empty((self.tables, self.hashes, self.dim)), np.empty((self.tables, self.hashes))
        for t in range(self.tables):
            for h in range(self.hashes):
                rng = np.random.default_rng([self.seed, t, h])
                a[t, h] = rng.standard_cauchy(self.dim) if self.kind == "cauchy" else rng.standard_normal(self.dim)
                b[t, h] = rng.uniform(0, self.width)
        return a, b

    def hash(self, vectors: np.ndarray) -> np.ndarray:
        """(rows, tables, hashes) base hashes."""
        a, b = self.projections()
        along = np.asarray(vectors, float) @ a.reshape(-1, self.dim).T
        along = along.reshape(len(vectors), self.tables, self.hashes)
        if self.kind == "sign":
            return (along >= 0).astype(np.int64)
        return np.floor((along + b) / self.width).astype(np.int64)

    def keys(self, vectors: np.ndarray) -> np.ndarray:
        """(rows, tables) compound keys in 64 bits. Keys that wrap alike only add candidates."""
        h = self.hash(vectors)
        out = h[:, :, 0].copy()
        for i in range(1, self.hashes):
            out = out * BASE + h[:, :, i]
        return out


def family_for(metric: str, dim: int, **kw) -> Family:
    return Family({"l2": "pstable", "l1": "cauchy", "cosine": "sign"}[metric], dim, **kw)


def lsh_keys(family: Family):
    """An Arrow function from a vector column to array<long>, a key for each table."""

    parts = (family.kind, family.dim, family.tables, family.hashes, family.width, family.seed)

    @F.arrow_udf(T.ArrayType(T.LongType()))
    def keys(vec):
        import pyarrow as pa

        own = Family(*parts)
        flat = vec.cast(pa.list_(pa.float64()))
        x = flat.flatten().to_numpy(zero_copy_only=False).reshape(-1, own.dim)
        k = own.keys(x)
        ends = pa.array(np.arange(len(x) + 1, dtype=np.int32) * own.tables)
        return pa.ListArray.from_arrays(ends, pa.array(k.ravel()))

    return keys


def _phi(x: float) -> float:
    return 0.5 * (1 + math.erf(x / math.sqrt(2)))


def p_collide(kind: str, r: float, w: float = 1.0) -> float:
    """Chance that one base hash agrees at distance r (for sign hashing r is the angle in radians)."""
    if kind == "sign":
        return 1 - r / math.pi
    if r == 0:
        return 1.0
    u = w / r
    if kind == "cauchy":
        return 2 * math.atan(u) / math.pi - math.log(1 + u * u) / (math.pi * u)
    return 1 - 2 * _phi(-u) - 2 / (math.sqrt(2 * math.pi) * u) * (1 - math.exp(-u * u / 2))


def rho(p1: float, p2: float) -> float:
    _check(p1, p2)
    return math.log(1 / p1) / math.log(1 / p2)


def _check(p1: float, p2: float) -> None:
    if not 0 < p2 < p1 < 1:
        raise ValueError("need 0 < p2 < p1 < 1")


def plan_cell(n: int, p1: float, p2: float, near: int, delta: float) -> dict:
    """Hashes in a key and tables for a cell of n records, so that up to `near` near points are all found with chance
    1 - delta / 2."""
    r = rho(p1, p2)
    if n <= 1:
        return {"hashes": 1, "tables": 1, "rho": r}
    return {"hashes": max(1, math.ceil(math.log(n) / math.log(1 / p2))), "tables": max(1, math.ceil(n**r * math.log(2 * near / delta))), "rho": r}


def plan_cells(n: Column, p1: float, p2: float, near: int, delta: float) -> Column:
    """The same as a column: struct<hashes, tables>."""
    r = rho(p1, p2)
    hashes = F.greatest(F.lit(1), F.ceil(F.ln(n) / math.log(1 / p2)).cast("int"))
    tables = F.when(n <= 1, F.lit(1)).otherwise(F.greatest(F.lit(1), F.ceil(F.pow(n, F.lit(r)) * math.log(2 * near / delta)).cast("int")))
    return F.struct(hashes.alias("hashes"), tables.alias("tables"))


def inspect_budget(k: int, tables: int, delta: float) -> int:
    """How many collisions to look at so that k near points are among them with chance 1 - delta / 2."""
    return k + math.ceil(2 * tables / delta)


def inspect_budgets(k: Column, tables: Column, delta: float) -> Column:
    """The same as a column."""
    return (k + F.ceil(2 * tables / F.lit(float(delta)))).cast("int")


def overall_success(n_cells: int, delta: float) -> float:
    """Chance that every cell returns its near points, by the union bound."""
    return min(1.0, max(0.0, 1 - n_cells * delta / 2))


def overall_successes(n_cells: Column, delta: float) -> Column:
    """The same as a column."""
    return F.least(F.lit(1.0), F.greatest(F.lit(0.0), 1 - n_cells * F.lit(float(delta)) / 2))


def delta_per_cell(delta: float, n_cells: int) -> float:
    return delta / max(1, n_cells)
