"""Code lengths in bits: plug-in data bits, leaf complexity, tree structure. As Spark columns and as numpy functions."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

CRITERIA = ("refined", "bic", "aic", "crude")
EXACT_TO = 10_000  # beyond, the asymptotic series differs from the exact value by less than 1e-10 bits


# ---- numpy / Python


def data_bits(n, n1):
    """Bits of n binary values with n1 ones under their own shares; 0 log 0 = 0."""
    n, n1 = np.asarray(n, float), np.asarray(n1, float)
    n0 = n - n1
    with np.errstate(divide="ignore", invalid="ignore"):
        a = np.where(n1 > 0, -n1 * np.log2(n1 / n), 0.0)
        b = np.where(n0 > 0, -n0 * np.log2(n0 / n), 0.0)
    return a + b


@lru_cache(maxsize=200_000)
def nml_exact(m: int) -> float:
    """log2 of the normaliser of the maximum-likelihood code of m binary values: the sum over k of the products
    (m - r + 1) / m for r up to k, whose terms fade after about 9 sqrt(m)."""
    if m <= 0:
        return 0.0
    r = np.arange(1, min(m, int(9 * math.sqrt(m)) + 60) + 1)
    return math.log2(1.0 + np.cumprod((m - r + 1) / m).sum())


@lru_cache(maxsize=1)
def _nml_table() -> np.ndarray:
    """The exact values up to EXACT_TO."""
    return np.array([nml_exact(m) for m in range(EXACT_TO + 1)])


def nml_asymptotic(m):
    m = np.asarray(m, float)
    with np.errstate(divide="ignore", invalid="ignore"):
        s = np.sqrt(np.pi * m / 2) + 2 / 3 + np.sqrt(2 * np.pi) / (24 * np.sqrt(m)) - 4 / (135 * m) + np.sqrt(2 * np.pi) / (576 * m**1.5)
        return np.where(m > 0, np.log2(s), 0.0)


def nml_bits(m, method: str = "auto"):
    """Leaf complexity of m rows (array or scalar). method: auto, exact or asymptotic."""
    m = np.asarray(m, np.int64)
    if method == "asymptotic":
        return nml_asymptotic(m)
    flat = m.ravel()
    if method == "exact":
        u, inv = np.unique(flat, return_inverse=True)
        return np.array([nml_exact(int(x)) for x in u], float)[inv].reshape(m.shape)
    out = _nml_table()[np.minimum(np.maximum(flat, 0), EXACT_TO)]
    large = flat > EXACT_TO
    if large.any():
        out[large] = nml_asymptotic(flat[large])
    return out.reshape(m.shape)


def complexity(m, criterion: str = "refined", total: int | None = None):
    """Model bits of a leaf with m rows under a criterion; total: rows of the data set (bic)."""
    m = np.asarray(m)
    if criterion == "refined":
        return nml_bits(m)
    if criterion == "bic":
        return np.full(m.shape, 0.5 * math.log2(total) if total else 0.0)
    if criterion == "aic":
        return np.full(m.shape, math.log2(math.e))
    if criterion == "crude":
        return 0.5 * np.log2(np.maximum(m, 1))
    raise ValueError(f"criterion must be one of {CRITERIA}")


def leaf_cost(n, n1, criterion: str = "refined", total: int | None = None):
    """Structure bit, complexity and data bits of a leaf."""
    return 1.0 + complexity(n, criterion, total) + data_bits(n, n1)


def split_cost(k: int) -> float:
    """Structure bits of an internal node: one bit and the choice among k attributes."""
    return 1.0 + math.log2(k)


def structure_bits(leaves: int, internal: int, k: int) -> float:
    return leaves + internal * split_cost(k)


# ---- Spark columns


def data_bits_col(n: Column, n1: Column) -> Column:
    part = lambda c: F.when(c > 0, -c * F.log2(c / n)).otherwise(F.lit(0.0))
    return part(n1) + part(n - n1)


def nml_bits_col(m: Column, method: str = "auto", exact_to: int = EXACT_TO) -> Column:
    """Leaf complexity as an expression: a fold for small m, the series for large."""
    d = m.cast("double")
    series = F.log2(F.sqrt(F.lit(math.pi / 2) * d) + F.lit(2 / 3) + F.lit(math.sqrt(2 * math.pi) / 24) / F.sqrt(d) - F.lit(4 / 135) / d + F.lit(math.sqrt(2 * math.pi) / 576) / F.pow(d, F.lit(1.5)))
    steps = F.sequence(F.lit(1), F.least(m.cast("int"), (F.sqrt(d) * 9 + 60).cast("int")))
    start = F.struct(F.lit(1.0).alias("s"), F.lit(1.0).alias("p"))

    def step(acc, r):
        p = acc["p"] * (d - r + 1) / d
        return F.struct((acc["s"] + p).alias("s"), p.alias("p"))

    exact = F.log2(F.aggregate(steps, start, step, lambda acc: acc["s"]))
    if method == "exact":
        some = exact
    elif method == "asymptotic":
        some = series
    else:
        some = F.when(m <= exact_to, exact).otherwise(series)
    return F.when(m > 0, some).otherwise(F.lit(0.0))


def complexity_col(m: Column, criterion: str = "refined", total: Column | None = None) -> Column:
    if criterion == "refined":
        return nml_bits_col(m)
    if criterion == "bic":
        return F.lit(0.5) * F.log2(total)
    if criterion == "aic":
        return F.lit(math.log2(math.e))
    return F.lit(0.5) * F.log2(F.greatest(m, F.lit(1)))


def leaf_cost_col(n: Column, n1: Column, criterion: str = "refined", total: Column | None = None) -> Column:
    return F.lit(1.0) + complexity_col(n, criterion, total) + data_bits_col(n, n1)
