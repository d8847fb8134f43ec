"""Distances of the form f(sum over dimensions of delta(q, x)), for columns and for arrays."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Metric:
    """delta and outer in numpy; outer_col and pair_col as columns; `sql` is delta in SQL over q and x."""

    name: str
    delta: Callable[[np.ndarray, np.ndarray], np.ndarray]
    outer: Callable[[np.ndarray], np.ndarray]
    delta_col: Callable[[Column, Column], Column]
    outer_col: Callable[[Column], Column]
    larger_is_closer: bool = False
    normalised: bool = False  # both sides are brought to unit length first

    def pair(self, q: Column, x: Column) -> Column:
        """Distance of two array columns, summed from the first dimension to the last."""
        if self.normalised:
            q, x = unit(q), unit(x)
        return self.outer_col(F.aggregate(F.zip_with(q, x, self.delta_col), F.lit(0.0), lambda a, d: a + d))

    def matrix(self, q: np.ndarray, x: np.ndarray) -> np.ndarray:
        """All distances of the rows of q and x, by direct differences."""
        if self.normalised:
            q, x = unit_rows(q), unit_rows(x)
        if self.name in ("dot", "cosine"):
            return q @ x.T
        out = np.empty((len(q), len(x)))
        step = max(1, (4 << 20) // max(1, x.size))
        for lo in range(0, len(q), step):
            out[lo : lo + step] = self.delta(q[lo : lo + step, None, :], x[None]).sum(axis=2)
        return self.outer(out)


def unit(v: Column) -> Column:
    norm = F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x))
    return F.transform(v, lambda x: F.when(norm > 0, x / norm).otherwise(x))


def unit_rows(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, norm, out=x.copy(), where=norm > 0)


def get(name: str, p: float | None = None) -> Metric:
    """'sql2', 'l2', 'l1', 'lp' with p > 0, 'dot' or 'cosine'."""
    same = lambda s: s
    if name in ("sql2", "l2"):
        root = name == "l2"
        return Metric(name, lambda q, x: (q - x) ** 2, np.sqrt if root else same, lambda q, x: (q - x) * (q - x), F.sqrt if root else same)
    if name == "l1":
        return Metric(name, lambda q, x: np.abs(q - x), same, lambda q, x: F.abs(q - x), same)
    if name == "lp":
        if p is None or p <= 0:
            raise ValueError("lp needs p > 0")
        return Metric(name, lambda q, x: np.abs(q - x) ** p, lambda s: s ** (1 / p), lambda q, x: F.pow(F.abs(q - x), F.lit(float(p))), lambda s: F.pow(s, F.lit(1 / p)))
    if name in ("dot", "cosine"):
        return Metric(name, lambda q, x: q * x, same, lambda q, x: q * x, same, True, name == "cosine")
    raise ValueError(f"unknown metric {name}")
