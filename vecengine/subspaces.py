"""Disjoint sets of dimensions, one for each codebook."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Layout:
    """M runs of dimensions over `order`, a permutation of 0..J-1; the first J mod M runs are one longer."""

    dims: int
    count: int
    order: tuple[int, ...] | None = None

    @property
    def widths(self) -> list[int]:
        base, more = divmod(self.dims, self.count)
        return [base + (m < more) for m in range(self.count)]

    @property
    def starts(self) -> list[int]:
        return [int(x) for x in np.cumsum([0, *self.widths[:-1]])]

    @property
    def width(self) -> int:
        return -(-self.dims // self.count)

    def columns(self) -> np.ndarray:
        """M x width: the dimension at each place of each subspace, -1 where padded."""
        order = np.arange(self.dims) if self.order is None else np.array(self.order)
        out = np.full((self.count, self.width), -1)
        for m, (s, w) in enumerate(zip(self.starts, self.widths, strict=True)):
            out[m, :w] = order[s : s + w]
        return out

    def cut(self, x: np.ndarray) -> np.ndarray:
        """Rows x J to M x rows x width; padded places are 0."""
        if self.order is None and self.dims % self.count == 0:
            return x.reshape(len(x), self.count, -1).transpose(1, 0, 2)
        c = self.columns()
        out = x[:, np.maximum(c, 0)].transpose(1, 0, 2).copy()
        out[np.broadcast_to((c < 0)[:, None, :], out.shape)] = 0
        return out

    def join(self, parts: np.ndarray) -> np.ndarray:
        """M x rows x width back to rows x J."""
        c = self.columns()
        out = np.empty((parts.shape[1], self.dims), parts.dtype)
        m, p = np.nonzero(c >= 0)
        out[:, c[m, p]] = parts[m, :, p].T
        return out


def split(dims: int, count: int, order: list[int] | None = None) -> Layout:
    if not 1 <= count <= dims:
        raise ValueError(f"{count} codebooks do not fit {dims} dimensions")
    if order is not None and sorted(order) != list(range(dims)):
        raise ValueError("order is no permutation of the dimensions")
    return Layout(dims, count, None if order is None else tuple(order))


def explode_sub(df: DataFrame, layout: Layout) -> DataFrame:
    """(id, m, sub): one row for each subvector of (id, vec), row-local."""
    vec = F.col("vec")
    if layout.order is not None:
        vec = F.transform(F.array(*[F.lit(d) for d in layout.order]), lambda d: F.get(F.col("vec"), d))
    parts = F.array(*[F.slice(vec, s + 1, w) for s, w in zip(layout.starts, layout.widths, strict=True)])
    return df.select("id", F.posexplode(parts).alias("m", "sub"))
