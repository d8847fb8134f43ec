"""Codebooks, rotations and table quantizers: small arrays that travel by broadcast, and their tables."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.subspaces import Layout


@dataclass(frozen=True)
class Codebooks:
    """centroids: M x K x width, zero where a subspace is narrower; rotation: J x J for row vectors, or None."""

    layout: Layout
    centroids: np.ndarray
    rotation: np.ndarray | None = None
    metric: str = "l2"

    @property
    def m(self) -> int:
        return self.centroids.shape[0]

    @property
    def k(self) -> int:
        return self.centroids.shape[1]

    @property
    def code_bytes(self) -> int:
        return -(-self.m // 2) if self.k <= 16 else self.m

    def turned(self, x: np.ndarray) -> np.ndarray:
        return x if self.rotation is None else x @ self.rotation

    # ------------------------------------------------------------ kernels

    def encode(self, x: np.ndarray, exact: bool = False) -> np.ndarray:
        """Codes (rows x M, uint8): the nearest centroid of each subvector, the lowest index on ties.

        exact: by direct differences in double precision; else by norms and products in single.
        """
        parts = self.layout.cut(self.turned(x))
        out = np.empty((len(x), self.m), np.uint8)
        if exact:
            for m in range(self.m):
                step = max(1, (4 << 20) // self.centroids[m].size)
                for lo in range(0, len(x), step):
                    d = ((parts[m, lo : lo + step, None, :] - self.centroids[m][None]) ** 2).sum(axis=2)
                    out[lo : lo + step, m] = d.argmin(axis=1)
            return out
        c = self.centroids.astype(np.float32)
        half = 0.5 * (c * c).sum(axis=2)
        if self.k <= 16:
            return self._encode16(parts, c, half, out)
        step = max(256, (1 << 20) // (self.m * self.k))
        for lo in range(0, len(x), step):  # scores of a block stay in cache
            block = np.ascontiguousarray(parts[:, lo : lo + step], np.float32)
            out[lo : lo + step] = (np.matmul(block, c.transpose(0, 2, 1)) - half[:, None, :]).argmax(axis=2).T
        return out

    def _encode16(self, parts: np.ndarray, c: np.ndarray, half: np.ndarray, out: np.ndarray) -> np.ndarray:
        """At most 16 centroids: the index rides in the low bits of each score, so that one integer maximum finds it.

        Scores are taken from the vector's least, so that their bits order like the numbers; what is equal to about 20 bits
        of their range goes to the lowest index. No vector's code depends on the others.
        """
        step = max(64, (1 << 17) // (self.m * self.k))  # scores of a block stay in cache
        tags = (15 - np.arange(self.k, dtype=np.int32))[None, :, None]
        parts = np.asarray(parts, np.float32)
        scores = np.empty((self.m, self.k, step), np.float32)
        for lo in range(0, parts.shape[1], step):
            block = parts[:, lo : lo + step].transpose(0, 2, 1)
            s = scores[:, :, : block.shape[2]]
            np.matmul(c, block, out=s)
            s -= half[:, :, None]
            s -= s.min(axis=1, keepdims=True)
            bits = s.view(np.int32)
            bits &= ~15
            bits |= tags
            out[lo : lo + step] = (15 - (bits.max(axis=1) & 15)).T
        return out

    def tables(self, q: np.ndarray, metric: metrics.Metric) -> np.ndarray:
        """queries x M x K partial distances."""
        if self.rotation is not None and metric.name in ("l1", "lp"):
            raise ValueError(f"a rotation does not keep {metric.name}")
        if metric.normalised:
            q = metrics.unit_rows(q)
        parts = self.layout.cut(self.turned(q))
        if metric.larger_is_closer:
            return np.matmul(parts, self.centroids.transpose(0, 2, 1)).transpose(1, 0, 2)
        if metric.name in ("l2", "sql2"):  # by norms and products
            y = np.matmul(parts, -2.0 * self.centroids.transpose(0, 2, 1))
            y += (parts * parts).sum(axis=2)[:, :, None]
            y += (self.centroids * self.centroids).sum(axis=2)[:, None, :]
            return np.maximum(y, 0.0, out=y).transpose(1, 0, 2)
        out = np.empty((len(q), self.m, self.k))
        for m in range(self.m):
            step = max(1, (4 << 20) // self.centroids[m].size)
            for lo in range(0, len(q), step):
                out[lo : lo + step, m] = metric.delta(parts[m, lo : lo + step, None, :], self.centroids[m][None]).sum(axis=2)
        return out

    def byte_tables(self, q: np.ndarray, metric: metrics.Metric, tq: TableQuantizer) -> np.ndarray:
        """tq.quantize(self.tables(q, metric)): for squared distances with the scale and offsets taken into the products."""
        if metric.name not in ("l2", "sql2"):
            return tq.quantize(self.tables(q, metric))
        parts = self.layout.cut(self.turned(q))
        z = np.matmul(parts, (-2.0 * tq.scale) * self.centroids.transpose(0, 2, 1))
        z += tq.scale * (parts * parts).sum(axis=2)[:, :, None]
        z += (tq.scale * ((self.centroids * self.centroids).sum(axis=2) - tq.offsets[:, None]) + 5e-10)[:, None, :]
        return np.clip(z, 0, 255, out=z).astype(np.uint8).transpose(1, 0, 2)

    def decode(self, codes: np.ndarray) -> np.ndarray:
        """Vectors (rows x J) that codes stand for."""
        parts = self.centroids[np.arange(self.m)[:, None], codes.T]
        x = self.layout.join(parts)
        return x if self.rotation is None else x @ self.rotation.T


def pack(codes: np.ndarray, k: int) -> np.ndarray:
    """Two 4-bit codes a byte, the first in the low half, for k <= 16; a byte each beyond."""
    if k > 16:
        return codes
    if codes.shape[1] % 2:
        codes = np.pad(codes, ((0, 0), (0, 1)))
    return codes[:, 0::2] | (codes[:, 1::2] << 4)


def unpack(data: np.ndarray, m: int, k: int) -> np.ndarray:
    if k > 16:
        return data
    out = np.empty((len(data), 2 * data.shape[1]), np.uint8)
    out[:, 0::2], out[:, 1::2] = data & 15, data >> 4
    return out[:, :m]


@dataclass(frozen=True)
class TableQuantizer:
    """b = clip(floor(scale * (y - offsets[m])), 0, 255); y is about b / scale + offsets[m]."""

    alpha: float
    scale: float
    offsets: np.ndarray
    midpoint: bool = False

    @property
    def bias(self) -> float:
        return float(self.offsets.sum()) + (0.5 * len(self.offsets) / self.scale if self.midpoint else 0.0)

    def quantize(self, y: np.ndarray) -> np.ndarray:
        """uint8 of y (.. x M x K). Half a unit of the ninth digit is added, as rounding to it would, so that a cutoff falls on its side."""
        z = y - self.offsets[:, None]
        z *= self.scale
        z += 5e-10
        return np.clip(z, 0, 255, out=z).astype(np.uint8)

    def dequantize(self, b: np.ndarray) -> np.ndarray:
        return (b + (0.5 if self.midpoint else 0.0)) / self.scale + self.offsets[:, None]


# ----------------------------------------------------------------------- store


def save(books: Codebooks, path: str, spark: SparkSession, tq: TableQuantizer | None = None, model_id: str = "model") -> None:
    """Write a model as small Parquet tables: meta, codebooks, rotation and quantizer."""
    lay = books.layout
    spark.createDataFrame([(model_id, lay.dims, lay.count, books.k, books.metric, list(lay.order) if lay.order else None)], "model_id string, dims int, m int, k int, metric string, order array<int>").coalesce(1).write.parquet(f"{path}/meta")
    to_frame(books, spark).withColumn("model_id", F.lit(model_id)).coalesce(1).write.parquet(f"{path}/codebooks")
    rows = [] if books.rotation is None else [(r, [float(x) for x in row]) for r, row in enumerate(books.rotation)]
    spark.createDataFrame(rows, "r int, row array<double>").coalesce(1).write.parquet(f"{path}/rotation")
    rows = [] if tq is None else [(books.metric, tq.alpha, tq.scale, [float(x) for x in tq.offsets], tq.midpoint, tq.bias)]
    spark.createDataFrame(rows, "metric string, alpha double, scale double, offsets array<double>, midpoint boolean, bias double").coalesce(1).write.parquet(f"{path}/quantizer")


def load(path: str, spark: SparkSession) -> tuple[Codebooks, TableQuantizer | None]:
    meta = spark.read.parquet(f"{path}/meta").first()
    layout = Layout(meta.dims, meta.m, tuple(meta.order) if meta.order else None)
    centroids = np.zeros((meta.m, meta.k, layout.width))
    for r in spark.read.parquet(f"{path}/codebooks").collect():
        centroids[r.m, r.i, : len(r.centroid)] = r.centroid
    rows = sorted(spark.read.parquet(f"{path}/rotation").collect())
    rotation = np.array([r.row for r in rows]) if rows else None
    q = spark.read.parquet(f"{path}/quantizer").first()
    tq = None if q is None else TableQuantizer(q.alpha, q.scale, np.array(q.offsets), q.midpoint)
    return Codebooks(layout, centroids, rotation, meta.metric), tq


def to_frame(books: Codebooks, spark: SparkSession) -> DataFrame:
    """(m, i, centroid) of M * K rows."""
    widths = books.layout.widths
    rows = [(m, i, [float(x) for x in books.centroids[m, i, : widths[m]]]) for m in range(books.m) for i in range(books.k)]
    return spark.createDataFrame(rows, "m int, i int, centroid array<double>")


def with_metric(books: Codebooks, metric: str) -> Codebooks:
    return replace(books, metric=metric)
