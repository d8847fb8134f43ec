"""What codebooks and data look like: usage, balance and correlation of subspaces."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.subspaces import Layout
from vecengine.train.rotation import _moments


def shares(usage: DataFrame) -> DataFrame:
    """(m, i, n, share) of (m, i, n)."""
    return usage.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("m")))


def entropy(usage: DataFrame) -> DataFrame:
    """(m, bits): entropy of each subspace's codes."""
    return shares(usage).groupBy("m").agg((-F.sum(F.col("share") * F.log2("share"))).alias("bits"))


def balance(df: DataFrame, layout: Layout, n: int) -> tuple[np.ndarray, float]:
    """Each subspace's det(covariance) ** (1 / M), and the mean absolute correlation across subspaces.

    Independent subspaces of equal determinant are what a product quantizer serves best.
    """
    s = _moments(df, None)
    j = layout.dims
    mean = s[:, -1] / n
    cov = s[:, :j] / n - np.outer(mean, mean)
    columns = layout.columns()
    dets = []
    for row in columns:
        c = row[row >= 0]
        sign, log = np.linalg.slogdet(cov[np.ix_(c, c)] + 1e-12 * np.eye(len(c)))
        dets.append(np.exp(log / layout.count) if sign > 0 else 0.0)
    sd = np.sqrt(np.maximum(np.diag(cov), 1e-300))
    corr = np.abs(cov / np.outer(sd, sd))
    owner = np.empty(j, int)
    for m, row in enumerate(columns):
        owner[row[row >= 0]] = m
    across = owner[:, None] != owner[None, :]
    return np.array(dets), float(corr[across].mean()) if across.any() else 0.0


def neighbour_correlation(df: DataFrame, dims: int) -> DataFrame:
    """(d, value): correlation of each dimension with the next, in one pass of mergeable moments."""
    rows = df.select("id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(dims - 2)), lambda d: F.struct(d.alias("d"), F.get("vec", d).alias("x"), F.get("vec", d + 1).alias("y")))).alias("p"))
    return rows.select("p.*").groupBy("d").agg(F.corr("x", "y").alias("value"))
