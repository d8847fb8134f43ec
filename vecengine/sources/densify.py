"""Sparse input made dense: signed hashing of map entries, or principal components."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.operators.arrays import lists, matrix
from vecengine.train.rotation import _moments


def signhash(df: DataFrame, dims: int) -> DataFrame:
    """(id, vec) of (id, entries map<string, double>): each key adds to one of dims places with a sign, by md5."""
    hexes = lambda k: F.md5(k.cast("binary"))
    rows = df.select("id", F.explode_outer("entries").alias("key", "x"))
    rows = rows.select("id", (F.conv(F.substring(hexes(F.col("key")), 1, 8), 16, 10).cast("long") % dims).cast("int").alias("d"), (F.col("x") * (1 - 2 * (F.conv(F.substring(hexes(F.col("key")), 9, 1), 16, 10).cast("int") % 2))).alias("x"))
    sums = rows.groupBy("id", "d").agg(F.sum("x").alias("x")).groupBy("id").agg(F.map_from_entries(F.filter(F.collect_list(F.struct("d", "x")), lambda s: s["d"].isNotNull())).alias("m"))
    return sums.select("id", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda d: F.coalesce(F.col("m")[d], F.lit(0.0))).alias("vec"))


def pca(df: DataFrame, dims: int) -> DataFrame:
    """(id, vec) on the dims leading principal directions: moments in one pass, eigenvectors on the driver."""
    n = df.count()
    s = _moments(df, None)
    j = len(s)
    mean = s[:, -1] / n
    vectors = np.linalg.eigh(s[:, :j] / n - np.outer(mean, mean))[1][:, ::-1][:, :dims]
    vectors = vectors * np.sign(vectors[np.abs(vectors).argmax(axis=0), np.arange(dims)])
    shared = df.sparkSession.sparkContext.broadcast((mean, vectors))

    def run(batches):
        mean, vectors = shared.value
        for batch in batches:
            x = matrix(batch.column(1))
            if len(x):
                yield pa.RecordBatch.from_arrays([batch.column(0), lists((x - mean) @ vectors)], names=["id", "vec"])

    return df.select("id", "vec").mapInArrow(run, "id long, vec array<double>")
