"""Vector tables: loading with validation, text forms, splits, simple transforms."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.operators.arrays import lists, matrix


def valid(vec: Column, dims: int) -> Column:
    return vec.isNotNull() & (F.size(vec) == dims) & F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))


def load(spark: SparkSession, path: str, id_col: str = "vec_id", vec_col: str = "embedding", dims: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(vectors (id, vec), quarantine (id, vec)) of a Parquet table; dims is taken from one row if not given.

    Bad rows (null, wrong length, null or non-finite entries, no id) are set aside, not lost and not fatal.
    """
    raw = spark.read.parquet(path).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))
    return checked(raw, dims)


def checked(raw: DataFrame, dims: int | None = None) -> tuple[DataFrame, DataFrame]:
    if dims is None:
        first = raw.where("vec is not null").select(F.size("vec").alias("n")).first()
        dims = first.n if first else 0
    ok = F.coalesce(valid(F.col("vec"), dims) & F.col("id").isNotNull(), F.lit(False))
    return raw.where(ok), raw.where(~ok)


def from_text(spark: SparkSession, path: str, fmt: str = "json", dims: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Vectors of JSON lines {"id": .., "vec": [..]} or of CSV 'id;x y z' lines."""
    if fmt == "json":
        raw = spark.read.schema("id long, vec array<double>").json(path)
    else:
        raw = spark.read.schema("id long, v string").option("sep", ";").csv(path).select("id", F.transform(F.split(F.trim("v"), "[ ,]+"), lambda x: x.try_cast("double")).alias("vec"))
    return checked(raw, dims)


def split_by_id(df: DataFrame, modulus: int = 5) -> tuple[DataFrame, DataFrame]:
    """(queries, the rest): ids divisible by the modulus are held out."""
    held = F.col("id") % modulus == 0
    return df.where(held), df.where(~held)


def center(df: DataFrame, means: list[float]) -> DataFrame:
    m = F.array(*[F.lit(float(x)) for x in means])
    return df.withColumn("vec", F.zip_with("vec", m, lambda a, b: a - b))


def means(df: DataFrame, dims: int) -> list[float]:
    """Mean of each entry, from sums within tasks."""

    def run(batches):
        n, total = 0, np.zeros(dims)
        for batch in batches:
            if batch.num_rows:
                n += batch.num_rows
                total += matrix(batch.column(0)).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array([n]), lists(total[None])], names=["n", "total"])

    rows = df.select("vec").where("vec is not null").mapInArrow(run, "n long, total array<double>").collect()
    n = sum(r.n for r in rows)
    return [sum(r.total[d] for r in rows) / n if n else None for d in range(dims)]


def scale(df: DataFrame, by: float) -> DataFrame:
    return df.withColumn("vec", F.transform("vec", lambda x: x * by))


def normalize(df: DataFrame) -> DataFrame:
    from vecengine.metrics import unit

    return df.withColumn("vec", unit(F.col("vec")))


def synth(spark: SparkSession, n: int, dims: int, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """n vectors of dims entries in [-1, 1) from an integer hash of id and dimension."""
    ids = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    entry = lambda d: F.pmod(F.xxhash64(F.col("id"), d, F.lit(seed)), F.lit(1 << 20)) / float(1 << 19) - 1.0
    return ids.select("id", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), entry).alias("vec"))
