"""Joins that the engine needs and Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.operators.ordered import carried


def asof(left: DataFrame, right: DataFrame, keys: list[str], left_at: str, right_at: str, take: list[str]) -> DataFrame:
    """left with `take` of the latest row of right whose right_at is at most left_at, within equal keys.

    One union in order of keys and time, ranges of which are gone over by themselves: no pairs are made, and a key of very
    many rows is no single task. Rows of left without such a row keep nulls.
    """
    a = left.select(*keys, F.col(left_at).alias("__at"), F.lit(1).alias("__side"), F.struct(*[F.col(c) for c in left.columns]).alias("__row"), F.lit(None).cast(right.select(F.struct(*take)).schema[0].dataType).alias("__take"))
    b = right.select(*keys, F.col(right_at).alias("__at"), F.lit(0).alias("__side"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"), F.struct(*take).alias("__take"))
    out = carried(a.union(b), keys, ["__at", "__side"], F.col("__take")).where("__side = 1")  # of one time, right's rows come first
    return out.select("__row.*", *[F.col("last")[c].alias(c) for c in take])


def self_join(df: DataFrame, most: float, metric, block: int = 500_000) -> DataFrame:
    """(a, b, dist) of pairs a < b within a distance; one side goes out in bounded blocks of queries.

    Above `block` vectors the table is written and each range of about so many ids is answered by itself.
    """
    from vecengine.operators import search
    from vecengine.plans.folders import scratch

    def pairs(rows: DataFrame, queries: DataFrame) -> DataFrame:
        out = search.exact_pairs(rows, search.gather(queries), metric, most)
        return out.where("query_id < vec_id").select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"), F.col("true_d").alias("dist"))

    n = df.count()
    if n <= block:
        return pairs(df, df)
    spark, count = df.sparkSession, -(-n // block)
    folder = scratch(spark, "self_join")
    df.select("id", "vec").write.parquet(f"{folder}/in")
    df = spark.read.parquet(f"{folder}/in")
    bounds = df.agg(F.percentile_approx("id", F.array(*[F.lit(k / count) for k in range(1, count)]), F.lit(max(10_000, 100 * count)))).first()[0]
    ends = [None, *sorted(set(bounds)), None]
    for lo, hi in zip(ends, ends[1:], strict=False):
        later = df if lo is None else df.where(F.col("id") > lo)  # b stands after a
        pairs(later, later if hi is None else later.where(F.col("id") <= hi)).write.mode("append").parquet(f"{folder}/out")
    return spark.read.schema("a long, b long, dist double").parquet(f"{folder}/out")
