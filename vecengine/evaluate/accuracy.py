"""Measures of accuracy over pairs (query_id, vec_id, true_d, approx_d) and ranked answers."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The ranks at which recall is reported.
RANKS = (1, 2, 5, 10, 20, 50, 100)


def mse(pairs: DataFrame) -> DataFrame:
    """(n, value): mean squared error of the distances."""
    gap = F.col("true_d") - F.col("approx_d")
    return pairs.agg(F.count(F.lit(1)).alias("n"), F.avg(gap * gap).alias("value"))


def pearson(pairs: DataFrame) -> DataFrame:
    """(n, value): correlation of true and approximate distances, by mergeable moments."""
    return pairs.agg(F.count(F.lit(1)).alias("n"), F.corr("true_d", "approx_d").alias("value"))


def recall_curve(nearest: DataFrame, ranked: DataFrame, n_queries: int, ranks: Sequence[int] = RANKS) -> DataFrame:
    """(r, recall): share of queries whose true neighbour is among the r best. nearest: one row a query."""
    hit = nearest.select("query_id", "vec_id").join(ranked.select("query_id", "vec_id", "rnk"), ["query_id", "vec_id"])
    counts = [F.sum((F.col("rnk") <= r).cast("long")).alias(f"r{r}") for r in ranks]
    row = hit.agg(*counts)
    pairs = F.array(*[F.struct(F.lit(r).alias("r"), (F.coalesce(F.col(f"r{r}"), F.lit(0)) / F.lit(n_queries)).alias("recall")) for r in ranks])
    return row.select(F.explode(pairs).alias("x")).select(F.col("x.r").alias("r"), F.col("x.recall").alias("recall"))


def recall_tolerant(nearest: DataFrame, ranked: DataFrame, n_queries: int, ranks: Sequence[int] = RANKS) -> DataFrame:
    """As recall_curve where `nearest` may hold several equally near vectors of a query: any of them counts."""
    hit = nearest.select("query_id", "vec_id").join(ranked.select("query_id", "vec_id", "rnk"), ["query_id", "vec_id"]).groupBy("query_id").agg(F.min("rnk").alias("rnk"))
    return recall_curve(hit.select("query_id", F.lit(0).alias("vec_id")), hit.select("query_id", F.lit(0).alias("vec_id"), "rnk"), n_queries, ranks)


def overlap(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """(query_id, overlap): share of the k exact answers that the other k hold."""
    both = a.where(F.col("rnk") <= k).select("query_id", "vec_id").join(b.where(F.col("rnk") <= k).select("query_id", "vec_id"), ["query_id", "vec_id"])
    counts = both.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return a.select("query_id").distinct().join(counts, "query_id", "left").select("query_id", (F.coalesce("n", F.lit(0)) / F.lit(k)).alias("overlap"))


def distortion(vdf: DataFrame, recon: DataFrame) -> DataFrame:
    """(n, value): squared error of reconstruction over squared distance from the mean."""
    parts = vdf.select("id", F.posexplode("vec").alias("d", "x")).join(recon.select("id", F.posexplode("vec").alias("d", "y")), ["id", "d"])
    by_dim = parts.groupBy("d").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("x") - F.col("y")) ** 2).alias("e"), (F.var_pop("x") * F.count(F.lit(1))).alias("s"))
    return by_dim.agg(F.max("n").alias("n"), (F.sum("e") / F.sum("s")).alias("value"))


def compression(dims: int, code_bytes: int) -> float:
    """Bytes of a single-precision vector over bytes of its code."""
    return 4 * dims / code_bytes


def at_tolerance(table: DataFrame, tolerances: Sequence[float] = (0.9, 0.95)) -> DataFrame:
    """(view, tol, bytes, ratio): for each view the fewest bytes with a correlation of at least tol.

    table: (view, bytes, r, ratio).
    """
    tol = table.select("*", F.explode(F.array(*map(F.lit, tolerances))).alias("tol")).where(F.col("r") >= F.col("tol"))
    return tol.groupBy("view", "tol").agg(F.min("bytes").alias("bytes"), F.max("ratio").alias("ratio"))


def op_counts(dims: int, m: int, k: int) -> dict[str, int]:
    """Multiply-adds to encode a vector or make a query's tables, lookups a pair, bytes of a byte table and a code."""
    return {"encode_madds": k * dims, "table_madds": k * dims, "lookups": m, "table_bytes": k * m, "code_bytes": -(-m // 2) if k <= 16 else m}
