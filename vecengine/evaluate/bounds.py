"""Bounds on the errors of entries, products and distances, beside what is measured.

Two are exact and are asserted (slack 1e-9): a product's error is at most the query's norm times the
error's norm, a distance's at most the error's norm. The tail bounds are reported only: they suppose
independent terms of mean zero, which data need not have; with M = 1, q = 10, x = 1 and a
reconstruction of 0 the squared distance is off by 19 though the error's norm is 1.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.model.codebooks import Codebooks, unpack
from vecengine.operators.arrays import bytes_of, matrix
from vecengine.operators.search import Queries, shared_queries

SLACK = 1e-9
PAIRED = 10_000  # queries that may be sent out for comparison with every vector in DataFrame operations


def _norm(v):
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x))


def _dot(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def _minus(a, b):
    return F.zip_with(a, b, lambda x, y: x - y)


def pair_bounds(qdf: DataFrame, vdf: DataFrame, recon: DataFrame) -> DataFrame:
    """(query_id, vec_id, dot_gap, dot_bound, l2_gap, l2_bound) of all pairs, for query sets whose size is checked here."""
    n = qdf.count()
    if n > PAIRED:
        raise ValueError(f"{n} queries: take them in several calls")
    both = vdf.select("id", "vec").join(recon.select("id", F.col("vec").alias("back")), "id").withColumn("err", _norm(_minus(F.col("vec"), F.col("back"))))
    q = F.broadcast(qdf.select(F.col("id").alias("query_id"), F.col("vec").alias("q")).withColumn("qn", _norm(F.col("q"))))
    p = both.join(q, how="cross")
    return p.select(
        "query_id",
        F.col("id").alias("vec_id"),
        F.abs(_dot(F.col("q"), F.col("vec")) - _dot(F.col("q"), F.col("back"))).alias("dot_gap"),
        (F.col("qn") * F.col("err")).alias("dot_bound"),
        F.abs(_norm(_minus(F.col("q"), F.col("vec"))) - _norm(_minus(F.col("q"), F.col("back")))).alias("l2_gap"),
        F.col("err").alias("l2_bound"),
    )


def violations(bounds: DataFrame, gap: str, bound: str) -> DataFrame:
    """(n, violations, max_gap)."""
    return bounds.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col(gap) > F.col(bound) + SLACK).cast("long")).alias("violations"), F.max(gap).alias("max_gap"))


def _distances(q: np.ndarray, x: np.ndarray, some: int = 1 << 16) -> np.ndarray:
    """All distances by norms and products; by differences where most of a square cancels out, so that roots are good to 1e-11."""
    size = (q * q).sum(axis=1)[:, None] + (x * x).sum(axis=1)[None]
    square = size - 2 * (q @ x.T)
    i, j = np.nonzero(square < 1e-3 * size)
    for at in range(0, len(i), some):
        a, b = i[at : at + some], j[at : at + some]
        square[a, b] = ((q[a] - x[b]) ** 2).sum(axis=1)
    return np.sqrt(np.maximum(square, 0.0))


def _gaps(vdf: DataFrame, q: Queries, measured: Callable[[np.ndarray], Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]], rows: int = 1024, queries: int = 256) -> DataFrame:
    """(n, violations, max_gap) over all pairs of measured(vectors)(queries), which gives gaps and their bounds.

    Only a count and a maximum of each task leave it; the queries are sent out in chunks, and blocks of pairs stay in cache.
    """

    def run(batches, shared):
        n, over, most, asked = 0, 0, 0.0, shared.value.vectors
        for batch in batches:
            x = matrix(batch.column(0))
            for at in range(0, len(x), rows):
                of = measured(x[at : at + rows])
                for lo in range(0, len(asked), queries):
                    gap, bound = of(asked[lo : lo + queries])
                    n, over, most = n + gap.size, over + int((gap > bound + SLACK).sum()), max(most, float(gap.max()))
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([over]), pa.array([most])], names=["n", "violations", "max_gap"])

    out = None
    for shared in shared_queries(vdf.sparkSession, q):
        part = vdf.select("vec").mapInArrow(lambda batches, shared=shared: run(batches, shared), "n long, violations long, max_gap double")
        out = part if out is None else out.union(part)
    return out.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.sum("violations").alias("violations"), F.max("max_gap").alias("max_gap"))


def product_gaps(vdf: DataFrame, q: Queries, books: Codebooks) -> DataFrame:
    """(n, violations, max_gap): errors of products by reconstruction against the norms of query and error, over all pairs."""

    def measured(x):
        wrong = x - books.decode(books.encode(x, True))
        size = np.sqrt((wrong * wrong).sum(axis=1))[None]
        return lambda own: (np.abs(own @ wrong.T), np.sqrt((own * own).sum(axis=1))[:, None] * size)

    return _gaps(vdf, q, measured)


def distance_gaps(vdf: DataFrame, q: Queries, books: Codebooks) -> DataFrame:
    """(n, violations, max_gap): errors of distances to reconstructions against the error's norm, over all pairs."""

    def measured(x):
        back = books.decode(books.encode(x, True))
        size = np.sqrt(((x - back) ** 2).sum(axis=1))[None]
        return lambda own: (np.abs(_distances(own, x) - _distances(own, back)), size)

    return _gaps(vdf, q, measured)


def identity_gaps(vdf: DataFrame, q: Queries) -> DataFrame:
    """(n, violations, max_gap): squared distances by norms and products against those by differences, over all pairs."""

    def measured(x):
        columns = np.ascontiguousarray(x.T)

        def of(own):
            gap = np.maximum((own * own).sum(axis=1)[:, None] + (x * x).sum(axis=1)[None] - 2 * (own @ x.T), 0.0)
            direct, part = np.zeros_like(gap), np.empty_like(gap)
            for d, column in enumerate(columns):  # in place: a block of pairs stays in cache
                np.subtract(own[:, d : d + 1], column, out=part)
                part *= part
                direct += part
            gap -= direct
            return np.abs(gap, out=gap), 0.0

        return of

    return _gaps(vdf, q, measured, queries=64)


def entry_errors(tables: DataFrame, tq) -> DataFrame:
    """(n, violations, max_gap) of entries within the cutoffs: 0 <= y - reconstruction < 1 / scale."""
    offset = F.element_at(F.array(*[F.lit(float(x)) for x in tq.offsets]), F.col("m") + 1)
    level = F.floor(F.round(tq.scale * (F.col("y") - offset), 9))
    inside = tables.where((level >= 0) & (level <= 255))
    gap = F.col("y") - (level / tq.scale + offset)
    return inside.agg(F.count(F.lit(1)).alias("n"), F.sum(((gap < -SLACK) | (gap >= 1 / tq.scale + SLACK)).cast("long")).alias("violations"), F.max(gap).alias("max_gap"))


def tails(vdf: DataFrame, codes: DataFrame, q: Queries, books: Codebooks, eps: Sequence[float]) -> DataFrame:
    """(kind, eps, n, rate, bound): how often an error exceeds eps over all pairs, and the mean of its two-sided tail bound.

    kind 'dot': of products, 2 exp(-eps^2 / (2 sum over subspaces of (query norm * error norm)^2)); 'sql2': of squared
    distances, with the error norms' fourth powers. Bounds above 1 count as 1. They are reported, not asserted. Sums
    are taken where the vectors lie; the queries are a bounded set.
    """
    shared = vdf.sparkSession.sparkContext.broadcast((q.vectors, books, tuple(eps)))

    def run(batches):
        asked, b, levels = shared.value
        qn = (b.layout.cut(b.turned(asked)) ** 2).sum(axis=2)  # M x queries
        for batch in batches:
            if not batch.num_rows:
                continue
            x, data = matrix(batch.column(0)), bytes_of(batch.column(1))
            back = b.decode(unpack(data, b.m, b.k))
            rn = (b.layout.cut(b.turned(x - back)) ** 2).sum(axis=2)  # M x rows
            for lo in range(0, len(asked), 256):
                own = asked[lo : lo + 256]
                dot = np.abs(own @ (x - back).T)
                gap = np.abs(((own[:, None] - x[None]) ** 2).sum(axis=2) - ((own[:, None] - back[None]) ** 2).sum(axis=2)) if len(own) * x.size < 1 << 24 else np.abs((x * x).sum(axis=1) - (back * back).sum(axis=1) - 2 * own @ (x - back).T)
                for kind, wrong, spread in (("dot", dot, qn[:, lo : lo + 256].T @ rn), ("sql2", gap, np.broadcast_to((rn * rn).sum(axis=0), gap.shape))):
                    for e in levels:
                        with np.errstate(divide="ignore"):
                            bound = np.minimum(1.0, 2 * np.exp(-(e**2) / (2 * spread)))
                        yield pa.RecordBatch.from_arrays([pa.array([kind]), pa.array([e]), pa.array([gap.size]), pa.array([int((wrong > e).sum())]), pa.array([float(bound.sum())])], names=["kind", "eps", "n", "over", "bound"])

    both = vdf.select("id", "vec").join(codes.select("id", "code"), "id").select("vec", "code")
    rows = both.mapInArrow(run, "kind string, eps double, n long, over long, bound double")
    return rows.groupBy("kind", "eps").agg(F.sum("n").alias("n"), (F.sum("over") / F.sum("n")).alias("rate"), (F.sum("bound") / F.sum("n")).alias("bound"))


def gaussian_tail(scale: float, sigma: float, eps: float) -> tuple[float, float]:
    """Tail bound of a normal entry beyond eps as printed, with a factor 1 / sigma, and without it."""
    import math

    body = math.exp(-(eps**2) / (2 * sigma**2))
    return body / sigma / scale, body / scale
