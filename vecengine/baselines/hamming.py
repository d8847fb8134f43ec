"""Binary embedding by signs of projections, compared by the number of differing bits."""

from __future__ import annotations

import hashlib
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.operators.arrays import lists, matrix
from vecengine.operators.search import CHUNK_BYTES, Best, _reduced

PAIRED = 10_000  # queries that may be sent out for comparison with every code in DataFrame operations


def signs(bits: int, dims: int) -> np.ndarray:
    """bits x dims of +1 and -1: the parity of the first hex digit of md5('bit:dim')."""
    return np.array([[1 - 2 * (int(hashlib.md5(f"{b}:{d}".encode()).hexdigest()[0], 16) & 1) for d in range(dims)] for b in range(bits)])


def gaussian(bits: int, dims: int, seed: int = 0) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((bits, dims))


def words(x: np.ndarray, projections: np.ndarray, mean: np.ndarray | None = None) -> np.ndarray:
    """rows x words of int64; bit b of a vector is bit b mod 64 of word b / 64, set where the projection is above 0.

    Projections are rounded to 9 digits, so that sums in another order give the same bit.
    """
    positive = np.round((x if mean is None else x - mean) @ projections.T, 9) > 0
    positive = np.pad(positive, ((0, 0), (0, -positive.shape[1] % 64)))
    weights = np.uint64(1) << np.arange(64, dtype=np.uint64)
    return (positive.reshape(len(x), -1, 64).astype(np.uint64) * weights).sum(axis=2, dtype=np.uint64).view(np.int64)


def encode(df: DataFrame, projections: np.ndarray, mean: np.ndarray | None = None) -> DataFrame:
    """(id, words array<long>) of (id, vec)."""
    shared = df.sparkSession.sparkContext.broadcast((projections, mean))

    def run(batches):
        for batch in batches:
            x = matrix(batch.column(1))
            if len(x):
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(words(x, *shared.value))], names=["id", "words"])

    return df.select("id", "vec").mapInArrow(run, "id long, words array<long>")


def distance(a, b, n_words: int):
    """Differing bits of two word arrays, in whole-stage code."""
    return reduce(lambda x, y: x + y, [F.bit_count(F.get(a, F.lit(w)).bitwiseXOR(F.get(b, F.lit(w)))) for w in range(n_words)]).cast("long")


def differing(columns: list[np.ndarray], word: np.ndarray) -> np.ndarray:
    """Differing bits of each code (words as columns) from one."""
    total = np.bitwise_count(columns[0] ^ word[0])
    for column, w in zip(columns[1:], word[1:], strict=True):
        total = total + np.bitwise_count(column ^ w).astype(np.uint16)
    return total.astype(np.uint16)


def scan_topk(codes: DataFrame, ids: np.ndarray, query_words: np.ndarray, k: int) -> DataFrame:
    """(query_id, rnk, vec_id, score) of codes (id, words), by population counts in numpy.

    ids, query_words: a bounded query set, sent out in chunks of at most CHUNK_BYTES.
    """
    sc = codes.sparkSession.sparkContext
    own = query_words.view(np.uint64)
    step = max(1, CHUNK_BYTES // max(1, own[:1].nbytes))
    parts = []
    for at in range(0, max(1, len(ids)), step):
        shared = sc.broadcast((ids[at : at + step], own[at : at + step]))

        def run(batches, shared=shared):
            few, own = shared.value
            best = Best(k, True)
            for batch in batches:
                x = matrix(batch.column(1), np.int64).view(np.uint64)
                columns = [np.ascontiguousarray(c) for c in x.T]
                for i, w in enumerate(own if len(x) else ()):
                    best.add(i, differing(columns, w)[:, None], batch.column(0).to_numpy())
            yield best.ranked(few, np.int64)

        parts.append(codes.select("id", "words").mapInArrow(run, "query_id long, vec_id long, score long"))
    return _reduced(parts, k, True)


def topk(codes: DataFrame, qcodes: DataFrame, k: int, n_words: int) -> DataFrame:
    """(query_id, rnk, vec_id, score) in DataFrame operations: a restatement over all pairs, for query sets whose size
    is checked here; `scan_topk` is the way for more."""
    n = qcodes.count()
    if n > PAIRED:
        raise ValueError(f"{n} queries: use scan_topk")
    q = F.broadcast(qcodes.select(F.col("id").alias("query_id"), F.col("words").alias("q")))  # at most PAIRED rows
    both = codes.select(F.col("id").alias("vec_id"), "words").join(q, how="cross").select("query_id", "vec_id", distance(F.col("words"), F.col("q"), n_words).alias("score"))
    best = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return both.withColumn("rnk", F.row_number().over(best)).where(F.col("rnk") <= k).select("query_id", F.col("rnk").cast("int").alias("rnk"), "vec_id", "score")
