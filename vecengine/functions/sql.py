"""SQL functions of a fitted model: encode a vector, distance of a code, entries of a code."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecengine import metrics
from vecengine.model.codebooks import Codebooks, TableQuantizer, pack, unpack


def register(spark: SparkSession, books: Codebooks, tq: TableQuantizer | None = None, prefix: str = "vq") -> None:
    """Register <prefix>_encode(vec), <prefix>_decode(code), <prefix>_distance(code, query) and <prefix>_entries(code)."""
    metric = metrics.get(books.metric if books.metric in ("l2", "sql2", "dot", "l1") else "l2")
    rank_down = metric.larger_is_closer

    def stack(s: pd.Series) -> np.ndarray:
        return np.stack([np.asarray(x, np.float64) for x in s])

    @F.pandas_udf(T.BinaryType())
    def encode(vec: pd.Series) -> pd.Series:
        ok = vec.notna()
        out = pd.Series([None] * len(vec), index=vec.index, dtype=object)
        if ok.any():
            out[ok] = [c.tobytes() for c in pack(books.encode(stack(vec[ok]), True), books.k)]
        return out

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def decode(code: pd.Series) -> pd.Series:
        data = np.stack([np.frombuffer(c, np.uint8) for c in code])
        return pd.Series(list(books.decode(unpack(data, books.m, books.k))))

    @F.pandas_udf(T.DoubleType())
    def distance(code: pd.Series, query: pd.Series) -> pd.Series:
        codes = unpack(np.stack([np.frombuffer(c, np.uint8) for c in code]), books.m, books.k)
        out = np.empty(len(code))
        keys = query.map(lambda q: np.asarray(q, np.float64).tobytes())
        for key in keys.unique():  # a query's tables are made once a batch
            own = (keys == key).to_numpy()
            y = books.tables(np.frombuffer(key)[None], metric)
            y = y if tq is None else tq.quantize(y)
            total = y[0][np.arange(books.m), codes[own]].astype(np.float64).sum(axis=1)
            total = total if tq is None else total / tq.scale + tq.bias
            out[own] = total if rank_down else metric.outer(np.maximum(total, 0))
        return pd.Series(out)

    m, k = books.m, books.k

    @F.udtf(returnType="m int, i int")
    class Entries:
        def eval(self, code: bytes):
            if code is not None:
                for at, i in enumerate(unpack(np.frombuffer(code, np.uint8)[None], m, k)[0]):
                    yield at, int(i)

    spark.udf.register(f"{prefix}_encode", encode)
    spark.udf.register(f"{prefix}_decode", decode)
    spark.udf.register(f"{prefix}_distance", distance)
    spark.udtf.register(f"{prefix}_entries", Entries)


def merge_best(k: int):
    """A grouped-aggregate function: the ids of the k least scores of a group, ties by least id.

    For groups of bounded size, such as the partial answers of a query: k a part.
    """

    @F.pandas_udf("array<long>")
    def best(vec_id: pd.Series, score: pd.Series) -> list:
        order = np.lexsort((vec_id.to_numpy(), score.to_numpy()))[:k]
        return vec_id.to_numpy()[order].tolist()

    return best
