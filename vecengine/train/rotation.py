"""A rotation learnt with the codebooks: alternate codebook rounds with the nearest orthogonal matrix."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from vecengine.model.codebooks import Codebooks
from vecengine.operators.arrays import matrix
from vecengine.subspaces import split
from vecengine.train import lloyd


def _block(x: np.ndarray, b: Codebooks | None, exact: bool) -> np.ndarray:
    y = np.hstack([x, np.ones((len(x), 1))]) if b is None else b.layout.join(b.centroids[np.arange(b.m)[:, None], b.encode(x, exact).T])
    return x.T @ y


def _moments(train: DataFrame | np.ndarray, books: Codebooks | None, exact: bool = True) -> np.ndarray:
    """Sum over rows of x' y, y the reconstruction in rotated space, or of x' x and the sums without books.

    Each task sends one J x J block; a tree of partial sums would only pay beyond some thousand tasks.
    """
    if isinstance(train, np.ndarray):
        return sum(_block(train[at : at + lloyd.AT_HAND], books, exact) for at in range(0, len(train), lloyd.AT_HAND))
    shared = train.sparkSession.sparkContext.broadcast(books)

    def partial(batches):
        total = None
        for batch in batches:
            x = matrix(batch.column(0))
            if len(x):
                block = _block(x, shared.value, exact)
                total = block if total is None else total + block
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary()), pa.array([total.shape[1]], pa.int32())], names=["block", "width"])

    rows = train.select("vec").mapInArrow(partial, "block binary, width int").collect()
    return sum(np.frombuffer(bytes(r.block)).reshape(-1, r.width) for r in rows)


def principal(s: np.ndarray, n: int, count: int) -> np.ndarray:
    """Principal directions, of the moments of n vectors, dealt out to `count` subspaces so that their products of variances balance."""
    j = len(s)
    mean = s[:, -1] / n
    values, vectors = np.linalg.eigh(s[:, :j] / n - np.outer(mean, mean))
    room = [j // count + (m < j % count) for m in range(count)]
    load, dealt = np.zeros(count), [[] for _ in range(count)]
    for d in np.argsort(-values):
        m = min((m for m in range(count) if len(dealt[m]) < room[m]), key=lambda m: load[m])
        dealt[m].append(d)
        load[m] += np.log(max(values[d], 1e-12))
    return vectors[:, [d for m in dealt for d in m]]


def fit(train: DataFrame | np.ndarray, dims: int, m: int, k: int, outer: int = 10, inner: int = 1, init: str = "eigen", seed: int = 0, exact: bool = True) -> Codebooks:
    """Rotated codebooks; the error does not rise from round to round. exact: as for `Codebooks.encode`."""
    at_hand = isinstance(train, np.ndarray)
    train = train if at_hand else train.persist()
    n = len(train) if at_hand else train.count()
    first = lambda rotation: lloyd.seeds(train, split(dims, m), k, "hash", seed, rotation)
    answer = {"sums": lloyd.step, "cross": _moments}
    books = lloyd.driven(rounds(dims, m, n, first, outer, inner, init), lambda what, books: answer[what](train, books, exact))
    if not at_hand:
        train.unpersist()
    return books


def rounds(dims: int, m: int, n: int, first: Callable, outer: int = 10, inner: int = 1, init: str = "eigen") -> lloyd.Asks:
    """The rounds of `fit` over n vectors: asks for sums and for blocks of moments. first(rotation): centroids to begin with."""
    rotation = principal((yield "cross", None), n, m) if init == "eigen" else np.eye(dims)
    books = yield from lloyd.rounds(Codebooks(split(dims, m), first(rotation), rotation), inner + 1)
    for _ in range(outer):
        u, _, vt = np.linalg.svd((yield "cross", books))
        books = yield from lloyd.rounds(Codebooks(books.layout, books.centroids, u @ vt), inner)
    return books
