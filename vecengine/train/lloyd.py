"""k-means in each subspace over a frame of training vectors.

The frame may be all vectors or a `sample`. Each round broadcasts the centroids, sums vectors by their centroid
within each task, adds the M * K partial sums up in one small aggregate and sends them to the driver;
no vector moves. `relational` does the same in DataFrame operations only.
"""

from __future__ import annotations

from collections.abc import Callable, Generator, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.model.codebooks import Codebooks
from vecengine.operators.arrays import lists, matrix, stacked
from vecengine.subspaces import Layout, explode_sub, split

AT_HAND = 4096  # rows of an array that a round takes at once


def sample(df: DataFrame, rows: int) -> DataFrame:
    """The `rows` vectors of least hash of the id: a bound where one is wanted, the same whatever the order of ids.

    On a large table a bound on the hash comes first, so that tasks do not each send their own `rows`
    vectors on.
    """
    n = df.count()
    if n <= rows:
        return df
    key = F.xxhash64("id")
    if n > 8 * rows:
        part = df.where(F.pmod(key, F.lit(1 << 40)) < F.lit(int((1 << 40) * 2 * rows / n)))
        if part.count() >= rows:
            df = part
    return df.orderBy(F.pmod(key, F.lit(1 << 40)), "id").limit(rows)


def gathered(df: DataFrame, rows: int, queries: int) -> tuple[np.ndarray, np.ndarray]:
    """Of `sample(df, rows)`, on the driver: the vectors in order of the hash that `seeds` takes, and the `queries` first
    ones of the sample's own order, in single precision, as fits compare. Vectors are not sorted: ids and hashes are, and
    what is above the last is left out."""
    order = F.pmod(F.xxhash64("id"), F.lit(1 << 40))
    last = df.select(order.alias("key"), "id").orderBy("key", "id").limit(rows).agg(F.max(F.struct("key", "id")).alias("x")).first().x
    if last is None:
        raise ValueError("no training vectors")
    within = (order < last.key) | ((order == last.key) & (F.col("id") <= last.id))
    t = df.where(within).select(F.col("vec").cast("array<float>").alias("vec"), F.xxhash64(F.lit(0), "id").alias("seed"), order.alias("key"), "id").toArrow()
    seed, key, ids = (t.column(c).to_numpy() for c in ("seed", "key", "id"))
    order = np.lexsort((ids, seed))
    x = stacked(t.column(0), order, np.float32)
    del t
    pa.default_memory_pool().release_unused()
    return x, x[np.argsort(order)[np.lexsort((ids, key))[:queries]]]


def seeds(train: DataFrame | np.ndarray, layout: Layout, k: int, init: str = "first", seed: int = 0, rotation: np.ndarray | None = None) -> np.ndarray:
    """M x K x width first centroids.

    'first': the k vectors of least id; 'hash': of least hash of the id; 'kmeans++': spread, from
    50 * k vectors of least hash. Vectors at hand (an array) are in the order wanted.
    """
    if isinstance(train, np.ndarray):
        x = train[: k if init != "kmeans++" else 50 * k]
    else:
        if init == "first":
            rows = train.orderBy("id").limit(k).collect()
        else:
            rows = train.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(k if init == "hash" else 50 * k).collect()
        x = np.array([r.vec for r in rows], np.float64)
    if len(x) < k:
        raise ValueError(f"{k} centroids need as many training vectors, not {len(x)}")
    parts = layout.cut(x if rotation is None else x @ rotation)
    if init != "kmeans++":
        return parts[:, :k].copy()
    rng = np.random.default_rng(seed)
    out = np.empty((layout.count, k, layout.width))
    for m in range(layout.count):
        out[m, 0] = parts[m, rng.integers(len(x))]
        d = ((parts[m] - out[m, 0]) ** 2).sum(axis=1)
        for i in range(1, k):
            total = d.sum()
            out[m, i] = parts[m, rng.choice(len(x), p=d / total) if total > 0 else rng.integers(len(x))]
            d = np.minimum(d, ((parts[m] - out[m, i]) ** 2).sum(axis=1))
    return out


def _sums(parts: Iterable[np.ndarray], b: Codebooks, exact: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sums and counts of the vectors nearest to each centroid, and each subspace's squared error."""
    total = np.zeros(b.centroids.shape)
    count = np.zeros(b.centroids.shape[:2], np.int64)
    error = np.zeros(b.m)
    for x in parts:
        if not len(x):
            continue
        codes = b.encode(x, exact)
        cut = b.layout.cut(b.turned(x))
        for m in range(b.m):
            count[m] += np.bincount(codes[:, m], minlength=b.k)
            for d in range(cut.shape[2]):
                total[m, :, d] += np.bincount(codes[:, m], cut[m, :, d], b.k)
            error[m] += ((cut[m] - b.centroids[m, codes[:, m]]) ** 2).sum()
    return total, count, error


def step(train: DataFrame | np.ndarray, books: Codebooks, exact: bool = True) -> tuple[np.ndarray, np.ndarray, float]:
    """Sums (M x K x width) and counts (M x K) of the vectors nearest to each centroid, and the total squared error."""
    if isinstance(train, np.ndarray):
        total, count, error = _sums((train[at : at + AT_HAND] for at in range(0, len(train), AT_HAND)), books, exact)
        return total, count, float(error.sum())
    shared = train.sparkSession.sparkContext.broadcast(books)

    def partial(batches):
        total, count, error = _sums((matrix(batch.column(0)) for batch in batches), shared.value, exact)
        m, i = np.nonzero(count)
        if len(m):
            yield pa.RecordBatch.from_arrays([pa.array(m, pa.int32()), pa.array(i, pa.int32()), lists(total[m, i]), pa.array(count[m, i]), pa.array(np.where(i == [np.flatnonzero(count[x])[0] for x in m], error[m], 0.0))], names=["m", "i", "total", "n", "error"])

    width = books.layout.width
    rows = train.select("vec").mapInArrow(partial, "m int, i int, total array<double>, n long, error double")
    rows = rows.groupBy("m", "i").agg(F.array(*[F.sum(F.get("total", F.lit(d))) for d in range(width)]).alias("total"), F.sum("n").alias("n"), F.sum("error").alias("error")).collect()
    total, count, error = np.zeros(books.centroids.shape), np.zeros(books.centroids.shape[:2], np.int64), 0.0
    for r in rows:
        total[r.m, r.i], count[r.m, r.i] = r.total, r.n
        error += r.error
    return total, count, error


def fit(train: DataFrame | np.ndarray, dims: int, m: int, k: int, iters: int = 10, init: str = "first", seed: int = 0, order: list[int] | None = None, rotation: np.ndarray | None = None, empty: str = "keep", tolerance: float = 0.0, exact: bool = True, start: np.ndarray | None = None) -> Codebooks:
    """Codebooks after `iters` rounds, or fewer where the error falls by less than `tolerance` of itself.

    empty: 'keep' leaves a centroid without vectors where it is; 'split' moves it beside the largest's.
    """
    layout = split(dims, m, order)
    books = Codebooks(layout, seeds(train, layout, k, init, seed, rotation) if start is None else start, rotation)
    return driven(rounds(books, iters, empty, tolerance), lambda _, books: step(train, books, exact))


Asks = Generator[tuple, object, Codebooks]  # asks for ('sums' or 'cross', books) and ends with the model


def rounds(books: Codebooks, iters: int, empty: str = "keep", tolerance: float = 0.0) -> Asks:
    """The rounds of `fit`: asks for the sums of each."""
    before = None
    for _ in range(iters):
        total, count, error = yield "sums", books
        new = np.where(count[:, :, None] > 0, total / np.maximum(count, 1)[:, :, None], books.centroids)
        if empty == "split":
            for a in range(books.m):
                for i in np.flatnonzero(count[a] == 0):
                    large = int(count[a].argmax())
                    new[a, i] = new[a, large] * (1 + 1e-4) + 1e-9
                    count[a, large] //= 2
                    count[a, i] = count[a, large]
        books = Codebooks(books.layout, new, books.rotation)
        if before is not None and before - error <= tolerance * before and tolerance > 0:
            break
        before = error
    return books


def driven(asks: Asks, answer: Callable) -> Codebooks:
    """What a fit ends with, where answer(what, books) gives what it asks for."""
    try:
        asked = next(asks)
        while True:
            asked = asks.send(answer(*asked))
    except StopIteration as end:
        return end.value


def relational_step(train: DataFrame, books: DataFrame, layout: Layout) -> DataFrame:
    """One round in DataFrame operations: (m, i, centroid) to (m, i, centroid).

    Codebooks (M * K rows) become an array a subspace, so assignment is row-local.
    """
    grouped = F.broadcast(books.groupBy("m").agg(F.array_sort(F.collect_list(F.struct("i", "centroid"))).alias("cs")))  # M rows
    near = explode_sub(train, layout).join(grouped, "m")
    square = lambda c: F.aggregate(F.zip_with("sub", c["centroid"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    near = near.withColumn("d", F.transform("cs", square)).select("m", (F.array_position("d", F.array_min("d")) - 1).cast("int").alias("i"), F.posexplode("sub").alias("p", "x"))
    means = near.groupBy("m", "i", "p").agg(F.avg("x").alias("x"))
    old = books.select("m", "i", F.posexplode("centroid").alias("p", "was"))
    both = old.join(means, ["m", "i", "p"], "left").select("m", "i", "p", F.coalesce("x", "was").alias("x"))
    return both.groupBy("m", "i").agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "x"))), lambda s: s["x"]).alias("centroid"))
