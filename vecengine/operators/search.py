"""Query tables, scans, top-k, re-ranking, range search and self-joins.

Queries are a bounded set: they are sent out in chunks of at most CHUNK_BYTES, tens of thousands of
them, and each chunk is one pass over the codes. Within a task every block of codes is scored for all
of a chunk's queries, group by group, and only each query's k best leave the task. Top-k scans send the
queries' vectors and make their tables in the tasks, as tables of 256 centroids are many times as large.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.model.codebooks import Codebooks, TableQuantizer, pack, unpack
from vecengine.operators.arrays import bytes_of, lists, matrix, restored, squeezed, stacked
from vecengine.train.together import passed

CHUNK_BYTES = 64 << 20


@dataclass(frozen=True)
class Queries:
    """Ids and vectors of a bounded set of queries."""

    ids: np.ndarray
    vectors: np.ndarray
    sent: dict = field(default_factory=dict, compare=False, repr=False)  # broadcasts of them, by application and size


def gather(qdf: DataFrame, most: int = 1_000_000) -> Queries:
    """Queries (id, vec) on the driver, in order of id; more than `most` are refused."""
    rows = qdf.select("id", "vec").limit(most + 1).toArrow()
    if rows.num_rows > most:
        raise ValueError(f"more than {most} queries: search them in several calls")
    if not rows.num_rows:
        return Queries(np.zeros(0, np.int64), np.zeros((0, 0)))
    ids = rows.column(0).to_numpy().astype(np.int64)
    order = np.argsort(ids, kind="stable")
    out = Queries(ids[order], stacked(rows.column(1), order))
    del rows
    pa.default_memory_pool().release_unused()
    return out


def shared_queries(spark, q: Queries) -> list:
    """Broadcasts of the queries in chunks of at most CHUNK_BYTES, one of none where there are none; the same ones for every
    scan, until `release`."""
    key = spark.sparkContext.applicationId, CHUNK_BYTES
    if key not in q.sent:
        step = max(1, CHUNK_BYTES // max(1, q.vectors[:1].nbytes))
        q.sent[key] = [spark.sparkContext.broadcast(Queries(q.ids[at : at + step], q.vectors[at : at + step])) for at in range(0, max(1, len(q.ids)), step)]
    return q.sent[key]


def release(q: Queries) -> None:
    """Takes back what scans have sent out of the queries; their answers must have been read."""
    for shared in q.sent.values():
        for x in shared:
            x.destroy()
    q.sent.clear()


GROUP_BYTES = 32  # of one table entry of all queries of a group: what one move copies
HELD_BYTES = 32 << 20  # of vectors that a task has at hand
BLOCK_ROWS = 512  # of vectors and queries whose distances are ranked at once
GROUPED = 4096  # queries whose best are kept at a time
CODE_BYTES = 32 << 20  # of codes and ids that a task has at hand
TABLE_BYTES = 16 << 20  # of the tables that a task makes at a time
PAIR_QUERIES, PAIR_ROWS = 64, 512  # of queries and vectors whose distances are summed up at once
TABLE_ROWS = 8192  # vectors at most that share a making of the queries' tables
PLACE_COST = 12  # dimensions of a product that take as long as looking up a code byte
MODEL_BYTES = 16 << 20  # of models and moments that go out at once
BLOCK_BYTES = 1 << 17  # of sums of a block of codes and a group of queries: they stay in cache


@dataclass(frozen=True)
class Scorer:
    """Scores codes for some queries. tables: uint8 for integer sums, else sums of the real tables.

    Queries go in groups: one entry of a group's table holds the numbers of all its queries side by side, so a code
    byte costs one move and one addition of GROUP_BYTES for the whole group.
    """

    ids: np.ndarray
    tables: np.ndarray  # queries x M x K, uint8 or real
    m: int
    k: int
    ascending: bool

    def merged(self, tables: np.ndarray) -> np.ndarray:
        """For 4-bit codes: queries x bytes x 256 sums of a byte's two entries."""
        t = tables.astype(np.uint16) if tables.dtype == np.uint8 else tables
        if t.shape[2] < 16:
            t = np.pad(t, ((0, 0), (0, 0), (0, 16 - t.shape[2])))
        if t.shape[1] % 2:
            t = np.pad(t, ((0, 0), (0, 1), (0, 0)))
        low, high = t[:, 0::2], t[:, 1::2]
        return (high[:, :, :, None] + low[:, :, None, :]).reshape(len(t), low.shape[1], 256)

    def groups(self) -> Iterator[tuple[int, np.ndarray]]:
        """(first query, bytes x entries x queries of the group): the last group is filled up with zeros."""
        byte = self.tables.dtype == np.uint8
        kind = np.dtype(np.uint16 if byte and 255 * self.m < 1 << 16 else np.int32 if byte else self.tables.dtype)
        size = GROUP_BYTES // kind.itemsize
        for lo in range(0, len(self.tables), size):
            t = self.tables[lo : lo + size]
            t = self.merged(t) if self.k <= 16 else t
            wide = 1 << (len(t) - 1).bit_length()
            out = np.zeros((t.shape[1], t.shape[2], wide), kind)
            out[:, :, : len(t)] = t.transpose(1, 2, 0)
            yield lo, out

    def sums(self, data: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
        """(first query, first code, codes x queries) over codes as columns of bytes (bytes x codes).

        The array is used again for the next one.
        """
        at = [column.astype(np.intp) for column in data]  # once for all queries: gathers take no other index
        n = data.shape[1]
        for lo, lut in self.groups():
            block = BLOCK_BYTES // (lut.shape[2] * lut.itemsize)
            held, more = (np.empty((min(n, block), lut.shape[2]), lut.dtype) for _ in range(2))
            for start in range(0, n, block):
                end = min(n, start + block)
                total, part = held[: end - start], more[: end - start]
                np.take(lut[0], at[0][start:end], axis=0, out=total, mode="clip")
                for b in range(1, len(at)):
                    np.take(lut[b], at[b][start:end], axis=0, out=part, mode="clip")
                    total += part
                yield lo, start, total[:, : len(self.ids) - lo]

    def scores(self, data: np.ndarray) -> Iterator[np.ndarray]:
        """One row of scores for each query in turn; a group's rows are used again for the next group."""
        held: np.ndarray | None = None
        n = data.shape[1]
        if not n:
            yield from (np.zeros(0, self.tables.dtype) for _ in self.ids)
            return
        for _, start, total in self.sums(data):
            if start == 0:
                held = np.empty((total.shape[1], n), total.dtype)
            held[:, start : start + len(total)] = total.T
            if start + len(total) == n:
                yield from held


def _true(mask: np.ndarray) -> np.ndarray:
    """Places of a mask that holds few: whole words of nothing are passed over."""
    if mask.size % 8:
        return np.flatnonzero(mask)
    at = np.flatnonzero(mask.view(np.uint64))
    word, place = np.nonzero(mask.reshape(-1, 8)[at])
    return 8 * at[word] + place


class Best:
    """The k best of each of some queries over blocks of scores, ties by least id.

    What is worse than a query's k-th best so far is dropped at once, the rest ranked now and then.
    """

    def __init__(self, k: int, ascending: bool) -> None:
        self.k, self.ascending = k, ascending
        self.bound: dict[int, np.ndarray] = {}
        self.parts: dict[int, list] = {}
        self.waiting: dict[int, int] = {}

    def add(self, lo: int, scores: np.ndarray, ids: np.ndarray) -> None:
        """scores: codes x queries from query `lo` on; a query comes in the same group every time."""
        n, size = scores.shape
        if lo not in self.bound:
            whole = np.issubdtype(scores.dtype, np.integer)
            ends = (np.iinfo(scores.dtype).max, np.iinfo(scores.dtype).min) if whole else (np.inf, -np.inf)
            self.bound[lo] = np.full(size, ends[0 if self.ascending else 1], scores.dtype)
            self.parts[lo], self.waiting[lo] = [], 0
            some = np.ascontiguousarray(scores[: max(1024, 8 * self.k)].T)  # the k-th best of a part bounds that of all
            if some.shape[1] > 4 * self.k:
                kth = self.k - 1 if self.ascending else some.shape[1] - self.k
                self.bound[lo] = np.partition(some, kth, axis=1)[:, kth].copy()
        if scores.flags.c_contiguous:  # one flat comparison with the bounds over and over; kept for no group, as there may be thousands
            flat, wide = scores.reshape(-1), np.tile(self.bound[lo], n)
            row, q = np.divmod(_true(flat <= wide if self.ascending else flat >= wide), size)
        else:  # queries lie side by side in the transpose
            turned, bound = scores.T, self.bound[lo][:, None]
            q, row = np.divmod(_true(np.ascontiguousarray(turned <= bound if self.ascending else turned >= bound).reshape(-1)), n)
        self.parts[lo].append((q, scores[row, q], ids[row]))
        self.waiting[lo] += len(q)
        if self.waiting[lo] > 4 * self.k * size + 1024:
            self._rank(lo)

    def _rank(self, lo: int) -> None:
        q, score, ids = (np.concatenate(x) for x in zip(*self.parts[lo], strict=True))
        key = score if self.ascending else -score.astype(np.int64 if np.issubdtype(score.dtype, np.integer) else np.float64)
        order = np.lexsort((ids, key, q))
        q, score, ids = q[order], score[order], ids[order]
        first = np.searchsorted(q, np.arange(len(self.bound[lo]) + 1))
        keep = np.arange(len(q)) - first[q] < self.k
        full = np.flatnonzero(np.diff(first) >= self.k)
        self.bound[lo][full] = score[first[full] + self.k - 1]
        self.parts[lo], self.waiting[lo] = [(q[keep], score[keep], ids[keep])], int(keep.sum())

    def ranked(self, queries: np.ndarray, kind) -> pa.RecordBatch:
        """(query_id, vec_id, score) of the k best of each query, given the queries' ids."""
        out = []
        for lo in sorted(self.parts):
            self._rank(lo)
            q, score, ids = self.parts[lo][0]
            out.append((queries[lo + q], ids, score.astype(kind)))
        columns = [np.concatenate(x) for x in zip(*out, strict=True)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, kind)]
        return pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["query_id", "vec_id", "score"])


def scorers(q: Queries, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None, real=np.float64, most: int | None = None) -> Iterator[Scorer]:
    """Chunks of queries with their tables, as bytes where tq is given, else of type `real`; at most `most`, or CHUNK_BYTES, a chunk."""
    step = max(1, (most or CHUNK_BYTES) // (books.m * books.k * (1 if tq is not None else np.dtype(real).itemsize)))
    for lo in range(0, len(q.ids), step):
        few = 4096  # real tables of so many queries at a time
        chunks = (q.vectors[at : min(at + few, lo + step)] for at in range(lo, min(lo + step, len(q.ids)), few))
        y = np.concatenate([books.tables(x, metric).astype(real, copy=False) if tq is None else books.byte_tables(x, metric, tq) for x in chunks])
        yield Scorer(q.ids[lo : lo + step], y, books.m, books.k, not metric.larger_is_closer)


def tables(qdf: DataFrame, books: Codebooks, metric: metrics.Metric) -> DataFrame:
    """(query_id, m, i, y) of each query (id, vec)."""
    shared = qdf.sparkSession.sparkContext.broadcast(books)

    def run(batches):
        b = shared.value
        for batch in batches:
            x = matrix(batch.column(1))
            if len(x):
                y = b.tables(x, metric)
                n, m, k = y.shape
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), m * k)), pa.array(np.tile(np.repeat(np.arange(m, dtype=np.int32), k), n)), pa.array(np.tile(np.arange(k, dtype=np.int32), n * m)), pa.array(y.reshape(-1))], names=["query_id", "m", "i", "y"])

    return qdf.select("id", "vec").mapInArrow(run, "query_id long, m int, i int, y double")


def _reduced(parts: list[DataFrame], k: int, ascending: bool, k_name: str = "rnk") -> DataFrame:
    best = Window.partitionBy("query_id").orderBy(F.col("score") if ascending else F.col("score").desc(), "vec_id")
    df = parts[0]
    for x in parts[1:]:
        df = df.union(x)
    return df.withColumn(k_name, F.row_number().over(best)).where(F.col(k_name) <= k).select("query_id", F.col(k_name).cast("int").alias(k_name), "vec_id", "score")


def scan_topk(codes: DataFrame, q: Queries, books: Codebooks, k: int, metric: metrics.Metric, tq: TableQuantizer | None = None, blocks: bool = False) -> DataFrame:
    """(query_id, rnk, vec_id, score): score is the integer sum where tq is given, else the table sum.

    codes: (id, code) packed, or blocks of them; further columns are pruned. Everything but ranking
    by the sum, such as the scale, the offsets and the outer function, is left to `finish`. As few tasks as run at once read
    them, as each sends on k rows a query.
    """
    kind = np.int64 if tq is not None else np.float64
    schema = "query_id long, vec_id long, score " + ("long" if tq is not None else "double")
    if not len(q.ids):
        return codes.sparkSession.createDataFrame([], schema.replace("vec_id", "rnk int, vec_id"))
    model = codes.sparkSession.sparkContext.broadcast((books, metric.name, tq))
    parts = []
    for shared in shared_queries(codes.sparkSession, q):

        def run(batches, shared=shared):
            q, (books, name, tq) = shared.value, model.value
            metric = metrics.get(name)
            for held in _codes_held(batches, blocks):
                for at in range(0, len(q.ids), GROUPED):  # what is kept of so many queries at a time
                    own, best, first = Queries(q.ids[at : at + GROUPED], q.vectors[at : at + GROUPED]), Best(k, not metric.larger_is_closer), 0
                    for s in scorers(own, books, metric, tq, most=TABLE_BYTES):
                        for ids, data in held:
                            for lo, start, total in s.sums(data):
                                best.add(first + lo, total, ids[start : start + len(total)])
                        first += len(s.ids)
                    yield best.ranked(own.ids, kind)

        parts.append(codes.select(*(("ids", "codes", "n") if blocks else ("id", "code"))).coalesce(codes.sparkSession.sparkContext.defaultParallelism).mapInArrow(run, schema))
    return _reduced(parts, k, not metric.larger_is_closer)


def _columns(batches, blocks: bool, rows: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, codes as columns of bytes) of about `rows` codes at a time: what one pass over the queries costs is spread."""
    ids: list = []
    data: list = []
    held = 0
    for batch in batches:
        if blocks:
            for a, c, n in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                ids.append(np.asarray(a, np.int64))
                data.append(np.frombuffer(c, np.uint8).reshape(-1, n))
                held += n
        elif batch.num_rows:
            ids.append(batch.column(0).to_numpy())
            data.append(bytes_of(batch.column(1)).T)
            held += batch.num_rows
        if held >= rows:
            yield np.concatenate(ids), np.concatenate(data, axis=1)
            ids, data, held = [], [], 0
    if held:
        yield np.concatenate(ids), np.concatenate(data, axis=1)


def _codes_held(batches, blocks: bool) -> Iterator[list[tuple[np.ndarray, np.ndarray]]]:
    """Blocks of `_columns`, of about CODE_BYTES at a time: each time gives k answers a query."""
    held: list = []
    for ids, data in _columns(batches, blocks):
        held.append((ids, data))
        if sum(x.nbytes + y.nbytes for x, y in held) >= CODE_BYTES:
            yield held
            held = []
    if held:
        yield held


def finish(top: DataFrame, metric: metrics.Metric, tq: TableQuantizer | None) -> DataFrame:
    """Adds `dist`: scale and offsets once for the sum, then the outer function."""
    total = F.col("score") / tq.scale + tq.bias if tq is not None else F.col("score")
    return top.withColumn("dist", metric.outer_col(F.greatest(total, F.lit(0.0)) if not metric.larger_is_closer else total))


def scan_pairs(codes: DataFrame, q: Queries, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None = None, most: float | None = None) -> DataFrame:
    """(query_id, vec_id, approx_d) of all pairs, or of those at most (at least, where larger is closer) `most`."""
    sc = codes.sparkSession.sparkContext
    parts = []
    for scorer in scorers(q, books, metric, tq):
        shared = sc.broadcast(scorer)

        def run(batches, shared=shared):
            s = shared.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                ids = batch.column(0).to_numpy()
                for qid, row in zip(s.ids, s.scores(np.ascontiguousarray(bytes_of(batch.column(1)).T)), strict=True):
                    total = row / tq.scale + tq.bias if tq is not None else row
                    d = total if metric.larger_is_closer else metric.outer(np.maximum(total, 0.0))
                    keep = np.ones(len(d), bool) if most is None else (d >= most if metric.larger_is_closer else d <= most)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(int(keep.sum()), qid)), pa.array(ids[keep]), pa.array(d[keep].astype(np.float64))], names=["query_id", "vec_id", "approx_d"])

        parts.append(codes.select("id", "code").mapInArrow(run, "query_id long, vec_id long, approx_d double"))
    return reduce(DataFrame.union, parts) if parts else codes.sparkSession.createDataFrame([], "query_id long, vec_id long, approx_d double")


def exact_topk(vdf: DataFrame, q: Queries, k: int, metric: metrics.Metric, products: bool = False, batch_queries: int = 1024) -> DataFrame:
    """(query_id, rnk, vec_id, score) by true distances of (id, vec).

    products: squared distances from norms and one matrix product for each batch of queries.
    """
    parts = []
    for shared in shared_queries(vdf.sparkSession, q):

        def run(batches, shared=shared):
            q = shared.value
            norms = np.einsum("ij,ij->i", q.vectors, q.vectors)
            for ids, x in _held(batches):
                size = np.einsum("ij,ij->i", x, x)
                for first in range(0, len(q.ids), GROUPED):  # what is kept of so many queries at a time
                    best = Best(k, not metric.larger_is_closer)
                    last = min(first + GROUPED, len(q.ids))
                    step = max(1, min(batch_queries, BLOCK_ROWS))
                    for lo in range(first, last, step):
                        own = q.vectors[lo : min(lo + step, last)]
                        for at in range(0, len(x), BLOCK_ROWS):
                            some = slice(at, at + BLOCK_ROWS)
                            d = np.maximum(norms[lo : lo + len(own), None] + size[some][None] - 2 * (own @ x[some].T), 0.0) if products else metric.matrix(own, x[some])
                            best.add(lo, d.T, ids[some])
                    yield best.ranked(q.ids, np.float64)
                    del best

        parts.append(vdf.select("id", "vec").mapInArrow(run, "query_id long, vec_id long, score double"))
    return _reduced(parts, k, not metric.larger_is_closer)


def _held(batches) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, vectors) of about HELD_BYTES at a time, whatever the batches: each gives k answers a query."""
    ids: list = []
    data: list = []

    def taken() -> tuple[np.ndarray, np.ndarray]:  # nothing is kept here beside what is given out
        out = (ids[0], data[0]) if len(data) == 1 else (np.concatenate(ids), np.concatenate(data))
        ids.clear()
        data.clear()
        return out

    for batch in batches:
        if batch.num_rows:
            ids.append(batch.column(0).to_numpy())
            data.append(matrix(batch.column(1)))
        del batch
        if sum(x.nbytes for x in data) >= HELD_BYTES:
            yield taken()
    if data:
        yield taken()


def exact_pairs(vdf: DataFrame, q: Queries, metric: metrics.Metric, most: float | None = None) -> DataFrame:
    """(query_id, vec_id, true_d) of all pairs, or of those within `most`."""
    sc = vdf.sparkSession.sparkContext
    step = max(1, CHUNK_BYTES // max(1, q.vectors[:1].nbytes))
    parts = [sc.broadcast(Queries(q.ids[at : at + step], q.vectors[at : at + step])) for at in range(0, max(1, len(q.ids)), step)]

    def run(batches, shared):
        q = shared.value
        for batch in batches:
            x, ids = matrix(batch.column(1)), batch.column(0).to_numpy()
            if not len(x):
                continue
            for lo in range(0, len(q.ids), 256):
                d = metric.matrix(q.vectors[lo : lo + 256], x)
                keep = np.ones(d.shape, bool) if most is None else (d >= most if metric.larger_is_closer else d <= most)
                i, j = np.nonzero(keep)
                yield pa.RecordBatch.from_arrays([pa.array(q.ids[lo + i]), pa.array(ids[j]), pa.array(d[i, j])], names=["query_id", "vec_id", "true_d"])

    out = [vdf.select("id", "vec").mapInArrow(lambda batches, shared=shared: run(batches, shared), "query_id long, vec_id long, true_d double") for shared in parts]
    return reduce(DataFrame.union, out)


def rerank(candidates: DataFrame, vdf: DataFrame, qdf: DataFrame, k: int, metric: metrics.Metric) -> DataFrame:
    """The k best by true distance of candidates (query_id, vec_id): two equi-joins and a ranking."""
    both = candidates.select("query_id", "vec_id").join(vdf.select(F.col("id").alias("vec_id"), F.col("vec").alias("x")), "vec_id").join(qdf.select(F.col("id").alias("query_id"), F.col("vec").alias("q")), "query_id")
    return _reduced([both.select("query_id", "vec_id", metric.pair(F.col("q"), F.col("x")).alias("score"))], k, not metric.larger_is_closer)


def _both(vdf: DataFrame, codes: DataFrame, q: Queries, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None, emit, schema: str) -> DataFrame:
    """emit(query ids, vector ids, true, approximate distances: queries x codes) over blocks of vectors beside their codes."""
    sc = codes.sparkSession.sparkContext
    both = vdf.select("id", "vec").join(codes.select("id", "code"), "id")
    out = None
    at = 0
    for scorer in scorers(q, books, metric, tq):
        shared = sc.broadcast((scorer, q.vectors[at : at + len(scorer.ids)]))
        at += len(scorer.ids)

        def run(batches, shared=shared):
            s, vectors = shared.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                ids, x = batch.column(0).to_numpy(), matrix(batch.column(1))
                for lo, start, total in s.sums(np.ascontiguousarray(bytes_of(batch.column(2)).T)):
                    total = total.T / tq.scale + tq.bias if tq is not None else total.T
                    d = total if metric.larger_is_closer else metric.outer(np.maximum(total, 0.0))
                    some = slice(start, start + d.shape[1])
                    yield emit(s.ids[lo : lo + len(d)], ids[some], metric.matrix(vectors[lo : lo + len(d)], x[some]), d)

        part = both.mapInArrow(run, schema)
        out = part if out is None else out.union(part)
    return out if out is not None else codes.sparkSession.createDataFrame([], schema)


def pairs(vdf: DataFrame, codes: DataFrame, q: Queries, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None = None) -> DataFrame:
    """(query_id, vec_id, true_d, approx_d): vectors and codes side by side, so nothing is joined over pairs."""

    def emit(qids, ids, true, d):
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(qids, len(ids))), pa.array(np.tile(ids, len(qids))), pa.array(true.reshape(-1)), pa.array(np.ascontiguousarray(d, np.float64).reshape(-1))], names=["query_id", "vec_id", "true_d", "approx_d"])

    return _both(vdf, codes, q, books, metric, tq, emit, "query_id long, vec_id long, true_d double, approx_d double")


def pair_moments(vdf: DataFrame, codes: DataFrame, q: Queries, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None = None) -> DataFrame:
    """(n, r, mse) of true against approximate distances over all pairs: no pair leaves its task, only sums of blocks do."""
    names = ["n", "t", "a", "tt", "aa", "ta", "e"]

    def emit(qids, ids, true, d):
        t, a = true.reshape(-1), np.ascontiguousarray(d, np.float64).reshape(-1)
        mt, ma = t.mean(), a.mean()
        row = (float(len(t)), mt, ma, ((t - mt) ** 2).sum(), ((a - ma) ** 2).sum(), ((t - mt) * (a - ma)).sum(), ((t - a) ** 2).sum())
        return pa.RecordBatch.from_arrays([pa.array([float(x)]) for x in row], names=names)

    rows = _both(vdf, codes, q, books, metric, tq, emit, ", ".join(f"{x} double" for x in names))
    n, t, a = F.col("n"), F.col("t"), F.col("a")
    sums = rows.agg(F.sum(n).alias("n"), F.sum(n * t).alias("t"), F.sum(n * a).alias("a"), F.sum(F.col("tt") + n * t * t).alias("tt"), F.sum(F.col("aa") + n * a * a).alias("aa"), F.sum(F.col("ta") + n * t * a).alias("ta"), F.sum("e").alias("e"))
    r = (F.col("ta") - t * a / n) / F.sqrt((F.col("tt") - t * t / n) * (F.col("aa") - a * a / n))
    return sums.select(n.cast("long").alias("n"), r.alias("r"), (F.col("e") / n).alias("mse"))


def moments(vdf: DataFrame, q: Queries | DataFrame, models: Sequence[tuple[Codebooks, TableQuantizer | None]], metric: metrics.Metric) -> list[tuple[int, float | None, float | None]]:
    """(n, r, mse) of `pair_moments` for each model, in passes over (id, vec): vectors are encoded where they are read.

    Of products ('dot') no pair is made: over all pairs their sums are those of each vector with the queries' second
    moments. Of 'l2' and 'sql2' true distances are taken once for all models, and the models' own as sums of table entries,
    or as products of the queries with what the codes stand for where these are shorter. What goes out to the tasks is
    taken back after each pass, on the executors' disks too. Queries of products may be a frame (id, vec) of any length.
    """
    if metric.name not in ("dot", "l2", "sql2"):
        raise ValueError(f"no moments of {metric.name}")
    total = np.zeros((len(models), 6))
    if isinstance(q, DataFrame) and metric.name != "dot":
        q = gather(q)
    if not len(q.ids) if isinstance(q, Queries) else q.isEmpty():
        return [(0, None, None)] * len(models)
    for first, sums, sent in _product_sums(vdf, q, models) if metric.name == "dot" else _distance_sums(vdf, q, models, metric):
        for r in sums.groupBy("at").agg(F.array(*[F.sum(F.get("sums", F.lit(c))) for c in range(6)]).alias("sums")).collect():
            total[first + r.at] += r.sums
        sent.destroy()
    out: list[tuple[int, float | None, float | None]] = []
    for n, t, a, tt, aa, ta in total:
        spread = (tt - t * t / n) * (aa - a * a / n) if n else 0.0
        out.append((int(n), float((ta - t * a / n) / np.sqrt(spread)) if spread > 0 else None, float((tt + aa - 2 * ta) / n) if n else None))
    return out


_SUMS = "at int, sums array<double>"


def _sums_batch(total: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.arange(len(total), dtype=np.int32)), lists(total)], names=["at", "sums"])


def _row_blocks(batches) -> Iterator[np.ndarray]:
    """Vectors by PAIR_ROWS: whole blocks, whatever the batches."""
    for _, x in _held(batches):
        for at in range(0, len(x), PAIR_ROWS):
            yield x[at : at + PAIR_ROWS]


def _own_moments(what: tuple[Codebooks, TableQuantizer] | None, x: np.ndarray) -> tuple:
    """(second moments, sums, count) of queries, or those of their byte tables' entries, with the products of the two in place of the count."""
    if what is None:
        return x.T @ x, x.sum(axis=0), len(x)
    wide = what[0].m * what[0].k
    second, cross, first = np.zeros((wide, wide)), np.zeros((x.shape[1], wide)), np.zeros(wide)
    for at in range(0, len(x), 256):  # squares of so many bytes add up without loss in single precision
        some = x[at : at + 256]
        b = what[0].byte_tables(some, metrics.get("dot"), what[1]).reshape(len(some), -1)
        single, double = b.astype(np.float32), b.astype(np.float64)
        second += single.T @ single
        cross += some.T @ double
        first += double.sum(axis=0)
    return second, first, cross


def _added(a: tuple, b: tuple) -> tuple:
    return tuple(x + y for x, y in zip(a, b, strict=True))


def _square_sum(codes: np.ndarray, k: int, second: np.ndarray) -> float:
    """Sum over rows of the entries of `second` (M * K square, symmetric) at all pairs of a row's places."""
    places = np.arange(codes.shape[1]) * k + codes
    flat = second.reshape(-1)
    total = flat.take(places * (len(second) + 1)).sum(dtype=np.float64)
    for m in range(codes.shape[1] - 1):
        total += 2 * flat.take(places[:, m, None] * len(second) + places[:, m + 1 :]).sum(dtype=np.float64)
    return float(total)


def _product_sums(vdf: DataFrame, q: Queries | DataFrame, models: Sequence[tuple[Codebooks, TableQuantizer | None]]) -> Iterator[tuple]:
    """(first model, sums, what is sent out for them) of as many models at a time as MODEL_BYTES hold, one at least."""
    coded = [None, *(model for model in models if model[1] is not None)]
    own = iter([_own_moments(what, q.vectors) for what in coded] if isinstance(q, Queries) else passed(q, coded, _own_moments, _added))
    *of_q, n_queries = next(own)
    of_bytes = [next(own) if tq is not None else None for _, tq in models]

    def run(batches, shared):
        (second, first), n_queries, models = shared.value
        total = np.zeros((len(models), 6))
        for x in _row_blocks(batches):
            n, xs = len(x) * n_queries, x @ second
            t, tt = x.sum(axis=0) @ first, np.vdot(xs, x)
            coded: dict[int, np.ndarray] = {}
            for at, (books, tq, b) in enumerate(models):
                if id(books) not in coded:
                    coded[id(books)] = books.encode(x.astype(np.float32))
                codes = coded[id(books)]
                if tq is None:
                    y = books.decode(codes)
                    total[at] += n, t, y.sum(axis=0) @ first, tt, np.vdot(y.T @ y, second), np.vdot(xs, y)
                else:
                    places = np.arange(books.m) * books.k + codes
                    a, aa = b[1][places].sum(), _square_sum(codes, books.k, b[0])
                    ta = sum(np.vdot(x, b[2][places[:, m]]) for m in range(books.m))
                    s, bias = tq.scale, tq.bias
                    total[at] += n, t, a / s + n * bias, tt, aa / s**2 + 2 * bias * a / s + n * bias**2, ta / s + bias * t
        yield _sums_batch(total)

    sc = vdf.sparkSession.sparkContext
    some: list[tuple] = []
    size = 0
    for at, (books, tq) in enumerate(models):
        b = of_bytes[at]
        if b is not None:  # rows of a place side by side
            b = (b[0].astype(np.int32) if b[0].max() < 1 << 31 else b[0], b[1], np.ascontiguousarray(b[2].T))
        some.append((books, tq, b))
        size += sum(x.nbytes for x in (books.centroids, books.rotation, *(b or ())) if x is not None)
        if size >= MODEL_BYTES or at + 1 == len(models):
            shared = sc.broadcast((of_q, n_queries, some))
            yield at + 1 - len(some), vdf.select("id", "vec").coalesce(sc.defaultParallelism).mapInArrow(lambda batches, shared=shared: run(batches, shared), _SUMS), shared
            some, size = [], 0


def _wide_tables(own: np.ndarray, books: Codebooks, metric: metrics.Metric, tq: TableQuantizer | None, space: np.ndarray) -> np.ndarray:
    """Code bytes x entries x queries: real entries, or whole ones where there is a quantizer; two 4-bit codes make a byte.

    space: what the tables are made in, of their type.
    """
    n = len(own)
    wide = space[: books.code_bytes * 256 * n].reshape(-1, 256, n)
    if tq is not None:
        t = books.byte_tables(own, metric, tq).transpose(1, 2, 0).astype(space.dtype)
    else:
        c, parts = books.centroids, books.layout.cut(books.turned(own)).transpose(0, 2, 1)
        c = np.concatenate([-2.0 * c, (c * c).sum(axis=2, keepdims=True), np.ones((*c.shape[:2], 1))], axis=2)
        parts = np.concatenate([parts, np.ones((len(c), 1, n)), (parts * parts).sum(axis=1, keepdims=True)], axis=1)
        t = np.matmul(c, parts, out=wide[:, : books.k] if books.k > 16 else None)
        np.maximum(t, 0.0, out=t)
    if books.k > 16:
        return wide
    t = np.pad(t, ((0, t.shape[0] % 2), (0, 16 - t.shape[1]), (0, 0)))
    np.add(t[1::2, :, None], t[0::2, None], out=wide.reshape(-1, 16, 16, n))
    return wide


def _looked_up(tables: np.ndarray, places: np.ndarray, out: np.ndarray, spare: np.ndarray) -> np.ndarray:
    """Sums (codes x queries) of the entries at the places (bytes x codes)."""
    tables[0].take(places[0], axis=0, out=out, mode="clip")
    for table, at in zip(tables[1:], places[1:], strict=True):
        table.take(at, axis=0, out=spare, mode="clip")
        out += spare
    return out


def _pair_sums(x: np.ndarray, vectors: np.ndarray, models: Sequence[tuple[Codebooks, TableQuantizer | None]], metric: metrics.Metric) -> np.ndarray:
    """Models x 6 sums over all pairs: each group of queries makes its tables once for all of x."""

    def beside_norms(y: np.ndarray) -> np.ndarray:
        return np.hstack([y, np.ones((len(y), 1)), (y * y).sum(axis=1, keepdims=True)])

    def finished(d: np.ndarray, clip: bool = True) -> np.ndarray:
        if clip:
            np.maximum(d, 0.0, out=d)
        return np.sqrt(d, out=d) if metric.name == "l2" else d

    total, dims = np.zeros((len(models), 6)), x.shape[1]
    true, single = beside_norms(x), x.astype(np.float32)
    coded: dict[int, np.ndarray] = {}
    sides: list[tuple[bool, np.ndarray]] = []  # whether to look up, and places or what the codes stand for
    for books, tq in models:
        if id(books) not in coded:
            coded[id(books)] = books.encode(single)
        codes = coded[id(books)]
        look = tq is not None or books.code_bytes * PLACE_COST < dims
        sides.append((look, np.ascontiguousarray(pack(codes, books.k).T, np.intp) if look else beside_norms(books.decode(codes))))
    del single
    rows = min(PAIR_ROWS, len(x))
    kinds = [np.float64 if tq is None else np.uint16 if 255 * books.m < 1 << 16 else np.int32 for books, tq in models]
    spare = {kind: np.empty((2, rows * PAIR_QUERIES), kind) for kind in {np.float64, *kinds}}
    spaces = {kind: np.empty(max((books.code_bytes for (books, _), (look, _), own in zip(models, sides, kinds, strict=True) if look and own is kind), default=0) * 256 * PAIR_QUERIES, kind) for kind in set(kinds)}
    held = np.empty(len(x) * PAIR_QUERIES)
    for at in range(0, len(vectors), PAIR_QUERIES):
        own = vectors[at : at + PAIR_QUERIES]
        left = np.vstack([-2 * own.T, (own * own).sum(axis=1)[None], np.ones((1, len(own)))])
        t = finished(np.matmul(true, left, out=held[: len(x) * len(own)].reshape(-1, len(own))))
        sums = np.array([t.size, t.sum(), 0, np.vdot(t, t), 0, 0])
        for i, ((books, tq), (look, side), kind) in enumerate(zip(models, sides, kinds, strict=True)):  # one model's tables at a time stay in cache
            table = _wide_tables(own, books, metric, tq, spaces[kind]) if look else None
            total[i] += sums
            for lo in range(0, len(x), rows):
                some = slice(lo, min(lo + rows, len(x)))
                shape = some.stop - lo, len(own)
                cut = lambda y, shape=shape: y[: shape[0] * shape[1]].reshape(shape)
                d = cut(spare[np.float64][0])
                if table is None:
                    finished(np.matmul(side[some], left, out=d))
                elif tq is None:
                    finished(_looked_up(table, side[:, some], d, cut(spare[np.float64][1])), False)
                else:
                    np.multiply(_looked_up(table, side[:, some], cut(spare[kind][0]), cut(spare[kind][1])), 1 / tq.scale, out=d)
                    d += tq.bias
                    finished(d, tq.bias < 0)
                total[i] += 0, 0, d.sum(), 0, np.vdot(d, d), np.vdot(t[some], d)
    return total


def _distance_sums(vdf: DataFrame, q: Queries, models: Sequence[tuple[Codebooks, TableQuantizer | None]], metric: metrics.Metric) -> Iterator[tuple]:
    """(0, sums, what is sent out for them) of as many queries at a time as CHUNK_BYTES hold.

    As few tasks as run at once read the vectors: tables of the queries are made in each.
    """
    sc = vdf.sparkSession.sparkContext

    def run(batches, shared):
        sent, models, name = shared.value
        vectors, metric = restored(sent), metrics.get(name)
        total = np.zeros((len(models), 6))
        for _, x in _held(batches):
            for at in range(0, len(x), TABLE_ROWS):
                total += _pair_sums(x[at : at + TABLE_ROWS], vectors, models, metric)
        yield _sums_batch(total)

    step = max(1, CHUNK_BYTES // max(1, q.vectors[:1].nbytes))
    for at in range(0, len(q.ids), step):
        shared = sc.broadcast((squeezed(q.vectors[at : at + step]), list(models), metric.name))
        yield 0, vdf.select("id", "vec").coalesce(sc.defaultParallelism).mapInArrow(lambda batches, shared=shared: run(batches, shared), _SUMS), shared


def unpacked(data: np.ndarray, books: Codebooks) -> np.ndarray:
    return unpack(data, books.m, books.k)
