"""Speed of encoding, tables, scans and products (w01 to w05).

Each method is timed twice: `kernel` is the array code alone in one process, which is what published
single-thread figures compare; `job` is the whole Spark job, scan of the input and transfer included.
Random data: none of the times depends on values. Threads of the linear algebra library are the
session's; set OMP_NUM_THREADS=1 to compare single threads.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.baselines import hamming
from vecengine.evaluate import accuracy, timing
from vecengine.model.codebooks import Codebooks, TableQuantizer, pack
from vecengine.operators import codes as code_ops
from vecengine.operators import matmul, search
from vecengine.operators.arrays import binary, matrix
from vecengine.sources import vectors
from vecengine.subspaces import split
from vecengine.workloads.common import shape, table

SQL2, DOT = metrics.get("sql2"), metrics.get("dot")


def random_books(method: str, nbytes: int, dims: int, seed: int = 0) -> Codebooks:
    m, k = shape(method, nbytes)
    rng = np.random.default_rng(seed)
    layout = split(dims, m)
    c = rng.uniform(-1, 1, (m, k, layout.width))
    for a, w in enumerate(layout.widths):
        c[a, :, w:] = 0
    turn = np.linalg.qr(rng.standard_normal((dims, dims)))[0] if method == "opq" else None
    return Codebooks(layout, c, turn)


def random_quantizer(books: Codebooks) -> TableQuantizer:
    return TableQuantizer(0.0, 16.0, np.zeros(books.m))


def clock(f, runs: int, trials: int = 1) -> float:
    """Mean over trials of the best of `runs` runs; the published protocol has 5 and 10."""
    total = 0.0
    for _ in range(trials):
        best = np.inf
        for _ in range(runs):
            began = time.perf_counter()
            f()
            best = min(best, time.perf_counter() - began)
        total += best
    return total / trials


def w01_encode(spark: SparkSession, sf_dir: str, n: int = 100_000, dims=(64, 128, 256, 512, 784), sizes=(8, 16, 32), methods=("btq", "pq", "opq"), runs: int = 2, trials: int = 1) -> DataFrame:
    """Vectors encoded a second by length and size."""
    rows = []
    for j in dims:
        df = vectors.synth(spark, n, j).selectExpr("id", "cast(vec as array<float>) as vec").persist()
        df.count()
        x = np.random.default_rng(1).uniform(-1, 1, (min(n, 20_000), j)).astype(np.float32)
        for nbytes in sizes:
            for method in methods:
                b = random_books(method, nbytes, j)
                job = timing.best_of(lambda b=b, df=df: code_ops.encode(df, b), runs, trials)
                kernel = clock(lambda b=b, x=x: [pack(b.encode(x[: n - lo]), b.k) for lo in range(0, n, len(x))], runs, trials)  # all n, in blocks
                rows.append((method, nbytes, j, n, job, n / job, kernel, n / kernel, timing.gb_per_second(n, j, kernel), accuracy.op_counts(j, b.m, b.k)["encode_madds"]))
        df.unpersist()
    return table(spark, rows, "method string, bytes int, dims int, n long, job_s double, job_vec_s double, kernel_s double, kernel_vec_s double, kernel_gb_s double, madds int")


def w02_tables(spark: SparkSession, sf_dir: str, n: int = 10_000, dims=(64, 128, 256, 512, 784), sizes=(8, 16, 32), methods=("btq", "pq", "opq"), runs: int = 2, trials: int = 1) -> DataFrame:
    """Queries whose tables are made a second, by the kernel and as a job that counts the tables' bytes."""
    rows = []
    for j in dims:
        q = np.random.default_rng(2).uniform(-1, 1, (n, j))
        df = vectors.synth(spark, n, j).persist()
        df.count()
        for nbytes in sizes:
            for method in methods:
                b = random_books(method, nbytes, j)
                tq = random_quantizer(b) if method == "btq" else None

                def make(q, b=b, tq=tq):
                    size = 0
                    for lo in range(0, len(q), 256):
                        size += (b.tables(q[lo : lo + 256], SQL2) if tq is None else b.byte_tables(q[lo : lo + 256], SQL2, tq)).nbytes
                    return size

                def job(make=make, df=df):
                    def run(batches):
                        for batch in batches:
                            yield pa.RecordBatch.from_arrays([pa.array([make(matrix(batch.column(0)))])], names=["size"])

                    return df.select("vec").mapInArrow(run, "size long")

                kernel, whole = clock(lambda q=q, make=make: make(q), runs, trials), timing.best_of(job, runs, trials)
                rows.append((method, nbytes, j, n, kernel, n / kernel, whole, n / whole))
        df.unpersist()
    return table(spark, rows, "method string, bytes int, dims int, n long, kernel_s double, q_s double, job_s double, job_q_s double")


#: Real tables are of single precision here, as the published ones; `pq64` has the double precision of `scan_topk`.
SCANNED = {"btq": ("btq", np.float32), "btqf": ("btq", np.float32), "pq": ("pq", np.float32), "opq": ("opq", np.float32), "pq64": ("pq", np.float64)}


def w03_scan(spark: SparkSession, sf_dir: str, n: int = 100_000, dims: int = 256, n_queries: int = 64, sizes=(8, 16, 32), batches=(1, 256, 1024), methods=tuple(SCANNED), runs: int = 2, trials: int = 1, jobs: bool = True) -> DataFrame:
    """Queries answered a second over n vectors, ten best each: codes, binary codes, and products of batches.

    batch: queries at hand at once. Of codes, those of one are scanned by themselves, more of them in groups that share
    each read of a code. job_*: the same scan of a table of the codes.
    """
    rng = np.random.default_rng(3)
    ids, q = np.arange(n), rng.uniform(-1, 1, (n_queries, dims))
    all_q = search.Queries(np.arange(n_queries), q)
    rows = []
    for nbytes in sizes:
        for method in methods:
            kind, real = SCANNED[method]
            b = random_books(kind, nbytes, dims)
            tq = random_quantizer(b) if method == "btq" else None
            packed = pack(rng.integers(0, b.k, (n, b.m)).astype(np.uint8), b.k)
            data = np.ascontiguousarray(packed.T)

            def scan(asked, b=b, tq=tq, data=data, real=real):
                for s in search.scorers(asked, b, SQL2, tq, real):
                    best = search.Best(10, True)
                    for lo, start, total in s.sums(data):
                        best.add(lo, total, ids[start : start + len(total)])
                    best.ranked(s.ids, np.float64)

            job = None
            if jobs and method != "pq64":
                codes = spark.createDataFrame(pa.table({"id": pa.array(ids), "code": binary(packed)})).persist()
                codes.count()
                job = timing.best_of(lambda codes=codes, b=b, tq=tq: search.scan_topk(codes, all_q, b, 10, SQL2, tq), runs, trials)
                codes.unpersist()
            for batch, some in ((1, [search.Queries(all_q.ids[i : i + 1], q[i : i + 1]) for i in range(min(8, n_queries))]), (n_queries, [all_q])):
                s = clock(lambda some=some, scan=scan: [scan(x) for x in some], runs, trials)
                asked = sum(len(x.ids) for x in some)
                rows.append((method, nbytes, batch, n, s / asked, asked / s, None if job is None or batch == 1 else n_queries / job))
        words = rng.integers(0, 1 << 63, (n, nbytes // 8), dtype=np.uint64)
        columns = [np.ascontiguousarray(c) for c in words.T]

        def ham(columns=columns, words=words):
            best = search.Best(10, True)
            for lo in range(0, n, 1 << 16):
                part = [c[lo : lo + (1 << 16)] for c in columns]
                for i, w in enumerate(words[:n_queries]):
                    best.add(i, hamming.differing(part, w)[:, None], ids[lo : lo + (1 << 16)])
            best.ranked(np.arange(n_queries), np.int64)

        s = clock(ham, runs, trials)
        rows.append(("hamming", nbytes, n_queries, n, s / n_queries, n_queries / s, None))
    x = rng.uniform(-1, 1, (n, dims)).astype(np.float32)
    norms = (x * x).sum(axis=1)
    for batch in batches:
        own = rng.uniform(-1, 1, (batch, dims)).astype(np.float32)

        def product(own=own):
            best = search.Best(10, True)
            for lo in range(0, n, 4096):
                d = norms[lo : lo + 4096, None] - 2 * (x[lo : lo + 4096] @ own.T)
                best.add(0, d, ids[lo : lo + 4096])
            best.ranked(np.arange(len(own)), np.float64)

        s = clock(product, runs, trials)
        rows.append((f"gemm{batch}", 4 * dims, batch, n, s / batch, batch / s, None))
    return table(spark, rows, "method string, bytes int, batch int, n long, seconds double, q_s double, job_q_s double")


def w04_square(spark: SparkSession, sf_dir: str, sides=(64, 128, 256, 512, 1024, 2048), nbytes: int = 16) -> DataFrame:
    """Square products: exact in Arrow blocks, approximate with and without encoding, as jobs."""
    rows = []
    for side in sides:
        a, b = vectors.synth(spark, side, side, 1, 4).persist(), vectors.synth(spark, side, side, 2, 4).persist()
        a.count(), b.count()
        books = random_books("btq", nbytes, side)
        tq = random_quantizer(books)
        codes = code_ops.encode(b, books).persist()
        codes.count()
        for engine, make in (("arrow", lambda a=a, b=b: matmul.exact(a, b, "arrow")), ("approx", lambda a=a, b=b, books=books, tq=tq: matmul.approx(a, b, books, tq)), ("approx_encoded", lambda a=a, b=b, books=books, tq=tq, codes=codes: matmul.approx(a, b, books, tq, codes))):
            rows.append((side, engine, nbytes, timing.best_of(make, 2)))
        for x in (a, b, codes):
            x.unpersist()
    return table(spark, rows, "side int, engine string, bytes int, seconds double")


def w05_tall(spark: SparkSession, sf_dir: str, n: int = 100_000, dims: int = 256, columns=(1, 16, 64, 256, 1024), sizes=(8, 16, 32), runs: int = 2, jobs=(1, 16, 64)) -> DataFrame:
    """A tall matrix by a thin one, the tall one's rows as the database: kernels, encoding counted and not, and whole
    jobs, whose products are summed up by column so that writing them is not what is timed."""
    rng = np.random.default_rng(5)
    x = rng.uniform(-1, 1, (n, dims)).astype(np.float32)
    thin = {c: rng.uniform(-1, 1, (dims, c)).astype(np.float32) for c in columns}
    tall = vectors.synth(spark, n, dims).persist()
    tall.count()
    column = lambda c: search.Queries(np.arange(c), np.ascontiguousarray(thin[c].T, np.float64))
    total = lambda df: df.groupBy("query_id").agg(F.sum(df.columns[-1]).alias("v"))
    rows = []
    for c in columns:
        job = timing.best_of(lambda c=c: total(search.exact_pairs(tall, column(c), DOT)), runs) if c in jobs else None
        rows.append(("exact", c, 4 * dims, clock(lambda c=c: x @ thin[c], runs), job))
    for nbytes in sizes:
        b = random_books("btq", nbytes, dims)
        encode = clock(lambda b=b: pack(b.encode(x), b.k), 1)
        data = np.ascontiguousarray(pack(b.encode(x), b.k).T)
        tq = random_quantizer(b)
        codes = code_ops.encode(tall, b).persist()
        codes.count()
        for c in columns:

            def multiply(b=b, q=column(c), tq=tq, data=data):
                for s in search.scorers(q, b, DOT, tq):
                    for _, _, sums in s.sums(data):
                        sums / tq.scale + tq.bias

            s = clock(multiply, runs)
            job = [None, None]
            if c in jobs:
                job = [timing.best_of(lambda v=v, c=c, b=b, tq=tq: total(search.scan_pairs(v(), column(c), b, DOT, tq)), runs) for v in (lambda codes=codes: codes, lambda b=b: code_ops.encode(tall, b))]
            rows += [("approx_encoded", c, nbytes, s, job[0]), ("approx", c, nbytes, s + encode, job[1])]
        codes.unpersist()
    tall.unpersist()
    return table(spark, rows, "engine string, columns int, bytes int, seconds double, job_s double")
