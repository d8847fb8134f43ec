"""Queries do the whole job: no caps, prefixes or samples in place of it."""

import inspect

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from vecengine import registry


def test_workloads_take_the_whole_grid(spark, monkeypatch):
    from vecengine.sources import views
    from vecengine.workloads import common, quality, writes

    whole = "/root/testdata/sf0.01"
    for view in ("v_embed", "v_walk"):
        s = common.split(spark, whole, view)
        assert s.queries.count() == views.VIEWS[view][0](spark, whole).where("id % 5 = 0").count()
    for module in (quality, writes):
        for name, f in inspect.getmembers(module, lambda f: inspect.isfunction(f) and f.__name__[:1] == "w" and f.__name__ in registry.QUERIES):
            given = []
            monkeypatch.setattr(module, name, lambda *a, given=given, **sizes: given.append(sizes))
            registry.QUERIES[name](None, whole)
            assert given == [{}]
            grid = {k: p.default for k, p in inspect.signature(f).parameters.items()}
            assert set(grid.get("sizes", (8, 16, 32))) == {8, 16, 32} and set(grid.get("methods", common.METHODS)) == set(common.METHODS)
            assert not any(v.startswith("v_walk_s") for v in grid.get("views", ()))


def test_fits_go_over_all_training_vectors(spark, sf, tmp_path, monkeypatch):
    from vecengine.baselines.simple import constant
    from vecengine.operators import search
    from vecengine.train import lloyd, table_quantizer

    n = 130_000
    x = np.random.default_rng(0).standard_normal((n, 64)).astype(np.float32)
    flat = pa.ListArray.from_arrays(pa.array(np.arange(0, 64 * n + 1, 64, dtype=np.int32)), pa.array(x.reshape(-1)))
    pq.write_table(pa.table({"vec_id": pa.array(np.arange(n)), "embedding": flat, "label": pa.array(np.zeros(n, np.int32))}), f"{tmp_path}/embeddings.parquet")
    counts = registry.QUERIES["kmeans_iter0"](spark, str(tmp_path)).where("m = 3").select("i", "n").distinct().toPandas()
    assert counts.n.sum() == n * 4 // 5

    q, v = registry.parts(spark, "/root/testdata/sf0.1")
    q = search.gather(q)
    true = search.exact_pairs(v, q, registry.L2).agg(F.count(F.lit(1)), F.avg("true_d")).first()
    assert true[0] == len(q.ids) * v.count() and abs(constant(v, q, registry.L2) - true[1]) < 1e-12

    seen = []
    cut = table_quantizer.cutoffs
    monkeypatch.setattr(table_quantizer, "cutoffs", lambda t, **how: seen.append(t.count()) or cut(t, **how))
    assert registry.QUERIES["alpha_variants"](spark, sf).count() == 64 and seen == [400 * 256] * 2

    few = {r.id for r in lloyd.sample(spark.range(10_000), 100).collect()}
    assert len(few) == 100 and 3_000 < np.mean(list(few)) < 7_000


def test_self_join_by_blocks(spark, sf, monkeypatch):
    from vecengine.operators import relational, search
    from vecengine.sources import views

    df = views.embed(spark, sf)
    rows = lambda out: sorted((r.a, r.b, round(r.dist, 9)) for r in out.collect())
    whole = rows(relational.self_join(df, 1.1, registry.L2))
    gather = search.gather
    monkeypatch.setattr(search, "gather", lambda q: gather(q, 200))  # as a table above the driver's bound
    assert len(whole) > 50 and rows(relational.self_join(df, 1.1, registry.L2, block=150)) == whole


def test_bounds_over_more_queries_than_one_table_of_pairs_takes(spark, tmp_path):
    rng = np.random.default_rng(1)
    n = 52_000  # 10,400 queries; some vectors are copies of others or all but
    x = rng.standard_normal((n, 64))
    x[n // 2 :] = x[: n - n // 2] + rng.choice([0.0, 1e-7], (n - n // 2, 1))
    ids = np.concatenate([np.arange(0, 5 * 10_400, 5), np.arange(1, 5 * 60, 5)])
    write_embeddings(tmp_path, ids, x[: len(ids)])
    for name in ("lemma_cauchy", "lemma_triangle", "gemm_norm_identity"):
        r = registry.QUERIES[name](spark, str(tmp_path)).first()
        assert (r.n, r.violations) == (10_400 * 60, 0), name


def write_embeddings(folder, ids, x):
    flat = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.astype(np.float32).reshape(-1)))
    pq.write_table(pa.table({"vec_id": pa.array(ids), "embedding": flat, "label": pa.array(np.zeros(len(ids), np.int32))}), f"{folder}/embeddings.parquet")


def test_bounds_are_those_of_pairs(spark):
    from vecengine.evaluate import bounds
    from vecengine.operators import search

    rng = np.random.default_rng(2)
    from vecengine.model.codebooks import Codebooks
    from vecengine.subspaces import split

    books = Codebooks(split(8, 4), rng.standard_normal((4, 16, 2)))
    x = rng.standard_normal((70, 8))
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>")
    own, back = x[:30], books.decode(books.encode(x, True))
    dist = lambda y: np.sqrt(((own[:, None] - y[None]) ** 2).sum(axis=2))
    for got, want in ((bounds.product_gaps, np.abs(own @ (x - back).T)), (bounds.distance_gaps, np.abs(dist(x) - dist(back)))):
        r = got(df, search.gather(df.where("id < 30")), books).first()
        assert (r.n, r.violations) == (2100, 0) and abs(r.max_gap - want.max()) < 1e-12


def test_best_keep_little_of_many_queries():
    import tracemalloc

    from vecengine.operators import search

    rng = np.random.default_rng(3)
    x, ids = rng.standard_normal((8192, 4)), np.arange(8192)
    tracemalloc.start()
    best = search.Best(2, True)
    for lo in range(0, 2048, 4):
        best.add(lo, x + lo, ids)
    held = tracemalloc.get_traced_memory()[0]
    tracemalloc.stop()
    assert held < 50 << 20  # a tile of bounds for each group would be 128 MB
    assert best.ranked(np.arange(2048), np.float64).column(1)[:2].to_pylist() == np.argsort(x[:, 0], kind="stable")[:2].tolist()


def test_exact_search_over_blocks(spark, monkeypatch):
    from vecengine.operators import search

    x = np.random.default_rng(4).integers(0, 4, (1500, 6)).astype(float)  # many ties
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>")
    q = search.gather(df.where("id < 1100"))
    for metric, sign in ((registry.DOT, -1), (registry.SQL2, 1)):
        want = np.argsort(np.round(sign * metric.matrix(x[:1100], x), 9), axis=1, kind="stable")[:, :3]
        rows = sorted((r.query_id, r.rnk, r.vec_id) for r in search.exact_topk(df, q, 3, metric).collect())
        assert np.array_equal(np.array([r[2] for r in rows]).reshape(-1, 3), want)


def test_product_by_coordinates_shuffles_no_pairs(spark):
    from vecengine.operators import matmul

    x = np.random.default_rng(5).standard_normal((40, 5))
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>")
    out = matmul.exact(df.where("id < 15"), df, "coord")
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "keys=[i#" not in plan and "sum(" not in plan
    got = {(r.i, r.j): r.v for r in out.collect()}
    assert len(got) == 600 and all(abs(v - x[i] @ x[j]) < 1e-9 for (i, j), v in got.items())
    few = spark.createDataFrame([(0, 1, 2.0), (1, 4, 3.0)], "id long, d int, x double")
    assert sorted(map(tuple, matmul.coordinates(few, few.where("d = 4")).collect())) == [(0, 1, 0.0), (1, 1, 9.0)]


def test_candidates_by_buckets_are_those_of_the_library(spark):
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    from vecengine.index import cells

    x = np.random.default_rng(6).standard_normal((900, 6))
    x[600:] = x[:300]
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>")
    q, v = df.where("id % 5 = 0"), df.where("id % 5 <> 0")
    a, b = (t.select("id", array_to_vector("vec").alias("x")) for t in (q, v))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", bucketLength=1.0, numHashTables=4, seed=7).fit(b)
    want = {(r.i, r.j): r.dist for r in model.approxSimilarityJoin(a, b, 1.2, "dist").select(F.col("datasetA.id").alias("i"), F.col("datasetB.id").alias("j"), "dist").collect()}
    out = cells.lsh_candidates(v, q, 1.2)
    assert "Join" not in out._jdf.queryExecution().executedPlan().toString()
    rows = out.collect()
    got = {(r.query_id, r.vec_id): r.dist for r in rows}
    assert len(rows) == len(got) and got.keys() == want.keys() and len(got) > 100 and all(abs(got[k] - want[k]) < 1e-9 for k in got)


def test_compression_reads_the_tables(spark, sf):
    out = registry.QUERIES["compression_ratio"](spark, sf)
    files = {f.rsplit("/", 1)[-1] for f in out.inputFiles()}
    assert files == {"embeddings.parquet", "events.parquet", "documents.parquet"}
    assert {(r.view, r.bytes): r.ratio for r in out.collect()}["v_walk", 16] == 32


def test_moments_of_all_models_are_those_of_pairs(spark, sf, monkeypatch):
    from vecengine.operators import codes as code_ops
    from vecengine.operators import search
    from vecengine.workloads import common, quality

    s = common.centred(common.split(spark, sf, "v_embed"))
    q = search.gather(s.queries)
    monkeypatch.setattr(search, "PAIR_QUERIES", 30)
    monkeypatch.setattr(search, "PAIR_ROWS", 70)
    for kind, metric in (("dot", "dot"), ("l2", "sql2"), ("sql2", "sql2")):
        fitted = list(common.models(spark, sf, "v_embed", s, (8, 32), common.METHODS, metric))
        got = search.moments(s.database, q, [(f.books, f.tq) for f in fitted], registry.metrics.get(kind))
        for f, (n, r, mse) in zip(fitted, got, strict=True):
            want = search.pair_moments(s.database, code_ops.encode(s.database, f.books), q, f.books, registry.metrics.get(kind), f.tq).first()
            assert n == want.n and abs(r - want.r) < 1e-9 and abs(mse - want.mse) < 1e-9 * max(1, want.mse), (kind, f.method, f.bytes)
    monkeypatch.setattr(search, "_both", None)  # vectors meet their codes in no join
    assert quality.w07_correlation(spark, sf, ("v_embed",), (8,)).count() == 8


def test_fits_at_hand_are_those_of_frames(spark, sf):
    from vecengine.operators import search
    from vecengine.train import lloyd, table_quantizer
    from vecengine.workloads import common

    s = common.split(spark, sf, "v_embed")
    made = common.fit_all(spark, [("btq", 8), ("pq", 8), ("opq", 8)], s.train, s.dims, rows=300, queries=40)
    for (books, tqs), method in zip(made, ("btq", "pq", "opq"), strict=True):
        want = common.fit_books(method, 8, s.train, s.dims, rows=300)
        if method != "opq":
            assert np.abs(books.centroids - want.centroids).max() < 1e-9
        error = [lloyd.step(s.train, b)[2] for b in (books, want)]
        assert abs(error[0] - error[1]) <= 0.01 * error[1]
        for name, tq in tqs.items():
            t = table_quantizer.fit(search.tables(lloyd.sample(s.train, 40), books, registry.metrics.get(name)))
            assert tq.alpha == t.alpha and abs(tq.scale - t.scale) < 1e-9 * t.scale and np.abs(tq.offsets - t.offsets).max() < 1e-9


def test_scan_makes_tables_in_tasks(spark, sf, monkeypatch):
    from vecengine.operators import codes as code_ops
    from vecengine.operators import search

    b = registry.books(spark, sf, 8, 256)
    codes, q = code_ops.encode(registry.parts(spark, sf)[1], b), registry.asked(spark, sf)
    rows = lambda: sorted(map(tuple, search.scan_topk(codes, q, b, 5, registry.SQL2).collect()))
    whole = rows()
    monkeypatch.setattr(search, "CHUNK_BYTES", 1 << 19)  # vectors of all queries, tables of few
    plan = search.scan_topk(codes, q, b, 5, registry.SQL2)._jdf.queryExecution().executedPlan().toString()
    assert "Union" not in plan and plan.count("MapInArrow") == 2
    monkeypatch.setattr(search, "TABLE_BYTES", 7 * 8 * 256 * 8)
    assert len(whole) == 5 * len(q.ids) and rows() == whole


def test_mips_fits_are_one_job(spark, sf, monkeypatch):
    from vecengine.train import table_quantizer
    from vecengine.workloads import common, quality

    jobs = []
    fit_all = common.fit_all
    monkeypatch.setattr(common, "fit_all", lambda spark, shapes, *a: jobs.append(shapes) or fit_all(spark, shapes, *a))
    monkeypatch.setattr(table_quantizer, "fit", None)
    r = quality.w11_mips(spark, sf, ("v_part",), ranks=(1, 100)).toPandas().pivot(index="bytes", columns="r", values="recall")
    assert jobs == [[("btq", 8), ("btq", 16), ("btq", 32)]] and (r[100] >= r[1]).all() and r[100].min() > 0.7


def test_order_measures_all_models_in_one_pass(spark, sf, monkeypatch):
    from vecengine.operators import codes as code_ops
    from vecengine.operators import search
    from vecengine.workloads import common, quality

    asked = []
    moments = search.moments
    monkeypatch.setattr(search, "moments", lambda v, q, models, metric: asked.append(len(models)) or moments(v, q, models, metric))
    out = {(r.perm, r.method): r for r in quality.w13_order(spark, sf, (8,), ("btqf", "pq")).collect()}
    assert asked == [2, 2] and len(out) == 4
    s = common.centred(common.split(spark, sf, "v_walk_perm"))
    f = next(iter(common.models(spark, sf, "v_walk_perm", s, (8,), ("pq",))))
    want = search.pair_moments(s.database, code_ops.encode(s.database, f.books), search.gather(s.queries), f.books, registry.L2).first()
    assert abs(out[True, "pq"].r - want.r) < 1e-9


def test_moments_leave_nothing_with_the_executors(spark, sf, monkeypatch):
    """What goes out for a pass is taken back after it, and is bounded; real tables are looked up by code bytes."""
    from vecengine.operators import arrays, search
    from vecengine.operators import codes as code_ops
    from vecengine.workloads import common

    x = np.random.default_rng(3).normal(size=(50, 7))
    assert (arrays.restored(arrays.squeezed(x)) == x).all() and arrays.restored(arrays.squeezed(x[:0])).shape == (0, 7)
    order = np.argsort(x[:, 0])
    assert (arrays.stacked(pa.chunked_array([arrays.lists(x[:20]), arrays.lists(x[20:])]), order) == x[order]).all()
    sent, back = [], []
    kind = type(spark.sparkContext.broadcast(0))
    send, destroy = kind.__init__, kind.destroy
    monkeypatch.setattr(kind, "__init__", lambda self, *a, **b: sent.append(self) or send(self, *a, **b))
    monkeypatch.setattr(kind, "destroy", lambda self, *a: back.append(self) or destroy(self, *a))
    s = common.centred(common.split(spark, sf, "v_embed"))
    q = search.gather(s.queries)
    shapes = [("btq", 8), ("pq", 16), ("opq", 8), ("btq", 7)]
    made = common.fit_all(spark, shapes, s.train, s.dims)
    monkeypatch.setattr(search, "PLACE_COST", 0)
    monkeypatch.setattr(search, "PAIR_QUERIES", 30)
    monkeypatch.setattr(search, "PAIR_ROWS", 70)
    monkeypatch.setattr(search, "TABLE_ROWS", 90)
    monkeypatch.setattr(search, "MODEL_BYTES", 1)
    monkeypatch.setattr(search, "CHUNK_BYTES", 64 * 8 * 40)
    for name, tables in (("l2", "sql2"), ("dot", "dot")):
        models = [(b, tqs.get(tables)) for b, tqs in made] + [(made[0][0], None), (made[3][0], None)]
        got = search.moments(s.database, q, models, registry.metrics.get(name))
        for (b, tq), (n, r, mse) in zip(models, got, strict=True):
            want = search.pair_moments(s.database, code_ops.encode(s.database, b), q, b, registry.metrics.get(name), tq).first()
            assert n == want.n and abs(r - want.r) < 1e-9 and abs(mse - want.mse) < 1e-9 * max(1, want.mse)
    ours = [x for x in sent if x in back]
    assert len(ours) == 1 + len(models) + -(-len(q.ids) // 40)  # of the fits, each model's products, each chunk of queries


def test_fits_go_over_all_training_vectors(spark, sf, monkeypatch):
    """Models and byte tables come from every vector, whether these are at hand or passed over."""
    from vecengine.train import lloyd, table_quantizer
    from vecengine.workloads import common

    s = common.split(spark, sf, "v_embed")
    n, shapes = s.train.count(), [("btq", 8), ("pq", 16), ("opq", 8)]
    x = lloyd.gathered(s.train, n, 0)[0].astype(np.float64)
    one = common.fit_all(spark, shapes, s.train, s.dims)
    monkeypatch.setattr(lloyd, "AT_HAND", 64)
    monkeypatch.setattr(lloyd, "sample", None)
    monkeypatch.setattr(lloyd, "gathered", None)
    made = common.fit_all(spark, shapes, s.train, s.dims)
    assert n > 200
    for (method, _), (a, of_a), (b, of_b) in zip(shapes, one, made, strict=True):
        if method != "opq":
            assert np.abs(a.centroids - b.centroids).max() < 1e-6
        error = [lloyd.step(x, books)[2] for books in (a, b)]
        assert max(error) <= 1.01 * min(error)
        for name in of_a:
            y = a.tables(x, registry.metrics.get(name))  # of all n
            want = table_quantizer.fit_arrays(y)
            loss = [((tq.dequantize(tq.quantize(y)) - y) ** 2).mean() for tq in (want, of_a[name], of_b[name])]
            assert of_a[name].alpha == want.alpha and of_a[name].scale == pytest.approx(want.scale, rel=1e-9) and loss[2] <= 1.01 * loss[0]
    y = np.random.default_rng(5).standard_cauchy((3_000, 4, 16)) * [[1], [10], [1e-3], [0]]  # long tails, one table of nothing
    ends = table_quantizer.ranges(y)
    grid = table_quantizer.bins(ends, table_quantizer.counted(y, table_quantizer.bins(ends)))
    n = sum(table_quantizer.counted(part, grid) for part in np.array_split(y, 3))
    for alphas in (table_quantizer.GRID, (0.02,)):
        want, got = table_quantizer.fit_arrays(y, alphas), table_quantizer.fit_counts(n, ends, grid, alphas)
        assert n.sum() == y.size and got.alpha == want.alpha and got.scale == pytest.approx(want.scale, rel=0.01)
        assert np.abs(got.offsets - want.offsets).max() < 0.01 * 255 / want.scale


def test_scans_keep_the_best_of_few_queries_at_a_time(spark, sf, monkeypatch):
    """What a task holds does not grow with the queries, and a view's frames and queries are taken back after it."""
    from vecengine.operators import codes as code_ops
    from vecengine.operators import search
    from vecengine.workloads import common, quality

    b = registry.books(spark, sf, 8, 16)
    q = registry.asked(spark, sf)
    codes = code_ops.encode(registry.parts(spark, sf)[1].repartition(2), b).persist()
    rows = lambda: sorted(map(tuple, search.scan_topk(codes, q, b, 5, registry.SQL2).collect()))
    whole, sent = rows(), search.shared_queries(spark, q)
    assert search.shared_queries(spark, q) is sent
    monkeypatch.setattr(search, "GROUPED", 16)
    monkeypatch.setattr(search, "CODE_BYTES", 1)
    source = inspect.getsource(search.scan_topk)
    assert "GROUPED" in source and [x[:3] for x in rows()] == [x[:3] for x in whole]
    search.release(q)
    assert not q.sent
    with common.freed(spark):
        assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "true"
    dropped, released = [], []
    drop, release = common.Split.drop, search.release
    monkeypatch.setattr(common.Split, "drop", lambda self: dropped.append(1) or drop(self))
    monkeypatch.setattr(search, "release", lambda q: released.append(len(q.sent)) or release(q))
    assert quality.w06_recall(spark, sf, ("v_embed",), (8,), ("btq",), (1,)).count() == 1
    assert dropped == [1] and released == [1]


def test_products_take_queries_from_a_frame(spark, sf, monkeypatch):
    """w08: no query comes to the driver, and no more tasks than run at once hold the models."""
    from vecengine.operators import search
    from vecengine.workloads import common, quality

    s = common.centred(common.split(spark, sf, "v_embed"))
    fitted = list(common.models(spark, sf, "v_embed", s, (8, 16), ("btq", "btqf"), "dot"))
    asked = [(f.books, f.tq) for f in fitted]
    q = search.gather(s.queries)
    for got, want in zip(search.moments(s.database, s.queries, asked, registry.metrics.get("dot")), search.moments(s.database, q, asked, registry.metrics.get("dot")), strict=True):
        assert got[0] == want[0] and got[1:] == pytest.approx(want[1:], rel=1e-9)
    monkeypatch.setattr(search, "gather", None)
    assert quality.w08_compression(spark, sf, ("v_embed",)).count() > 0
