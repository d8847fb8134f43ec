"""Worked micro cases, invariants and parity of the forms of the vector engine."""

import os

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.evaluate import accuracy, bounds, timing
from vecengine.functions import sql
from vecengine.model import codebooks as cb
from vecengine.operators import codes as code_ops
from vecengine.operators import relational, search
from vecengine.plans import choose
from vecengine.sources import vectors
from vecengine.streaming import features
from vecengine.streaming import vectors as streams
from vecengine.subspaces import Layout, split
from vecengine.train import lloyd, rotation, table_quantizer

SQL2, L2, DOT = metrics.get("sql2"), metrics.get("l2"), metrics.get("dot")
TINY = cb.Codebooks(split(4, 2), np.array([[[0.0, 0], [1, 1]], [[0, 0], [1, 1]]]))


def frame(spark, x, start=0):
    return spark.createDataFrame([(start + i, [float(v) for v in row]) for i, row in enumerate(x)], "id long, vec array<double>")


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((400, 12)).cumsum(axis=1)
    df = frame(spark, x).persist()
    df.count()
    return x, df


def test_two_by_two():
    x = np.array([[0.1, 0, 0.9, 1]])
    for exact in (True, False):
        assert TINY.encode(x, exact).tolist() == [[0, 1]]
    y = TINY.tables(x, SQL2)[0]
    assert np.allclose(y, [[0.01, 1.81], [1.81, 0.01]])
    assert np.allclose(TINY.decode(np.array([[0, 1]], np.uint8)), [[0, 0, 1, 1]])


def test_tie_takes_lowest():
    assert TINY.encode(np.array([[0.5, 0.5, 0.5, 0.5]]), True).tolist() == [[0, 0]]


@pytest.mark.parametrize(("j", "m", "widths"), [(7, 3, [3, 2, 2]), (4, 4, [1, 1, 1, 1]), (5, 1, [5])])
def test_uneven(j, m, widths):
    lay = split(j, m)
    assert lay.widths == widths
    x = np.arange(2 * j, dtype=float).reshape(2, j)
    assert np.array_equal(lay.join(lay.cut(x)), x)


def test_order_and_bad_layouts():
    lay = split(4, 2, [3, 1, 0, 2])
    x = np.array([[10.0, 11, 12, 13]])
    assert lay.cut(x)[:, 0].tolist() == [[13, 11], [10, 12]]
    assert np.array_equal(lay.join(lay.cut(x)), x)
    for bad in ((3, 4, None), (3, 0, None), (3, 1, [0, 0, 1])):
        with pytest.raises(ValueError):
            split(*bad)


def test_quantile_edges(spark):
    t = spark.createDataFrame([(0, 0, i, float(i)) for i in range(101)], "query_id long, m int, i int, y double")
    tq = table_quantizer.fit(t, alphas=(0.0,))
    assert tq.scale == pytest.approx(2.55)
    y = np.arange(101.0)[None]
    b = tq.quantize(y)
    assert b[0, 0] == 0 and b[0, 100] == 255
    error = y - tq.dequantize(b)
    assert (error >= -1e-9).all() and (error < 1 / tq.scale + 1e-9).all()
    assert (np.diff(b[0].astype(int)) >= 0).all()


def test_constant_rows_have_unit_scale(spark):
    t = spark.createDataFrame([(0, 0, i, 3.0) for i in range(16)], "query_id long, m int, i int, y double")
    tq = table_quantizer.fit(t)
    assert tq.scale == 1.0 and not tq.quantize(np.full((1, 16), 3.0)).any() and tq.alpha == 0.0


def test_negative_entries(spark):
    t = spark.createDataFrame([(0, m, i, float(-i - 5 * m)) for m in range(2) for i in range(16)], "query_id long, m int, i int, y double")
    tq = table_quantizer.fit(t, alphas=(0.0,))
    assert (tq.offsets < 0).all()
    y = np.array([[-i - 5.0 * m for i in range(16)] for m in range(2)])
    assert np.abs(tq.dequantize(tq.quantize(y)) - y).max() < 1 / tq.scale


@pytest.mark.parametrize("m", [1, 2, 3, 16])
def test_pack_round_trip(m):
    c = np.random.default_rng(m).integers(0, 16, (20, m)).astype(np.uint8)
    p = cb.pack(c, 16)
    assert p.shape[1] == -(-m // 2) and np.array_equal(cb.unpack(p, m, 16), c)
    if m % 2:
        assert not (p[:, -1] >> 4).any()


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 6), st.integers(1, 12), st.integers(0, 2**16))
def test_sums_of_any_shape(m, n, seed):
    rng = np.random.default_rng(seed)
    books = cb.Codebooks(split(2 * m, m), rng.standard_normal((m, 16, 2)))
    q, x = rng.standard_normal((3, 2 * m)), rng.standard_normal((n, 2 * m))
    codes = books.encode(x, True)
    tq = cb.TableQuantizer(0, 20.0, np.zeros(m))
    for quantizer in (None, tq):
        for s in search.scorers(search.Queries(np.arange(3), q), books, SQL2, quantizer):
            got = np.array(list(s.scores(np.ascontiguousarray(cb.pack(codes, 16).T))))
            t = s.tables[:, np.arange(m)[None], codes].astype(float).sum(axis=2)
            assert np.allclose(got, t)
    assert np.array_equal(books.encode(books.decode(codes), True), books.encode(books.decode(codes), True))
    assert np.allclose(books.decode(books.encode(books.decode(codes), True)), books.decode(codes))


def test_bound_counterexample():
    """The tail bound on squared distances fails for M = 1: the gap is 19 while the error's norm is 1."""
    q, x, back = 10.0, 1.0, 0.0
    assert abs((q - x) ** 2 - (q - back) ** 2) == 19 and abs(x - back) == 1


def test_relational_rounds_equal_arrays(spark, data):
    _, df = data
    start = lloyd.fit(df, 12, 4, 8, 0)
    table, lay = cb.to_frame(start, spark), Layout(12, 4)
    for _ in range(2):
        table = lloyd.relational_step(df, table, lay)
    books = lloyd.fit(df, 12, 4, 8, 2)
    for r in table.collect():
        assert np.allclose(r.centroid, books.centroids[r.m, r.i])
    a = {(r.id, r.m): r.code for r in code_ops.encode_relational(df, cb.to_frame(books, spark), lay).collect()}
    b = {(r.id, r.m): r.code for r in code_ops.exploded(code_ops.encode(df, books, exact=True), books).collect()}
    assert a == b


def test_error_never_rises(spark, data):
    _, df = data
    errors = [lloyd.step(df, lloyd.fit(df, 12, 3, 16, n))[2] for n in range(5)]
    assert all(b <= a + 1e-9 for a, b in zip(errors, errors[1:], strict=False))


def test_seeds(spark, data):
    _, df = data
    for init in ("first", "hash", "kmeans++"):
        assert lloyd.fit(df, 12, 3, 16, 2, init, empty="split").centroids.shape == (3, 16, 4)
    with pytest.raises(ValueError):
        lloyd.fit(df.limit(3), 12, 3, 16, 1)


def test_rotation_is_orthogonal_and_helps(spark, data):
    x, df = data
    turned = rotation.fit(df, 12, 3, 16, outer=3)
    assert np.allclose(turned.rotation @ turned.rotation.T, np.eye(12))
    assert lloyd.step(df, turned)[2] <= lloyd.step(df, rotation.fit(df, 12, 3, 16, outer=0))[2] + 1e-6
    with pytest.raises(ValueError):
        turned.tables(x[:1], metrics.get("l1"))
    d = turned.tables(x[:2], SQL2)
    approx = d[:, np.arange(3), turned.encode(x[:1], True)[0]].sum(axis=1)
    assert np.allclose(approx, ((x[:2] - turned.decode(turned.encode(x[:1], True))) ** 2).sum(axis=1))


def test_store(spark, data, tmp_path):
    _, df = data
    books = rotation.fit(df, 12, 3, 16, outer=1)
    tq = table_quantizer.fit(search.tables(df.limit(20), books, SQL2))
    cb.save(books, str(tmp_path / "m"), spark, tq)
    again, tq2 = cb.load(str(tmp_path / "m"), spark)
    assert np.array_equal(again.centroids, books.centroids) and np.array_equal(again.rotation, books.rotation)
    assert tq2.scale == tq.scale and np.array_equal(tq2.offsets, tq.offsets)


def test_forms_of_the_scan_agree(spark, data):
    x, df = data
    books = lloyd.fit(df, 12, 6, 16, 3)
    tq = table_quantizer.fit(search.tables(df.limit(30), books, SQL2))
    q = search.Queries(np.arange(5), x[:5])
    codes = code_ops.encode(df, books, exact=True)
    rows = lambda d: sorted(map(tuple, d.collect()))
    top = rows(search.scan_topk(codes, q, books, 7, SQL2, tq))
    assert top == rows(search.scan_topk(code_ops.to_blocks(codes, 64), q, books, 7, SQL2, tq, blocks=True))
    b = tq.quantize(books.tables(q.vectors, SQL2))
    tables = spark.createDataFrame([(i, m, k, int(b[i, m, k])) for i in range(5) for m in range(6) for k in range(16)], "query_id long, m int, i int, b int")
    full = {(r.query_id, r.vec_id): r.score for r in choose.scan_relational(code_ops.exploded(codes, books), tables).collect()}
    assert all(full[(r[0], r[2])] == r[3] for r in top)
    one = choose.scan_expr(code_ops.encode(df, books, "array", True), b[0].tolist())
    assert {r.vec_id: r.score for r in one.collect()} == {v: s for (i, v), s in full.items() if i == 0}
    assert choose.engine(1, books) == "expr" and choose.engine(9, books) == "arrow"
    near = rows(search.finish(search.scan_topk(codes, q, books, 1, SQL2, tq), L2, tq))
    assert len(near) == 5


@pytest.mark.parametrize("kind", [np.uint16, np.int32, np.float64])
@pytest.mark.parametrize("k", [1, 10, 3000])
def test_best_keeps_ties_by_id(kind, k):
    rng = np.random.default_rng(1)
    s, ids = rng.integers(0, 50, (40_000, 3)).astype(kind), rng.permutation(40_000)
    for up in (True, False):
        best = search.Best(k, up)
        for lo in (0, 2_000, 2_001, 9_000, 25_000, 40_000):
            hi = {0: 2_000, 2_000: 2_001, 2_001: 9_000, 9_000: 25_000, 25_000: 40_000, 40_000: 40_000}[lo]
            best.add(5, s[lo:hi], ids[lo:hi])
        got = best.ranked(np.arange(100, 110), np.float64).to_pandas()
        for q in range(3):
            key = s[:, q].astype(float) if up else -s[:, q].astype(float)
            order = np.lexsort((ids, key))[:k]
            own = got[got.query_id == 105 + q]
            assert np.array_equal(own.vec_id, ids[order]) and np.array_equal(own.score, s[order, q])
    assert search.Best(k, True).ranked(np.arange(3), np.float64).num_rows == 0


@pytest.mark.parametrize("m,k,tq", [(6, 16, True), (5, 16, False), (3, 256, False), (4, 7, True), (300, 16, True)])
@pytest.mark.parametrize("queries", [1, 3, 16, 37])
def test_grouped_sums_are_table_sums(m, k, tq, queries):
    rng = np.random.default_rng(2)
    tables = rng.integers(0, 256, (queries, m, k)).astype(np.uint8) if tq else rng.standard_normal((queries, m, k))
    codes = rng.integers(0, k, (5_000, m)).astype(np.uint8)
    s = search.Scorer(np.arange(queries), tables, m, k, True)
    want = tables.astype(np.int64 if tq else np.float64)[:, np.arange(m)[None], codes].sum(axis=2)
    got = np.stack([x.copy() for x in s.scores(np.ascontiguousarray(cb.pack(codes, k).T))])
    assert np.array_equal(got, want) if tq else np.allclose(got, want)


def test_pair_moments_are_those_of_pairs(spark, data):
    x, df = data
    books = lloyd.fit(df, 12, 6, 16, 2)
    codes, q = code_ops.encode(df, books, exact=True), search.Queries(np.arange(30), x[:30])
    for metric, tq in ((L2, None), (DOT, table_quantizer.fit(search.tables(df.limit(50), books, DOT)))):
        p = search.pairs(df, codes, q, books, metric, tq)
        gap = F.col("true_d") - F.col("approx_d")
        want = p.agg(F.count(F.lit(1)), F.corr("true_d", "approx_d"), F.avg(gap * gap)).first()
        assert tuple(search.pair_moments(df, codes, q, books, metric, tq).first()) == pytest.approx(tuple(want))


def test_byte_tables_are_quantized_tables():
    rng = np.random.default_rng(8)
    for m in (3, 5):
        layout = split(12, m)
        c = rng.standard_normal((m, 16, layout.width))
        for a, w in enumerate(layout.widths):
            c[a, :, w:] = 0
        books, tq = cb.Codebooks(layout, c), cb.TableQuantizer(0.0, 7.3, rng.standard_normal(m))
        q = rng.standard_normal((500, 12))
        slow = np.stack([[((layout.cut(x[None])[a, 0] - c[a]) ** 2).sum(axis=1) for a in range(m)] for x in q])
        for metric in (SQL2, L2):
            assert np.allclose(books.tables(q, metric), slow) and np.array_equal(books.byte_tables(q, metric, tq), tq.quantize(slow))
        assert np.array_equal(books.byte_tables(q, DOT, tq), tq.quantize(books.tables(q, DOT)))


@pytest.mark.parametrize("m", [1, 4, 5, 12])
def test_fast_encoding_finds_a_nearest_centroid(m):
    rng = np.random.default_rng(3)
    for k in (16, 9, 200):
        layout = split(12, m)
        c = rng.standard_normal((m, k, layout.width))
        for a, w in enumerate(layout.widths):
            c[a, :, w:] = 0
        books = cb.Codebooks(layout, c)
        x = rng.standard_normal((3_000, 12)) * rng.choice([1e-3, 1, 100], (3_000, 1))
        fast, slow = books.encode(x.astype(np.float32)), books.encode(x, exact=True)
        parts = layout.cut(x)
        far = lambda code: ((parts - c[np.arange(m)[:, None], code.T]) ** 2).sum(axis=2)
        assert (fast == slow).mean() > 0.99 and (far(fast) <= far(slow) + 1e-4 * (1 + (parts**2).sum(axis=2).max())).all()


def test_byte_tables_cost_little(spark, data):
    x, df = data
    books = lloyd.fit(df, 12, 6, 16, 5)
    tq = table_quantizer.fit(search.tables(df.limit(50), books, SQL2))
    q = search.Queries(np.arange(40), x[:40])
    codes = code_ops.encode(df, books, exact=True)
    r = [search.pairs(df, codes, q, books, L2, t).agg(F.corr("true_d", "approx_d").alias("r")).first().r for t in (tq, None)]
    assert abs(r[0] - r[1]) < 0.01 and r[1] > 0.9
    nn = search.exact_topk(df, q, 1, SQL2)
    curve = [c.recall for c in accuracy.recall_curve(nn, search.scan_topk(codes, q, books, 100, SQL2, tq), 40).orderBy("r").collect()]
    assert curve == sorted(curve) and curve[-1] > 0.9
    assert accuracy.recall_tolerant(nn, search.scan_topk(codes, q, books, 100, SQL2, tq), 40).orderBy("r").collect()[-1].recall == curve[-1]


def test_bounds_hold(spark, data):
    _, df = data
    books = lloyd.fit(df, 12, 4, 16, 2)
    back = code_ops.reconstruct(code_ops.encode(df, books, exact=True), books)
    p = bounds.pair_bounds(df.limit(5), df, back)
    for gap, bound in (("dot_gap", "dot_bound"), ("l2_gap", "l2_bound")):
        assert bounds.violations(p, gap, bound).first().violations == 0
    assert 0 <= accuracy.distortion(df, back).first().value < 1


def test_bad_rows_are_set_aside(spark):
    raw = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [1.0, float("nan")]), (5, [1.0, None]), (None, [1.0, 2.0]), (6, [float("inf"), 0.0])], "id long, vec array<double>")
    good, bad = vectors.checked(raw, 2)
    assert [r.id for r in good.collect()] == [1] and bad.count() == 6


def test_text_vectors_load(spark, tmp_path):
    (tmp_path / "v.csv").write_text("1;0.5 1.5\n2;bad 1\n")
    good, bad = vectors.from_text(spark, str(tmp_path / "v.csv"), "csv", 2)
    assert [r.vec for r in good.collect()] == [[0.5, 1.5]] and bad.count() == 1


def test_ops_replay_and_tombstones(spark):
    rows = [("upsert", 1, 1, [0.0, 0.0, 0.0, 0.0]), ("upsert", 2, 1, [1.0, 1.0, 1.0, 1.0]), ("upsert", 1, 3, [1.0, 1.0, 0.0, 0.0]), ("delete", 2, 2, None), ("upsert", 2, 0, [0.0, 0.0, 0.0, 0.0])]
    ops = spark.createDataFrame(rows, "op string, vec_id long, version long, embedding array<float>")
    empty = spark.createDataFrame([], "id long, code binary, version long, live boolean")
    once = streams.apply_ops(empty, ops, TINY)
    twice = streams.apply_ops(once, ops, TINY)
    want = [(1, bytes([1]), 3, True), (2, None, 2, False)]
    clean = lambda t: sorted((r.id, None if r.code is None else bytes(r.code), r.version, r.live) for r in t.collect())
    assert clean(once) == want and clean(twice) == want
    again = streams.apply_ops(twice, spark.createDataFrame([("upsert", 2, 5, [1.0, 1.0, 1.0, 1.0])], ops.schema), TINY)
    assert [r.id for r in streams.survivors(again).orderBy("id").collect()] == [1, 2]


def test_late_events_are_dropped(spark, tmp_path):
    import json

    def batch(name, rows):
        (tmp_path / "in").mkdir(exist_ok=True)
        (tmp_path / "in" / name).write_text("\n".join(json.dumps(dict(zip(("ts", "user_id", "event_type", "value", "props"), r, strict=True))) for r in rows))

    batch("a.json", [("2024-01-01T10:00:00", 1, "click", 1.0, '{"k": 1}'), ("2024-01-03T10:00:00", 1, "view", 2.0, '{"k": 2}')])
    batch("b.json", [("2024-01-04T10:00:00", 1, "view", 2.0, '{"k": 2}')])  # late rows are told by the watermark before the last
    batch("c.json", [("2024-01-01T11:00:00", 1, "click", 9.0, '{"k": 9}'), ("2024-01-09T00:00:00", 1, "view", 2.0, '{"k": 2}')])
    for n, name in enumerate(("a.json", "b.json", "c.json")):
        os.utime(tmp_path / "in" / name, (1_700_000_000 + n, 1_700_000_000 + n))
    sdf = spark.readStream.schema("ts timestamp, user_id long, event_type string, value double, props string").option("maxFilesPerTrigger", 1).json(str(tmp_path / "in"))
    out = features.features(sdf, list(features.TYPES), "1 day", watermark="1 hour")
    q = out.writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
    q.awaitTermination()
    first = [r for r in spark.table("late").collect() if r.start_ts.day == 1]
    assert len(first) == 1 and first[0].n == 1  # the late click of 9.0 is not in it


def test_asof(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 1, 2), ("b", 9, 3)], "k string, t int, id int")
    right = spark.createDataFrame([("a", 2, "x"), ("a", 5, "y"), ("b", 10, "z")], "k string, f int, v string")
    got = {r.id: r.v for r in relational.asof(left, right, ["k"], "t", "f", ["v"]).collect()}
    assert got == {1: "y", 2: None, 3: None}


def test_sql_functions(spark, data):
    x, df = data
    books = lloyd.fit(df, 12, 4, 16, 2)
    sql.register(spark, books)
    df.createOrReplaceTempView("vv")
    r = spark.sql("select id, vq_encode(vec) as code, vq_distance(vq_encode(vec), vec) as d from vv where id = 3").first()
    assert bytes(r.code) == cb.pack(books.encode(x[3:4], True), 16)[0].tobytes()
    assert r.d == pytest.approx(np.linalg.norm(x[3] - books.decode(books.encode(x[3:4], True))[0]))
    n = spark.sql("select count(*) as n from (select vq_encode(vec) as code from vv) t, lateral vq_entries(t.code)").first().n
    assert n == 400 * 4


def test_tolerance_and_timing(spark):
    t = spark.createDataFrame([("v", 8, 0.91, 32.0), ("v", 16, 0.96, 16.0)], "view string, bytes int, r double, ratio double")
    assert {(r.tol, r.bytes, r.ratio) for r in accuracy.at_tolerance(t).collect()} == {(0.9, 8, 32.0), (0.95, 16, 16.0)}
    assert accuracy.compression(128, 8) == 64 and accuracy.op_counts(128, 16, 16)["encode_madds"] * 16 == accuracy.op_counts(128, 8, 256)["encode_madds"]
    s = spark.createDataFrame([("w", "a", 2.0), ("w", "b", 1.0)], "workload string, method string, seconds double")
    assert {r.method: r.ratio for r in timing.speedup(s, "a").collect()} == {"a": 1.0, "b": 2.0}


@pytest.mark.parametrize("parts", ["1", "7", "40"])
def test_carried_is_a_window(spark, parts):
    from pyspark.sql import Window

    from vecengine.operators.ordered import carried

    rng = np.random.default_rng(4)
    rows = [([None, "a", "b", "hot"][min(3, int(g))], int(t), None if rng.random() < 0.6 else f"v{t}", n) for n, (g, t) in enumerate(zip(rng.integers(0, 9, 3_000), rng.integers(0, 500, 3_000), strict=True))]
    df = spark.createDataFrame(rows, "g string, t int, v string, n int")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    try:
        got = sorted(map(str, carried(df, ["g"], ["t", "n"], F.col("v")).select("n", "last", "place").collect()))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    w = Window.partitionBy("g").orderBy("t", "n")
    want = df.select("n", F.last("v", ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1)).alias("last"), F.row_number().over(w).cast("long").alias("place"))
    assert got == sorted(map(str, want.collect()))
    assert carried(df.limit(0), ["g"], ["t"], F.col("v")).collect() == []


def test_code_table_goes_on_after_a_restart(spark, tmp_path):
    rows = [[("upsert", i, 1, [float(i % 2)] * 4) for i in range(10)], [("upsert", 3, 2, [0.0] * 4), ("delete", 5, 2, None)], [("upsert", 7, 3, [0.0, 0.0, 1.0, 1.0]), ("upsert", 11, 1, [1.0] * 4)]]
    schema = "op string, vec_id long, version long, embedding array<float>"
    batches = [spark.createDataFrame(r, schema) for r in rows]
    whole = streams.apply_ops(spark.createDataFrame([], streams.TABLE), spark.createDataFrame(sum(rows, []), schema), TINY)
    clean = lambda t: sorted((r.id, None if r.code is None else bytes(r.code), r.version, r.live) for r in t.collect())
    first = streams.CodeTable(spark, str(tmp_path), TINY, 3)
    first.merge(batches[0], 0)
    first.merge(batches[1], 1)
    again = streams.CodeTable(spark, str(tmp_path), TINY, 99)  # a new process: buckets and state are those of the manifest
    assert again.buckets == 3 and again.version == 1 and clean(again.read()) == clean(first.read())
    again.merge(batches[1], 1)  # runs again: nothing
    again.merge(batches[2], 2)
    assert clean(again.read()) == clean(whole)
    with pytest.raises(RuntimeError, match="another writer"):
        first.merge(batches[2], 2)


def test_keyed_state_keeps_the_newest(spark, tmp_path):
    rows = [("upsert", 1, 1, [0.0] * 4), ("upsert", 2, 1, [1.0] * 4), ("upsert", 1, 3, [1.0, 1.0, 0.0, 0.0]), ("delete", 2, 2, None), ("upsert", 2, 0, [0.0] * 4)]
    for r in rows:
        spark.createDataFrame([r], "op string, vec_id long, version long, embedding array<float>").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    changes = streams.latest_codes(streams.source(spark, str(tmp_path / "in"), streams.OPS, 1), TINY)
    q = changes.writeStream.format("memory").queryName("newest").outputMode("update").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.table("newest").groupBy("id").agg(F.max_by(F.struct("code", "version", "live"), F.struct("version", ~F.col("live"))).alias("x")).collect()
    assert {r.id: (None if r.x.code is None else bytes(r.x.code), r.x.version, r.x.live) for r in last} == {1: (bytes([1]), 3, True), 2: (None, 2, False)}


def test_packed_files(spark, tmp_path):
    from vecengine.sources import packed

    x = np.random.default_rng(5).standard_normal((1_000, 6)).astype(np.float32)
    assert packed.write(frame(spark, x, 50), f"file://{tmp_path}/v", 4) == 1_000
    got = sorted((r.id, r.vec) for r in packed.read(spark, f"file://{tmp_path}/v", 700).collect())
    assert [i for i, _ in got] == list(range(1_000)) and np.array_equal(np.array([v for _, v in got], np.float32), x)
    (tmp_path / "e").mkdir()
    assert packed.read(spark, f"{tmp_path}/e").collect() == []
    (tmp_path / "e" / "a.fvecs").write_bytes(b"\x02\0\0\0\0\0\0\0")
    with pytest.raises(Exception, match="no whole number"):
        packed.read(spark, f"{tmp_path}/e").collect()


def test_products_by_raster_and_merged_answers(spark, data):
    from vecengine.functions.sql import merge_best
    from vecengine.operators import matmul

    x, df = data
    v = {(r.i, r.j): r.v for r in matmul._blocks(df.limit(60), df, 16, 3).collect()}
    assert len(v) == 60 * 400 and v[7, 301] == pytest.approx(float(x[7] @ x[301]))
    t = spark.createDataFrame([(1, 5, 2.0), (1, 4, 2.0), (1, 9, 1.0), (2, 1, 0.0)], "q int, vec_id long, score double")
    assert {r.q: r.b for r in t.groupBy("q").agg(merge_best(2)("vec_id", "score").alias("b")).collect()} == {1: [9, 4], 2: [1]}


def test_rotation_and_spread_seeds(spark, data):
    """OPQ: orthogonal, error never above that of the plain quantizer it starts from; spread seeds do no worse than first ones."""
    x, df = data
    opq = rotation.fit(df, 12, 4, 16, 6)
    assert np.allclose(opq.rotation @ opq.rotation.T, np.eye(12), atol=1e-8)
    error = lambda b: ((x - b.decode(b.encode(x, True))) ** 2).sum()
    plain = lloyd.fit(df, 12, 4, 16, 6, "hash")
    assert error(opq) < error(plain)
    spread = lloyd.fit(df, 12, 4, 16, 6, "kmeans++", 3, empty="split")
    assert error(spread) < 1.1 * error(lloyd.fit(df, 12, 4, 16, 6))
    turned = search.exact_topk(df, search.Queries(np.arange(5), x[:5]), 1, SQL2).collect()
    assert all(r.query_id == r.vec_id and r.score == pytest.approx(0) for r in turned)


def test_lsh_and_principal_components(spark, data):
    from vecengine.index import cells
    from vecengine.sources import densify

    x, df = data
    found = {(r.query_id, r.vec_id) for r in cells.lsh_candidates(df, df.limit(30), 1.5, tables=8, width=4.0).collect()}
    d = np.linalg.norm(x[:30, None] - x[None], axis=2)
    near = set(zip(*np.nonzero(d < 1.5), strict=True))
    assert found <= {(int(a), int(b)) for a, b in near} and len(found) > 0.9 * len(near)
    y = np.array([r.vec for r in densify.pca(df, 3).orderBy("id").collect()])
    c = x - x.mean(axis=0)
    want = c @ np.linalg.svd(c)[2][:3].T
    assert np.allclose(np.abs(y), np.abs(want), atol=1e-6)


def test_no_queries_and_no_vectors(spark, data):
    x, df = data
    books = lloyd.fit(df, 12, 6, 16, 1)
    codes, none = code_ops.encode(df, books, exact=True), search.Queries(np.zeros(0, np.int64), np.zeros((0, 12)))
    some = search.Queries(np.arange(2), x[:2])
    for out in (search.scan_topk(codes, none, books, 3, SQL2), search.scan_pairs(codes, none, books, SQL2), search.exact_topk(df, none, 3, SQL2), search.pairs(df, codes, none, books, SQL2), search.scan_topk(codes.limit(0), some, books, 3, SQL2), search.exact_topk(df.limit(0), some, 3, SQL2), search.exact_pairs(df, none, SQL2)):
        assert out.collect() == []
