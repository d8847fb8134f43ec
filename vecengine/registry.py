"""All queries of the vector engine, by name; each takes (spark, sf_dir) and returns a DataFrame.

Fitted models are kept for a session and folder, as a user would keep them in tables. Queries are the
vectors whose id is divisible by 5, the database is the rest.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.baselines import hamming
from vecengine.evaluate import accuracy, bounds, diagnose
from vecengine.index import cells
from vecengine.model.codebooks import Codebooks, TableQuantizer
from vecengine.operators import codes as code_ops
from vecengine.operators import matmul, relational, search, surround
from vecengine.plans.kept import kept
from vecengine.plans.oracles import ORACLES  # noqa: F401
from vecengine.sources import densify, vectors, views
from vecengine.streaming import features
from vecengine.streaming import vectors as streams
from vecengine.subspaces import explode_sub, split
from vecengine.train import lloyd, rotation, table_quantizer

FLAGSHIP = "btq_scan_topk"
FIT_QUERIES = 1_000  # about so many training vectors stand in as queries when a table quantizer is fitted, all of fewer
SQL2, L2, DOT = metrics.get("sql2"), metrics.get("l2"), metrics.get("dot")
DIMS = 64

def parts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(queries, database) of the embeddings."""
    return vectors.split_by_id(views.embed(spark, sf_dir))


def training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What codebooks are fitted on: all vectors that are no queries, as in the SQL."""
    return parts(spark, sf_dir)[1]


def books(spark: SparkSession, sf_dir: str, m: int = 16, k: int = 16, iters: int = 3) -> Codebooks:
    return kept(spark, ("books", sf_dir, m, k, iters), lambda: lloyd.fit(training(spark, sf_dir), DIMS, m, k, iters))


def fit_tables(spark: SparkSession, sf_dir: str, b: Codebooks, metric: metrics.Metric) -> DataFrame:
    """Table entries of the training vectors that stand in as queries: a sample by md5 of the id, as in the SQL."""
    train = training(spark, sf_dir)
    place = F.conv(F.substring(F.md5(F.col("id").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    return search.tables(train.where(place * F.lit(train.count()) < F.lit(FIT_QUERIES << 32)), b, metric)


def quantizer(spark: SparkSession, sf_dir: str, m: int = 16, metric: metrics.Metric = SQL2) -> TableQuantizer:
    b = books(spark, sf_dir, m)
    return kept(spark, ("tq", sf_dir, m, metric.name), lambda: table_quantizer.fit(fit_tables(spark, sf_dir, b, metric)))


def asked(spark: SparkSession, sf_dir: str) -> search.Queries:
    return search.gather(parts(spark, sf_dir)[0])


def codes_of(spark: SparkSession, sf_dir: str, b: Codebooks, everything: bool = False) -> DataFrame:
    df = views.embed(spark, sf_dir) if everything else parts(spark, sf_dir)[1]
    return code_ops.encode(df, b, exact=True)


# ---------------------------------------------------------------- the queries


def metric_query(name: str, p: float | None = None):
    def run(spark, sf_dir):
        out = search.exact_pairs(parts(spark, sf_dir)[1], asked(spark, sf_dir), metrics.get(name, p))
        return out.select("query_id", "vec_id", F.round("true_d", 6).alias("value"))

    return run


def subspace_split(spark, sf_dir):
    rows = explode_sub(views.embed(spark, sf_dir), split(DIMS, 16)).select("id", "m", F.posexplode("sub").alias("p", "v"))
    return rows.select(F.col("id").alias("vec_id"), "m", (F.col("m") * 4 + F.col("p")).cast("int").alias("d"), F.round("v", 6).alias("v"))


def kmeans_query(iters: int):
    def run(spark, sf_dir):
        b = books(spark, sf_dir, 16, 16, iters)
        count = lloyd.step(training(spark, sf_dir), b)[1]
        w = b.layout.width
        rows = [(m, i, m * w + d, float(b.centroids[m, i, d]), int(count[m, i])) for m in range(b.m) for i in range(b.k) for d in range(w)]
        return spark.createDataFrame(rows, "m int, i int, d int, value double, n long").withColumn("value", F.round("value", 6))

    return run


def code_query(m: int, k: int):
    def run(spark, sf_dir):
        b = books(spark, sf_dir, m, k)
        return code_ops.exploded(codes_of(spark, sf_dir, b, True), b).select(F.col("id").alias("vec_id"), "m", "code")

    return run


def fast_codes_near(spark, sf_dir):
    """(n, near): subvectors, and those whose code by the fast kernel is as near as the nearest centroid, to six digits."""
    b = books(spark, sf_dir)
    df = views.embed(spark, sf_dir)
    fast, slow = code_ops.reconstruct(code_ops.encode(df, b), b), code_ops.reconstruct(code_ops.encode(df, b, exact=True), b)
    rows = df.join(fast.withColumnRenamed("vec", "fast"), "id").join(slow.withColumnRenamed("vec", "slow"), "id")
    w = b.layout.width
    square = lambda other: F.transform(F.sequence(F.lit(0), F.lit(b.m - 1)), lambda m: F.aggregate(F.zip_with(F.slice("vec", m * w + 1, F.lit(w)), F.slice(other, m * w + 1, F.lit(w)), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    gaps = rows.select(F.explode(F.zip_with(square("fast"), square("slow"), lambda x, y: x - y)).alias("gap"))
    return gaps.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("gap") < 1e-6).cast("long")).alias("near"))


def pack4(spark, sf_dir):
    out = code_ops.pack4(code_query(16, 16)(spark, sf_dir).withColumnRenamed("vec_id", "id"))
    return out.withColumnRenamed("id", "vec_id")


def unpack4(spark, sf_dir):
    return code_ops.unpack4(pack4(spark, sf_dir).withColumnRenamed("vec_id", "id"), 16).withColumnRenamed("id", "vec_id")


def table_query(metric):
    def run(spark, sf_dir):
        return search.tables(parts(spark, sf_dir)[0], books(spark, sf_dir), metric).withColumn("y", F.round("y", 6))

    return run


def scan_query(m: int, k: int, byte: bool, n: int = 10, metric=SQL2):
    def run(spark, sf_dir):
        b = books(spark, sf_dir, m, k)
        tq = quantizer(spark, sf_dir, m, metric) if byte else None
        out = search.scan_topk(codes_of(spark, sf_dir, b), asked(spark, sf_dir), b, n, metric, tq)
        return out if byte else out.withColumn("score", F.round("score", 6))

    return run


def blocked_scan(spark, sf_dir):
    """The scan over blocks of codes: the same answers as over rows."""
    b = books(spark, sf_dir)
    return search.scan_topk(code_ops.to_blocks(codes_of(spark, sf_dir, b), 256), asked(spark, sf_dir), b, 10, SQL2, quantizer(spark, sf_dir), blocks=True)


def table_quantiles(spark, sf_dir):
    t = fit_tables(spark, sf_dir, books(spark, sf_dir), SQL2)
    grid = table_quantizer.GRID
    both = t.groupBy("m").agg(F.percentile("y", F.array(*map(F.lit, grid))).alias("lo"), F.percentile("y", F.array(*[F.lit(1 - a) for a in grid])).alias("hi"))
    return both.select("m", F.explode(F.arrays_zip(F.array(*map(F.lit, grid)).alias("alpha"), "lo", "hi")).alias("r")).select("m", "r.alpha", F.round("r.lo", 6).alias("lo"), F.round("r.hi", 6).alias("hi"))


def alpha_grid_loss(spark, sf_dir):
    t = fit_tables(spark, sf_dir, books(spark, sf_dir), SQL2)
    out = table_quantizer.grid_loss(t, table_quantizer.cutoffs(t))
    return out.select("alpha", F.round("scale", 6).alias("scale"), F.round("loss", 8).alias("loss"))


def alpha_best(spark, sf_dir):
    t = fit_tables(spark, sf_dir, books(spark, sf_dir), SQL2)
    out = table_quantizer.grid_loss(t, table_quantizer.cutoffs(t)).orderBy("loss", "alpha").limit(1)
    return out.select("alpha", F.round("scale", 6).alias("scale"), F.round("loss", 8).alias("loss"))


def alpha_variants(spark, sf_dir):
    """Loss by alpha for either pooling and either weighting of entries, with and without the half step."""
    b = books(spark, sf_dir)
    t = fit_tables(spark, sf_dir, b, SQL2).persist()
    usage = code_ops.usage(codes_of(spark, sf_dir, b), b)
    out = None
    for pool in ("shifted", "raw"):
        cut = table_quantizer.cutoffs(t, pool=pool).persist()
        for weight, u in (("uniform", None), ("usage", usage)):
            for half in (False, True):
                loss = table_quantizer.grid_loss(t, cut, u, half)
                part = loss.select(F.lit(pool).alias("pool"), F.lit(weight).alias("weight"), F.lit(half).alias("midpoint"), "alpha", F.round("scale", 6).alias("scale"), F.round("loss", 8).alias("loss"))
                out = part if out is None else out.union(part)
    return out


def byte_tables(spark, sf_dir):
    tq = quantizer(spark, sf_dir)
    t = search.tables(parts(spark, sf_dir)[0], books(spark, sf_dir), SQL2)
    offset = F.element_at(F.array(*[F.lit(float(x)) for x in tq.offsets]), F.col("m") + 1)
    return t.select("query_id", "m", "i", table_quantizer.byte_of(F.col("y"), offset, F.lit(float(tq.scale))).cast("int").alias("b"))


def dequant_distance(spark, sf_dir):
    b = books(spark, sf_dir)
    out = search.scan_pairs(codes_of(spark, sf_dir, b), asked(spark, sf_dir), b, L2, quantizer(spark, sf_dir))
    return out.select("query_id", "vec_id", F.round("approx_d", 6).alias("value"))


def recon(spark, sf_dir, everything: bool = True):
    b = books(spark, sf_dir)
    return code_ops.reconstruct(codes_of(spark, sf_dir, b, everything), b)


def reconstruct(spark, sf_dir):
    return recon(spark, sf_dir).select(F.col("id").alias("vec_id"), F.posexplode("vec").alias("d", "value")).withColumn("value", F.round("value", 6))


def recon_mse(spark, sf_dir):
    both = views.embed(spark, sf_dir).join(recon(spark, sf_dir).withColumnRenamed("vec", "back"), "id")
    return both.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(SQL2.pair(F.col("vec"), F.col("back"))), 6).alias("value"))


def recall_query(m: int, k: int, byte: bool):
    def run(spark, sf_dir):
        q = asked(spark, sf_dir)
        nn = search.exact_topk(parts(spark, sf_dir)[1], q, 1, SQL2)
        out = accuracy.recall_curve(nn, scan_query(m, k, byte, 100)(spark, sf_dir), len(q.ids))
        return out.withColumn("recall", F.round("recall", 6))

    return run


def pair_query(metric, fit_metric, measure):
    def run(spark, sf_dir):
        b = books(spark, sf_dir)
        v = parts(spark, sf_dir)[1]
        p = search.pairs(v, code_ops.encode(v, b, exact=True), asked(spark, sf_dir), b, metric, quantizer(spark, sf_dir, 16, fit_metric))
        return measure(p).withColumn("value", F.round("value", 6))

    return run


def compression_ratio(spark, sf_dir):
    """(view, bytes, ratio): bytes of a view's vectors in single precision, counted over its table, over bytes of their codes."""
    read = lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")
    floats = lambda name, n: n.select(F.lit(name).alias("view"), "n", (F.col("n") * views.VIEWS[name][1]).alias("floats"))
    walks = read("events").groupBy("event_type").agg(F.greatest(F.count("event_id") - views.VIEWS["v_walk"][1] + 1, F.lit(0)).alias("n"))
    texts = read("documents").agg(F.count("doc_id").alias("n"))
    given = read("embeddings").agg(F.count("vec_id").alias("n"), F.sum(F.size("embedding")).alias("floats")).select(F.lit("v_embed").alias("view"), "n", "floats")
    all_views = given.union(floats("v_walk", walks.agg(F.sum("n").alias("n")))).union(floats("v_text512", texts)).union(floats("v_text784", texts))
    sizes = all_views.select("*", F.explode(F.array(F.lit(8), F.lit(16), F.lit(32))).alias("bytes"))
    return sizes.select("view", "bytes", F.try_divide(4.0 * F.col("floats"), F.col("n") * F.col("bytes")).alias("ratio"))


def exact_nn(spark, sf_dir):
    return search.exact_topk(parts(spark, sf_dir)[1], asked(spark, sf_dir), 10, L2).withColumn("score", F.round("score", 6))


def exact_mips(spark, sf_dir):
    q, v = vectors.split_by_id(views.part(spark, sf_dir).persist())  # read once for the queries and for each chunk of them
    return search.exact_topk(v, search.gather(q), 10, DOT).withColumn("score", F.round("score", 6))


def rerank_topk(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    return search.rerank(scan_query(16, 16, True, 50)(spark, sf_dir), v, q, 10, SQL2).withColumn("score", F.round("score", 6))


def hamming_codes(spark, sf_dir):
    c = hamming.encode(views.embed(spark, sf_dir), hamming.signs(64, DIMS))
    word = F.get("words", F.lit(0))
    return c.select(F.col("id").alias("vec_id"), F.posexplode(F.array(word.bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned(word, 32))).alias("half", "bits"))


def hamming_topk(spark, sf_dir):
    q, signs = asked(spark, sf_dir), hamming.signs(64, DIMS)
    return hamming.scan_topk(hamming.encode(parts(spark, sf_dir)[1], signs), q.ids, hamming.words(q.vectors, signs), 10)


def gemm_norm_identity(spark, sf_dir):
    """Squared distances by norms and products against those by differences, over all pairs."""
    return bounds.identity_gaps(parts(spark, sf_dir)[1], asked(spark, sf_dir)).withColumn("max_gap", F.round("max_gap", 6))


def gemm_topk(spark, sf_dir, batch: int = 256):
    """Exact neighbours by norms and products of query batches."""
    return search.exact_topk(parts(spark, sf_dir)[1], asked(spark, sf_dir), 10, SQL2, True, batch).withColumn("score", F.round("score", 6))


def matmul_coord(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    return matmul.exact(q, v, "coord").withColumn("v", F.round("v", 6))


def matmul_block(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    return matmul.exact(q, v, "block").withColumn("v", F.round("v", 6))


def matmul_arrow(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    return matmul.exact(v, q, "arrow").select(F.col("j").alias("i"), F.col("i").alias("j"), F.round("v", 6).alias("v"))


def matmul_approx(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    b = books(spark, sf_dir)
    return matmul.approx(q, v, b, quantizer(spark, sf_dir, 16, DOT), code_ops.encode(v, b, exact=True)).withColumn("v", F.round("v", 6))


def naive_table_saturation(spark, sf_dir):
    t = search.tables(parts(spark, sf_dir)[0], books(spark, sf_dir), SQL2)
    rows = t.select("y", F.explode(F.array(F.lit(0.001), F.lit(1.0), F.lit(1000.0))).alias("scale"))
    b = table_quantizer.naive(F.col("y") * F.col("scale") * F.col("scale"))
    return rows.groupBy("scale").agg(F.round(F.avg((b == 0).cast("double")), 6).alias("share0"), F.round(F.avg((b == 255).cast("double")), 6).alias("share255"))


def lemma(measure):
    def run(spark, sf_dir):
        out = measure(parts(spark, sf_dir)[1], asked(spark, sf_dir), books(spark, sf_dir))
        return out.withColumn("max_gap", F.round("max_gap", 6))

    return run


def lemma_entry_error(spark, sf_dir):
    t = search.tables(parts(spark, sf_dir)[0], books(spark, sf_dir), SQL2)
    return bounds.entry_errors(t, quantizer(spark, sf_dir)).withColumn("max_gap", F.round("max_gap", 6))


def coarse_cell_scan(spark, sf_dir, t: int = 4):
    coarse = books(spark, sf_dir, 1, 16)
    celled = cells.assign(parts(spark, sf_dir)[1], coarse)
    return cells.cell_topk(celled, asked(spark, sf_dir), coarse, t, 10).withColumn("score", F.round("score", 6))


def product_cell_scan(spark, sf_dir, t: int = 32):
    """Two half codebooks make 64 cells; the nearest t are visited."""
    coarse = books(spark, sf_dir, 2, 8)
    return cells.cell_topk(cells.assign(parts(spark, sf_dir)[1], coarse), asked(spark, sf_dir), coarse, t, 10).withColumn("score", F.round("score", 6))


def range_search(spark, sf_dir):
    b = books(spark, sf_dir)
    out = search.scan_pairs(codes_of(spark, sf_dir, b), asked(spark, sf_dir), b, L2, quantizer(spark, sf_dir), 1.2)
    return out.select("query_id", "vec_id", F.round("approx_d", 6).alias("dist"))


def similarity_self_join(spark, sf_dir):
    return relational.self_join(views.embed(spark, sf_dir), 1.1, L2).withColumn("dist", F.round("dist", 6))


def lsh_candidates(spark, sf_dir):
    q, v = parts(spark, sf_dir)
    return cells.lsh_candidates(v, q, 1.2)


def codebook_usage(spark, sf_dir):
    b = books(spark, sf_dir)
    return diagnose.shares(code_ops.usage(codes_of(spark, sf_dir, b, True), b)).withColumn("share", F.round("share", 6))


def codebook_entropy(spark, sf_dir):
    b = books(spark, sf_dir)
    return diagnose.entropy(code_ops.usage(codes_of(spark, sf_dir, b, True), b)).withColumn("bits", F.round("bits", 6))


def overlap_at_k(spark, sf_dir):
    exact = search.exact_topk(parts(spark, sf_dir)[1], asked(spark, sf_dir), 10, SQL2)
    return accuracy.overlap(exact, scan_query(16, 16, True)(spark, sf_dir), 10).withColumn("overlap", F.round("overlap", 6))


def op_log(spark, sf_dir) -> DataFrame:
    """Insert all, then turn every seventh vector around, then delete every eleventh."""
    t = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    row = lambda op, version, vec: F.struct(F.lit(op).alias("op"), F.lit(version).cast("long").alias("version"), vec.alias("embedding"))
    none = F.lit(None).cast("array<float>")
    ops = F.array(row("upsert", 1, F.col("embedding")), row("upsert", 2, F.when(F.col("vec_id") % 7 == 0, F.reverse("embedding"))), row("delete", 3, none))
    rows = t.select("vec_id", F.explode(ops).alias("o")).select("o.op", "vec_id", "o.version", "o.embedding")
    return rows.where((F.col("version") == 1) | ((F.col("version") == 2) & (F.col("vec_id") % 7 == 0)) | ((F.col("version") == 3) & (F.col("vec_id") % 11 == 0)))


def ops_merge_final(spark, sf_dir):
    b = books(spark, sf_dir)
    empty = spark.createDataFrame([], "id long, code binary, version long, live boolean")
    table = streams.survivors(streams.apply_ops(empty, op_log(spark, sf_dir), b))
    return code_ops.exploded(table, b).select(F.col("id").alias("vec_id"), "m", "code")


def view_query(name: str):
    def run(spark, sf_dir):
        return views.VIEWS[name][0](spark, sf_dir).select("id", F.posexplode("vec").alias("d", "v")).withColumn("v", F.round("v", 6))

    return run


def events_query(**how):
    def run(spark, sf_dir):
        events = spark.read.parquet(f"{sf_dir}/events.parquet")
        out = features.features(events, list(features.TYPES), **how)
        at = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
        return out.select("user_id", at("start_ts").alias("start_at"), at("end_ts").alias("end_at"), "n", F.posexplode("vec").alias("d", "v")).withColumn("v", F.round("v", 6))

    return run


def split_counts(spark, sf_dir):
    t = views.embed(spark, sf_dir)
    return t.groupBy(F.when(F.col("id") % 5 == 0, "query").otherwise("database").alias("part")).agg(F.count(F.lit(1)).alias("n"))


def subspace_balance_corr(spark, sf_dir):
    return diagnose.neighbour_correlation(views.embed(spark, sf_dir), DIMS).withColumn("value", F.round("value", 6))


def asof_model_version(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "event_type")
    days = spark.createDataFrame([("2024-01-02", 1), ("2024-01-11", 2), ("2024-01-21", 3)], "day string, version int")
    versions = days.select(F.col("day").cast("timestamp_ntz").alias("valid_from"), "version").join(F.broadcast(spark.createDataFrame([(t,) for t in features.TYPES], "event_type string")), how="cross")
    return relational.asof(events, versions, ["event_type"], "ts", "valid_from", ["version"]).select("event_id", "version")


def usage_query(kind: str):
    def run(spark, sf_dir):
        b = books(spark, sf_dir)
        label = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), "label")
        rows = code_ops.exploded(codes_of(spark, sf_dir, b, True), b).join(label, "id")
        return getattr(rows, kind)("m", "label").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("code").alias("used"))

    return run


def opq_model(spark, sf_dir) -> Codebooks:
    return kept(spark, ("opq", sf_dir), lambda: rotation.fit(training(spark, sf_dir), DIMS, 8, 64, 3))


def opq_rotation(spark, sf_dir):
    r = opq_model(spark, sf_dir).rotation
    return spark.createDataFrame([(i, [float(x) for x in row]) for i, row in enumerate(r)], "r int, row array<double>")


def opq_codes(spark, sf_dir):
    b = opq_model(spark, sf_dir)
    return code_ops.exploded(codes_of(spark, sf_dir, b, True), b).select(F.col("id").alias("vec_id"), "m", "code")


def opq_recall(spark, sf_dir):
    b, q, v = opq_model(spark, sf_dir), asked(spark, sf_dir), parts(spark, sf_dir)[1]
    ranked = search.scan_topk(code_ops.encode(v, b, exact=True), q, b, 100, SQL2)
    return accuracy.recall_curve(search.exact_topk(v, q, 1, SQL2), ranked, len(q.ids))


def kmeans_pp(spark, sf_dir):
    """Codebooks from spread seeds, with empty centroids moved beside the largest."""
    b = kept(spark, ("pp", sf_dir), lambda: lloyd.fit(training(spark, sf_dir), DIMS, 16, 16, 5, "kmeans++", 3, empty="split", tolerance=1e-4))
    from vecengine.model.codebooks import to_frame

    return to_frame(b, spark)


def densify_pca(spark, sf_dir):
    return densify.pca(views.part(spark, sf_dir), 16)


def densify_signhash(spark, sf_dir):
    t = views.part(spark, sf_dir).select("id", F.map_from_entries(F.filter(F.transform("vec", lambda x, i: F.struct(i.cast("string").alias("key"), x.alias("value"))), lambda s: s["value"] != 0)).alias("entries"))
    return densify.signhash(t, 16).select("id", F.posexplode("vec").alias("d", "v")).withColumn("v", F.round("v", 6))


def constant_loss(spark, sf_dir):
    """Mean squared error where every distance is answered by their mean."""
    from vecengine.baselines.simple import constant

    q, v = asked(spark, sf_dir), parts(spark, sf_dir)[1]
    c = constant(v, q, L2)
    return accuracy.mse(search.exact_pairs(v, q, L2).withColumn("approx_d", F.lit(c))).withColumn("value", F.round("value", 6))


def streaming_encode(spark, sf_dir):
    """Vectors encoded by a stream of the table's files, read back from its sink."""
    from vecengine.plans.folders import scratch

    b = books(spark, sf_dir)
    folder = scratch(spark, "stream")
    views.embed(spark, sf_dir).select(F.col("id").alias("vec_id"), F.col("vec").cast("array<float>").alias("embedding")).repartition(5, "vec_id").write.parquet(f"{folder}/in")
    sdf = streams.source(spark, f"{folder}/in", "vec_id long, embedding array<float>", 1)
    streams.encode_stream(sdf, b).writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/cp").trigger(availableNow=True).start().awaitTermination()
    return code_ops.exploded(spark.read.schema("id long, code binary").parquet(f"{folder}/out"), b).select(F.col("id").alias("vec_id"), "m", "code")


def streaming_ops(spark, sf_dir):
    """The operation log as a stream of five files, merged batch by batch."""
    from vecengine.plans.folders import scratch

    b = books(spark, sf_dir)
    folder = scratch(spark, "ops")
    op_log(spark, sf_dir).repartition(5, "vec_id").write.parquet(f"{folder}/in")
    table = streams.CodeTable(spark, f"{folder}/table", b, 4)
    table.run(streams.source(spark, f"{folder}/in", streams.OPS, 1), f"{folder}/cp")
    return code_ops.exploded(streams.survivors(table.read()), b).select(F.col("id").alias("vec_id"), "m", "code")


def streaming_topk(spark, sf_dir):
    """Queries that arrive in files, each micro-batch answered on the code table."""
    from vecengine.plans.folders import scratch

    b, tq = books(spark, sf_dir), quantizer(spark, sf_dir)
    folder = scratch(spark, "answers")
    q, v = parts(spark, sf_dir)
    q.repartition(2, "id").write.parquet(f"{folder}/in")
    codes = code_ops.encode(v, b, exact=True)

    def each(batch, batch_id):
        streams.answer(batch, codes, b, tq, 10, "sql2").write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    sdf = streams.source(spark, f"{folder}/in", "id long, vec array<double>", 1)
    sdf.writeStream.foreachBatch(each).option("checkpointLocation", f"{folder}/cp").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/out").select("query_id", "rnk", "vec_id", "score", F.round("dist", 6).alias("dist"))


def streaming_state(spark, sf_dir):
    """The operation log as a stream whose state is the newest version of each id; the last change of each is its code."""
    from vecengine.plans.folders import scratch

    b = books(spark, sf_dir)
    folder = scratch(spark, "state")
    op_log(spark, sf_dir).repartition(5, "version").write.parquet(f"{folder}/in")

    def each(batch, batch_id):
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    changes = streams.latest_codes(streams.source(spark, f"{folder}/in", streams.OPS, 1), b)
    changes.writeStream.outputMode("update").foreachBatch(each).option("checkpointLocation", f"{folder}/cp").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.schema(f"{streams.TABLE}, batch long").parquet(f"{folder}/out").groupBy("id").agg(F.max_by(F.struct("code", "live"), F.struct("version", ~F.col("live"))).alias("last"))
    return code_ops.exploded(out.where("last.live").select("id", "last.code"), b).select(F.col("id").alias("vec_id"), "m", "code")


def topk_merge(spark, sf_dir):
    """Ten nearest vectors by byte tables from three parts of the codes, whose answers a grouped aggregate merges."""
    from functools import reduce

    from vecengine.functions.sql import merge_best

    b, codes = books(spark, sf_dir), codes_of(spark, sf_dir, books(spark, sf_dir))
    parts_ = [search.scan_topk(codes.where(F.col("id") % 3 == r), asked(spark, sf_dir), b, 10, SQL2, quantizer(spark, sf_dir)) for r in range(3)]
    best = reduce(DataFrame.union, parts_).groupBy("query_id").agg(merge_best(10)("vec_id", "score").alias("ids"))
    return best.select("query_id", F.posexplode("ids").alias("at", "vec_id")).select("query_id", (F.col("at") + 1).alias("rnk"), "vec_id")


def packed_round_trip(spark, sf_dir):
    """Vectors written as packed files and read back by the data source; ids are places in order of vec_id."""
    from vecengine.plans.folders import scratch
    from vecengine.sources import packed

    folder = scratch(spark, "packed")
    packed.write(views.embed(spark, sf_dir), folder, 3)
    out = packed.read(spark, folder, 1 << 14)
    return out.select("id", F.posexplode("vec").alias("d", "v")).withColumn("v", F.round(F.col("v").cast("double"), 6))


def tail_bounds(spark, sf_dir):
    """How often errors of products and squared distances pass a level, beside their tail bounds."""
    b, v = books(spark, sf_dir), parts(spark, sf_dir)[1]
    out = bounds.tails(v, code_ops.encode(v, b, exact=True), asked(spark, sf_dir), b, (0.1, 0.3, 1.0, 2.0))
    return out.withColumns({"rate": F.round("rate", 6), "bound": F.round("bound", 6)})


def subspace_balance(spark, sf_dir):
    """(m, level, across): each subspace's determinant ** (1 / M), and the mean correlation across subspaces."""
    df = views.embed(spark, sf_dir)
    levels, across = diagnose.balance(df, split(DIMS, 16), df.count())
    return spark.createDataFrame([(m, float(x), across) for m, x in enumerate(levels)], "m int, level double, across double")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "metric_l1": metric_query("l1"),
    "metric_l2": metric_query("l2"),
    "metric_lp3": metric_query("lp", 3),
    "metric_dot": metric_query("dot"),
    "metric_cosine": metric_query("cosine"),
    "subspace_split": subspace_split,
    "vq_codes": code_query(1, 16),
    "kmeans_iter0": kmeans_query(0),
    "kmeans_iter1": kmeans_query(1),
    "kmeans_iter3": kmeans_query(3),
    "btq_codes_8": code_query(16, 16),
    "btq_codes_16": code_query(32, 16),
    "btq_codes_32": code_query(64, 16),
    "pq_codes": code_query(8, 256),
    "fast_codes_near": fast_codes_near,
    "pack4": pack4,
    "unpack4": unpack4,
    "query_tables_l2": table_query(SQL2),
    "query_tables_dot": table_query(DOT),
    "pq_scan_topk": scan_query(8, 256, False),
    "btqf_scan_topk": scan_query(16, 16, False),
    "btq_scan_topk": scan_query(16, 16, True),
    "table_quantiles": table_quantiles,
    "alpha_grid_loss": alpha_grid_loss,
    "alpha_best": alpha_best,
    "byte_tables": byte_tables,
    "dequant_distance": dequant_distance,
    "reconstruct": reconstruct,
    "recon_mse": recon_mse,
    "recall_curve_btq": recall_query(16, 16, True),
    "recall_curve_btqf": recall_query(16, 16, False),
    "recall_curve_pq": recall_query(8, 256, False),
    "corr_dot": pair_query(DOT, DOT, accuracy.pearson),
    "corr_l2": pair_query(L2, SQL2, accuracy.pearson),
    "loss_mse": pair_query(L2, SQL2, accuracy.mse),
    "compression_ratio": compression_ratio,
    "exact_nn": exact_nn,
    "exact_mips": exact_mips,
    "rerank_topk": rerank_topk,
    "hamming_codes": hamming_codes,
    "hamming_topk": hamming_topk,
    "gemm_norm_identity": gemm_norm_identity,
    "matmul_coord": matmul_coord,
    "matmul_approx": matmul_approx,
    "naive_table_saturation": naive_table_saturation,
    "lemma_cauchy": lemma(bounds.product_gaps),
    "lemma_triangle": lemma(bounds.distance_gaps),
    "lemma_entry_error": lemma_entry_error,
    "coarse_cell_scan": coarse_cell_scan,
    "range_search": range_search,
    "similarity_self_join": similarity_self_join,
    "codebook_usage": codebook_usage,
    "overlap_at_k": overlap_at_k,
    "ops_merge_final": ops_merge_final,
    "walk_vectors": view_query("v_walk"),
    "text_vectors": view_query("v_text512"),
    "part_vectors": view_query("v_part"),
    "events_tumbling": events_query(length="1 day"),
    "events_sliding": events_query(length="1 day", slide="12 hours"),
    "events_session": events_query(session_gap="6 hours"),
    "split_counts": split_counts,
    "subspace_balance_corr": subspace_balance_corr,
    "asof_model_version": asof_model_version,
    "cube_usage": usage_query("cube"),
    "rollup_usage": usage_query("rollup"),
    # Without a restatement in SQL, or the same answer by another form.
    "blocked_scan": blocked_scan,
    "gemm_topk": gemm_topk,
    "matmul_block": matmul_block,
    "matmul_arrow": matmul_arrow,
    "product_cell_scan": product_cell_scan,
    "opq_rotation": opq_rotation,
    "opq_codes": opq_codes,
    "opq_recall": opq_recall,
    "kmeans_pp": kmeans_pp,
    "densify_pca": densify_pca,
    "densify_signhash": densify_signhash,
    "lsh_candidates": lsh_candidates,
    "codebook_entropy": codebook_entropy,
    "alpha_variants": alpha_variants,
    "constant_loss": constant_loss,
    "streaming_encode": streaming_encode,
    "streaming_ops": streaming_ops,
    "streaming_topk": streaming_topk,
    "streaming_state": streaming_state,
    "topk_merge": topk_merge,
    "packed_round_trip": packed_round_trip,
    "tail_bounds": tail_bounds,
    "subspace_balance": subspace_balance,
}


def workload(module: str, name: str):
    """An experiment over its whole grid, whole views and all held-out queries."""

    def run(spark, sf_dir):
        from importlib import import_module

        return getattr(import_module(f"vecengine.workloads.{module}"), name)(spark, sf_dir)

    return run


QUERIES |= surround.QUERIES
QUERIES |= {
    "w01_encode": workload("speed", "w01_encode"),
    "w02_tables": workload("speed", "w02_tables"),
    "w03_scan": workload("speed", "w03_scan"),
    "w04_square": workload("speed", "w04_square"),
    "w05_tall": workload("speed", "w05_tall"),
    "w06_recall": workload("quality", "w06_recall"),
    "w07_correlation": workload("quality", "w07_correlation"),
    "w08_compression": workload("quality", "w08_compression"),
    "w09_alpha": workload("quality", "w09_alpha"),
    "w10_writes": workload("writes", "w10_writes"),
    "w11_mips": workload("quality", "w11_mips"),
    "w12_truncation": workload("quality", "w12_truncation"),
    "w13_order": workload("quality", "w13_order"),
    "w14_codecs": workload("writes", "w14_codecs"),
}
ORACLES = ORACLES | surround.ORACLES | {"blocked_scan": ORACLES["btq_scan_topk"], "matmul_block": ORACLES["matmul_coord"], "matmul_arrow": ORACLES["matmul_coord"], "streaming_encode": ORACLES["btq_codes_8"], "streaming_ops": ORACLES["ops_merge_final"], "streaming_state": ORACLES["ops_merge_final"]}

