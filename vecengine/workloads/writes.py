"""Writes while queries are served (w10) and general compression (w14)."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession

from vecengine import metrics
from vecengine.baselines.simple import parquet_codec
from vecengine.evaluate import timing
from vecengine.operators import search
from vecengine.plans.folders import scratch
from vecengine.sources import views
from vecengine.streaming import vectors as streams
from vecengine.workloads.common import fit, split, table

SQL2 = metrics.get("sql2")


def w10_writes(spark: SparkSession, sf_dir: str, log: DataFrame | None = None) -> DataFrame:
    """(kind, ops, seconds): an operation log merged in five batches with a search after each."""
    from vecengine.registry import op_log

    s = split(spark, sf_dir, "v_embed")
    f = fit("btq", 8, s.train, s.dims)
    q = search.gather(s.queries)
    folder = scratch(spark, "w10")
    (log if log is not None else op_log(spark, sf_dir)).repartition(5, "vec_id").write.parquet(f"{folder}/in")
    code_table = streams.CodeTable(spark, f"{folder}/table", f.books, 4)
    rows = []

    def each(batch, batch_id):
        code_table.merge(batch, batch_id)
        rows.append(("write", "merge", code_table.log[-1][3]))
        began = time.perf_counter()
        timing.run(search.scan_topk(streams.survivors(code_table.read()), q, f.books, 10, SQL2, f.tq))
        rows.append(("read", "topk", time.perf_counter() - began))

    sdf = streams.source(spark, f"{folder}/in", streams.OPS, 1)
    sdf.writeStream.foreachBatch(each).option("checkpointLocation", f"{folder}/cp").trigger(availableNow=True).start().awaitTermination()
    return timing.read_write(table(spark, rows, "kind string, op string, seconds double"))


def w14_codecs(spark: SparkSession, sf_dir: str, codecs=("none", "snappy", "zstd")) -> DataFrame:
    """(view, codec, bytes, mb_s): vectors through general-purpose compressors, and as codes of 8 bytes."""
    rows = []
    for view in ("v_embed", "v_walk"):
        make, dims = views.VIEWS[view]
        df = make(spark, sf_dir).selectExpr("id", "cast(vec as array<float>) as vec").persist()
        n = df.count()
        for codec in codecs:
            size, seconds = parquet_codec(df, codec, f"{scratch(spark, 'w14')}/{codec}")
            rows.append((view, codec, size, n * dims * 4 / 1e6 / seconds))
        rows.append((view, "codes8", 8 * n, None))
        df.unpersist()
    return table(spark, rows, "view string, codec string, bytes long, mb_s double")
