"""Plans stay as they should be: pruned scans, no shuffle in encoding, ranking pushed below it."""

import numpy as np

from vecengine import metrics, registry
from vecengine.operators import codes as code_ops
from vecengine.operators import search


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_encode_neither_shuffles_nor_reads_more(spark, sf):
    b = registry.books(spark, sf)
    text = plan(code_ops.encode(registry.parts(spark, sf)[1], b))
    assert "Exchange" not in text and "label" not in text.split("ReadSchema")[1]


def test_topk_ranks_before_the_shuffle(spark, sf):
    text = plan(registry.scan_query(16, 16, True)(spark, sf))
    assert text.count("WindowGroupLimit") == 2 and text.count("Exchange") == 1


def test_exact_scan_has_no_join(spark, sf):
    text = plan(search.exact_topk(registry.parts(spark, sf)[1], registry.asked(spark, sf), 10, metrics.get("l2")))
    assert "Join" not in text and "CartesianProduct" not in text


def test_query_tables_are_chunked():
    from vecengine.model.codebooks import Codebooks
    from vecengine.subspaces import split

    b = Codebooks(split(64, 64), np.zeros((64, 16, 1)))
    q = search.Queries(np.arange(2000), np.zeros((2000, 64)))
    parts = list(search.scorers(q, b, metrics.get("sql2"), None))
    assert sum(len(p.ids) for p in parts) == 2000 and all(p.tables.nbytes <= search.CHUNK_BYTES and next(p.groups())[1].nbytes <= 1 << 20 for p in parts)


def test_workloads_run_small(spark, sf):
    from vecengine.workloads import quality, speed, writes

    assert speed.w01_encode(spark, sf, 500, (64,), (8,), ("btq", "pq"), 1).count() == 2
    assert speed.w02_tables(spark, sf, 50, (64,), (8,), runs=1).count() == 3
    assert speed.w03_scan(spark, sf, 2000, 64, 4, (8,), (1,), runs=1).count() == 12
    assert speed.w04_square(spark, sf, (64,)).count() == 3
    assert speed.w05_tall(spark, sf, 1000, 64, (2,), (8,), 1).count() == 3
    r = quality.w06_recall(spark, sf, ("v_embed",), (8,), ("btq", "btqf")).toPandas()
    assert len(r) == 14 and abs(r[r.method == "btq"].recall.mean() - r[r.method == "btqf"].recall.mean()) < 0.03
    r = quality.w07_correlation(spark, sf, ("v_embed",), (8,), ("btq", "btqf"), ("dot",)).toPandas()
    assert abs(r.r[0] - r.r[1]) < 0.01 and r.r.min() > 0.7
    assert writes.w14_codecs(spark, sf, ("snappy",)).count() == 4
