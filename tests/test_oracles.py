"""Every query that has a DuckDB twin gives the same rows."""

import duckdb
import pytest

from vecengine import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(frame):
    frame = frame[sorted(frame.columns)]
    frame = frame.astype(object).where(frame.notna(), None)
    key = lambda r: tuple((v is None, v) if v is not None else (True, 0) for v in r)
    return list(frame.columns), sorted(map(tuple, frame.itertuples(index=False)), key=key)


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_same_rows(spark, duck, sf, name):
    assert rows(registry.QUERIES[name](spark, sf).toPandas()) == rows(duck.sql(registry.ORACLES[name]).df())


#: The experiments on a part of their grid: test_whole.py holds the registered ones to all of it.
SMALL = {
    "w01_encode": ("speed", {"n": 2_000, "dims": (64, 100), "sizes": (8,), "runs": 1}),
    "w02_tables": ("speed", {"n": 500, "dims": (64, 100), "sizes": (8,), "runs": 1}),
    "w03_scan": ("speed", {"n": 20_000, "n_queries": 20, "sizes": (8, 32), "batches": (1, 16), "runs": 1}),
    "w04_square": ("speed", {"sides": (32, 64)}),
    "w05_tall": ("speed", {"n": 5_000, "columns": (1, 16), "sizes": (8,), "runs": 1}),
    "w06_recall": ("quality", {"views": ("v_embed", "v_walk"), "sizes": (8,)}),
    "w07_correlation": ("quality", {"views": ("v_walk",), "sizes": (8,)}),
    "w08_compression": ("quality", {"views": ("v_walk",)}),
    "w09_alpha": ("quality", {"views": ("v_embed",)}),
    "w10_writes": ("writes", {}),
    "w11_mips": ("quality", {"views": ("v_part",), "sizes": (8,)}),
    "w12_truncation": ("quality", {"scales": (1e-3, 1.0)}),
    "w13_order": ("quality", {"sizes": (8,), "methods": ("btq", "opq")}),
    "w14_codecs": ("writes", {"codecs": ("snappy",)}),
}


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES) - set(SMALL)))
def test_runs(spark, sf, name):
    assert registry.QUERIES[name](spark, sf).collect()


@pytest.mark.parametrize("name", sorted(SMALL))
def test_workload_runs(spark, sf, name):
    from importlib import import_module

    module, grid = SMALL[name]
    assert getattr(import_module(f"vecengine.workloads.{module}"), name)(spark, sf, **grid).collect()


def test_every_query_is_run():
    assert set(registry.ORACLES) <= set(registry.QUERIES) and {n for n in registry.QUERIES if n[0] == "w" and n[1].isdigit()} == set(SMALL)
