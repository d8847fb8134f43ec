"""Matrix products: approximate on codes, exact in blocks, by coordinates or by Arrow."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.model.codebooks import Codebooks, TableQuantizer
from vecengine.operators import codes as code_ops
from vecengine.operators import search
from vecengine.operators.arrays import lists, matrix

DOT = metrics.get("dot")


def approx(rows: DataFrame, columns: DataFrame, books: Codebooks, tq: TableQuantizer | None = None, encoded: DataFrame | None = None, database: str = "B") -> DataFrame:
    """(i, j, v) of the product of rows (id, vec) and columns (id, vec).

    database: the side whose vectors become codes, 'B' the columns or 'A' the rows; the other side is
    sent out as query tables in chunks, so it should be the smaller. encoded: its code table, if built.
    """
    data, asked = (columns, rows) if database == "B" else (rows, columns)
    codes = encoded if encoded is not None else code_ops.encode(data, books)
    out = search.scan_pairs(codes, search.gather(asked), books, DOT, tq)
    i, j = ("query_id", "vec_id") if database == "B" else ("vec_id", "query_id")
    return out.select(F.col(i).alias("i"), F.col(j).alias("j"), F.col("approx_d").alias("v"))


def exact(rows: DataFrame, columns: DataFrame, engine: str = "arrow") -> DataFrame:
    """(i, j, v). 'arrow': columns are sent out in chunks, each task multiplies its rows; 'block': both sides in
    blocks, a join on the cells of a raster, for two large sides; 'coord': both sides as coordinates, see `coordinates`."""
    if engine == "coord":
        a, b = (df.select("id", F.posexplode("vec").alias("d", "x")) for df in (rows, columns))
        return coordinates(a, b)
    if engine == "arrow":
        return search.exact_pairs(rows, search.gather(columns), DOT).select(F.col("vec_id").alias("i"), F.col("query_id").alias("j"), F.col("true_d").alias("v"))
    if engine == "block":
        return _blocks(rows, columns)
    raise ValueError(f"unknown engine {engine}")


def coordinates(rows: DataFrame, columns: DataFrame) -> DataFrame:
    """(i, j, v) of two matrices by coordinates (id, d, x); what is missing is 0.

    A row's coordinates meet by its id, and rows in blocks, where the sums over shared dimensions are taken: no entry of a
    pair and a dimension is shuffled.
    """
    from vecengine.sources import views

    most = rows.select("d").union(columns.select("d")).agg(F.max("d")).first()[0]
    dims = 0 if most is None else most + 1

    def whole(df: DataFrame) -> DataFrame:
        return views.dense(df.groupBy("id").agg(F.collect_list("d").alias("at"), F.collect_list("x").alias("x")), dims)

    return _blocks(whole(rows), whole(columns))


def as_rows(product: DataFrame) -> DataFrame:
    """(i, vec) of (i, j, v): a row's entries in order of j."""
    return product.groupBy("i").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("vec"))


def _blocks(rows: DataFrame, columns: DataFrame, size: int = 1024, grid: int = 8) -> DataFrame:
    """Blocks of rows meet blocks of columns in the cells of a grid x grid raster: neither side has to fit one task.

    Each block goes to one line of the raster by a hash of its first id and is sent to the line's `grid` cells, so what is
    shuffled is grid times either side, and a cell holds 1 / grid of each.
    """

    def gathered(df: DataFrame, name: str) -> DataFrame:
        def run(batches):
            for batch in batches:
                x = matrix(batch.column(1))
                for lo in range(0, len(x), size):
                    yield pa.RecordBatch.from_arrays([pa.array([batch.column(0).to_numpy()[lo : lo + size]], pa.list_(pa.int64())), pa.array([x[lo : lo + size].tobytes()], pa.binary())], names=[f"{name}_ids", f"{name}_data"])

        return df.select("id", "vec").mapInArrow(run, f"{name}_ids array<long>, {name}_data binary")

    def multiply(batches):
        for batch in batches:
            for ai, a, bi, b in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                v = np.frombuffer(a).reshape(len(ai), -1) @ np.frombuffer(b).reshape(len(bi), -1).T
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(ai), len(bi))), pa.array(np.tile(np.array(bi), len(ai))), pa.array(v.reshape(-1))], names=["i", "j", "v"])

    line = lambda name: F.pmod(F.xxhash64(F.get(f"{name}_ids", F.lit(0))), F.lit(grid))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(grid - 1).cast("long")))
    left = gathered(rows, "a").select("a_ids", "a_data", line("a").alias("r"), every.alias("c"))
    right = gathered(columns, "b").select("b_ids", "b_data", line("b").alias("c"), every.alias("r"))
    both = left.join(right.hint("shuffle_hash"), ["r", "c"]).select("a_ids", "a_data", "b_ids", "b_data")
    return both.mapInArrow(multiply, "i long, j long, v double")


def dense(x: np.ndarray) -> pa.ListArray:
    return lists(x)
