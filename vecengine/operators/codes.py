"""Code tables: encoding of vectors, packed and blocked layouts, reconstruction. No step shuffles."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.model.codebooks import Codebooks, pack, unpack
from vecengine.operators.arrays import binary, bytes_of, lists, matrix


def encode(df: DataFrame, books: Codebooks, out: str = "packed", exact: bool = False) -> DataFrame:
    """(id, code) of (id, vec). out: 'packed' binary, or 'array' of M small ints."""
    shared = df.sparkSession.sparkContext.broadcast(books)

    def run(batches):
        b = shared.value
        for batch in batches:
            x = matrix(batch.column(1), np.float64 if exact else np.float32)
            codes = b.encode(x, exact) if len(x) else np.zeros((0, b.m), np.uint8)
            column = binary(pack(codes, b.k)) if out == "packed" else lists(codes.astype(np.int16))
            yield pa.RecordBatch.from_arrays([batch.column(0), column], names=["id", "code"])

    return df.select("id", "vec").mapInArrow(run, "id long, code " + ("binary" if out == "packed" else "array<short>"))


def encode_relational(df: DataFrame, books: DataFrame, layout) -> DataFrame:
    """(id, m, code) in DataFrame operations: row-local distances to each subspace's centroids."""
    from vecengine.subspaces import explode_sub

    cs = F.broadcast(books.groupBy("m").agg(F.array_sort(F.collect_list(F.struct("i", "centroid"))).alias("cs")))  # M rows
    square = lambda c: F.aggregate(F.zip_with("sub", c["centroid"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    near = explode_sub(df, layout).join(cs, "m").withColumn("d", F.transform("cs", square))
    return near.select("id", "m", (F.array_position("d", F.array_min("d")) - 1).cast("int").alias("code"))


def exploded(codes: DataFrame, books: Codebooks) -> DataFrame:
    """(id, m, code) of packed codes, by bit operations on their bytes."""
    hexes = F.hex("code")
    byte = lambda b: F.conv(F.substring(hexes, 2 * b + 1, 2), 16, 10).cast("int")
    if books.k > 16:
        parts = [byte(m) for m in range(books.m)]
    else:
        parts = [byte(m // 2).bitwiseAND(15) if m % 2 == 0 else F.shiftright(byte(m // 2), 4) for m in range(books.m)]
    return codes.select("id", F.posexplode(F.array(*parts)).alias("m", "code"))


def pack4(codes: DataFrame) -> DataFrame:
    """(id, byte_ix, byte_val) of (id, m, code) rows of one id's M codes: low half first."""
    pairs = codes.groupBy("id", F.floor(F.col("m") / 2).cast("int").alias("byte_ix"))
    return pairs.agg(F.sum(F.when(F.col("m") % 2 == 0, F.col("code")).otherwise(F.shiftleft("code", 4))).cast("int").alias("byte_val"))


def unpack4(packed: DataFrame, m: int) -> DataFrame:
    """(id, m, code) of (id, byte_ix, byte_val), row-local; the last high half of an odd m is left out."""
    halves = F.array(F.col("byte_val").bitwiseAND(15), F.shiftright("byte_val", 4))
    return packed.select("id", "byte_ix", F.posexplode(halves).alias("h", "code")).select("id", (2 * F.col("byte_ix") + F.col("h")).cast("int").alias("m"), "code").where(F.col("m") < m)


def to_blocks(codes: DataFrame, v: int = 4096) -> DataFrame:
    """(ids, codes, n): v codes a row, one codebook's bytes after another, within each partition's order."""

    def run(batches):
        ids, data = [], []
        held = 0
        for batch in batches:
            ids.append(batch.column(0).to_numpy())
            data.append(bytes_of(batch.column(1)))
            held += batch.num_rows
            if held >= v:
                a, d = np.concatenate(ids), np.concatenate(data)
                cut = held // v * v
                for at in range(0, cut, v):
                    yield _block(a[at : at + v], d[at : at + v])
                ids, data, held = [a[cut:]], [d[cut:]], held - cut
        if held:
            yield _block(np.concatenate(ids), np.concatenate(data))

    return codes.select("id", "code").mapInArrow(run, "ids array<long>, codes binary, n int")


def _block(ids: np.ndarray, data: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([ids], pa.list_(pa.int64())), pa.array([np.ascontiguousarray(data.T).tobytes()], pa.binary()), pa.array([len(ids)], pa.int32())], names=["ids", "codes", "n"])


def reconstruct(codes: DataFrame, books: Codebooks) -> DataFrame:
    """(id, vec) that packed codes stand for."""
    shared = codes.sparkSession.sparkContext.broadcast(books)

    def run(batches):
        b = shared.value
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(b.decode(unpack(bytes_of(batch.column(1)), b.m, b.k)).astype(np.float64))], names=["id", "vec"])

    return codes.select("id", "code").mapInArrow(run, "id long, vec array<double>")


def write(codes: DataFrame, path: str, layout: str = "row", files: int | None = None, v: int = 4096) -> None:
    """A code table sorted by cell, where there is one, and id; 'block' stores v codes a row."""
    keys = [c for c in ("cell", "id") if c in codes.columns]
    out = codes.repartitionByRange(*([files] if files else []), *keys).sortWithinPartitions(*keys)
    (to_blocks(out, v) if layout == "block" else out).write.parquet(path)


def usage(codes: DataFrame, books: Codebooks) -> DataFrame:
    """(m, i, n): how often each code occurs, counted within tasks first."""

    def run(batches):
        count = np.zeros((books_m, books_k), np.int64)
        for batch in batches:
            if batch.num_rows:
                c = unpack(bytes_of(batch.column(0)), books_m, books_k)
                for m in range(books_m):
                    count[m] += np.bincount(c[:, m], minlength=books_k)
        m, i = np.nonzero(count)
        yield pa.RecordBatch.from_arrays([pa.array(m, pa.int32()), pa.array(i, pa.int32()), pa.array(count[m, i])], names=["m", "i", "n"])

    books_m, books_k = books.m, books.k
    return codes.select("code").mapInArrow(run, "m int, i int, n long").groupBy("m", "i").agg(F.sum("n").alias("n"))
