"""Shared parts of the training-data operators: tables, durable cuts, word hashing, components.

Words everywhere are maximal runs of bytes other than space and 0x09-0x0D in the
UTF-8 text; that is the same as maximal runs of the matching code points.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.operators.ordered import carried  # noqa: F401
from vecengine.plans.folders import cut
from vecengine.plans.folders import scratch as work_dir  # noqa: F401

MASK64 = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# ---------------------------------------------------------------- numpy kernels


def mix64(x: np.ndarray) -> np.ndarray:
    """Invertible 64-bit finaliser (xor-shift and multiply)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


BASE = 0x9E3779B97F4A7C15
_TABLES: dict[int, np.ndarray] = {}


def powers(n: int, base: int = BASE) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2 ** 64; kept and grown by doubling."""
    have = _TABLES.get(base)
    if have is None or len(have) < n:
        step = np.full(max(n, 1 << 12, 2 * (0 if have is None else len(have))), base, dtype=np.uint64)
        step[0] = 1
        _TABLES[base] = have = np.multiply.accumulate(step)
    return have[:n]


INVERSE = pow(BASE, -1, 1 << 64)


def utf8_buffer(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if isinstance(column, pa.ChunkedArray):  # no chunk at all
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.large_string())
    column = column.cast(pa.large_string()).fill_null("")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and document index of each word."""
    n = len(raw)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = ~((raw == 32) | ((raw >= 9) & (raw <= 13)))
    first = np.zeros(n + 1, bool)
    first[offsets[:-1]] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = inside[:-1]
    before[first[:n]] = False
    starts = np.flatnonzero(inside & ~before)
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = inside[1:]
    after[np.flatnonzero(first[1:])] = False
    ends = np.flatnonzero(inside & ~after) + 1
    docs = np.searchsorted(offsets, starts, side="right") - 1
    return starts, ends, docs


def prefix_hashes(raw: np.ndarray) -> np.ndarray:
    """h with h[e] - h[s] = sum of (byte + 1) * BASE ** position over raw[s:e], modulo 2 ** 64."""
    out = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * powers(len(raw)), out=out[1:])
    return out


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, prefix: np.ndarray | None = None) -> np.ndarray:
    """64-bit hash of each span of bytes; equal spans hash alike wherever they stand."""
    if len(starts) == 0:
        return np.zeros(0, np.uint64)
    prefix = prefix_hashes(raw) if prefix is None else prefix
    shifted = (prefix[ends] - prefix[starts]) * powers(len(raw) + 1, INVERSE)[starts]
    return mix64(shifted + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def ascii_lower(raw: np.ndarray) -> np.ndarray:
    return raw + (((raw >= 65) & (raw <= 90)).astype(np.uint8) << 5)


def row_slices(offsets: np.ndarray, most: int = 1 << 20):
    """Ranges of rows of about `most` bytes of text, one row at least: bounds the memory of a kernel."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1
        j = min(n, max(j, i + 1))
        yield i, j
        i = j


# ------------------------------------------------------------------- components


def _forest(batches):
    """Links u -> least id of the component, of all links that one task holds."""
    us, vs = [], []
    for batch in batches:
        us.append(batch.column(0).to_numpy())
        vs.append(batch.column(1).to_numpy())
    if not us:
        return
    ids, flat = np.unique(np.concatenate([*us, *vs]), return_inverse=True)
    u, v = np.split(flat, 2)
    label = np.arange(len(ids))
    while True:
        new = label.copy()
        low = np.minimum(label[u], label[v])
        np.minimum.at(new, label[u], low)
        np.minimum.at(new, label[v], low)
        while (new != new[new]).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[label])], names=["id", "component_id"])


def components(edges: DataFrame, most_rounds: int = 40, one_task: int = 500_000) -> DataFrame:
    """Connected components of (a, b) links of long ids: (id, component_id), the least id reachable.

    Up to one_task links fit one executor task, which contracts them in arrays. Beyond that comes
    alternating star contraction: each round links the larger neighbours of a node, then the
    smaller ones, to the least of them. Only (node, minimum) aggregates and equi-joins are used, so
    a hub's neighbours are never gathered in one place. Rounds grow with the logarithm of the
    longest chain. Both give the same rows. Nodes that stand in no link are not returned.
    """
    e = cut(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v"))
    if e.count() <= one_task:
        return cut(e.coalesce(1).mapInArrow(_forest, "id long, component_id long"))
    e, seen = e.distinct(), None
    for _ in range(most_rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        e = cut(small.union(least.select("u", F.col("m").alias("v"))).distinct())
        state = e.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(u, v))")).first()
        if tuple(state) == seen:
            break
        seen = tuple(state)
    else:
        raise RuntimeError(f"no fixed point after {most_rounds} rounds of contraction")
    return e.groupBy("u").agg(F.min("v").alias("component_id")).select(F.col("u").alias("id"), "component_id").union(e.select(F.col("v").alias("id"), F.col("v").alias("component_id")).distinct())
