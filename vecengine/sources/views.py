"""Vector views of the given tables: (id, vec array<double>), all deterministic."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from numpy.lib.stride_tricks import sliding_window_view
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.operators.arrays import lists
from vecengine.operators.ordered import carried, changes


def embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return t.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))


def walk(spark: SparkSession, sf_dir: str, dims: int = 128, stride: int = 1, multiplier: int | None = None, chunk: int = 4096) -> DataFrame:
    """Sliding windows over a random walk for each event type: strongly correlated neighbours.

    Events are numbered within their type by ranges of time, and each `chunk` of numbers is a group of its own, which
    also gets the dims - 1 events before it: no type is one task. stride keeps each stride-th window; multiplier permutes
    the dimensions by d * multiplier mod dims.
    """
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "event_type", "ts", "value")
    numbered = carried(events, ["event_type"], ["ts", "event_id"], F.lit(None).cast("long")).select("event_id", "event_type", "value", (F.col("place") - 1).alias("at"))
    before = F.col("at") % chunk >= chunk - (dims - 1)
    both = numbered.select("*", F.explode(F.when(before, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))).alias("late")).withColumn("group", F.floor(F.col("at") / chunk) + F.col("late"))
    rows = both.repartition("event_type", "group").sortWithinPartitions("event_type", "group", "at").select("event_id", "event_type", "group", "at", "late", "value")
    places = None if multiplier is None else np.arange(dims) * multiplier % dims

    def windows(group: pa.Table):
        at, late = (group.column(c).to_numpy() for c in ("at", "late"))
        keep = np.flatnonzero((late == 0) & (at >= dims - 1) & ((at + 1 - dims) % stride == 0))
        if not len(keep):
            return
        s = np.cumsum(pc.fill_null(group.column("value").cast(pa.float64()), 50.0).to_numpy() - 50)
        x = sliding_window_view(s, dims)[keep + 1 - dims]
        x = (x - x[:, :1]) / 100
        ids = group.column("event_id").combine_chunks().take(pa.array(keep))
        yield pa.RecordBatch.from_arrays([ids, lists(x if places is None else x[:, places])], names=["id", "vec"])

    def run(batches):
        left: pa.Table | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t = (t if left is None else pa.concat_tables([left, t])).combine_chunks()
            new = np.logical_or(*(changes(t.column(c).chunk(0)) for c in ("event_type", "group")))
            starts = [0, *(np.flatnonzero(new) + 1)]
            for lo, hi in zip(starts, starts[1:], strict=False):
                yield from windows(t.slice(lo, hi - lo))
            left = t.slice(starts[-1])
        if left is not None:
            yield from windows(left)

    return rows.mapInArrow(run, "id long, vec array<double>")


def text(spark: SparkSession, sf_dir: str, dims: int = 512, normalise: bool = True, cap: int = 255) -> DataFrame:
    """Word counts by md5 bucket: unit vectors, or raw counts up to cap. Documents without letters are zero vectors."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    words = F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}]+", " ")

    def run(batches):
        known: dict[str, int] = {"": -1}
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                ids, some = batch.column(0).slice(lo, 2048), pc.split_pattern(batch.column(1).slice(lo, 2048), " ")
                own = some.flatten().dictionary_encode()
                new = own.dictionary.to_pylist()
                if len(known) > 1 << 20:
                    known = {"": -1}
                known.update((w, int.from_bytes(hashlib.md5(w.encode()).digest()[:4], "big") % dims) for w in new if w not in known)
                bucket = np.array([known[w] for w in new], np.int64)[own.indices.to_numpy()]
                row = np.repeat(np.arange(len(ids)), pc.list_value_length(some).to_numpy())[bucket >= 0]
                n = np.bincount(row * dims + bucket[bucket >= 0], minlength=len(ids) * dims).reshape(-1, dims)
                row, at = np.nonzero(n)
                ends = pa.array(np.searchsorted(row, np.arange(len(ids) + 1)).astype(np.int32))
                yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(ends, pa.array(at.astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(n[row, at].astype(np.float64)))], names=["id", "at", "x"])

    counts = docs.select(F.col("doc_id").alias("id"), words.alias("words")).mapInArrow(run, f"id {docs.schema['doc_id'].dataType.simpleString()}, at array<int>, x array<double>")
    rows = counts.groupBy("id").agg(F.flatten(F.collect_list("at")).alias("at"), F.flatten(F.collect_list("x")).alias("x"))
    return dense(rows, dims, "unit" if normalise else "cap", cap, True)


def dense(rows: DataFrame, dims: int, after: str = "", cap: float = 0.0, add: bool = False) -> DataFrame:
    """(id, vec) of (id, at array<int>, x array<double>): entries put at their places, the rest 0.

    after: 'unit' brings rows to unit length (zero rows stay), 'cap' cuts entries off at `cap`. add: entries of one place add up.
    """

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            at, x = batch.column(1), batch.column(2)
            out = np.zeros((batch.num_rows, dims))
            row = np.repeat(np.arange(batch.num_rows), pc.list_value_length(at).to_numpy(zero_copy_only=False))
            place, entry = at.flatten().to_numpy(zero_copy_only=False).astype(int), x.flatten().to_numpy(zero_copy_only=False)
            if add:
                out = np.bincount(row * dims + place, entry, out.size).reshape(out.shape)
            else:
                out[row, place] = entry
            if after == "unit":
                norm = np.sqrt((out * out).sum(axis=1, keepdims=True))
                out = np.divide(out, norm, out=out, where=norm > 0)
            elif after == "cap":
                out = np.minimum(out, cap)
            yield pa.RecordBatch.from_arrays([batch.column(0), lists(out)], names=["id", "vec"])

    return rows.select("id", "at", "x").mapInArrow(run, "id long, vec array<double>")


def part(spark: SparkSession, sf_dir: str, months: int = 84) -> DataFrame:
    """Quantity of each part by month from January 1995: sparse, non-negative."""
    t = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_partkey", "l_quantity", "l_shipdate")
    month = ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).alias("d")
    sums = t.select("l_partkey", "l_quantity", month).where((F.col("d") >= 0) & (F.col("d") < months)).groupBy("l_partkey", "d").agg(F.sum("l_quantity").alias("q"))
    rows = sums.groupBy(F.col("l_partkey").alias("id")).agg(F.collect_list("d").alias("at"), F.collect_list("q").alias("x"))
    return dense(rows, months)


#: Name, builder and number of dimensions.
VIEWS = {
    "v_embed": (embed, 64),
    "v_walk": (walk, 128),
    "v_walk_s16": (lambda s, d: walk(s, d, stride=16), 128),
    "v_walk_perm": (lambda s, d: walk(s, d, multiplier=37), 128),
    "v_text512": (text, 512),
    "v_text784": (lambda s, d: text(s, d, 784, normalise=False), 784),
    "v_part": (part, 84),
}
