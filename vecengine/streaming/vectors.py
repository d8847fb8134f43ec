"""Vectors that arrive: encoding, inserts, updates and deletes of a code table, answers to queries."""

from __future__ import annotations

import time
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from vecengine import metrics
from vecengine.model.codebooks import Codebooks, TableQuantizer, pack
from vecengine.operators import codes as code_ops
from vecengine.operators import search
from vecengine.operators.arrays import matrix
from vecengine.plans.folders import Manifests

OPS = "op string, vec_id long, version long, embedding array<float>"


def source(spark: SparkSession, folder: str, schema: str = "vec_id long, embedding array<float>, label int", files_per_batch: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def encode_stream(sdf: DataFrame, books: Codebooks, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(id, code) of a stream of vectors: the batch kernel, no state."""
    rows = sdf.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec")).where("vec is not null")
    return code_ops.encode(rows, books, exact=True)


def latest(ops: DataFrame) -> DataFrame:
    """The operation of the greatest version for each id; a delete wins over an upsert of its version."""
    order = Window.partitionBy("vec_id").orderBy(F.col("version").desc(), (F.col("op") == "delete").desc())
    return ops.withColumn("nth", F.row_number().over(order)).where("nth = 1").drop("nth")


def apply_ops(table: DataFrame, ops: DataFrame, books: Codebooks) -> DataFrame:
    """A code table (id, code, version, live) after operations (op, vec_id, version, embedding).

    Deletes stay as tombstones (live false), so that a late or repeated older operation changes nothing;
    `survivors` drops them. Running the same operations again gives the same table.
    """
    new = latest(ops)
    vectors = new.where("op <> 'delete'").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    coded = code_ops.encode(vectors, books, exact=True)
    rows = new.select(F.col("vec_id").alias("id"), "version", (F.col("op") != "delete").alias("live")).join(coded, "id", "left").select("id", "code", "version", "live")
    order = Window.partitionBy("id").orderBy(F.col("version").desc(), F.col("live").asc())
    return table.select("id", "code", "version", "live").union(rows).withColumn("nth", F.row_number().over(order)).where("nth = 1").drop("nth")


def survivors(table: DataFrame) -> DataFrame:
    return table.where("live").select("id", "code")


TABLE = "id long, code binary, version long, live boolean"


class CodeTable:
    """A code table in versions of a folder, merged batch by batch.

    Every micro-batch writes only the buckets of ids that it touches, beside the old ones, and then puts a manifest of
    all buckets in place under its number. A table that is opened again goes on from the last manifest; a batch that runs
    again finds its number taken and stops, so a batch cut off half-way leaves files that no manifest lists and no trace else.
    """

    def __init__(self, spark: SparkSession, folder: str, books: Codebooks, buckets: int = 16) -> None:
        self.spark, self.folder, self.books = spark, folder.rstrip("/"), books
        self.manifests = Manifests(spark, f"{self.folder}/manifest")
        self.version, known = self.manifests.latest()
        known = known or {"buckets": buckets, "live": {}}
        self.buckets: int = known["buckets"]
        self.live: dict[int, str] = {int(b): path for b, path in known["live"].items()}
        self.log: list[tuple] = []  # of this process: (batch, operations, deletes, seconds)

    def read(self) -> DataFrame:
        if not self.live:
            return self.spark.createDataFrame([], TABLE)
        return self.spark.read.schema(TABLE).parquet(*self.live.values())

    def merge(self, batch: DataFrame, batch_id: int) -> None:
        """For foreachBatch."""
        if batch_id <= self.version:
            return
        began = time.perf_counter()
        batch = batch.withColumn("bucket", F.pmod(F.xxhash64("vec_id"), F.lit(self.buckets)).cast("int")).persist()
        touched = sorted(r.bucket for r in batch.select("bucket").distinct().collect())
        old = [self.live[b] for b in touched if b in self.live]
        table = self.spark.read.schema(TABLE).parquet(*old) if old else self.spark.createDataFrame([], TABLE)
        merged = apply_ops(table, batch.drop("bucket"), self.books).withColumn("bucket", F.pmod(F.xxhash64("id"), F.lit(self.buckets)).cast("int"))
        path = f"{self.folder}/batch-{batch_id}-{uuid.uuid4().hex}"
        merged.repartition("bucket").write.partitionBy("bucket").parquet(path)
        live = self.live | {b: f"{path}/bucket={b}" for b in touched}
        if not self.manifests.put(batch_id, {"buckets": self.buckets, "live": live}):
            raise RuntimeError(f"another writer put batch {batch_id} in place: open the table again")
        self.live, self.version = live, batch_id
        counts = {r.op: r.n for r in batch.groupBy("op").agg(F.count(F.lit(1)).alias("n")).collect()}
        batch.unpersist()
        self.log.append((batch_id, sum(counts.values()), counts.get("delete", 0), time.perf_counter() - began))

    def run(self, ops: DataFrame, checkpoint: str):
        """Merge a stream of operations until it has no more files."""
        query = ops.writeStream.foreachBatch(self.merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        query.awaitTermination()
        return query


def latest_codes(ops: DataFrame, books: Codebooks) -> DataFrame:
    """A stream (id, code, version, live) of changes from a stream of operations: each id's newest version is kept as state.

    A row goes out where an operation is newer than what is known of its id, so late and repeated ones change nothing.
    Deleted ids keep their version as a tombstone.
    """
    rows = ops.select(F.col("vec_id").cast("long").alias("id"), F.col("version").cast("long").alias("version"), (F.col("op") != "delete").alias("live"), F.when(F.col("op") != "delete", F.col("embedding").cast("array<double>")).alias("vec"))
    shared = ops.sparkSession.sparkContext.broadcast(books)

    def code(batches):
        b = shared.value
        for batch in batches:
            codes = np.full(batch.num_rows, None, object)
            has = batch.column(3).is_valid().to_numpy(zero_copy_only=False)
            if has.any():
                codes[has] = [c.tobytes() for c in pack(b.encode(matrix(batch.column(3).drop_null()), True), b.k)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(codes, pa.binary())], names=["id", "version", "live", "code"])

    def newest(key, frames, state):
        version, live = state.get if state.exists else (None, True)
        best = None
        for frame in frames:
            for r in frame.sort_values(["version", "live"], ascending=[True, False]).itertuples():
                if version is None or r.version > version or (r.version == version and live and not r.live):
                    version, live, best = int(r.version), bool(r.live), r
        if best is not None:
            state.update((version, live))
            yield pd.DataFrame({"id": [key[0]], "code": [best.code], "version": [version], "live": [live]})

    coded = rows.mapInArrow(code, "id long, version long, live boolean, code binary")
    return coded.groupBy("id").applyInPandasWithState(newest, "id long, code binary, version long, live boolean", "version long, live boolean", "update", GroupStateTimeout.NoTimeout)


def answer(batch: DataFrame, codes: DataFrame, books: Codebooks, tq: TableQuantizer, k: int = 10, metric: str = "l2") -> DataFrame:
    """Top-k of a micro-batch of queries (id, vec)."""
    kind = metrics.get(metric)
    return search.finish(search.scan_topk(codes, search.gather(batch), books, k, kind, tq), kind, tq)
