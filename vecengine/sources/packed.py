"""Packed vector files as a Spark data source: each record is an int32 length and so many float32 numbers, little-endian.

All records of a file have one length, so a file splits at any record. Ids are the places of the
vectors in the order of file names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from vecengine.operators.arrays import lists, matrix
from vecengine.plans.folders import resolve

SUFFIX = ".fvecs"


def _length(store, path: str) -> int:
    with store.open_input_file(path) as f:
        return int(np.frombuffer(f.read(4), "<i4")[0]) if f.size() else 0


class Piece(InputPartition):
    def __init__(self, path: str, dims: int, first_id: int, start: int, count: int) -> None:
        self.path, self.dims, self.first_id, self.start, self.count = path, dims, first_id, start, count


class Reader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.bytes = options["path"], int(options.get("partitionbytes", 128 << 20))

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, root = resolve(self.path)
        found = sorted((x.path, x.size) for x in store.get_file_info(fs.FileSelector(root)) if x.path.endswith(SUFFIX))
        out, first = [], 0
        for path, size in found:
            dims = _length(store, path)
            record = 4 + 4 * dims
            if dims and size % record:
                raise ValueError(f"{path}: {size} bytes are no whole number of vectors of {dims}")
            count = size // record if dims else 0
            step = max(1, self.bytes // record)
            out += [Piece(path, dims, first + at, at, min(step, count - at)) for at in range(0, count, step)]
            first += count
        return out or [Piece("", 0, 0, 0, 0)]

    def read(self, piece: Piece) -> Iterator[pa.RecordBatch]:
        if not piece.count:
            return
        record, rows = 4 + 4 * piece.dims, 8192
        with resolve(self.path)[0].open_input_file(piece.path) as f:
            f.seek(piece.start * record)
            for at in range(0, piece.count, rows):
                n = min(rows, piece.count - at)
                data = np.frombuffer(f.read(n * record), "<i4").reshape(n, -1)
                if (data[:, 0] != piece.dims).any():
                    raise ValueError(f"{piece.path}: vectors differ in length")
                x = np.ascontiguousarray(data[:, 1:]).view("<f4")
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(n) + piece.first_id + at), lists(x)], names=["id", "vec"])


class PackedVectors(DataSource):
    """spark.dataSource.register(PackedVectors); spark.read.format('packed_vectors').load(folder).

    Option partitionBytes bounds what a task reads.
    """

    @classmethod
    def name(cls) -> str:
        return "packed_vectors"

    def schema(self) -> str:
        return "id long, vec array<float>"

    def reader(self, schema) -> DataSourceReader:
        return Reader({k.lower(): v for k, v in self.options.items()})


def read(spark: SparkSession, folder: str, partition_bytes: int = 128 << 20) -> DataFrame:
    spark.dataSource.register(PackedVectors)
    return spark.read.format("packed_vectors").option("partitionBytes", partition_bytes).load(folder)


def write(df: DataFrame, folder: str, files: int = 8) -> int:
    """Vectors (id, vec) in order of id as packed files, one a task; returns their number.

    A file gets its name when it is whole, and a task that runs again writes the same rows over it.
    """
    ranged = df.select("id", "vec").repartitionByRange(files, "id").sortWithinPartitions("id")

    def put(batches):
        from pyspark import TaskContext

        store, root = resolve(folder)
        context = TaskContext.get()
        name = f"{root}/part-{context.partitionId():06d}{SUFFIX}"
        draft, sink, n = f"{name}.{context.taskAttemptId()}", None, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column(1), np.float32)
            if sink is None:
                store.create_dir(root, recursive=True)
                sink = store.open_output_stream(draft)
            sink.write(np.hstack([np.full((len(x), 1), x.shape[1], "<i4"), x.astype("<f4").view("<i4")]).tobytes())
            n += len(x)
        if sink is not None:
            sink.close()
            store.move(draft, name)
            yield pa.RecordBatch.from_arrays([pa.array([n])], names=["n"])

    return ranged.mapInArrow(put, "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
