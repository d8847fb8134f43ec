"""What a row takes from the rows before it in its group, without a task for each group."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecengine.plans.folders import cut


def changes(column: pa.Array) -> np.ndarray:
    """Of each row but the first: whether it differs from the one before; nulls equal each other."""
    a, b = column.slice(1), column.slice(0, len(column) - 1)
    differ = pc.fill_null(pc.not_equal(a, b), False).to_numpy(zero_copy_only=False)
    return differ | (pc.is_null(a).to_numpy(zero_copy_only=False) != pc.is_null(b).to_numpy(zero_copy_only=False))


def carried(df: DataFrame, group: list[str], order: list[str], value: Column) -> DataFrame:
    """df with `last`, the last value that is not null of the rows before this one in its group, and `place`, 1 for the
    group's first row.

    Rows are sorted by range, so one group may lie in many tasks; a task goes over its rows once, and what a group
    brings from earlier tasks comes from a table of one row a task.
    """
    names, width = df.columns, len(group)
    keys = [*(f"__g{i}" for i in range(width)), *(f"__o{i}" for i in range(len(order)))]
    own = [*(F.col(c).alias(k) for c, k in zip([*group, *order], keys, strict=True)), value.alias("__v")]
    ranged = df.select(*own, *names).repartitionByRange(*keys).sortWithinPartitions(*keys)
    kind = ranged.schema["__v"].dataType
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in ranged.schema.fields), f"__part int, last {kind.simpleString()}, place long, __first boolean"])

    def run(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        key, count, held, still = None, 0, None, True  # held: the group's last value; still: in the first group of the task
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            columns, v = [batch.column(i) for i in range(width)], batch.column(len(keys))
            new = np.zeros(n, bool)
            for c in columns:
                new[1:] |= changes(c)
            start_key = [c[0].as_py() for c in columns]
            new[0] = key is None or start_key != key
            at = np.arange(n)
            start = np.maximum.accumulate(np.where(new, at, -1))  # -1: the group began in an earlier batch
            seen = np.maximum.accumulate(np.where(v.is_valid().to_numpy(zero_copy_only=False), at, -1))
            before = np.concatenate([[-1], seen[:-1]])
            here = before >= np.maximum(start, 0)
            source = np.where(here, before + 1, np.where(start < 0, 0, -1))  # 0 is what is held, -1 nothing
            pool = pa.concat_arrays([pa.array([None if held is None else held.as_py()], v.type), v])
            last = pool.take(pa.array(source, pa.int64(), mask=source < 0))
            place = np.where(start < 0, count + at + 1, at - start + 1)
            change = new.copy()
            change[0] &= key is not None
            first = still & (np.cumsum(change) == 0)
            still = bool(first[-1])
            if seen[-1] >= max(int(start[-1]), 0):
                held = v[int(seen[-1])]
            elif start[-1] >= 0:
                held = None
            key, count = [c[n - 1].as_py() for c in columns], int(place[-1])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(n, part, np.int32)), last, pa.array(place, pa.int64()), pa.array(first)], names=[*batch.schema.names, "__part", "last", "place", "__first"])

    rows = cut(ranged.mapInArrow(run, schema))
    head = F.struct(*[F.col(f"__g{i}") for i in range(width)])
    ends = rows.groupBy("__part").agg(F.min(head).alias("head"), F.max_by(F.struct(head.alias("tail"), "place", F.coalesce("__v", "last").alias("v")), F.struct(*keys, "place")).alias("end"))
    run_of = Window.partitionBy("tail").orderBy("__part").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ends = ends.select("__part", "head", F.col("end.tail").alias("tail"), F.col("end.place").alias("n"), F.col("end.v").alias("v"))
    ends = ends.withColumn("so_far", F.struct("tail", F.sum("n").over(run_of).alias("n"), F.last("v", ignorenulls=True).over(run_of).alias("v")))
    ends = ends.withColumn("up", F.lag("so_far").over(Window.orderBy("__part")))  # a row a task
    carry = ends.where(F.col("up.tail").eqNullSafe(F.col("head"))).select("__part", F.col("up.n").alias("__more"), F.col("up.v").alias("__from"))
    out = rows.join(F.broadcast(carry), "__part", "left")
    return out.select(*names, F.when(F.col("__first"), F.coalesce("last", "__from")).otherwise(F.col("last")).alias("last"), (F.col("place") + F.when(F.col("__first"), F.coalesce("__more", F.lit(0))).otherwise(0)).alias("place"))
