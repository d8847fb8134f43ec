"""Size-tiered shards under a versioned manifest.

Arrivals are appended as small immutable Parquet shards. Shards of one size tier are merged, `fan`
of them at a time, into larger ones up to a target size. Each change is a new manifest that lists
all live shards, put in place by a rename that fails if that version exists, so readers see one
version or the next and writers that lose the race start over from the winner's. A merge is one
task: it streams its inputs and needs no shuffle.
"""

from __future__ import annotations

import json
import math
import time
import uuid
from collections import defaultdict
from dataclasses import asdict, dataclass

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C
from vecengine.llm.files import resolve


@dataclass(frozen=True)
class Shard:
    name: str
    rows: int
    bytes: int
    arrival: int


class Conflict(RuntimeError):
    """Another writer committed this version first."""


WRITTEN = "job long, name string, rows long, bytes long"


class _Roll:
    """Writes batches to files of about `most` bytes; names hold a random part for each attempt."""

    def __init__(self, store, root: str, schema: pa.Schema, most: int) -> None:
        self.store, self.root, self.schema, self.most = store, root, schema, most
        self.sink = self.writer = None
        self.done: list[tuple[str, int, int]] = []

    def put(self, batch: pa.RecordBatch) -> None:
        step = max(1, batch.num_rows // max(1, math.ceil(4 * batch.nbytes / self.most)))
        for at in range(0, batch.num_rows, step):
            if self.writer is None:
                self.name, self.rows = f"shard-{uuid.uuid4().hex}.parquet", 0
                self.sink = self.store.open_output_stream(f"{self.root}/{self.name}")
                self.writer = pq.ParquetWriter(self.sink, self.schema, compression="zstd", compression_level=1)
            part = batch.slice(at, step)
            self.writer.write_batch(part)
            self.rows += part.num_rows
            if self.sink.tell() >= self.most:
                self.close()

    def close(self) -> None:
        if self.writer is not None:
            self.writer.close()
            size = self.sink.tell()
            self.sink.close()
            self.done.append((self.name, self.rows, size))
            self.writer = None

    def report(self, job: int) -> pa.RecordBatch:
        self.close()
        rows = [(job, *x) for x in self.done]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.string(), pa.int64(), pa.int64()))], names=["job", "name", "rows", "bytes"])


class ShardStore:
    """A folder of shards and manifests. small, target: bytes of an arrival's shard and of a finished one."""

    def __init__(self, spark: SparkSession, folder: str, small: int = 8 << 20, target: int = 512 << 20, fan: int = 8) -> None:
        self.spark, self.folder, self.small, self.target, self.fan = spark, folder.rstrip("/"), small, target, fan
        jvm, self._conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.folder).getFileSystem(self._conf)
        for sub in ("data", "manifest"):
            self._fs.mkdirs(self._path(f"{self.folder}/{sub}"))

    # ------------------------------------------------------------- manifests

    def versions(self) -> list[int]:
        found = self._fs.listStatus(self._path(f"{self.folder}/manifest"))
        names = [x.getPath().getName() for x in found]
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def shards(self, version: int | None = None) -> tuple[int, list[Shard]]:
        """Version and its shards; the latest by default, 0 and none at first."""
        known = self.versions()
        version = version if version is not None else (known[-1] if known else 0)
        if version == 0:
            return 0, []
        source = self._fs.open(self._path(f"{self.folder}/manifest/v{version:09d}.json"))
        try:
            text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(source, "UTF-8")
        finally:
            source.close()
        return version, [Shard(**x) for x in json.loads(text)["shards"]]

    def commit(self, version: int, shards: list[Shard], what: str) -> int:
        """Put the next version after `version` in place, or raise Conflict."""
        jvm = self.spark._jvm
        draft = self._path(f"{self.folder}/manifest/.draft-{uuid.uuid4().hex}")
        final = self._path(f"{self.folder}/manifest/v{version + 1:09d}.json")
        sink = self._fs.create(draft, False)
        sink.write(bytearray(json.dumps({"version": version + 1, "what": what, "shards": [asdict(s) for s in shards]}).encode()))
        sink.close()
        rename = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
        options = self.spark.sparkContext._gateway.new_array(rename, 1)
        options[0] = rename.NONE
        try:
            jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self._conf).rename(draft, final, options)
        except Exception as e:
            self._fs.delete(draft, False)
            if "FileAlreadyExists" in str(e):
                raise Conflict(f"version {version + 1} exists") from None
            raise
        return version + 1

    def change(self, add: list[Shard], drop: set[str], what: str, tries: int = 20) -> int:
        """Commit on top of whatever is latest; a dropped shard must still be live."""
        for _ in range(tries):
            version, live = self.shards()
            if drop - {s.name for s in live}:
                raise Conflict("a merged shard is no longer live")
            try:
                return self.commit(version, [s for s in live if s.name not in drop] + add, what)
            except Conflict:
                continue
        raise Conflict("too many other writers")

    # ------------------------------------------------------------------ data

    def append(self, df: DataFrame) -> int:
        """Append rows as small shards, one arrival for each input task; returns the version."""
        data, small = f"{self.folder}/data", self.small

        def write(batches):
            from pyspark import TaskContext

            store, root = resolve(data)
            roll = None
            for batch in batches:
                roll = roll or _Roll(store, root, batch.schema, small)
                roll.put(batch)
            if roll is not None:
                yield roll.report(TaskContext.get().partitionId())

        version, live = self.shards()
        start = 1 + max((s.arrival for s in live), default=-1)
        rows = C.cut(df.mapInArrow(write, WRITTEN)).orderBy("job", "name").collect()  # a row a shard, as the manifest
        return self.change([Shard(r.name, r.rows, r.bytes, start + r.job) for r in rows], set(), f"append {len(rows)}")

    def tier(self, size: int) -> int:
        """0 up to small, then one more for each factor of fan."""
        return max(0, math.ceil(math.log(max(size, 1) / self.small, self.fan) - 1e-9))

    def plan(self, shards: list[Shard], final: bool = False) -> list[list[Shard]]:
        """Groups to merge: by tier and arrival, fan at least, or two where final, up to about the target."""
        by_tier: dict[int, list[Shard]] = defaultdict(list)
        for s in shards:
            if s.bytes < 0.7 * self.target:
                by_tier[0 if final else self.tier(s.bytes)].append(s)
        out = []
        for tier in sorted(by_tier):
            group: list[Shard] = []
            for s in sorted(by_tier[tier], key=lambda s: (s.arrival, s.name)):
                if group and (sum(x.bytes for x in group) + s.bytes > 1.1 * self.target or (len(group) >= self.fan and not final)):
                    out.append(group)
                    group = []
                group.append(s)
            out.append(group)
        least = 2 if final else self.fan
        return [g for g in out if len(g) >= least or (len(g) > 1 and sum(x.bytes for x in g) >= 0.7 * self.target)]

    def compact(self, final: bool = False) -> int:
        """Merge until no tier has a group; final also gathers what is left over. Returns the version."""
        while True:
            version, live = self.shards()
            groups = self.plan(live, final)
            if not groups:
                return version
            data, target = f"{self.folder}/data", 2 * self.target
            plan = self.spark.sparkContext.broadcast([[s.name for s in g] for g in groups])  # of the manifest's size
            tasks = self.spark.range(0, len(groups), 1, len(groups))  # one job a task

            def merge(batches, plan=plan):
                store, root = resolve(data)
                for batch in batches:
                    for job in batch.column(0).to_pylist():
                        roll = None
                        for name in plan.value[job]:
                            with store.open_input_file(f"{root}/{name}") as source:
                                for part in pq.ParquetFile(source).iter_batches(batch_size=8192):
                                    roll = roll or _Roll(store, root, part.schema, target)
                                    roll.put(part)
                        if roll is not None:
                            yield roll.report(job)

            made = C.cut(tasks.mapInArrow(merge, WRITTEN)).orderBy("job", "name").collect()
            new = [Shard(r.name, r.rows, r.bytes, min(s.arrival for s in groups[r.job])) for r in made]
            self.change(new, {s.name for g in groups for s in g}, f"merge {sum(map(len, groups))} into {len(new)}")

    def vacuum(self, retain_s: float = 7 * 86_400.0) -> int:
        """Delete what is older than retain_s and no version that readers may still be on lists; returns the number of files.

        Those versions are the latest and any younger than retain_s. Files of writers at work are young, orphans of
        writers that died are not. Nothing else deletes files, so call it when and where no reader is older.
        """
        limit = time.time() * 1000 - retain_s * 1000
        held = {x.getPath().getName(): x for x in self._fs.listStatus(self._path(f"{self.folder}/manifest"))}
        known = self.versions()
        live = [v for v in known if v == known[-1] or held[f"v{v:09d}.json"].getModificationTime() > limit]
        wanted = {s.name for v in live for s in self.shards(v)[1]}
        gone = 0
        files = self._fs.listFiles(self._path(f"{self.folder}/data"), False)
        while files.hasNext():
            x = files.next()
            if x.getPath().getName() not in wanted and x.getModificationTime() <= limit:
                gone += self._fs.delete(x.getPath(), False)
        for name, x in held.items():
            if name not in {f"v{v:09d}.json" for v in live} and x.getModificationTime() <= limit:
                self._fs.delete(x.getPath(), False)
        return gone

    def read(self, version: int | None = None) -> DataFrame:
        """Rows of a version with their shard's name, size and number of rows."""
        version, live = self.shards(version)
        if not live:
            raise ValueError("the store has no shard")
        rows = self.spark.read.parquet(*[f"{self.folder}/data/{s.name}" for s in live]).withColumn("shard", F.col("_metadata.file_name"))
        listed = self.spark.createDataFrame([(s.name, s.rows, s.bytes) for s in live], "shard string, shard_rows long, shard_bytes long")
        return rows.join(F.broadcast(listed), "shard").withColumn("version", F.lit(version).cast("long"))  # a manifest


def shard_documents(docs: DataFrame, small: int = 8 << 20, target: int = 64 << 20, fan: int = 8) -> DataFrame:
    """Append, compact, and read back: docs' columns and shard, shard_rows, shard_bytes, version.

    Nulls, long texts and repeated rows are kept as they are. Columns of docs named like those that are
    added, whatever the case, are refused. An empty table makes no shard and gives an empty result.
    """
    clash = {c.lower() for c in docs.columns} & {"shard", "shard_rows", "shard_bytes", "version"}
    if clash:
        raise ValueError(f"columns clash: {sorted(clash)}")
    store = ShardStore(docs.sparkSession, C.work_dir(docs.sparkSession, "shards"), small, target, fan)
    store.append(docs)
    store.compact()
    store.compact(final=True)
    store.vacuum(0.0)  # the folder is new and no one else's
    if not store.shards()[1]:
        return docs.withColumns({"shard": F.lit(""), "shard_rows": F.lit(0).cast("long"), "shard_bytes": F.lit(0).cast("long"), "version": F.lit(0).cast("long")}).limit(0)
    return store.read()


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents as read back of compacted shards; listed: their shard holds as many rows as the manifest says."""
    out = shard_documents(C.table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source", "n_chars"))
    held = out.groupBy("shard").agg(F.count(F.lit(1)).alias("held"))  # a row a shard, as the manifest
    out = out.join(F.broadcast(held), "shard")
    return out.select("doc_id", F.octet_length("text").cast("long").alias("text_bytes"), F.md5(F.col("text").cast("binary")).alias("text_md5"), "lang", "source", "n_chars", ((F.col("held") == F.col("shard_rows")) & (F.col("shard_bytes") > 0)).alias("listed"))


#: What must come back of the shards.
SHARDS_SQL = "SELECT doc_id, CAST(strlen(text) AS BIGINT) AS text_bytes, md5(text) AS text_md5, lang, source, n_chars, true AS listed FROM documents"
