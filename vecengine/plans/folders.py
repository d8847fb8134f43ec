"""Folders for what a query writes on its way: in the cluster's shared folder, where it names one."""

from __future__ import annotations

import json
import tempfile
import uuid

from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession


def shared(spark: SparkSession) -> str:
    """spark.checkpoint.dir, else the checkpoint folder in use; a private one only where Spark runs on this machine alone."""
    sc = spark.sparkContext
    configured, current = spark.conf.get("spark.checkpoint.dir", None), sc._jsc.sc().getCheckpointDir()
    if not current.isDefined():
        if not configured and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(configured or tempfile.mkdtemp(prefix="vecengine-"))
    return configured or sc._jsc.sc().getCheckpointDir().get()


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh folder of our own below the shared one."""
    return f"{shared(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder; survives lost executors and ends the lineage."""
    shared(df.sparkSession)
    return df.checkpoint(eager=True)


def resolve(uri: str) -> tuple[fs.FileSystem, str]:
    """File system and path of a folder's URI: file, hdfs, s3 and gs, or a plain path."""
    return fs.FileSystem.from_uri(uri if "://" in uri else "file://" + uri.removeprefix("file:"))


class Manifests:
    """Versions of a JSON object in a folder, each put in place by a rename that fails where the version exists."""

    def __init__(self, spark: SparkSession, folder: str) -> None:
        self.folder = folder.rstrip("/")
        self._jvm, self._conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        self._gateway = spark.sparkContext._gateway
        self._path = self._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.folder).getFileSystem(self._conf)
        self._fs.mkdirs(self._path(self.folder))

    def latest(self) -> tuple[int, dict | None]:
        """Greatest version and its object; -1 and None at first."""
        names = [x.getPath().getName() for x in self._fs.listStatus(self._path(self.folder))]
        known = [int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")]
        if not known:
            return -1, None
        source = self._fs.open(self._path(f"{self.folder}/v{max(known):012d}.json"))
        try:
            return max(known), json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(source, "UTF-8"))
        finally:
            source.close()

    def put(self, version: int, value: dict) -> bool:
        """Whether this call put the version in place; False where it exists."""
        draft, final = self._path(f"{self.folder}/.draft-{uuid.uuid4().hex}"), self._path(f"{self.folder}/v{version:012d}.json")
        sink = self._fs.create(draft, False)
        sink.write(bytearray(json.dumps(value).encode()))
        sink.close()
        rename = getattr(self._jvm.org.apache.hadoop.fs, "Options$Rename")
        options = self._gateway.new_array(rename, 1)
        options[0] = rename.NONE
        try:
            self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self._conf).rename(draft, final, options)
        except Exception as e:
            self._fs.delete(draft, False)
            if "FileAlreadyExists" not in str(e):
                raise
            return False
        return True
