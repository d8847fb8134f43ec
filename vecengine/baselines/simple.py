"""The ends of the scale: a constant answer, and general-purpose compression of the vectors."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine import metrics
from vecengine.operators import search


def constant(vdf: DataFrame, q: search.Queries, metric: metrics.Metric) -> float:
    """Mean distance of the queries to all vectors: the estimate for every pair."""
    return search.exact_pairs(vdf, q, metric).agg(F.avg("true_d")).first()[0]


def parquet_codec(df: DataFrame, codec: str, path: str) -> tuple[int, float]:
    """Bytes on disk and seconds of writing a frame with a codec."""
    began = time.perf_counter()
    df.write.option("compression", codec).parquet(path)
    seconds = time.perf_counter() - began
    jvm, conf = df.sparkSession._jvm, df.sparkSession.sparkContext._jsc.hadoopConfiguration()
    folder = jvm.org.apache.hadoop.fs.Path(path)
    return folder.getFileSystem(conf).getContentSummary(folder).getLength(), seconds
