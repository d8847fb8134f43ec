"""A corpus pipeline of four operators: toxicity, near-duplicates, source mixing, sentence pieces.

Every stage works on all that its predecessor kept and all but the last return the columns of
documents. run() writes each stage's rows as Parquet in the shared folder and reads them again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C
from vecengine.llm import mixing, near_dedup, pieces, toxicity

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
MODEL = f"{pieces.TOKENIZERS}/piece_bpe_32k.model"


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score under 0.5, null and empty texts among them."""
    scorer = toxicity.learn(docs, C.table(spark, sf_dir, "labels"))
    return toxicity.score(docs.withColumn("body", F.col("text")), scorer, COLUMNS, "body").where("score < 0.5").select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group on 5-word shingles at 0.8, the one of least id; rows without an id stay."""
    groups = near_dedup.groups(docs, near_dedup.NearDup()).where("not kept").select(F.col("doc_id").alias("gone")).distinct()
    return docs.select(*COLUMNS).join(groups, F.col("doc_id") == F.col("gone"), "left_anti")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of the mix, one row for each epoch that takes any of their words.

    A document on the edge of its source's budget stays whole. Documents without words are in no mix.
    """
    taken = mixing.mix(docs).where("taken > 0").select(F.col("doc_id").alias("id"), F.ceil(F.col("taken") / F.col("size")).cast("int").alias("epochs"))
    taken = taken.groupBy("id").agg(F.max("epochs").alias("epochs"))
    out = docs.select(*COLUMNS).join(taken, F.col("doc_id").eqNullSafe(F.col("id")))
    return out.select(*COLUMNS, F.explode(F.sequence(F.lit(1), "epochs")).alias("epoch")).select(*COLUMNS)


def to_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens, ids and whether the ids decode to the text."""
    return pieces.encode_texts(docs, MODEL, ("doc_id", "lang", "source"))


STAGES = [("toxicity", drop_toxic), ("near_dedup", drop_near_copies), ("mix_sources", mix_sources), ("sentencepiece", to_pieces)]

#: Learning, hashing and merging have no SQL form; tests hold the pipeline against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    folder = C.work_dir(spark, "pipeline")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
