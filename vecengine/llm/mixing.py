"""Mixing sources to target weights: water-filled budgets, hash-random order, exact cuts.

All in DataFrame functions. Text is read once, for its number of words; what is shuffled after
that is a narrow row per document. Prefix sums are distributed: hash-random keys are split by
their leading hex digits into about sqrt(n) ranges a source, the ranges' totals are summed up in
key order, and each range is then summed on its own. A hot source has as many ranges as any other.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecengine.llm import common as C

WORD = r"[^\x20\x09-\x0D]+"


def budgets(sizes: DataFrame, weights: Sequence[int], share: float, most: int) -> DataFrame:
    """sizes: (source, source_size), one row a source. Adds target.

    Sources in code-point order, null last, take the weights in turn. The budget is `share` of all
    sizes, dealt by weight; no source gets more than `most` times its size, and what that leaves
    over is dealt again by weight among the rest. In order of size over weight the bound sources
    come first, so one running sum finds the final level.
    """
    by_name = Window.orderBy(F.col("source").isNull(), F.col("source"))
    table = sizes.withColumn("nth", F.row_number().over(by_name))
    table = table.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("nth") - 1) % len(weights) + 1).cast("long"))
    table = table.withColumn("bound", most * F.col("source_size"))
    order = Window.orderBy((F.col("bound") / F.col("weight")), "nth")
    everything = Window.partitionBy()
    table = table.withColumn("total", F.sum("source_size").over(everything) * F.lit(share))
    before = F.coalesce(F.sum("bound").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    after = F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))
    table = table.withColumn("level", (F.col("total") - before) / after)
    table = table.withColumn("full", F.col("bound") <= F.col("weight") * F.col("level"))
    table = table.withColumn("final", F.max(F.when(~F.col("full"), F.col("level"))).over(everything))
    return table.select("source", "source_size", F.when(F.col("full"), F.col("bound").cast("double")).otherwise(F.col("weight") * F.col("final")).alias("target"))


def mix(docs: DataFrame, weights: Sequence[int] = (3, 1, 2), share: float = 1.5, most: int = 2, salt: str = "mix") -> DataFrame:
    """(doc_id, size, source_size, target, taken) for each row of docs (doc_id, source, text).

    size counts words (null text: 0). taken is the number of the document's words that the mix
    takes: whole epochs, and in the last one all documents up to the source's exact budget, the
    document on the edge in part. Null sources are one source. Rows that repeat an id are taken
    each on their own; equal rows are interchangeable. Rows are never dropped; a source without
    words has target 0. Other columns are ignored. The order depends on ids and salt alone, so
    reruns agree.
    """
    sized = docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))
    sized = C.cut(sized.withColumn("key", F.md5(F.concat(F.lit(salt), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))))
    digits = max(1, int(math.log(max(sized.count(), 1), 16) / 2))
    ranged = sized.withColumn("range", F.substring("key", 1, digits))
    sums = C.cut(ranged.groupBy("source", "range").agg(F.sum("size").alias("range_size")))
    plan = budgets(sums.groupBy("source").agg(F.sum("range_size").alias("source_size")), weights, share, most)
    upto = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.withColumn("offset", F.coalesce(F.sum("range_size").over(upto), F.lit(0)))
    offsets = offsets.join(plan.withColumnRenamed("source", "of"), F.col("source").eqNullSafe(F.col("of"))).select(F.col("source").alias("s"), F.col("range").alias("r"), "offset", "source_size", "target")
    own = Window.partitionBy("source", "range").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    running = ranged.withColumn("running", F.sum("size").over(own))
    both = running.join(offsets, F.col("source").eqNullSafe(F.col("s")) & (F.col("range") == F.col("r")))
    whole = F.floor("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.expr("cast(floor(target) as bigint) div source_size")).otherwise(F.lit(0))
    rest = whole - F.col("epochs") * F.col("source_size") - (F.col("offset") + F.col("running") - F.col("size"))
    taken = F.col("epochs") * F.col("size") + F.greatest(F.lit(0), F.least(F.col("size"), rest))
    return both.withColumn("epochs", epochs).select("doc_id", "size", "source_size", "target", taken.cast("long").alias("taken"))


def op5_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, sources weighing 3, 1, 2, repeating, 150% of all words, at most two epochs."""
    return mix(C.table(spark, sf_dir, "documents"))


MIX_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         md5('mix' || coalesce(CAST(doc_id AS VARCHAR), '')) AS key
  FROM documents),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
named AS (SELECT *, row_number() OVER (ORDER BY source IS NULL, source) AS nth FROM sources),
weighed AS (SELECT *, CASE (nth - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, 2 * source_size AS bound FROM named),
levels AS (
  SELECT *, ((SELECT sum(source_size) FROM sources) * 1.5::DOUBLE - coalesce(sum(bound) OVER (ORDER BY bound::DOUBLE / weight, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(weight) OVER (ORDER BY bound::DOUBLE / weight, nth ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed),
targets AS (
  SELECT source, source_size, CASE WHEN bound <= weight * level THEN bound::DOUBLE
         ELSE weight * (SELECT max(level) FROM levels WHERE bound > weight * level) END AS target
  FROM levels),
placed AS (
  SELECT d.doc_id, d.size, t.source_size, t.target, CAST(floor(t.target) AS BIGINT) AS budget,
         CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.key, d.doc_id, d.size ROWS UNBOUNDED PRECEDING) - d.size AS BIGINT) AS before
  FROM sized d JOIN targets t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       CAST(CASE WHEN source_size = 0 THEN 0 ELSE (budget // source_size) * size + greatest(0, least(size, budget % source_size - before)) END AS BIGINT) AS taken
FROM placed
"""
