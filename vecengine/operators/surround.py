"""What users of the vector engine do around it: joins, windows, sets, pivots, sketches over codes and answers."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def labelled_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, toxic, quality) of all documents, unlabelled ones kept: a left outer join."""
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("toxic").alias("toxic"), F.max("quality").alias("quality"))
    return table(spark, sf_dir, "documents").select("doc_id").join(labels, "doc_id", "left")


def unlabelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents without a label: an anti-join."""
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti")


def both_ways(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(part, n): ids of documents and of pages on one side, the other, or both: a full outer join."""
    a = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("k"), F.lit(1).alias("a"))
    b = table(spark, sf_dir, "pages").select((F.col("page_id") * 3).alias("k"), F.lit(1).alias("b"))
    part = F.when(F.col("a").isNull(), "right").when(F.col("b").isNull(), "left").otherwise("both")
    return a.join(b, "k", "full").groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n"))


def order_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(custkey, n_orders, n_lines, quantity) by customer: lines are summed by order before the join."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_quantity").alias("q"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").hint("merge")
    both = orders.join(lines, orders.o_orderkey == lines.l_orderkey, "left")
    return both.groupBy(F.col("o_custkey").alias("custkey")).agg(F.count(F.lit(1)).alias("n_orders"), F.sum(F.coalesce("lines", F.lit(0))).alias("n_lines"), F.round(F.sum(F.coalesce("q", F.lit(0.0))), 4).alias("quantity"))


def pivot_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(year, m01 .. m12): quantity shipped, months as columns."""
    t = table(spark, sf_dir, "lineitem").select(F.year("l_shipdate").alias("year"), F.date_format("l_shipdate", "MM").alias("m"), "l_quantity")
    wide = t.groupBy("year").pivot("m", [f"{m:02d}" for m in range(1, 13)]).agg(F.sum("l_quantity"))
    return wide.select("year", *[F.coalesce(F.round(f"{m:02d}", 4), F.lit(0.0)).alias(f"m{m:02d}") for m in range(1, 13)])


def unpivot_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(year, month, quantity): the pivoted table turned back."""
    wide = pivot_months(spark, sf_dir)
    return wide.unpivot("year", [f"m{m:02d}" for m in range(1, 13)], "month", "quantity")


def rank_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranks of each user's events by value, and the values around them."""
    t = table(spark, sf_dir, "events").select("event_id", "user_id", "value", "ts")
    by_value = Window.partitionBy("user_id").orderBy(F.col("value").desc(), "event_id")
    ties = Window.partitionBy("user_id").orderBy(F.col("value").desc())
    time = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t.select(
        "event_id",
        F.row_number().over(by_value).cast("long").alias("rn"),
        F.rank().over(ties).cast("long").alias("rk"),
        F.dense_rank().over(ties).cast("long").alias("dr"),
        F.ntile(4).over(by_value).cast("long").alias("quarter"),
        F.lag("value").over(time).alias("before"),
        F.lead("value").over(time).alias("after"),
        F.round(F.sum("value").over(time.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"),
        F.first("value").over(time).alias("first"),
    )


def hour_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, n_hour): each user's events in the hour before, by a range frame over time."""
    t = table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    back = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)
    return t.select("event_id", F.count(F.lit(1)).over(back).alias("n_hour"))


def json_numbers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, n, mean_k, distinct_k) from a JSON column."""
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(k), 6).alias("mean_k"), F.countDistinct(k).alias("distinct_k"))


def grouped_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(lang, source, n): documents by language, by source, and in all: grouping sets."""
    docs = table(spark, sf_dir, "documents")
    return docs.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n")).select("lang", "source", "n")


def string_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, host, n_tags, title_md5) by string functions."""
    html = F.col("html")
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), (F.size(F.split(html, "<[a-z]")) - 1).cast("long").alias("n_tags"), F.md5(F.regexp_extract(html, "<title>([^<]*)", 1).cast("binary")).alias("title_md5"))


def percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, p05, p50, p95, sd): exact percentiles; `approximate_percentiles` has mergeable ones."""
    p = F.percentile("value", F.array(*map(F.lit, (0.05, 0.5, 0.95))))
    t = table(spark, sf_dir, "events").groupBy("event_type").agg(p.alias("p"), F.round(F.stddev("value"), 6).alias("sd"))
    return t.select("event_type", *[F.round(F.get("p", F.lit(i)), 6).alias(n) for i, n in enumerate(("p05", "p50", "p95"))], "sd")


def approximate_percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, p05, p50, p95, users): sketches that merge across partitions and days."""
    t = table(spark, sf_dir, "events").groupBy("event_type").agg(F.percentile_approx("value", F.array(*map(F.lit, (0.05, 0.5, 0.95))), F.lit(1000)).alias("p"), F.approx_count_distinct("user_id").alias("users"))
    return t.select("event_type", *[F.get("p", F.lit(i)).alias(n) for i, n in enumerate(("p05", "p50", "p95"))], "users")


def lateral_latest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(custkey, rnk, orderkey): the two dearest orders of each customer, by a lateral join with a limited subquery."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    dear = orders.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(2)
    top = table(spark, sf_dir, "customer").select("c_custkey").lateralJoin(dear)
    best = Window.partitionBy("c_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return top.select(F.col("c_custkey").alias("custkey"), F.row_number().over(best).cast("int").alias("rnk"), F.col("o_orderkey").alias("orderkey"))


def id_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(part, n): set operations on the customers with orders of either of two kinds, with and without repeats."""
    orders = table(spark, sf_dir, "orders")
    urgent = orders.where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("k"))
    done = orders.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k"))
    sets = {
        "either": urgent.union(done).distinct(),
        "all": urgent.unionByName(done),
        "both": urgent.intersect(done),
        "both_all": urgent.intersectAll(done),
        "first_only": urgent.subtract(done),
        "first_only_all": urgent.exceptAll(done),
    }
    out = [df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part"), "n") for name, df in sets.items()]
    return reduce(DataFrame.unionAll, out)


QUERIES = {f.__name__: f for f in (labelled_vectors, unlabelled, both_ways, order_features, pivot_months, unpivot_months, rank_windows, hour_frame, json_numbers, grouped_sets, string_stats, percentiles, approximate_percentiles, lateral_latest, id_sets)}

_WIDE = "SELECT CAST(year(l_shipdate) AS INTEGER) AS year, " + ", ".join(f"coalesce(round(sum(l_quantity) FILTER (month(l_shipdate) = {m}), 4), 0.0) AS m{m:02d}" for m in range(1, 13)) + " FROM lineitem GROUP BY 1"
ORACLES = {
    "labelled_vectors": "SELECT d.doc_id, CAST(max(toxic) AS INTEGER) AS toxic, CAST(max(quality) AS INTEGER) AS quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.doc_id",
    "unlabelled": "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)",
    "both_ways": "SELECT CASE WHEN d.doc_id IS NULL THEN 'right' WHEN p.k IS NULL THEN 'left' ELSE 'both' END AS part, CAST(count(*) AS BIGINT) AS n FROM documents d FULL JOIN (SELECT page_id * 3 AS k FROM pages) p ON d.doc_id = p.k GROUP BY 1",
    "order_features": "SELECT o_custkey AS custkey, CAST(count(*) AS BIGINT) AS n_orders, CAST(sum(coalesce(lines, 0)) AS BIGINT) AS n_lines, round(sum(coalesce(q, 0.0)), 4) AS quantity FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS lines, sum(l_quantity) AS q FROM lineitem GROUP BY 1) ON o_orderkey = l_orderkey GROUP BY 1",
    "pivot_months": _WIDE,
    "unpivot_months": f"UNPIVOT ({_WIDE}) ON COLUMNS(* EXCLUDE year) INTO NAME month VALUE quantity",
    "rank_windows": "SELECT event_id, row_number() OVER v AS rn, rank() OVER t AS rk, dense_rank() OVER t AS dr, ntile(4) OVER v AS quarter, lag(value) OVER s AS before, lead(value) OVER s AS after, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running, first_value(value) OVER s AS first FROM events WINDOW v AS (PARTITION BY user_id ORDER BY value DESC, event_id), t AS (PARTITION BY user_id ORDER BY value DESC), s AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "hour_frame": "SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 hour PRECEDING AND CURRENT ROW) AS BIGINT) AS n_hour FROM events",
    "json_numbers": "SELECT event_type, CAST(count(*) AS BIGINT) AS n, round(avg(k), 6) AS mean_k, CAST(count(DISTINCT k) AS BIGINT) AS distinct_k FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events) GROUP BY 1",
    "grouped_sets": "SELECT lang, source, CAST(count(*) AS BIGINT) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "string_stats": "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, CAST(len(regexp_extract_all(html, '<[a-z]')) AS BIGINT) AS n_tags, md5(regexp_extract(html, '<title>([^<]*)', 1)) AS title_md5 FROM pages",
    "percentiles": "SELECT event_type, round(quantile_cont(value, 0.05), 6) AS p05, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.95), 6) AS p95, round(stddev(value), 6) AS sd FROM events GROUP BY 1",
    "id_sets": "WITH a AS (SELECT o_custkey AS k FROM orders WHERE o_orderpriority = '1-URGENT'), b AS (SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F') "
    + " UNION ALL ".join(f"SELECT '{part}' AS part, CAST(count(*) AS BIGINT) AS n FROM (SELECT k FROM a {op} SELECT k FROM b)" for part, op in (("either", "UNION"), ("all", "UNION ALL"), ("both", "INTERSECT"), ("both_all", "INTERSECT ALL"), ("first_only", "EXCEPT"), ("first_only_all", "EXCEPT ALL"))),
    "lateral_latest": "SELECT c_custkey AS custkey, CAST(o.rnk AS INTEGER) AS rnk, o.o_orderkey AS orderkey FROM customer, LATERAL (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS rnk FROM orders WHERE o_custkey = c_custkey) o WHERE o.rnk <= 2",
}
