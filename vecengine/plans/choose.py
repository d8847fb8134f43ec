"""Choice of a physical form by sizes that are known before a query runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecengine.model.codebooks import Codebooks

#: Terms up to which an unrolled sum stays in one generated method.
MOST_TERMS = 1024


def engine(n_queries: int, books: Codebooks, oracle: bool = False) -> str:
    """'relational' to restate, 'expr' for one query on few terms, else 'arrow'."""
    if oracle:
        return "relational"
    return "expr" if n_queries == 1 and books.m * books.k <= MOST_TERMS else "arrow"


def expr_sum(code: Column, table: list[list[int]]) -> Column:
    """Sum of one query's byte table over an array of codes, unrolled: literals and lookups in whole-stage code."""
    total = None
    for m, entries in enumerate(table):
        term = F.element_at(F.array(*map(F.lit, entries)), F.get(code, F.lit(m)).cast("int") + 1)
        total = term if total is None else total + term
    return total


def scan_expr(codes: DataFrame, table: list[list[int]]) -> DataFrame:
    """(vec_id, score) of (id, code array) for one query."""
    return codes.select(F.col("id").alias("vec_id"), expr_sum(F.col("code"), table).cast("long").alias("score"))


def scan_relational(codes: DataFrame, tables: DataFrame, value: str = "b") -> DataFrame:
    """(query_id, vec_id, score) of (id, m, code) and (query_id, m, i, value): the restatement for tests."""
    both = codes.join(tables, (codes.m == tables.m) & (codes.code == tables.i))
    return both.groupBy("query_id", F.col("id").alias("vec_id")).agg(F.sum(value).alias("score"))
