"""Learning of the byte quantizer of query tables: cutoffs by quantile, one scale, a grid over alpha.

Works on (query_id, m, i, y) table entries of sampled queries. The sample is bounded (queries * M * K
entries), so exact percentiles are fine; `approximate` takes mergeable sketches instead.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.model.codebooks import TableQuantizer

# The grid of shares that are cut off at either end.
GRID = (0.0, 0.001, 0.002, 0.005, 0.01, 0.02, 0.05, 0.1)
BINS = 4096  # of a table's range, where entries are counted


def _quantile(column: str, alphas: list[float], approximate: bool):
    if approximate:
        return F.percentile_approx(column, F.array(*map(F.lit, alphas)), F.lit(10_000))
    return F.percentile(column, F.array(*map(F.lit, alphas)))


def cutoffs(tables: DataFrame, alphas: tuple[float, ...] = GRID, pool: str = "shifted", per_table: bool = False, approximate: bool = False) -> DataFrame:
    """(m, alpha, offset, scale): offset is table m's alpha-quantile, scale sends the pooled cutoff to 255.

    pool: 'shifted' pools y - offset; 'raw' pools y. per_table: a scale for each table, for diagnosis.
    """
    low = tables.groupBy("m").agg(_quantile("y", list(alphas), approximate).alias("q"))
    low = low.select("m", F.posexplode("q").alias("at", "offset")).withColumn("alpha", F.element_at(F.array(*map(F.lit, alphas)), F.col("at") + 1))
    if pool == "raw":
        both = tables.agg(_quantile("y", list(alphas), approximate).alias("l"), _quantile("y", [1 - a for a in alphas], approximate).alias("h")).select(F.posexplode(F.arrays_zip("l", "h")).alias("at", "r"))
        span = both.select("at", (F.col("r.h") - F.col("r.l")).alias("span"))
        out = low.join(F.broadcast(span), "at")  # a row for each alpha
    else:
        shifted = tables.join(F.broadcast(low), "m").withColumn("z", F.col("y") - F.col("offset"))  # M rows for each alpha
        keys = ["at", "m"] if per_table else ["at"]
        level = 1 - F.element_at(F.array(*map(F.lit, alphas)), F.col("at") + 1)
        if approximate:
            span = shifted.groupBy(*keys).agg(F.percentile_approx("z", F.array(*[F.lit(1 - a) for a in alphas]), F.lit(10_000)).alias("q")).select(*keys, F.get("q", F.col("at")).alias("span"))
        else:
            span = shifted.groupBy(*keys).agg(F.percentile("z", F.array(*[F.lit(1 - a) for a in alphas])).alias("q")).select(*keys, F.get("q", F.col("at")).alias("span"))
        del level
        out = low.join(F.broadcast(span), keys)
    return out.select("m", "alpha", "offset", F.when(F.col("span") > 0, 255 / F.col("span")).otherwise(F.lit(1.0)).alias("scale"))


def byte_of(y, offset, scale):
    """Column form of the quantizer; clipped before the cast."""
    return F.greatest(F.lit(0.0), F.least(F.lit(255.0), F.floor(F.round(scale * (y - offset), 9)).cast("double")))


def grid_loss(tables: DataFrame, cut: DataFrame, usage: DataFrame | None = None, midpoint: bool = False) -> DataFrame:
    """(alpha, scale, loss): mean squared error of the entries as reconstructed, for each alpha at once.

    usage: (m, i, n) weighs an entry by how often its code occurs in the database.
    """
    both = tables.join(F.broadcast(cut), "m")  # M rows for each alpha
    back = (byte_of(F.col("y"), F.col("offset"), F.col("scale")) + (0.5 if midpoint else 0.0)) / F.col("scale") + F.col("offset")
    square = (back - F.col("y")) * (back - F.col("y"))
    if usage is None:
        return both.groupBy("alpha").agg(F.max("scale").alias("scale"), F.avg(square).alias("loss"))
    both = both.join(F.broadcast(usage), ["m", "i"])
    return both.groupBy("alpha").agg(F.max("scale").alias("scale"), (F.sum(square * F.col("n")) / F.sum("n")).alias("loss"))


def fit(tables: DataFrame, alphas: tuple[float, ...] = GRID, pool: str = "shifted", usage: DataFrame | None = None, midpoint: bool = False, approximate: bool = False) -> TableQuantizer:
    """The quantizer of least loss, the smallest alpha on ties."""
    cut = cutoffs(tables, alphas, pool, approximate=approximate).persist()
    best = grid_loss(tables, cut, usage, midpoint).orderBy("loss", "alpha").first()
    rows = cut.where(F.col("alpha") == best.alpha).orderBy("m").collect()
    cut.unpersist()
    return TableQuantizer(best.alpha, best.scale, np.array([r.offset for r in rows]), midpoint)


def fit_arrays(y: np.ndarray, alphas: tuple[float, ...] = GRID) -> TableQuantizer:
    """As `fit`, of entries at hand (queries x M x K)."""
    best: tuple | None = None
    for alpha in alphas:
        offsets = np.quantile(y, alpha, axis=(0, 2))
        z = y - offsets[:, None]
        span = float(np.quantile(z, 1 - alpha))
        scale = 255 / span if span > 0 else 1.0
        z = np.clip(np.floor(np.round(scale * z, 9)), 0, 255) / scale + offsets[:, None] - y
        loss = float((z * z).mean())
        if best is None or loss < best[0]:
            best = loss, TableQuantizer(alpha, scale, offsets)
    return best[1]


def ranges(y: np.ndarray) -> np.ndarray:
    """2 x M: least entry and, its sign turned, greatest entry of each table (queries x M x K); the least of both add up."""
    return np.stack([y.min(axis=(0, 2)), -y.max(axis=(0, 2))])


def bins(ends: np.ndarray, n: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(least entry, bins a unit, first place and number of parts of each bin) of each table: BINS equal bins, and where
    counts of these are given, each is cut into equal parts as many as its share of the entries takes of BINS more."""
    low, high = ends[0], -ends[1]
    by = np.divide(BINS, high - low, out=np.zeros(len(low)), where=high > low)
    parts = np.ones((len(low), BINS), np.int64) if n is None else 1 + BINS * n // n.sum(axis=1, keepdims=True)
    first = np.cumsum(parts, axis=1) - parts + parts.sum(axis=1).max() * np.arange(len(low))[:, None]
    return low, by, first, parts


def counted(y: np.ndarray, grid: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
    """Tables x places: entries (queries x M x K) by part of a bin."""
    low, by, first, parts = grid
    z = y - low[:, None]
    z *= by[:, None]
    at = np.minimum(z, BINS - 1).astype(np.intp)
    wide = int(parts.sum(axis=1).max())
    if wide > BINS:
        z -= at
        at += BINS * np.arange(len(low))[:, None]
        cut = parts.reshape(-1)[at]
        z *= cut
        at = first.reshape(-1)[at] + np.minimum(z, cut - 1, out=z).astype(np.intp)
    else:
        at += BINS * np.arange(len(low))[:, None]
    return np.bincount(at.reshape(-1), minlength=wide * len(low)).reshape(-1, wide)


def _level(at: np.ndarray, n: np.ndarray, share: float) -> float:
    """The value below which `share` of the counts lie; at: values in order."""
    upto = np.cumsum(n)
    return float(at[min(np.searchsorted(upto, share * (upto[-1] - 1), "right"), len(at) - 1)])


def fit_counts(n: np.ndarray, ends: np.ndarray, grid: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray], alphas: tuple[float, ...] = GRID) -> TableQuantizer:
    """As `fit_arrays`, of the counts of any number of queries: ends are exact, what lies between is taken as the middle of
    its part, which holds about 1 / BINS of its table's entries or is 1 / BINS**2 of the range."""
    low, high = ends[0], -ends[1]
    _, by, _, parts = grid
    m, at = np.nonzero(n)
    bin_of = np.concatenate([np.repeat(np.arange(BINS), p) for p in parts])
    within = np.concatenate([(np.arange(p.sum()) - np.repeat(np.cumsum(p) - p, p) + 0.5) / np.repeat(p, p) for p in parts])
    place = (np.cumsum(parts.sum(axis=1)) - parts.sum(axis=1))[m] + at
    step = np.divide(1, by, out=np.zeros(len(by)), where=by > 0)
    y, weight = low[m] + (bin_of[place] + within[place]) * step[m], n[m, at]
    best: tuple | None = None
    for alpha in alphas:
        offsets = np.array([_level(y[m == a], weight[m == a], alpha) for a in range(len(n))]) if alpha else low
        z = y - offsets[m]
        order = np.argsort(z)
        span = _level(z[order], weight[order], 1 - alpha) if alpha else float((high - low).max())
        scale = 255 / span if span > 0 else 1.0
        z = np.clip(np.floor(np.round(scale * z, 9)), 0, 255) / scale - z
        loss = float((z * z) @ weight / weight.sum())
        if best is None or loss < best[0]:
            best = loss, TableQuantizer(alpha, scale, offsets)
    return best[1]


def naive(y, scale: float = 1.0, shift: float = 0.0):
    """The weak alternative: a fixed scale and shift, truncated to a byte."""
    return F.greatest(F.lit(0.0), F.least(F.lit(255.0), F.floor(y * scale + shift).cast("double"))).cast("int")
