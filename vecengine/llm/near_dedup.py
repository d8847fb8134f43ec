"""Near-duplicate documents: MinHash bands, odd sketches, exact confirmation, star components.

Plan, for documents of any number of copies and groups of any size:

1. One pass over the text makes a row per document: the size of its shingle set, a 128-bit set
   digest, one hash for each band and a parity bitmap (odd sketch) of the MinHash samples.
2. Documents with equal sets collapse to a class, named by its smallest id, by a partial
   aggregate. All further work is on class representatives.
3. In each band bucket every member is paired with the bucket's smallest member only, so that a
   bucket of n makes n - 1 pairs. XOR population counts of the sketches reject far pairs; those
   left are confirmed on full sets. Links become components.
4. Buckets whose members lie in several components go on: all are paired with the smallest member
   outside the first component. What then still straddles components is compared across components
   only, block by block (`across`). Thus no pair that shares a band is left unexamined, none is
   made within what is already known to be one component, and only links are sent on.

A pair with similarity s shares no band with probability (1 - s ** rows) ** bands; with 32 bands
of 5 rows that is 3e-6 at s = 0.8 and less above it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C


@dataclass(frozen=True)
class NearDup:
    """words: shingle length; percent: link where 100 * shared >= percent * united."""

    words: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 5
    sketch_words: int = 4  # of 64 bits
    slack: float = 0.25  # candidates whose estimate is below the threshold by more are rejected
    pivot_rounds: int = 1
    seed: int = 20240229

    @property
    def samples(self) -> int:
        return self.bands * self.rows


# ---------------------------------------------------------------------- kernels


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, sorted within each document, and the offsets of documents."""
    raw = C.ascii_lower(raw)
    starts, ends, docs = C.word_spans(raw, offsets)
    n_docs = len(offsets) - 1
    hashes = C.span_hashes(raw, starts, ends)
    counts = np.bincount(docs, minlength=n_docs)
    first = np.cumsum(counts) - counts
    n_sh = np.where(counts == 0, 0, np.maximum(counts - words + 1, 1))
    owner = np.repeat(np.arange(n_docs), n_sh)
    at = np.arange(len(owner)) - np.repeat(np.cumsum(n_sh) - n_sh, n_sh) + first[owner]
    last = (first + counts)[owner]
    value = np.zeros(len(owner), np.uint64)
    for k in range(words):
        inside = at + k < last
        word = hashes[np.minimum(at + k, max(len(hashes) - 1, 0))] if len(hashes) else value
        value = np.where(inside, C.mix64(value * np.uint64(0x9DDFEA08EB382D69) + word), value)
    order = np.lexsort((value, owner))
    value, owner = value[order], owner[order]
    keep = np.ones(len(value), bool)
    keep[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
    value, owner = value[keep], owner[keep]
    return value, np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=n_docs))])


def signatures(value: np.ndarray, bounds: np.ndarray, p: NearDup) -> tuple[np.ndarray, np.ndarray]:
    """Band hashes (documents x bands) and odd sketches (documents x sketch_words) of non-empty sets."""
    n = len(bounds) - 1
    rng = np.random.default_rng(p.seed)
    multipliers = rng.integers(1, 1 << 32, p.samples, dtype=np.uint64).astype(np.uint32) | np.uint32(1)
    masks = rng.integers(0, 1 << 32, p.samples, dtype=np.uint64).astype(np.uint32)
    least = np.empty((p.samples, n), np.uint32)
    short = (value >> np.uint64(32)).astype(np.uint32)
    block = np.flatnonzero(np.diff(bounds // (1 << 15), prepend=-1)[:-1] > 0) if n else np.zeros(0, int)
    block = np.append(block, n)
    for lo, hi in zip(block[:-1], block[1:], strict=True):  # some 32k hashes at a time stay in cache
        part, starts = short[bounds[lo] : bounds[hi]], (bounds[lo:hi] - bounds[lo]).astype(np.intp)
        for j in range(p.samples):
            least[j, lo:hi] = np.minimum.reduceat((part ^ masks[j]) * multipliers[j], starts)
    bands = np.zeros((n, p.bands), np.uint64)
    sketch = np.zeros((n, p.sketch_words), np.uint64)
    rows = np.arange(n)
    for j in range(p.samples):
        sample = C.mix64(least[j].astype(np.uint64) + np.uint64((j + 1) * 0x9E3779B97F4A7C15 & C.MASK64))
        bands[:, j // p.rows] = C.mix64(bands[:, j // p.rows] * np.uint64(0x9DDFEA08EB382D69) + sample)
        bit = sample % np.uint64(64 * p.sketch_words)
        sketch[rows, (bit >> np.uint64(6)).astype(np.intp)] ^= np.uint64(1) << (bit & np.uint64(63))
    return bands, sketch


def _lists(values: np.ndarray, width: int) -> pa.Array:
    flat = pa.array(np.ascontiguousarray(values).reshape(-1).view(np.int64))
    return pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, width, dtype=np.int32)), flat)


def sign(docs: DataFrame, p: NearDup, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n, d1, d2, bands, sketch) for each row; n = 0 for empty sets, whose other columns are empty."""
    schema = "id long, n long, d1 long, d2 long, bands array<long>, sketch array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, offsets = C.utf8_buffer(batch.column(1))
            for i, j in C.row_slices(offsets):
                own = raw[offsets[i] : offsets[j]]
                value, bounds = shingle_sets(own, offsets[i : j + 1] - offsets[i], p.words)
                n = np.diff(bounds)
                some = n > 0
                packed = np.concatenate([[0], np.cumsum(n[some])])
                d = np.zeros((2, j - i), np.uint64)
                if some.any():
                    d[0, some] = np.add.reduceat(C.mix64(value), packed[:-1])
                    d[1, some] = np.add.reduceat(C.mix64(value + np.uint64(0x51ED270B7F4A7C15)), packed[:-1])
                bands, sketch = signatures(value, packed, p)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i).cast(pa.int64()), pa.array(n.astype(np.int64)), pa.array(d[0].view(np.int64)), pa.array(d[1].view(np.int64)), _spread(bands, some, p.bands), _spread(sketch, some, p.sketch_words)],
                    names=["id", "n", "d1", "d2", "bands", "sketch"],
                )

    return docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")).mapInArrow(run, schema)


def _spread(values: np.ndarray, some: np.ndarray, width: int) -> pa.Array:
    offsets = np.concatenate([[0], np.cumsum(some * width)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.ascontiguousarray(values).reshape(-1).view(np.int64)))


# ------------------------------------------------------------------------ pairs


def flips(a: str, b: str, p: NearDup):
    """Bits in which two sketches differ."""
    return reduce(lambda x, y: x + y, [F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i])) for i in range(p.sketch_words)])


def most_flips(p: NearDup) -> int:
    """Flips expected at the threshold less slack; an odd sketch with more stands for farther sets.

    m = 2 * samples * (1 - s) parity flips over n bits leave n / 2 * (1 - (1 - 2 / n) ** m) set.
    """
    n, s = 64 * p.sketch_words, max(0.0, p.percent / 100 - p.slack)
    return int(np.ceil(n / 2 * (1 - (1 - 2 / n) ** (2 * p.samples * (1 - s)))))


def full_sets(docs: DataFrame, wanted: DataFrame, p: NearDup) -> DataFrame:
    """(id, items) of the wanted ids: sorted 64-bit hashes of the whole set, made again from the text."""
    texts = docs.select(F.col("doc_id").alias("id"), "text", F.xxhash64("text").alias("h"), F.length("text").alias("n")).join(wanted, "id", "left_semi").dropDuplicates(["id", "h", "n"]).select("id", "text")

    def sets(batches):
        for batch in batches:
            raw, offsets = C.utf8_buffer(batch.column(1))
            for i, j in C.row_slices(offsets):
                value, bounds = shingle_sets(raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], p.words)
                data = value.tobytes()
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array([data[8 * x : 8 * y] for x, y in zip(bounds[:-1], bounds[1:], strict=True)], pa.binary())], names=["id", "items"])

    return texts.mapInArrow(sets, "id long, items binary")


def confirm(pairs: DataFrame, full: DataFrame) -> DataFrame:
    """(a, b, shared, united) of distinct pairs of ids, on full sets.

    Both joins are plain equi-joins, so an id that stands in many pairs is split by AQE.
    """
    both = pairs.select("a", "b").join(full.select(F.col("id").alias("a"), F.col("items").alias("x")), "a").join(full.select(F.col("id").alias("b"), F.col("items").alias("y")), "b")

    def compare(batches):
        for batch in batches:
            shared, united = [], []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                both = np.concatenate([x, y])
                both.sort(kind="stable")
                same = int((both[1:] == both[:-1]).sum())
                shared.append(same)
                united.append(len(both) - same)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(shared, pa.int64()), pa.array(united, pa.int64())], names=["a", "b", "shared", "united"])

    return both.select("a", "b", "x", "y").mapInArrow(compare, "a long, b long, shared long, united long")


def _possible(p: NearDup):
    """Sizes and sketches of two rows (n1, s1 and n2, s2) that leave a link possible.

    A set of x and one of y items cannot reach the threshold unless min >= percent of max.
    """
    return (100 * F.least("n1", "n2") >= p.percent * F.greatest("n1", "n2")) & (flips("s1", "s2", p) <= most_flips(p))


def links(docs: DataFrame, p: NearDup) -> tuple[DataFrame, DataFrame]:
    """(members, component table). members: doc_id, n, rep; components of representatives: id, component_id.

    docs has doc_id and text; ids are taken as given, null ids link with nothing.
    """
    signed = C.cut(sign(docs, p))
    classes = signed.where("n > 0 and id is not null").groupBy("n", "d1", "d2").agg(F.min("id").alias("rep"))
    members = signed.select("id", "n", "d1", "d2").join(classes, ["n", "d1", "d2"], "left").select(F.col("id").alias("doc_id"), "n", F.coalesce("rep", "id").alias("rep"))
    reps = signed.where("n > 0").join(classes.select(F.col("rep").alias("id")), "id", "left_semi").dropDuplicates(["id", "d1", "d2"]).select("id", "n", "bands", "sketch")
    spread = reps.select("id", F.explode("bands").alias("bucket"))  # a band's number is part of its hash
    crowded = spread.groupBy("bucket").agg(F.count(F.lit(1)).alias("size"), F.min("id").alias("pivot")).where("size > 1").drop("size")
    bucket = C.cut(spread.join(crowded, "bucket").select("bucket", "id", "pivot"))
    ids = bucket.select("id").distinct()
    bits = C.cut(reps.join(ids, "id", "left_semi"))
    full = C.cut(full_sets(docs, ids, p))

    def measured(pairs: DataFrame) -> DataFrame:
        return confirm(pairs, full).where(100 * F.col("shared") >= p.percent * F.col("united")).select("a", "b")

    # Every member against the bucket's least id.
    pairs = bucket.where("id <> pivot").select(F.col("pivot").alias("a"), F.col("id").alias("b")).distinct()
    sides = bits.select(F.col("id").alias("a"), F.col("n").alias("n1"), F.col("sketch").alias("s1")), bits.select(F.col("id").alias("b"), F.col("n").alias("n2"), F.col("sketch").alias("s2"))
    found = C.cut(measured(pairs.join(sides[0], "a").join(sides[1], "b").where(_possible(p)).select("a", "b")))
    component = C.components(found)
    for turn in range(p.pivot_rounds + 1):
        # Members of buckets that lie in several components. `asked`: it was a pivot there, so all its links there are known.
        placed = bucket.withColumn("asked", F.col("id").eqNullSafe(F.col("pivot"))).join(component, "id", "left").select("bucket", "id", "asked", F.coalesce("component_id", "id").alias("c"))
        straddling = placed.groupBy("bucket").agg(F.min("c").alias("low"), F.max("c").alias("high"), F.sum((~F.col("asked")).cast("int")).alias("open")).where("low <> high and open > 0")
        placed = C.cut(placed.join(straddling.select("bucket", "low"), "bucket"))
        if placed.isEmpty():
            break
        if turn == p.pivot_rounds:
            component = C.components(found.union(C.cut(across(placed, bits, full, p))))
            break
        # One more pivot for each bucket, outside its first component.
        rows = placed.where("not asked").join(bits, "id")
        pivot = placed.where("not asked and c <> low").groupBy("bucket").agg(F.min("id").alias("next"))
        left = rows.select("bucket", F.col("id").alias("a"), F.col("c").alias("ca"), F.col("n").alias("n1"), F.col("sketch").alias("s1")).join(pivot, "bucket").where("a = next")
        right = rows.select("bucket", F.col("id").alias("b"), F.col("c").alias("cb"), F.col("n").alias("n2"), F.col("sketch").alias("s2"))
        new = left.join(right, "bucket").where((F.col("ca") != F.col("cb")) & _possible(p)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        found = C.cut(found.union(measured(new)))
        component = C.components(found)
        bucket = placed.join(pivot, "bucket", "left").select("bucket", "id", F.when(F.col("asked") | F.col("id").eqNullSafe(F.col("next")), F.col("id")).alias("pivot"))
    return members, component


def across(placed: DataFrame, bits: DataFrame, full: DataFrame, p: NearDup, block: int = 256) -> DataFrame:
    """Links (a, b) that join components of placed (bucket, id, c): all that any shared bucket allows.

    Buckets that share members form a crowd. Of a crowd's components the largest is its main one; each
    member outside it (few, as a rule) is compared with all members, in tasks of about `block` of the
    first by `block` of the second, so a crowd of any size is spread. Within a task pairs go by
    ascending sketch distance, and a pair whose components have been linked is skipped; the sets
    are at hand, so what leaves a task is confirmed links only.
    """
    heads = placed.groupBy("bucket").agg(F.min("id").alias("b"))
    crowd = C.components(placed.select("bucket", F.col("id").alias("a")).join(heads, "bucket").select("a", "b"))
    known = C.cut(placed.select("id", "c").distinct().join(crowd.select("id", F.col("component_id").alias("crowd")), "id"))
    sizes = known.groupBy("crowd", "c").agg(F.count(F.lit(1)).alias("n"))
    plan = sizes.groupBy("crowd").agg(F.max(F.struct("n", "c")).alias("top"), F.sum("n").alias("n")).select("crowd", F.col("top.c").alias("main"), F.ceil(F.col("n") / block).alias("parts"), F.ceil((F.col("n") - F.col("top.n")) / block).alias("outer")).where("outer > 0")
    rows = known.join(plan, "crowd").join(bits.select("id", "n", "sketch"), "id").join(full, "id").select("crowd", "id", "c", "n", "sketch", "items", "main", "parts", "outer", F.xxhash64("id").alias("h"))
    keys = lambda i, j: [i.cast("long").alias("i"), j.cast("long").alias("j"), *[F.col(k).alias(k) for k in ("crowd", "id", "c", "n", "sketch", "items")]]  # noqa: E731  (aliases part the two sides)
    each = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    left = rows.where("c <> main").withColumn("j", each("parts")).select(*keys(F.pmod("h", F.col("outer")), F.col("j")))
    right = rows.withColumn("i", each("outer")).select(*keys(F.col("i"), F.pmod("h", F.col("parts"))))
    near = most_flips(p)

    def match(x: pa.Table, y: pa.Table) -> pa.Table:
        out: list[tuple[int, int]] = []
        if x.num_rows and y.num_rows:
            (xi, xc, xn), (yi, yc, yn) = ([t[c].to_numpy() for c in ("id", "c", "n")] for t in (x, y))
            xs, ys = (np.stack([np.asarray(s, np.int64) for s in t["sketch"].to_pylist()]).view(np.uint64) for t in (x, y))
            flips = np.bitwise_count(xs[:, None, :] ^ ys[None]).sum(axis=2)
            fits = (flips <= near) & (xc[:, None] != yc[None]) & (100 * np.minimum(xn[:, None], yn[None]) >= p.percent * np.maximum(xn[:, None], yn[None]))
            a, b = np.nonzero(fits)
            order = np.argsort(flips[a, b], kind="stable")
            sets = [[np.frombuffer(v.as_buffer(), np.uint64) for v in t["items"]] for t in (x, y)]
            up: dict[int, int] = {}

            def root(c: int) -> int:
                while c in up:
                    c = up[c]
                return c

            for i, j in zip(a[order].tolist(), b[order].tolist(), strict=True):
                ci, cj = root(int(xc[i])), root(int(yc[j]))
                if ci != cj:
                    both = np.concatenate([sets[0][i], sets[1][j]])
                    both.sort(kind="stable")
                    shared = int((both[1:] == both[:-1]).sum())
                    if 100 * shared >= p.percent * (len(both) - shared):
                        up[max(ci, cj)] = min(ci, cj)
                        out.append((int(xi[i]), int(yi[j])))
        return pa.table({"a": pa.array([o[0] for o in out], pa.int64()), "b": pa.array([o[1] for o in out], pa.int64())})

    return left.groupBy("crowd", "i", "j").cogroup(right.groupBy("crowd", "i", "j")).applyInArrow(match, "a long, b long")


def groups(docs: DataFrame, p: NearDup) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of docs.

    Null and wordless texts have an empty set and link with nothing. A text shorter than a shingle
    is one shingle. Rows that repeat a doc_id keep their own row and share its component: an id of
    several texts links where any of them does. Other columns of docs are ignored, whatever their
    names. An empty table gives an empty result.
    """
    docs = docs.select("doc_id", "text")
    members, component = links(docs, p)
    out = members.join(component.withColumnRenamed("id", "rep"), "rep", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "rep").alias("component_id")).withColumn("kept", F.col("doc_id") == F.col("component_id"))


def op6_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of all documents on 2-word shingles at 0.8."""
    return groups(C.table(spark, sf_dir, "documents"), NearDup(words=2))
