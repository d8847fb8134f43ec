"""Document fingerprints from closed syncmers over words, in DataFrame functions only.

The alphabet is words (an ideograph or a syllable block counts as one, a run of other characters
as pieces of at most PIECE). Of each run of k words the hashes of its inner runs of s words are
compared; the run is an anchor where the least of them stands first or last. That depends on
nothing outside the run, so equal passages give equal anchors wherever they stand, and any
k - s + 1 neighbouring runs hold at least one anchor.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecengine.llm import common as C

PIECE = 32
LEAST = -(1 << 63)
#: CJK radicals to unified ideographs, Hangul syllables, compatibility ideographs.
SINGLE = r"⺀-鿿가-힯豈-﫿"
SPACE = " \t\n\x0b\f\r"


def let(value: Column, body) -> Column:
    """body(value) with value computed once for the row."""
    return F.transform(F.array(value), body)[0]


def tokens(text: Column) -> Column:
    """The words of a text in order, by one split: what stands alone is first set apart by spaces, and only texts
    with a word longer than PIECE are gone over again."""
    apart = F.when(text.rlike(f"[{SINGLE}]"), F.regexp_replace(text, f"([{SINGLE}])", " $1 ")).otherwise(text)
    long = lambda w: F.length(w) > PIECE
    cut = lambda w: F.transform(F.sequence(F.lit(1), F.length(w), F.lit(PIECE)), lambda i: F.substr(w, i, F.lit(PIECE)))

    def pieces(words: Column) -> Column:
        return F.when(F.exists(words, long), F.flatten(F.transform(words, lambda w: F.when(long(w), cut(w)).otherwise(F.array(w))))).otherwise(words)

    def words(t: Column) -> Column:
        return F.when(t == "", F.array().cast("array<string>")).otherwise(let(F.split(t, f"[{SPACE}]+"), pieces))

    return let(F.btrim(apart, F.lit(SPACE)), words)


def anchors(text: Column, k: int = 4, s: int = 2) -> Column:
    """array<struct<h, at>>: hash and 1-based word position of each anchor, in text order.

    A text of fewer than k words is a single anchor of all its words at 1; a wordless one has none.
    """
    hashes = F.transform(tokens(text), lambda t: F.xxhash64(t))
    width = k - s + 1

    def inner(h: Column) -> Column:
        """Hashes of the runs of s words."""
        runs = h
        for j in range(1, s):
            runs = F.zip_with(F.slice(runs, F.lit(1), F.size(runs) - 1), F.slice(h, F.lit(j + 1), F.size(h) - j), lambda a, b: F.xxhash64(a, b))
        return runs

    def chosen(g: Column) -> Column:
        """Of the runs of `width` neighbouring hashes, those whose least stands at an edge."""
        names = [f"g{j}" for j in range(width)]
        rows = F.arrays_zip(*[F.slice(g, F.lit(j + 1), F.size(g) - (width - 1)).alias(n) for j, n in enumerate(names)])

        def pick(x: Column, i: Column) -> Column:
            middle = [x[n] for n in names[1:-1]]
            closed = F.least(x[names[0]], x[names[-1]]) <= (F.least(*middle) if len(middle) > 1 else middle[0])
            return F.when(closed, F.struct(F.xxhash64(*[x[names[j]] for j in sorted({*range(0, width, s), width - 1})]).alias("h"), (i + 1).alias("at")))

        return F.filter(F.transform(rows, pick), lambda x: x.isNotNull())

    def all_of(h: Column) -> Column:
        whole = F.array(F.struct(F.aggregate(h, F.lit(0).cast("long"), lambda a, x: F.xxhash64(a, x)).alias("h"), F.lit(1).alias("at")))
        none = F.filter(whole, lambda x: F.lit(False))
        return F.when(F.size(h) == 0, none).when(F.size(h) < k, whole).otherwise(let(inner(h), chosen))

    return let(hashes, all_of)


def sketch(text: Column, keep: int = 64, k: int = 4, s: int = 2) -> Column:
    """The `keep` anchors of least hash, each hash once at its first place, by hash: a short form for display and lookup."""
    return least(anchors(text, k, s), keep)


def least(found: Column, keep: int = 64) -> Column:
    """sketch() of a text whose anchors are at hand."""

    def first(a: Column) -> Column:
        return F.filter(F.transform(F.sequence(F.lit(1), F.size(a)), lambda i: F.when((i == 1) | (F.element_at(a, i)["h"] != F.element_at(a, F.greatest(i - 1, F.lit(1)))["h"]), F.element_at(a, i))), lambda x: x.isNotNull())

    bound = (F.lit(float(LEAST)) + F.lit(2.0**64 * 3 * keep) / F.size(found)).cast("long")  # about 3 * keep hashes are below
    some = let(F.filter(found, lambda x: x["h"] <= bound), lambda c: F.when(F.size(F.array_distinct(F.transform(c, lambda x: x["h"]))) >= keep, c).otherwise(found))
    few = F.when(F.size(found) <= 4 * keep, found).otherwise(some)
    ordered = let(F.sort_array(few), lambda a: F.when(F.size(a) == 0, a).otherwise(first(a)))
    return F.slice(ordered, 1, keep)


def render(fp: Column) -> Column:
    """Text form: 16 hex digits, '@' and position for each anchor."""
    return F.array_join(F.transform(fp, lambda x: F.concat(F.lpad(F.lower(F.hex(x["h"])), 16, "0"), F.lit("@"), x["at"].cast("string"))), " ")


def hash_set(found: Column) -> Column:
    return F.array_distinct(F.transform(found, lambda x: x["h"]))


def overlap(x: Column, y: Column) -> Column:
    """Share of common hashes among those of either set, 0 to 1. Two empty sets are alike (1); an empty and another are not (0)."""
    return let(F.size(F.array_intersect(x, y)), lambda n: F.when(F.size(x) + F.size(y) == 0, F.lit(1.0)).otherwise(n / (F.size(x) + F.size(y) - n)))


def likeness(a: Column, b: Column) -> Column:
    """overlap() of the anchor sets of two texts as they are."""
    return let(F.struct(hash_set(a).alias("x"), hash_set(b).alias("y")), lambda p: overlap(p["x"], p["y"]))


def matches(a: Column, b: Column) -> Column:
    """array<struct<at_a, at_b, shift>> of each pair of places at which an anchor stands in both: positional matching.

    By hash, then place. Both sides are sorted as one, so that only equal neighbours meet.
    """
    side = lambda fp, n: F.transform(fp, lambda x: F.struct(x["h"].alias("h"), F.lit(n).alias("side"), x["at"].alias("at")))

    def pairs(run: Column) -> Column:
        there = F.filter(run, lambda y: y["side"] == 1)
        return F.flatten(F.transform(F.filter(run, lambda x: x["side"] == 0), lambda x: F.transform(there, lambda y: F.struct(x["at"].alias("at_a"), y["at"].alias("at_b"), (y["at"] - x["at"]).alias("shift")))))

    def runs(s: Column) -> Column:
        at = lambda i: F.element_at(s, i.cast("int"))["h"]
        starts = F.filter(F.sequence(F.lit(1), F.size(s)), lambda i: (i == 1) | (at(i) != at(F.greatest(i - 1, F.lit(1)))))
        return let(starts, lambda p: F.flatten(F.transform(F.arrays_zip(p.alias("i"), F.concat(F.slice(p, F.lit(2), F.size(p) - 1), F.array(F.size(s) + 1)).alias("j")), lambda r: let(F.slice(s, r["i"], r["j"] - r["i"]), pairs))))

    none = F.filter(F.array(F.struct(F.lit(0).alias("at_a"), F.lit(0).alias("at_b"), F.lit(0).alias("shift"))), lambda x: F.lit(False))
    return let(F.sort_array(F.concat(side(a, 0), side(b, 1))), lambda s: F.when(F.size(s) == 0, none).otherwise(runs(s)))


def followers(keys: DataFrame) -> DataFrame:
    """keys: distinct (kid, h, n). Adds nk, nh: the next key in order, after the last the first.

    Keys are range-partitioned and numbered by partition; only a partition's ends look beyond it, in
    a table of one row a partition.
    """
    ranged = C.cut(keys.repartitionByRange("kid", "h").withColumn("part", F.spark_partition_id()))
    own = Window.partitionBy("part").orderBy("kid", "h")
    led = ranged.withColumn("next", F.lead(F.struct("kid", "h")).over(own))
    heads = ranged.groupBy("part").agg(F.min(F.struct("kid", "h")).alias("head"))
    line = Window.orderBy("part")
    ends = heads.select("part", F.coalesce(F.lead("head").over(line), F.first("head").over(line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("after"))
    out = led.join(F.broadcast(ends), "part").withColumn("next", F.coalesce("next", "after"))  # a row a partition
    return out.select("kid", "h", "n", F.col("next.kid").alias("nk"), F.col("next.h").alias("nh"))


def compare_with_next(docs: DataFrame, keep: int = 64) -> DataFrame:
    """Anchors of each text and of its edit with the next document, and the likeness of the whole texts.

    anchors and edited_anchors hold every anchor in text order, and near_edited and near_next compare
    all of them; fingerprint and edited_fingerprint show the `keep` of least hash.

    The edited text is the text with its last floor(n_chars / 2) code points replaced by the first
    as many, or all, of the next document by ascending doc_id; after the last comes the first, and
    a lone document follows itself. Null texts are empty. A null doc_id comes first. Rows that
    repeat an id are ordered by a hash of their text; equal rows share one result. Other columns
    are ignored. An empty table gives an empty result.
    """
    base = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST)).alias("kid"), F.coalesce("text", F.lit("")).alias("text"))
    base = base.select("kid", F.xxhash64("text").alias("h"), "text")
    order = C.cut(followers(base.select("kid", "h", F.length("text").alias("n")).distinct()))
    give = order.select(F.col("nk").alias("kid"), F.col("nh").alias("h"), F.col("kid").alias("to_kid"), F.col("h").alias("to_h"), (F.col("n") / 2).cast("int").alias("need"))
    given = base.join(give, ["kid", "h"]).select("to_kid", "to_h", F.col("text").alias("after"), "need")
    given = given.withColumnsRenamed({"to_kid": "kid", "to_h": "h"}).dropDuplicates(["kid", "h"])
    both = base.join(given, ["kid", "h"])
    both = both.select("kid", F.length("text").alias("n"), anchors(F.col("text")).alias("own"), hash_set(anchors(F.col("after"))).alias("next"), F.expr("concat(substring(text, 1, length(text) - need), substring(after, 1, need))").alias("edited"))
    both = both.select("kid", "n", "own", "next", hash_set(F.col("own")).alias("have"), F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"), anchors(F.col("edited")).alias("changed"))
    return both.select(
        F.nullif("kid", F.lit(LEAST)).alias("doc_id"),
        F.col("n").cast("long").alias("n_chars"),
        "edited_sha256",
        render(least(F.col("own"), keep)).alias("fingerprint"),
        render(least(F.col("changed"), keep)).alias("edited_fingerprint"),
        overlap(F.col("have"), hash_set(F.col("changed"))).alias("near_edited"),
        overlap(F.col("have"), F.col("next")).alias("near_next"),
        F.col("own").alias("anchors"),
        F.col("changed").alias("edited_anchors"),
    )


def op9_closed_syncmers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of all documents and of their edits."""
    return compare_with_next(C.table(spark, sf_dir, "documents"))
