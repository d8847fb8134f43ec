"""Quotation linking: from messages that quote each other to reply-ordered conversations.

Lines that begin with one or more '>' are quotes of that level. Quoted passages are normalised and
hashed, and joined to the passages that messages wrote themselves: first within the conversation, to
the latest earlier message, else to the earliest message of another conversation. What equals no
passage is looked for by its lines and sentences, in the same order. A message answers the latest
message that it quotes at level 1, or the one before it.
"""

from __future__ import annotations

import re

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C

QUOTE = re.compile(r"[ \t]*((?:>[ \t]?)+)(.*)", re.S)
#: A line that introduces a quote.
INTRO = re.compile(r"\s*(?:(?:on|am|le|el)\b.{0,200}\b(?:wrote|schrieb|écrit|a écrit|escribió)\s*:|-{2,}\s*original message\s*-{2,}|in reply to .{0,200}:)\s*", re.I)


def normal(text: str) -> str:
    return " ".join(text.casefold().split())


def key_of(text: str) -> int:
    """Signed 64-bit hash of a passage's normal form."""
    value = xxhash.xxh64_intdigest(normal(text).encode("utf-8", "surrogatepass"))
    return value - (1 << 64) if value >= 1 << 63 else value


def blocks(text: str) -> list[tuple[int, str]]:
    """(level, text) of the runs of lines of one level in order; introductions of quotes are left out."""
    out: list[tuple[int, list[str]]] = []
    for line in text.split("\n"):
        m = QUOTE.fullmatch(line)
        level, body = (m[1].count(">"), m[2]) if m else (0, line)
        if out and out[-1][0] == level:
            out[-1][1].append(body)
        else:
            out.append((level, [body]))
    for (level, lines), (after, _) in zip(out, out[1:], strict=False):
        if after > level:
            while lines and not lines[-1].strip():
                lines.pop()
            if lines and INTRO.fullmatch(lines[-1]):
                lines.pop()
    return [(level, "\n".join(lines)) for level, lines in out]


def paragraphs(text: str) -> list[str]:
    return [p for p in re.split(r"\n[ \t]*\n", text) if p.strip()]


SENTENCE = re.compile(r"(?<=[.!?…])\s+|(?<=[。！？])\s*")
#: What a trimmed quote loses or gains at its ends.
TRIM = " \t\n.…[]"


def pieces(text: str) -> list[int]:
    """Hashes of a passage's lines and sentences, without marks of trimming; a sentence may go over several lines."""
    found = [*text.split("\n"), *(x for p in paragraphs(text) for x in SENTENCE.split(p))]
    return list(dict.fromkeys(key_of(x) for x in (y.strip(TRIM) for y in found) if x))


def parse(text: str | None) -> tuple[str, list[int], list[tuple[int, int, list[int]]]]:
    """Own text without quotes, hashes of own passages, and (level, hash, hashes of pieces) of quoted ones.

    Own passages are the whole, its blocks and their paragraphs; a quoted block counts whole, and by
    paragraphs where it has several.
    """
    parts = blocks((text or "").replace("\r\n", "\n"))
    own = [body.strip("\n") for level, body in parts if level == 0 and body.strip()]
    whole = "\n".join(own).strip()
    made = dict.fromkeys(key_of(x) for x in [whole, *own, *(p for b in own for p in paragraphs(b))] if x.strip())
    quoted = []
    for level, body in parts:
        if level and body.strip():
            several = paragraphs(body)
            quoted += [(level, key_of(x), pieces(x)) for x in ([body, *several] if len(several) > 1 else [body])]
    return whole, list(made), quoted


def parsed(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text, own array<long>, quoted array<struct<level, key, pieces>>) of each row."""

    def run(batches):
        for batch in batches:
            rows = [parse(x) for x in batch.column(3).to_pylist()]
            quoted = pa.array([[{"level": a, "key": b, "pieces": c} for a, b, c in r[2]] for r in rows], pa.list_(pa.struct([("level", pa.int32()), ("key", pa.int64()), ("pieces", pa.list_(pa.int64()))])))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.list_(pa.int64())), quoted], names=["conv_id", "turn", "role", "text", "own", "quoted"])

    picked = messages.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), F.col("role").cast("string"), F.col("text").cast("string"))
    return picked.mapInArrow(run, "conv_id long, turn long, role string, text string, own array<long>, quoted array<struct<level: int, key: long, pieces: array<long>>>")


def earlier(asks: DataFrame, wrote: DataFrame) -> DataFrame:
    """asks (conv_id, turn, key, ...) with from_turn: the latest earlier turn of the conversation that wrote the key, or null."""
    extra = [c for c in asks.columns if c not in ("conv_id", "turn", "key")]
    own = wrote.select("conv_id", "turn", "key", F.lit(1).cast("long").alias("writes"), *(F.lit(None).cast(asks.schema[c].dataType).alias(c) for c in extra))
    both = own.union(asks.select("conv_id", "turn", "key", F.lit(0).cast("long"), *extra))  # of one turn, asks come first
    found = C.carried(both, ["conv_id", "key"], ["turn", "writes"], F.when(F.col("writes") == 1, F.col("turn")))
    return found.where("writes = 0").withColumnRenamed("last", "from_turn").drop("writes", "place")


def outside(asks: DataFrame, wrote: DataFrame) -> DataFrame:
    """asks (conv_id, key, ...) with `first` (conv_id, turn): the earliest author of the key in another conversation, or null."""
    first = wrote.groupBy("key").agg(F.min(F.struct("conv_id", "turn")).alias("first"))
    out = C.cut(asks.join(first, "key", "left"))
    own = out.where("first.conv_id = conv_id").select("key", F.col("conv_id").alias("mine")).distinct()
    if own.isEmpty():
        return out
    second = wrote.join(own, "key").where("conv_id <> mine").groupBy("key").agg(F.min(F.struct("conv_id", "turn")).alias("second"))
    out = out.join(second, "key", "left")
    return out.withColumn("first", F.when(F.col("first.conv_id") == F.col("conv_id"), F.col("second")).otherwise(F.col("first"))).drop("second")


def own_pieces(rows: DataFrame) -> DataFrame:
    """(conv_id, turn, key) of the lines and sentences of own texts."""

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array([pieces(x or "") for x in batch.column(2).to_pylist()], pa.list_(pa.int64()))], names=["conv_id", "turn", "keys"])

    return rows.select("conv_id", "turn", "text").mapInArrow(run, "conv_id long, turn long, keys array<long>").select("conv_id", "turn", F.explode("keys").alias("key"))


def linked(rows: DataFrame) -> DataFrame:
    """(conv_id, turn, level, key, n, from_conv, from_turn) of each quoted passage; from_* is null where none is found.

    A passage that is found by pieces is linked to the message that wrote most of them: the latest of
    the conversation's, or the earliest elsewhere.
    """
    wrote = rows.select("conv_id", "turn", F.explode("own").alias("key")).distinct()
    told = rows.select("conv_id", "turn", F.explode("quoted").alias("q"))
    quotes = told.select("conv_id", "turn", "q.level", "q.key").groupBy("conv_id", "turn", "key").agg(F.min("level").alias("level"), F.count(F.lit(1)).alias("n"))
    near = C.cut(earlier(quotes, wrote))
    shown = ["conv_id", "turn", "level", "key", "n"]
    done = near.where("from_turn is not null").select(*shown, F.col("conv_id").alias("from_conv"), "from_turn")
    left = near.where("from_turn is null").select(*shown)
    if left.isEmpty():
        return done
    passage = ["conv_id", "turn", "passage"]
    asks = told.select("conv_id", "turn", F.col("q.key").alias("passage"), F.explode("q.pieces").alias("key")).join(left.select("conv_id", "turn", F.col("key").alias("passage")), passage, "left_semi").distinct()
    parts = own_pieces(rows)

    def voted(hits: DataFrame, of: list, order) -> DataFrame:
        """Of each passage the author of most pieces, by `order` on ties."""
        count = hits.groupBy(*passage, *of).agg(F.count(F.lit(1)).alias("c"))
        return count.groupBy(*passage).agg(F.max_by(F.struct(*of), F.struct("c", *order)).alias("a")).withColumnRenamed("passage", "key")

    def split_off(found: DataFrame, conv, turn) -> None:
        nonlocal done, left
        both = C.cut(left.join(found, ["conv_id", "turn", "key"], "left"))
        done = done.union(both.where("a is not null").select(*shown, conv.alias("from_conv"), turn.alias("from_turn")))
        left = both.where("a is null").select(*shown)

    split_off(voted(earlier(asks, parts).where("from_turn is not null"), ["from_turn"], ["from_turn"]), F.col("conv_id"), F.col("a.from_turn"))
    far = F.col("a.conv_id"), F.col("a.turn")
    split_off(outside(left.select("conv_id", "turn", "key"), wrote).select("conv_id", "turn", "key", F.col("first").alias("a")), *far)
    if not left.isEmpty():
        still = asks.join(left.select("conv_id", "turn", F.col("key").alias("passage")), passage, "left_semi")
        hits = outside(still, parts).where("first is not null").select(*passage, F.col("first.conv_id").alias("c_id"), F.col("first.turn").alias("c_turn"))
        best = voted(hits, ["c_id", "c_turn"], [F.bitwise_not("c_id"), F.bitwise_not("c_turn")])
        split_off(best, F.col("a.c_id"), F.col("a.c_turn"))
    none = F.lit(None).cast("long")
    return done.union(left.select(*shown, none.alias("from_conv"), none.alias("from_turn")))


def conversations(messages: DataFrame) -> DataFrame:
    """Messages without quotes in reply order.

    (conv_id, turn, role, text, parent_turn, linked_by, depth, position, n_quotes, n_linked) for each
    distinct (conv_id, turn) of messages (conv_id, turn, role, text): linked_by is 'quote', 'order' or
    'root'; depth counts replies from the root; position orders a conversation by thread, and within
    it a reply never stands before what it answers. Quotes of other conversations count as linked and
    give no parent. Rows that share conv_id and turn become one, with the least role and text; null
    ids are ids like others, null texts are empty. Other columns are ignored.
    """
    rows = parsed(messages)
    one = rows.groupBy("conv_id", "turn").agg(F.min(F.struct("role", "text", "own", F.transform("quoted", lambda q: F.struct(q["level"].alias("level"), q["key"].alias("key"), q["pieces"].alias("pieces"))).alias("quoted"))).alias("m"))
    rows = C.cut(one.select(F.coalesce("conv_id", F.lit(-(1 << 63))).alias("conv_id"), F.coalesce("turn", F.lit(-(1 << 63))).alias("turn"), "m.role", "m.text", "m.own", "m.quoted"))
    links = linked(rows)
    found = links.groupBy("conv_id", "turn").agg(
        F.sum("n").alias("n_quotes"),
        F.sum(F.when(F.col("from_turn").isNotNull(), F.col("n")).otherwise(0)).alias("n_linked"),
        F.max(F.when((F.col("level") == 1) & (F.col("from_conv") == F.col("conv_id")), F.col("from_turn"))).alias("quoted_turn"),
    )
    lines = C.carried(rows.select("conv_id", "turn"), ["conv_id"], ["turn"], F.col("turn"))
    placed = lines.select("conv_id", "turn", F.col("last").alias("before")).join(found, ["conv_id", "turn"], "left")
    parent = F.coalesce("quoted_turn", "before")
    by = F.when(F.col("quoted_turn").isNotNull(), "quote").when(F.col("before").isNotNull(), "order").otherwise("root")
    placed = C.cut(placed.select("conv_id", "turn", parent.alias("parent_turn"), by.alias("linked_by"), F.coalesce("n_quotes", F.lit(0)).alias("n_quotes"), F.coalesce("n_linked", F.lit(0)).alias("n_linked")))
    # Depth and root by pointer doubling: parents are earlier turns, so there is no cycle. Only rows that
    # have not come to their root (`open`) are joined again.
    hop = placed.select("conv_id", "turn", F.coalesce("parent_turn", "turn").alias("up"), F.col("parent_turn").isNotNull().cast("long").alias("depth"), F.col("parent_turn").isNotNull().alias("open"))
    while True:
        pending = hop.where("open")
        if pending.isEmpty():
            break
        above = hop.select("conv_id", F.col("turn").alias("up"), F.col("up").alias("higher"), F.col("depth").alias("more"), F.col("open").alias("on"))
        moved = pending.join(above, ["conv_id", "up"]).select("conv_id", "turn", F.col("higher").alias("up"), (F.col("depth") + F.col("more")).alias("depth"), F.col("on").alias("open"))
        hop = C.cut(hop.where("not open").union(moved))
    hop = hop.drop("open")
    threads = C.carried(hop.withColumnRenamed("up", "root"), ["conv_id"], ["root", "turn"], F.lit(None).cast("long")).select("conv_id", "turn", "depth", F.col("place").alias("position"))
    out = rows.select("conv_id", "turn", "role", "text").join(placed, ["conv_id", "turn"]).join(threads, ["conv_id", "turn"])
    null = lambda c: F.nullif(c, F.lit(-(1 << 63)))
    return out.select(null("conv_id").alias("conv_id"), null("turn").alias("turn"), "role", "text", null("parent_turn").alias("parent_turn"), "linked_by", "depth", "position", F.col("n_quotes").cast("long").alias("n_quotes"), F.col("n_linked").cast("long").alias("n_linked"))


def as_mail(messages: DataFrame) -> DataFrame:
    """Messages in mail style: each quotes the one before at level 1 and the one before that at level 2.

    Rows that share conv_id and turn are told in the order of a hash of role and text, equal ones as one.
    """
    quote = lambda c, mark: F.concat(F.lit(mark), F.replace(c, F.lit("\n"), F.lit("\n" + mark)), F.lit("\n"))
    null = lambda c: F.coalesce(F.col(c).cast("long"), F.lit(-(1 << 63)))
    told = messages.select(null("conv_id").alias("conv_id"), null("turn").alias("turn"), "role", F.col("text").alias("said"), F.xxhash64("role", "text").alias("h"))
    told = told.dropDuplicates(["conv_id", "turn", "h"])
    placed = C.carried(told.select("conv_id", "turn", "h"), ["conv_id"], ["turn", "h"], F.lit(None).cast("long")).drop("last")
    told = C.cut(told.join(placed, ["conv_id", "turn", "h"]))
    ago = lambda n, name: told.where("said is not null").select("conv_id", (F.col("place") + n).alias("place"), F.col("said").alias(name))
    told = told.join(ago(1, "one"), ["conv_id", "place"], "left").join(ago(2, "two"), ["conv_id", "place"], "left")
    back = lambda c: F.nullif(F.col(c), F.lit(-(1 << 63))).alias(c)
    return told.select(back("conv_id"), back("turn"), "role", F.concat(F.coalesce(quote(F.col("two"), ">> "), F.lit("")), F.coalesce(quote(F.col("one"), "> "), F.lit("")), F.coalesce("said", F.lit(""))).alias("text"))


def op8_chat_quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations written out in mail style, then read back: quotes linked and taken off, replies ordered."""
    return conversations(as_mail(C.table(spark, sf_dir, "conversations")))
