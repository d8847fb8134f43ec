"""SentencePiece encoding and decoding by a batched Viterbi pass in numpy.

Text is split into units that no piece can cross (before a run of spaces, around characters that
stand in no longer piece). Distinct units of a batch are encoded once. All their substrings are
probed at once, by 64-bit hash, in the sorted keys of the pieces. Then all units advance together,
one character a step, the ended ones falling out: for each length of the last piece the candidates
are compared and the best one's backpointer is stored. One backward pass reads the pieces off.

For a unigram vocabulary the path of the greatest sum of scores is kept. For a merge vocabulary
(BPE) scores are merge ranks, whose sum means nothing; there a candidate is admissible only where
merging would leave its boundary standing, which is a property of the two pieces that meet. Exactly
one path of admissible pieces ends at each place, and it is what merging gives; so the ids are those
of the library for either kind.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C

MARK = "▁"  # stands for a space in pieces
TOKENIZERS = "/opt/tokenizers"
LONG = 512  # characters of a unit beyond which it is encoded by itself


@dataclass
class Vocabulary:
    """Pieces as arrays; a space is kept as one byte in place of the mark."""

    kind: str  # 'unigram' or 'bpe'
    data: bytes  # all pieces, one after another, by id; byte pieces as their byte, special ones empty
    bounds: np.ndarray
    scores: np.ndarray
    keys: np.ndarray  # sorted hashes of ordinary pieces
    ids: np.ndarray  # their ids
    byte_ids: np.ndarray  # of the 256 byte pieces, or empty
    unknown: int
    prefix: bool
    longest: int
    alone: np.ndarray  # for each byte: an ASCII character in no longer piece
    rank: np.ndarray  # by id: place in merge order; single characters before all
    by_rank: np.ndarray
    left: np.ndarray  # by rank: ranks of the two pieces that merge into it, itself for a character
    right: np.ndarray
    pair_keys: np.ndarray  # sorted left * size + right
    pair_ranks: np.ndarray

    @cached_property
    def sieve(self) -> np.ndarray:
        """By the leading 20 bits of a hash: whether any key has them."""
        out = np.zeros(1 << 20, bool)
        out[(self.keys >> np.uint64(44)).astype(np.int64)] = True
        return out

    @property
    def floor(self) -> np.float32:
        """Score of an unknown character."""
        return np.float32(self.scores[self.ids].min() - np.float32(10))


def merges(text: str, score: dict[str, float]) -> list[str]:
    """Pieces of a text by best-first merging: the plain form for one unit."""
    part = list(text)
    before, after = list(range(-1, len(part) - 1)), [*range(1, len(part)), -1]
    queue: list = []

    def offer(i: int) -> None:
        j = after[i] if i >= 0 else -1
        if i >= 0 and j >= 0 and (s := score.get(part[i] + part[j])) is not None:
            heapq.heappush(queue, (-s, i, len(part[i]) + len(part[j])))

    for i in range(len(part) - 1):
        offer(i)
    while queue:
        _, i, size = heapq.heappop(queue)
        j = after[i] if part[i] else -1
        if j < 0 or not part[i] or len(part[i]) + len(part[j]) != size:
            continue
        part[i] += part[j]
        part[j] = ""
        after[i] = after[j]
        if after[j] >= 0:
            before[after[j]] = i
        offer(before[i])
        offer(i)
    return [x for x in part if x]


def load(path: str) -> Vocabulary:
    """Read a model file. Only the identity normaliser is known; others are refused."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    model = pb.ModelProto()
    with open(path, "rb") as f:
        model.ParseFromString(f.read())
    return build(model)


def build(model) -> Vocabulary:
    spec = model.normalizer_spec
    if spec.precompiled_charsmap or spec.remove_extra_whitespaces or model.trainer_spec.treat_whitespace_as_suffix or model.trainer_spec.model_type not in (1, 2):
        raise ValueError("only unigram and BPE models with the identity normaliser are supported")
    kind = "unigram" if model.trainer_spec.model_type == 1 else "bpe"
    texts, ordinary, byte_ids, unknown = [], [], {}, 0
    for i, p in enumerate(model.pieces):
        text = p.piece.replace(MARK, " ")
        if p.type == 6:
            byte_ids[int(p.piece[3:5], 16)] = i
            texts.append(bytes([int(p.piece[3:5], 16)]))
        elif p.type in (1, 4):
            ordinary.append(i)
            texts.append(text.encode())
            if text.lstrip(" ").find(" ") >= 0:
                raise ValueError("a piece spans words")
        else:
            unknown = i if p.type == 2 else unknown
            texts.append(b"")
    data = b"".join(texts)
    bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    raw = np.frombuffer(data, np.uint8)
    scores = np.array([p.score for p in model.pieces], np.float32)
    own = np.array(ordinary)
    hashes = C.span_hashes(raw, bounds[own], bounds[own + 1])
    order = np.argsort(hashes)
    chars = {i: texts[i].decode() for i in ordinary}
    alone = np.zeros(256, bool)
    alone[:128] = True
    for t in chars.values():
        if len(t) > 1:
            alone[np.frombuffer(t.encode(), np.uint8)] = False
    alone[32] = False
    longest = max(map(len, chars.values()))
    size = len(texts)
    rank = np.full(size, -1, np.int64)
    ranked = sorted(ordinary, key=lambda i: (len(chars[i]) > 1, -scores[i] if len(chars[i]) > 1 else 0, i))
    rank[ranked] = np.arange(len(ranked))
    by_rank = np.array(ranked)
    left = np.arange(len(ranked))
    right = np.arange(len(ranked))
    pairs = {}
    if kind == "bpe":
        score = {t: float(scores[i]) for i, t in chars.items()}
        of = {t: int(rank[i]) for i, t in chars.items()}
        for i, t in chars.items():
            if len(t) > 1:
                less = {k: v for k in {t[a:b] for a in range(len(t)) for b in range(a + 2, len(t) + 1)} if k != t and (v := score.get(k)) is not None}
                two = merges(t, less)
                if len(two) == 2 and all(x in of for x in two):
                    r = int(rank[i])
                    left[r], right[r] = of[two[0]], of[two[1]]
                    pairs[of[two[0]] * len(ranked) + of[two[1]]] = r
    pair_keys = np.array(sorted(pairs), np.int64)
    return Vocabulary(
        kind, data, bounds, scores, hashes[order], own[order], np.array([byte_ids[b] for b in range(256)] if len(byte_ids) == 256 else [], np.int64), unknown,
        spec.add_dummy_prefix, longest, alone, rank, by_rank, left, right, pair_keys, np.array([pairs[k] for k in pair_keys.tolist()], np.int64),
    )


def _meets(v: Vocabulary, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether merging leaves the boundary between pieces of ranks a and b; ranks under 0 meet anything.

    Walks the two merge trees down along the boundary, the later merge first: the boundary falls
    where a pair across it merges before the pieces on either side of it were made.
    """
    out = np.ones(len(a), bool)
    at = np.flatnonzero((a >= 0) & (b >= 0))
    a, b = a[at], b[at]
    limit = np.full(len(at), len(v.by_rank) + 1, np.int64)
    size = len(v.by_rank)
    while len(at):
        key = a * size + b
        i = np.minimum(np.searchsorted(v.pair_keys, key), max(len(v.pair_keys) - 1, 0))
        joined = (v.pair_keys[i] == key) & (v.pair_ranks[i] < limit) if len(v.pair_keys) else np.zeros(len(at), bool)
        out[at[joined]] = False
        la, rb = v.right[a], v.left[b]
        fixed_a, fixed_b = la == a, rb == b
        down_a = ~fixed_a & ((a > b) | fixed_b)
        down_b = ~fixed_b & ~down_a
        limit = np.where(down_a, a, np.where(down_b, b + 1, limit))
        a, b = np.where(down_a, la, a), np.where(down_b, rb, b)
        go = ~joined & (down_a | down_b)
        at, a, b, limit = at[go], a[go], b[go], limit[go]
    return out


def _ragged(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Concatenated ranges [start, start + count)."""
    total = int(counts.sum())
    return np.repeat(starts - (np.cumsum(counts) - counts), counts) + np.arange(total)


class Encoder:
    """Encodes batches; keeps the ids of units it has met, up to a bound."""

    def __init__(self, v: Vocabulary, most_units: int = 400_000) -> None:
        self.v, self.most = v, most_units
        self.clear()

    def clear(self) -> None:
        self.keys = np.zeros(0, np.uint64)
        self.start = np.zeros(0, np.int64)
        self.count = np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.int32)

    def encode(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, bounds by document) of UTF-8 texts."""
        v, n = self.v, len(offsets) - 1
        raw, offsets = _spaces(raw, offsets)
        if v.prefix:
            some = np.diff(offsets) > 0
            raw = np.insert(raw, offsets[:-1][some], 32)
            offsets = offsets + np.concatenate([[0], np.cumsum(some)])
        if not len(raw):
            return np.zeros(0, np.int32), np.zeros(n + 1, np.int64)
        space, alone = raw == 32, v.alone[raw]
        cut = alone | space
        cut[1:] &= alone[1:] | ~space[:-1]
        cut[1:] |= alone[:-1]
        cut[offsets[:-1][np.diff(offsets) > 0]] = True
        starts = np.flatnonzero(cut)
        ends = np.append(starts[1:], len(raw))
        prefix = C.prefix_hashes(raw)
        units, first, which = np.unique(C.span_hashes(raw, starts, ends, prefix), return_index=True, return_inverse=True)
        at = np.minimum(np.searchsorted(self.keys, units), max(len(self.keys) - 1, 0))
        new = self.keys[at] != units if len(self.keys) else np.ones(len(units), bool)
        if new.any():
            if len(self.keys) + new.sum() > self.most:
                self.clear()
                new[:] = True
            ids, counts = self._units(raw, starts[first[new]], ends[first[new]], prefix)
            keys = np.concatenate([self.keys, units[new]])
            order = np.argsort(keys, kind="stable")
            self.start = np.concatenate([self.start, len(self.flat) + np.cumsum(counts) - counts])[order]
            self.count = np.concatenate([self.count, counts])[order]
            self.keys, self.flat = keys[order], np.concatenate([self.flat, ids.astype(np.int32)])
            at = np.searchsorted(self.keys, units)
        counts = self.count[at][which]
        docs = np.searchsorted(offsets, starts, side="right") - 1
        ids = self.flat[_ragged(self.start[at][which], counts)]
        return ids, np.concatenate([[0], np.cumsum(np.bincount(docs, weights=counts, minlength=n).astype(np.int64))])

    def _units(self, raw, starts, ends, prefix) -> tuple[np.ndarray, np.ndarray]:
        """Ids and number of ids of each unit."""
        v = self.v
        chars = np.flatnonzero((raw & 0xC0) != 0x80)
        first = np.searchsorted(chars, starts)
        length = np.searchsorted(chars, ends) - first
        odd = length > LONG
        if v.kind == "bpe":  # equal scores of runs of spaces are settled by place
            odd |= (ends - starts > 1) & (raw[np.minimum(starts + 1, len(raw) - 1)] == 32) & (raw[starts] == 32)
        place = np.append(chars, len(raw))
        order = np.argsort(-length, kind="stable")
        order = order[~odd[order]]
        tokens: list = [None] * 0
        unit_ids, step_no, token, size = [], [], [], []
        lost = np.zeros(len(starts), bool)
        if len(order):
            f, ln = first[order], length[order]
            base = np.cumsum(ln + 1) - (ln + 1)
            char = _ragged(f, ln)
            stop = np.repeat(f + ln, ln)
            inverse = C.powers(len(raw) + 1, C.INVERSE)
            found, row = [], np.arange(len(char))
            for k in range(1, v.longest + 1):
                row = row[char[row] + k <= stop[row]]
                s, e = place[char[row]], place[char[row] + k]
                h = C.mix64((prefix[e] - prefix[s]) * inverse[s] + (e - s).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
                maybe = v.sieve[(h >> np.uint64(44)).astype(np.int64)]
                at, h = row[maybe], h[maybe]
                i = np.minimum(np.searchsorted(v.keys, h), len(v.keys) - 1)
                hit = v.keys[i] == h
                here = np.full(len(char), -1, np.int32)
                here[at[hit]] = v.ids[i[hit]]
                found.append(here)
            at_char = np.cumsum(ln) - ln  # where a unit's characters begin in found
            total = int((ln + 1).sum())
            best = np.full(total, -np.inf, np.float32)
            best[base] = 0
            last = np.full(total, -3, np.int32)  # id of the piece that ends here; -1: an unknown character, -2: the start
            last[base] = -2
            back = np.zeros(total, np.int32)
            for j in range(1, int(ln[0]) + 1):
                live = int(np.searchsorted(-ln, -j, side="right"))
                here = base[:live] + j
                for k in range(min(j, v.longest), 0, -1):
                    piece = found[k - 1][at_char[:live] + j - k]
                    score = np.where(piece >= 0, v.scores[piece], v.floor if k == 1 else -np.inf).astype(np.float32)
                    row = np.flatnonzero((piece >= 0) | (k == 1))
                    if not len(row):
                        continue
                    came = here[row] - k
                    if v.kind == "unigram":
                        total_score = best[came] + score[row]
                        row = row[total_score > best[here[row]]]
                        total_score = best[here[row] - k] + score[row]
                    else:
                        fits = (last[came] != -3) & (last[here[row]] == -3)
                        row, came = row[fits], came[fits]
                        before = last[came]
                        row = row[_meets(v, np.where(before >= 0, v.rank[before], -1), np.where(piece[row] >= 0, v.rank[piece[row]], -1))]
                        total_score = np.zeros(len(row), np.float32)
                    best[here[row]], last[here[row]], back[here[row]] = total_score, piece[row], k
            where, rows, step = base + ln, np.arange(len(order)), 0
            lost[order[last[where] == -3]] = True
            rows = rows[last[where] != -3]
            while len(rows):
                w = where[rows]
                unit_ids.append(order[rows])
                step_no.append(np.full(len(rows), step))
                token.append(last[w])
                size.append(place[f[rows] + w - base[rows]] - back_width(place, f[rows] + w - base[rows], back[w]))
                # byte place of the character, for unknown ones
                tokens.append(back_width(place, f[rows] + w - base[rows], back[w]))
                where[rows] = w - back[w]
                rows = rows[where[rows] > base[rows]]
                step += 1
        for u in np.flatnonzero(odd | lost):
            self._alone(raw, int(starts[u]), int(ends[u]), int(u), unit_ids, step_no, token, size, tokens)
        u, s, t = np.concatenate(unit_ids), np.concatenate(step_no), np.concatenate(token)
        width, at = np.concatenate(size), np.concatenate(tokens)
        order = np.lexsort((-s, u))
        u, t, width, at = u[order], t[order].astype(np.int64), width[order], at[order]
        known = t >= 0
        fallback = len(v.byte_ids) > 0
        each = np.where(known, 1, width if fallback else 1)
        ids = np.repeat(t, each)
        unknown = np.repeat(~known, each)
        if unknown.any():
            ids[unknown] = v.byte_ids[raw[_ragged(at[~known], width[~known])]] if fallback else v.unknown
        return ids, np.bincount(u, weights=each, minlength=len(starts)).astype(np.int64)

    def _alone(self, raw, start, end, u, unit_ids, step_no, token, size, tokens) -> None:
        """One unit by the plain forms, as steps from its end."""
        v = self.v
        if not hasattr(self, "by_text"):
            self.by_text = {v.data[v.bounds[i] : v.bounds[i + 1]].decode(): int(i) for i in v.ids}
            self.by_score = {t: float(v.scores[i]) for t, i in self.by_text.items()}
        text = raw[start:end].tobytes().decode("utf-8", "surrogateescape")
        parts = merges(text, self.by_score) if v.kind == "bpe" else best_path(text, self.by_score, float(v.floor), v.longest)
        at, n = start, len(parts)
        for i, x in enumerate(parts):
            w = len(x.encode("utf-8", "surrogateescape"))
            for seq, value in ((unit_ids, u), (step_no, n - i), (token, self.by_text.get(x, -1)), (size, w), (tokens, at)):
                seq.append(np.array([value]))
            at += w


def back_width(place: np.ndarray, at: np.ndarray, back: np.ndarray) -> np.ndarray:
    """Byte place `back` characters before a character."""
    return place[at - back]


def best_path(text: str, score: dict[str, float], floor: float, longest: int) -> list[str]:
    """Pieces of the path of greatest total, in single precision; the longest last piece on ties."""
    n = len(text)
    best = [np.float32(0)] + [None] * n
    back = [0] * (n + 1)
    for j in range(1, n + 1):
        for k in range(min(j, longest), 0, -1):
            s = score.get(text[j - k : j], floor if k == 1 else None)
            if s is not None and best[j - k] is not None and (best[j] is None or best[j - k] + np.float32(s) > best[j]):
                best[j], back[j] = best[j - k] + np.float32(s), k
    out = []
    while n:
        out.append(text[n - back[n] : n])
        n -= back[n]
    return out[::-1]


def _spaces(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Literal marks count as spaces, as in the library."""
    n = len(raw)
    if n < 3:
        return raw, offsets
    mark = np.flatnonzero((raw[:-2] == 0xE2) & (raw[1:-1] == 0x96) & (raw[2:] == 0x81))
    if not len(mark):
        return raw, offsets
    keep = np.ones(n, bool)
    keep[mark + 1] = keep[mark + 2] = False
    raw = raw.copy()
    raw[mark] = 32
    return raw[keep], np.concatenate([[0], np.cumsum(keep)])[offsets]


def decode(v: Vocabulary, ids: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets of the texts; the leading space that encoding adds is taken off."""
    width = (v.bounds[ids + 1] - v.bounds[ids]).astype(np.int64)
    raw = np.frombuffer(v.data, np.uint8)[_ragged(v.bounds[ids].astype(np.int64), width)]
    offsets = np.concatenate([[0], np.cumsum(width)])[bounds]
    if v.prefix and len(raw):
        head = offsets[:-1][np.diff(offsets) > 0]
        head = head[raw[head] == 32]
        raw = np.delete(raw, head)
        offsets = offsets - np.searchsorted(head, offsets, side="left")
    return raw, offsets


# ------------------------------------------------------------------------ Spark


def encode_texts(docs: DataFrame, model: str, columns: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """columns, n_tokens long, ids array<int>, round_trip boolean for each row.

    model: path of a model file, read on the driver and broadcast as arrays (a vocabulary's size). Null
    and empty texts have no ids. round_trip says whether decoding gives the text back; a text that
    holds the mark itself decodes to a space there. Other columns are ignored.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(load(model))
    picked = docs.select(*columns, F.col(text_col).cast("string").alias("__text"))
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[:-1]] + ["n_tokens long", "ids array<int>", "round_trip boolean"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(shared.value)
        for batch in batches:
            raw, offsets = C.utf8_buffer(batch.column(len(columns)))
            for i, j in C.row_slices(offsets):
                own, off = raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
                ids, bounds = encoder.encode(own, off)
                back, places = decode(encoder.v, ids, bounds)
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids, pa.int32()))
                yield pa.RecordBatch.from_arrays([*(c.slice(i, j - i) for c in batch.columns[:-1]), pa.array(np.diff(bounds)), lists, pa.array(_same(own, off, back, places))], names=[*columns, "n_tokens", "ids", "round_trip"])

    return picked.mapInArrow(run, schema)


def _same(a: np.ndarray, a_off: np.ndarray, b: np.ndarray, b_off: np.ndarray) -> np.ndarray:
    """For each text, whether its bytes are equal in both buffers."""
    out = np.diff(a_off) == np.diff(b_off)
    if len(a) == len(b) and out.all():
        wrong = np.flatnonzero(a != b)
        out[np.searchsorted(a_off, wrong, side="right") - 1] = False
        return out
    for i in np.flatnonzero(out):
        out[i] = np.array_equal(a[a_off[i] : a_off[i + 1]], b[b_off[i] : b_off[i + 1]])
    return out


def decode_ids(rows: DataFrame, model: str, columns: tuple[str, ...] = ("doc_id",), ids_col: str = "ids") -> DataFrame:
    """columns, text for each row of ids; null ids give an empty text, bytes that are no UTF-8 are replaced."""
    shared = rows.sparkSession.sparkContext.broadcast(load(model))
    picked = rows.select(*columns, F.coalesce(F.col(ids_col), F.array().cast("array<int>")).alias("__ids"))
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[:-1]] + ["text string"])

    def run(batches):
        for batch in batches:
            lists = batch.column(len(columns))
            ids = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            bounds = lists.offsets.to_numpy().astype(np.int64)
            raw, places = decode(shared.value, ids, bounds - bounds[0])
            data = raw.tobytes()
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array([data[x:y].decode("utf-8", "replace") for x, y in zip(places[:-1], places[1:], strict=True)], pa.string())], names=[*columns, "text"])

    return picked.mapInArrow(run, schema)


def op2_sentencepiece(spark: SparkSession, sf_dir: str, model: str = f"{TOKENIZERS}/piece_bpe_32k.model") -> DataFrame:
    """Ids of all documents and whether they decode to the text."""
    return encode_texts(C.table(spark, sf_dir, "documents"), model)
