"""Toxicity by weak supervision: voters, a generative label model, a linear classifier.

Voters are lexicons of whole words and word beginnings, mined from a bounded sample of labelled rows
(each row is voted on by lexicons mined without its fold), a fixed seed lexicon, and patterns:
look-alike spelling, spelled-out letters, shouting. The label model holds, for either class, what
each voter says given what the voter it depends on most says: accuracies and correlations are
parameters of one generative model, fitted by expectation-maximisation on the votes alone. Labels
give its parameters a prior; a row's own label never votes on the row. A logistic model learns the
posterior and scores every text in one pass of numpy over the UTF-8 bytes, with no join.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C

# Common insults, a seed that data replaces and extends.
SEEDS = "idiot idiots moron morons stupid dumb loser losers scum trash pathetic worthless disgusting clown imbecile jerk bastard bitch shit fuck fucking asshole retard retarded whore slut crap dumbass douche".split()
LOOKALIKES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s"}

KINDS = (0, 4, 5, 6)  # whole words, and word beginnings of so many characters
LEVELS = ((24.0, 4.5), (24.0, 3.0), (11.0, 1.5))  # sure, strict and loose lexicons: least G statistic and log-odds
SHAPES = 2 * len(LEVELS) * len(KINDS)  # columns of hits in a design row
PATTERNS = ("seed", "lookalike", "spelled", "capitals", "exclaims")


@dataclass(frozen=True)
class Toxicity:
    """sample_rows bounds the labelled rows that are learnt from; the rest is learnt on the driver from them."""

    sample_rows: int = 12_000
    folds: int = 4
    least_docs: int = 4
    single: int = 200  # features with a weight of their own
    ridge: float = 1.0
    trust: float = 4.0  # weight of the counts that labels give, the prior of the label model, beside those of the votes


def held_out(doc_id):
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


# --------------------------------------------------------------------- features


def tokens(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of letters, digits and non-ASCII bytes of lower-cased text: start, end, document."""
    inside = ((raw >= 97) & (raw <= 122)) | ((raw >= 48) & (raw <= 57)) | (raw >= 128)
    plain = np.where(inside, np.uint8(97), np.uint8(32))
    return C.word_spans(plain, offsets)


def text_features(raw: np.ndarray, offsets: np.ndarray, low: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(document, kind index, feature hash) of each feature of each token, and patterns by document.

    raw, offsets: the texts as they are; low, bounds: the same in lower case.
    """
    n = len(offsets) - 1
    upper = (raw >= 65) & (raw <= 90)
    sums = lambda mask: np.add.reduceat(np.append(mask, 0).astype(np.int64), offsets[:-1]) * (np.diff(offsets) > 0) if n else np.zeros(0)
    letters = sums(upper | ((raw >= 97) & (raw <= 122)))
    start, end, doc = tokens(low, bounds)
    prefix = C.prefix_hashes(low)
    places = np.append(np.flatnonzero((low & 0xC0) != 0x80), len(low))
    first = np.searchsorted(places, start)
    length = np.searchsorted(places, end) - first
    docs, kinds, hashes = [doc], [np.zeros(len(doc), np.int8)], [C.span_hashes(low, start, end, prefix)]
    for at, k in enumerate(KINDS[1:], 1):
        row = np.flatnonzero(length >= k)
        docs.append(doc[row])
        kinds.append(np.full(len(row), at, np.int8))
        hashes.append(C.span_hashes(low, start[row], places[first[row] + k], prefix) ^ np.uint64(k * 0xA5A5A5A5A5A5))
    swap = np.arange(256, dtype=np.uint8)
    for a, b in LOOKALIKES.items():
        swap[ord(a)] = ord(b)
    other = swap[low]
    o_start, o_end, o_doc = tokens(other, bounds)
    o_hash = C.span_hashes(other, o_start, o_end)
    swapped = np.concatenate([[0], np.cumsum(other != low)])
    changed = swapped[o_end] > swapped[o_start]
    seeds = _seed_hashes()
    single = length == 1
    run = np.zeros(len(single), bool)
    if len(single) >= 4:
        run[3:] = single[3:] & single[2:-1] & single[1:-2] & single[:-3] & (doc[3:] == doc[:-3])
    count = lambda d, mask: np.bincount(d[mask], minlength=n)[:n]
    patterns = np.stack(
        [count(doc, np.isin(hashes[0], seeds)), count(o_doc, changed & np.isin(o_hash, seeds)), count(doc, run), sums(upper) / np.maximum(letters, 1), sums(raw == 33) / np.maximum(np.diff(offsets), 1)],
        axis=1,
    ).astype(np.float32) if n else np.zeros((0, len(PATTERNS)), np.float32)
    return np.concatenate(docs), np.concatenate(kinds), np.concatenate(hashes), patterns


def _seed_hashes() -> np.ndarray:
    data = "".join(SEEDS).encode()
    bounds = np.concatenate([[0], np.cumsum([len(w) for w in SEEDS])])
    return np.sort(C.span_hashes(np.frombuffer(data, np.uint8), bounds[:-1], bounds[1:]))


def slices(column) -> Iterator[tuple[int, int, tuple]]:
    """(first row, last row + 1, arguments of text_features) of about a megabyte of texts at a time.

    Lower case is Unicode's, by the text alone: nothing depends on which texts share a batch.
    """
    column = column.cast(pa.large_string()).fill_null("")
    raw, offsets = C.utf8_buffer(column)
    for i, j in C.row_slices(offsets):
        part, at = raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        if (part >= 128).any():
            yield i, j, (part, at, *C.utf8_buffer(pc.utf8_lower(column.slice(i, j - i))))
        else:
            yield i, j, (part, at, C.ascii_lower(part), at)


def distinct(doc: np.ndarray, feature: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each feature once a document."""
    order = np.lexsort((feature, doc))
    doc, feature = doc[order], feature[order]
    keep = np.ones(len(doc), bool)
    keep[1:] = (doc[1:] != doc[:-1]) | (feature[1:] != feature[:-1])
    return doc[keep], feature[keep]


# ------------------------------------------------------------------ label model


def g_and_odds(n1: np.ndarray, n0: np.ndarray, t1: float, t0: float) -> tuple[np.ndarray, np.ndarray]:
    """G statistic of a feature's share of either class, and its smoothed log-odds."""
    n, p = n1 + n0, t1 / (t1 + t0)
    with np.errstate(divide="ignore", invalid="ignore"):
        g = 2 * (np.where(n1 > 0, n1 * np.log(n1 / (n * p)), 0) + np.where(n0 > 0, n0 * np.log(n0 / (n * (1 - p))), 0))
    return np.nan_to_num(g), np.log((n1 + 0.5) / (t1 + 1)) - np.log((n0 + 0.5) / (t0 + 1))


@dataclass
class LabelModel:
    """says[j, y, u, v]: how often voter j says v - 1 (against, nothing, for) where the class is y and the
    voter it depends on, leans[j], says u - 1. A voter that leans on none (-1) has the same row for each u."""

    prior: float
    says: np.ndarray
    leans: np.ndarray

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        odds = np.log(self.says[:, 1]) - np.log(self.says[:, 0])
        z = np.full(len(votes), np.log(self.prior / (1 - self.prior)))
        for j, up in enumerate(self.leans):
            z += odds[j][votes[:, up] + 1 if up >= 0 else 0, votes[:, j] + 1]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def accuracy(self) -> np.ndarray:
        """Of each voter: how often it is right where it says anything, with no regard to the others."""
        out = np.zeros((len(self.leans), 2, 3))
        for j in self.in_order():
            up = self.leans[j]
            out[j] = self.says[j, :, 0] if up < 0 else np.einsum("yu,yuv->yv", out[up], self.says[j])
        weigh = np.array([1 - self.prior, self.prior])
        right, said = out[:, 0, 0] * weigh[0] + out[:, 1, 2] * weigh[1], (out[:, :, [0, 2]].sum(axis=2) * weigh).sum(axis=1)
        return right / said

    def in_order(self) -> list[int]:
        """Voters, each after the one it leans on."""
        out: list[int] = []
        while len(out) < len(self.leans):
            out += [j for j, up in enumerate(self.leans) if j not in out and (up < 0 or up in out)]
        return out


def pair_counts(votes: np.ndarray, q: np.ndarray) -> np.ndarray:
    """counts[j, k, y, u, v]: expected rows of class y on which voter k says u - 1 and voter j says v - 1."""
    n, m = votes.shape
    flags = np.zeros((n, m, 3))
    np.put_along_axis(flags, (votes + 1).astype(np.intp)[:, :, None], 1.0, axis=2)
    flat = flags.reshape(n, 3 * m)
    out = np.empty((m, m, 2, 3, 3))
    for y, w in enumerate((1 - q, q)):
        out[:, :, y] = (flat.T @ (flat * w[:, None])).reshape(m, 3, m, 3).transpose(2, 0, 1, 3)
    return out


def dependence(counts: np.ndarray) -> np.ndarray:
    """Mutual information of each two voters given the class, in nats a row: what they share beyond it."""
    p = counts / counts[0, 0].sum()
    p_y = p.sum(axis=(3, 4), keepdims=True)
    with np.errstate(divide="ignore", invalid="ignore"):
        inside = p * (np.log(p) + np.log(p_y) - np.log(p.sum(axis=4, keepdims=True)) - np.log(p.sum(axis=3, keepdims=True)))
    return np.nan_to_num(inside, posinf=0.0, neginf=0.0).sum(axis=(2, 3, 4))


def spanning_tree(shared: np.ndarray, least: float) -> np.ndarray:
    """The voter that each one leans on: the tree of greatest dependence, without branches under `least`."""
    m = len(shared)
    leans, best, via, left = np.full(m, -1), np.full(m, -np.inf), np.full(m, -1), set(range(m))
    while left:
        j = max(sorted(left), key=lambda j: best[j])
        left.discard(j)
        leans[j] = via[j] if best[j] > least else -1
        for k in left:
            if shared[j, k] > best[k]:
                best[k], via[k] = shared[j, k], j
    return leans


def fit_label_model(votes: np.ndarray, prior: float, believed: np.ndarray, trust: float = 1.0, rounds: int = 30, trees: int = 2, least: float = 0.002) -> LabelModel:
    """Expectation-maximisation over votes (rows x voters: -1, 0 or 1) of a model in which voters lean on each other.

    believed: a probability a row that only sets the prior: `trust` times the counts it gives, and the share
    `prior` of the class, are added to what the votes say in every round; beliefs in single rows come from their
    votes alone. The tree of dependences is drawn anew from the posterior after each fit, `trees` times.
    """
    n, m = votes.shape
    base = trust * pair_counts(votes, np.asarray(believed, float)) + 0.5
    leans = np.full(m, -1)
    model = LabelModel(prior, np.empty((m, 2, 3, 3)), leans)

    def refit(counts: np.ndarray) -> None:
        for j, up in enumerate(model.leans):
            c = counts[j, up] if up >= 0 else np.repeat(np.einsum("yvv->yv", counts[j, j])[:, None], 3, axis=1)
            model.says[j] = c / c.sum(axis=2, keepdims=True)

    refit(base)
    q = model.posterior(votes)
    for turn in range(trees + 1):
        if turn:
            model.leans = spanning_tree(dependence(base + pair_counts(votes, q)), least)
        for _ in range(rounds):
            refit(base + pair_counts(votes, q))
            model.prior = float(np.clip((trust * prior * n + q.sum()) / ((trust + 1) * n), 1e-3, 1 - 1e-3))
            was, q = q, model.posterior(votes)
            if np.abs(q - was).max() < 1e-7:
                break
    return model


def fit_logistic(x: np.ndarray, q: np.ndarray, ridge: float, rounds: int = 30) -> np.ndarray:
    """Weights, bias last, of the logistic model of soft labels q, by damped Newton steps."""
    x = np.hstack([x, np.ones((len(x), 1))])
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (p - q) + penalty * w
        step = np.linalg.solve((x * (p * (1 - p) + 1e-6)[:, None]).T @ x + np.diag(penalty), gradient)
        w -= step * min(1.0, 4 / (np.abs(step).max() + 1e-9))
        if np.abs(step).max() < 1e-5:
            break
    return w


@dataclass
class Scorer:
    keys: np.ndarray  # sorted hashes of lexicon features
    level: np.ndarray  # by key: 3 sure, 2 strict, 1 loose, 0 none of them
    kind: np.ndarray
    own: np.ndarray  # by key: column of its own, or -1
    singles: int
    weights: np.ndarray

    def rows(self, doc: np.ndarray, feature: np.ndarray, patterns: np.ndarray) -> np.ndarray:
        """Design rows from distinct (document, feature) pairs."""
        n = len(patterns)
        at = np.minimum(np.searchsorted(self.keys, feature), max(len(self.keys) - 1, 0))
        hit = self.keys[at] == feature if len(self.keys) else np.zeros(len(feature), bool)
        return design(doc[hit], self.kind[at[hit]], self.level[at[hit]], self.own[at[hit]], patterns, self.singles, n)

    def score(self, texts: tuple) -> np.ndarray:
        doc, _, feature, patterns = text_features(*texts)
        sieve = np.zeros(1 << 18, bool)
        sieve[(self.keys >> np.uint64(46)).astype(np.int64)] = True
        maybe = sieve[(feature >> np.uint64(46)).astype(np.int64)]
        doc, feature = distinct(doc[maybe], feature[maybe])
        z = (self.rows(doc, feature, patterns) * self.weights[:-1]).sum(axis=1) + self.weights[-1]  # row by row alike in any batch
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def design(doc, kind, level, own, patterns, singles: int, n: int) -> np.ndarray:
    """Hits by kind and level as log1p and as flags, patterns, and single features."""
    out = []
    for k in range(len(KINDS)):
        for least in range(len(LEVELS), 0, -1):
            hits = np.bincount(doc[(kind == k) & (level >= least)], minlength=n)[:n]
            out += [np.log1p(hits), hits > 0]
    out = np.stack(out, axis=1).astype(np.float64) if n else np.zeros((0, SHAPES))
    own_x = np.zeros((n, singles))
    own_x[doc[own >= 0], own[own >= 0]] = 1
    shape = np.hstack([np.log1p(patterns[:, :3]), patterns[:, 3:]])
    return np.hstack([out, shape, own_x])


@dataclass
class Mined:
    """Counts of the sample by fold: rows of either class, and rows of either class with each feature."""

    rows1: np.ndarray  # folds
    rows0: np.ndarray
    n1: np.ndarray  # features x folds
    n0: np.ndarray

    def levels(self, without: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Level (3 sure, 2 strict, 1 loose, 0 none) and G statistic of each feature on all folds but one."""
        use = np.arange(len(self.rows1)) != (-1 if without is None else without)
        g, odds = g_and_odds(self.n1[:, use].sum(axis=1), self.n0[:, use].sum(axis=1), float(self.rows1[use].sum()), float(self.rows0[use].sum()))
        level = np.zeros(len(g), np.int64)
        for at, (least_g, least_odds) in enumerate(LEVELS):
            level = np.maximum(level, np.where((g >= least_g) & (odds >= least_odds), len(LEVELS) - at, 0))
        return level, g


def fit(row: np.ndarray, col: np.ndarray, patterns: np.ndarray, y: np.ndarray, fold: np.ndarray, keys: np.ndarray, kind: np.ndarray, mined: Mined, p: Toxicity) -> Scorer:
    """Learn from a sample: (row, col) pairs say which row has which key."""
    n, m = len(y), len(keys)
    by_fold = np.stack([mined.levels(k)[0] for k in range(p.folds)], axis=1)
    level_at = by_fold[col, fold[row]]
    level, g = mined.levels()
    single = np.argsort(-np.where(level >= 2, g, -1), kind="stable")[: p.single]
    single = single[level[single] >= 2]
    own = np.full(m, -1, np.int64)
    own[single] = np.arange(len(single))
    x = design(row, kind[col], level_at, own[col], patterns, len(single), n)
    votes = []
    for k in range(len(KINDS)):
        sure, strict, loose = (np.bincount(row[(kind[col] == k) & (level_at >= least)], minlength=n) for least in (3, 2, 1))
        votes += [np.where(sure > 1, 1, np.where(sure == 0, -1, 0)), np.where(strict > 0, 1, 0), np.where(strict > 1, 1, np.where(strict == 0, -1, 0)), np.where(loose > 1, 1, np.where(loose == 0, -1, 0))]
    votes += [np.where(patterns[:, j] > 0, 1, 0) for j in range(3)]
    votes += [np.where(patterns[:, 3] > 0.5, 1, 0), np.where(patterns[:, 4] > 0.02, 1, 0)]
    votes = np.stack(votes, axis=1).astype(np.int8)
    model = fit_label_model(votes, float(np.clip(y.mean(), 0.01, 0.99)), y, p.trust)
    weights = fit_logistic(x, model.posterior(votes), p.ridge)
    keep = level > 0
    return Scorer(keys[keep], level[keep], kind[keep], own[keep], len(single), weights)


def seed_scorer() -> Scorer:
    """For want of labels of both classes: seeds and patterns with fixed weights."""
    w = np.zeros(SHAPES + len(PATTERNS) + 1)
    w[SHAPES : SHAPES + 3] = (4.0, 3.0, 0.5)
    w[-1] = -2.0
    none = np.zeros(0, np.int64)
    return Scorer(np.zeros(0, np.uint64), none, none, none, 0, w)


# ------------------------------------------------------------------------ Spark


def learn(docs: DataFrame, labels: DataFrame, p: Toxicity = Toxicity()) -> Scorer:
    """A scorer from labelled rows that are not held out: at most p.sample_rows, by a hash of the id."""
    known = labels.where("toxic is not null and doc_id is not null").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.select("doc_id", (F.col("toxic") > 0).alias("y"), F.xxhash64(F.lit("toxic"), "doc_id").alias("key"))
    total = labels.count()
    if total > 8 * p.sample_rows:  # a threshold on the hash first, so that tasks send on a bounded number of rows
        known = known.where(F.pmod("key", F.lit(1 << 40)) < F.lit(int((1 << 40) * 4 * p.sample_rows / total)))
    sample = C.cut(known.orderBy(F.pmod("key", F.lit(1 << 40)), "key").limit(p.sample_rows))  # bounded, so it may be broadcast
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(sample), "doc_id").select("text", "y", F.pmod("key", F.lit(p.folds)).cast("int").alias("fold"), "key")
    texts = C.cut(texts)

    def count(batches):
        for batch in batches:
            for _, _, texts in slices(batch.column(0)):
                doc, kind, feature, _ = text_features(*texts)
                _, one = distinct(doc, feature)
                found, n = np.unique(one, return_counts=True)
                first = np.unique(feature, return_index=True)[1]
                yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(kind[first].astype(np.int32)), pa.array(n.astype(np.int64))], names=["feature", "kind", "n"])

    counts = texts.where("y").select("text").mapInArrow(count, "feature long, kind int, n long").groupBy("feature").agg(F.min("kind").alias("kind"), F.sum("n").alias("n")).where(F.col("n") >= p.least_docs)
    found = counts.select("feature", "kind").toPandas()  # at most what the sample's toxic rows share
    order = np.argsort(found["feature"].to_numpy().view(np.uint64))
    keys, kind = found["feature"].to_numpy().view(np.uint64)[order], found["kind"].to_numpy().astype(np.int64)[order]
    sizes = texts.groupBy("fold").agg(F.sum(F.col("y").cast("long")).alias("n1"), F.count(F.lit(1)).alias("n")).toPandas()
    mined = Mined(np.zeros(p.folds), np.zeros(p.folds), np.zeros((len(keys), p.folds)), np.zeros((len(keys), p.folds)))
    mined.rows1[sizes["fold"]], mined.rows0[sizes["fold"]] = sizes["n1"], sizes["n"] - sizes["n1"]
    if not mined.rows1.sum() or not mined.rows0.sum():
        return seed_scorer()
    sc = docs.sparkSession.sparkContext
    shared = sc.broadcast(keys)

    def hits(keys: np.ndarray, doc: np.ndarray, feature: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(keys, feature), max(len(keys) - 1, 0))
        hit = keys[at] == feature if len(keys) else np.zeros(len(feature), bool)
        return distinct(doc[hit], at[hit])

    def tally(batches):
        n = np.zeros((len(shared.value), p.folds, 2), np.int32)
        for batch in batches:
            side, fold = batch.column(1).to_numpy(zero_copy_only=False).astype(int), batch.column(2).to_numpy()
            for i, _, texts in slices(batch.column(0)):
                doc, _, feature, _ = text_features(*texts)
                doc, col = hits(shared.value, doc, feature)
                np.add.at(n, (col, fold[i + doc], side[i + doc]), 1)
        col, fold, side = np.nonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(col, pa.int32()), pa.array(fold, pa.int32()), pa.array(side, pa.int32()), pa.array(n[col, fold, side].astype(np.int64))], names=["col", "fold", "side", "n"])

    table = texts.select("text", "y", "fold").mapInArrow(tally, "col int, fold int, side int, n long").groupBy("col", "fold", "side").agg(F.sum("n").alias("n")).toPandas()
    for side, into in ((1, mined.n1), (0, mined.n0)):
        own = table[table["side"] == side]
        into[own["col"], own["fold"]] = own["n"]
    keep = np.flatnonzero(np.max([mined.levels(k)[0] for k in (None, *range(p.folds))], axis=0) > 0) if len(keys) else np.zeros(0, int)
    keys, kind = keys[keep], kind[keep]
    mined = Mined(mined.rows1, mined.rows0, mined.n1[keep], mined.n0[keep])
    kept = sc.broadcast(keys)

    def probe(batches):
        for batch in batches:
            for i, j, texts in slices(batch.column(0)):
                doc, _, feature, patterns = text_features(*texts)
                doc, col = hits(kept.value, doc, feature)
                cut = np.searchsorted(doc, np.arange(j - i + 1))
                data = col.astype(np.int32).tobytes()
                yield pa.RecordBatch.from_arrays(
                    [batch.column(1).slice(i, j - i), batch.column(2).slice(i, j - i), batch.column(3).slice(i, j - i), pa.array([data[4 * a : 4 * b] for a, b in zip(cut[:-1], cut[1:], strict=True)], pa.binary()), pa.array([x.tobytes() for x in patterns], pa.binary())],
                    names=["y", "fold", "key", "cols", "patterns"],
                )

    rows = texts.select("text", "y", "fold", "key").mapInArrow(probe, "y boolean, fold int, key long, cols binary, patterns binary").toPandas().sort_values("key", kind="stable")
    y = rows["y"].to_numpy().astype(bool)
    cols = [np.frombuffer(c, np.int32) for c in rows["cols"]]
    patterns = np.frombuffer(b"".join(rows["patterns"]), np.float32).reshape(-1, len(PATTERNS))
    row = np.repeat(np.arange(len(y)), [len(c) for c in cols])
    return fit(row, np.concatenate(cols).astype(np.int64), patterns, y, rows["fold"].to_numpy(), keys, kind, mined, p)


def score(docs: DataFrame, scorer: Scorer, columns: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """columns and score double (0 to 1, likelier toxic) for each row; one pass, no shuffle. Null texts are empty."""
    shared = docs.sparkSession.sparkContext.broadcast(scorer)
    picked = docs.select(F.col(text_col).cast("string").alias("__text"), *columns)
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[1:]] + ["score double"])

    def run(batches):
        for batch in batches:
            for i, j, texts in slices(batch.column(0)):
                yield pa.RecordBatch.from_arrays([*(c.slice(i, j - i) for c in batch.columns[1:]), pa.array(shared.value.score(texts))], names=[*columns, "score"])

    return picked.mapInArrow(run, schema)


def judge(docs: DataFrame, labels: DataFrame, p: Toxicity = Toxicity()) -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row of docs (doc_id, text).

    labels: doc_id, toxic; the greatest label counts where an id has several, null labels and those
    of held-out ids count for nothing. Without labels of both classes fixed weights of the seeds
    score. Null texts are empty; repeated rows are scored each; other columns are ignored.
    """
    out = score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), learn(docs, labels, p))
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of all documents, learnt from labels."""
    return judge(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "labels"))
