"""Near-duplicate embeddings: navigable small-world graphs per shard, audited, verified and united.

Equal vectors of a label collapse to one. A label of many vectors is dealt to regions around some of
them, and a region to shards of bounded size by a hash of the id. Each shard's task builds a layered
graph and answers its own vectors. A vector also goes to the shards before its own that can hold a
link of it: with centres c, own one a, angle t(q, c) and d the angle of the least cosine, a vector of
region b within d of q has t(q, b) <= t(q, a) + 2 d, so all other regions are left out. Those queries
meet a shard's graph in tasks of bounded size. Searches run in lockstep for blocks of queries: all
beams take a step at a time in array operations.

A beam is widened until a sample of its queries, compared with all of the shard, has lost nothing;
a query whose beam is full of links is answered against the whole shard in blocks. All reported
links have their cosine taken anew in double precision.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C


@dataclass(frozen=True)
class Hnsw:
    least: float = 0.98
    degree: int = 12
    build_beam: int = 32
    beam: int = 16
    audit: int = 64  # queries of each search that are first compared with the whole shard
    evidence: int = 1_000  # links between different vectors on which the beam has to show its recall
    recall: float = 0.999
    shard_rows: int = 20_000
    regions: int = 4096  # about so many centres at most, of all labels
    seed: int = 7


# ------------------------------------------------------------------------ graph


class Graph:
    """Layers of bounded-degree neighbour lists over unit vectors (float32)."""

    def __init__(self, x: np.ndarray, p: Hnsw) -> None:
        self.x, self.p = x, p
        n = len(x)
        rng = np.random.default_rng(p.seed)
        order = rng.permutation(n)
        height = np.minimum((-np.log(1.0 - rng.random(n)) / np.log(p.degree)).astype(int), 6)
        self.layers: list[np.ndarray] = []
        self.entry = int(order[np.argmax(height[order])]) if n else 0
        for level in range(int(height.max(initial=0)), -1, -1):
            members = order[height[order] >= level]
            self.layers.insert(0, np.full((n, (2 if level == 0 else 1) * p.degree), -1, np.int32))
            self._build(members[members != self.entry], level)

    def _build(self, members: np.ndarray, level: int) -> None:
        """Insert in batches that double, each searched on the graph so far and linked both ways."""
        links = self.layers[0]
        done = np.array([self.entry])
        at = 0
        while at < len(members):
            batch = members[at : at + max(16, min(len(done), 1024))]
            ids, scores = self.search(self.x[batch], self.p.build_beam, upto=0, built=level)
            within = self.x[batch] @ self.x[batch].T  # links inside the batch
            np.fill_diagonal(within, -2)
            near = min(8, len(batch) - 1)
            if near > 0:
                own = np.argpartition(-within, near - 1, axis=1)[:, :near]
                ids = np.concatenate([ids, batch[own]], axis=1)
                scores = np.concatenate([scores, np.take_along_axis(within, own, 1)], axis=1)
            self._link(links, batch, ids, scores, links.shape[1])
            done = np.append(done, batch)
            at += len(batch)

    def _pick(self, ids: np.ndarray, scores: np.ndarray, most: int) -> np.ndarray:
        """Of each row's candidates those that are nearer to the row than to any picked before; filled up by score."""
        order = np.argsort(-scores, axis=1, kind="stable")
        ids, scores = np.take_along_axis(ids, order, 1), np.take_along_axis(scores, order, 1)
        valid = (ids >= 0) & (scores > -2)
        v = self.x[np.maximum(ids, 0)]
        cross = np.einsum("bid,bjd->bij", v, v)
        picked = np.zeros(ids.shape, bool)
        count = np.zeros(len(ids), int)
        for j in range(ids.shape[1]):
            blocked = (picked[:, :j] & (cross[:, j, :j] > scores[:, j, None])).any(axis=1)
            take = valid[:, j] & ~blocked & (count < most)
            picked[:, j] = take
            count += take
        rank = np.argsort(np.where(picked, 0, np.where(valid, 1, 2)), axis=1, kind="stable")[:, :most]
        out = np.where(np.take_along_axis(valid, rank, 1), np.take_along_axis(ids, rank, 1), -1)
        if out.shape[1] < most:
            out = np.pad(out, ((0, 0), (0, most - out.shape[1])), constant_values=-1)
        return out

    def _link(self, links: np.ndarray, batch: np.ndarray, ids: np.ndarray, scores: np.ndarray, most: int) -> None:
        keep = max(1, most // 2)
        chosen = self._pick(ids, scores, keep)
        links[batch, :keep] = chosen
        src = np.repeat(batch, keep)
        dst = chosen.reshape(-1)
        ok = (dst >= 0) & (dst != src)
        src, dst = src[ok], dst[ok]
        order = np.argsort(dst, kind="stable")
        src, dst = src[order], dst[order]
        heads, first, counts = np.unique(dst, return_index=True, return_counts=True)
        for lo in range(0, len(heads), 1024):  # reverse links, pruned to the same rule
            h, f, c = heads[lo : lo + 1024], first[lo : lo + 1024], counts[lo : lo + 1024]
            width = min(int(c.max()), 2 * most)
            at = f[:, None] + np.arange(width)[None, :]
            new = np.where(np.arange(width)[None, :] < c[:, None], src[np.minimum(at, len(src) - 1)], -1)
            both = np.concatenate([links[h], new], axis=1)
            both = np.sort(both, axis=1)
            both[:, 1:][both[:, 1:] == both[:, :-1]] = -1
            s = np.einsum("bd,bjd->bj", self.x[h], self.x[np.maximum(both, 0)])
            s[both < 0] = -2
            links[h] = self._pick(both, s, most)

    def search(self, q: np.ndarray, beam: int, upto: int = 0, built: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of each query's beam, best first; -1 where the beam is not full.

        built: while building, the level that layers[0] stands for.
        """
        n = len(q)
        ids = np.full((n, 1), self.entry, np.int64)
        for layer in range(len(self.layers) - 1, 0, -1):
            ids = self._walk(q, ids, self.layers[layer], 1)[0]
        return self._walk(q, ids, self.layers[0], beam)

    def _walk(self, q: np.ndarray, ids: np.ndarray, links: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
        n = len(q)
        best = np.full((n, beam), -1, np.int64)
        best[:, 0] = ids[:, 0]
        score = np.full((n, beam), -2.0, np.float32)
        score[:, 0] = np.einsum("bd,bd->b", q, self.x[ids[:, 0]])
        open_ = np.zeros((n, beam), bool)
        open_[:, 0] = True
        seen = np.zeros((n, len(self.x)), bool)
        seen[np.arange(n), ids[:, 0]] = True
        live = np.arange(n)
        while len(live):
            at = np.argmax(np.where(open_[live], score[live], -3), axis=1)
            some = open_[live, at]
            live, at = live[some], at[some]
            if not len(live):
                break
            node = best[live, at]
            open_[live, at] = False
            near = links[node].astype(np.int64)
            fresh = (near >= 0) & ~seen[live[:, None], np.maximum(near, 0)]
            seen[live[:, None], np.where(near >= 0, near, node[:, None])] = True
            s = np.einsum("bd,bjd->bj", q[live], self.x[np.maximum(near, 0)])
            s[~fresh] = -2
            all_s = np.concatenate([score[live], s], axis=1)
            all_i = np.concatenate([best[live], np.where(fresh, near, -1)], axis=1)
            all_o = np.concatenate([open_[live], fresh], axis=1)
            top = np.argsort(-all_s, axis=1, kind="stable")[:, :beam]
            score[live], best[live] = np.take_along_axis(all_s, top, 1), np.take_along_axis(all_i, top, 1)
            open_[live] = np.take_along_axis(all_o, top, 1)
        return best, score


def range_links(g: Graph, q: np.ndarray, exact_q: np.ndarray, exact_x: np.ndarray, p: Hnsw, same: bool = False):
    """Yields (query rows, shard rows) arrays of all links at p.least, by block of queries.

    exact_*: the unit vectors in double precision. Queries are compared in full until p.evidence links
    between different vectors (same: queries and shard are the same rows) are known; the beam doubles
    until it finds them too. Where links are so few that this takes half the queries, all are compared
    in full. A query with a full beam of links is compared in full.
    """
    slack = 1e-5
    rng = np.random.default_rng(p.seed)

    def full(rows: np.ndarray):
        for lo in range(0, len(rows), 256):
            own = rows[lo : lo + 256]
            a, b = np.nonzero(exact_q[own] @ exact_x.T >= p.least)
            yield own[a], b

    def beams(rows: np.ndarray, beam: int):
        """Links from beams, and the rows whose beam is full of links."""
        block = max(16, min(2048, (64 << 20) // max(1, len(g.x))))
        for lo in range(0, len(rows), block):
            own = rows[lo : lo + block]
            ids, scores = g.search(q[own], beam)
            hit = (ids >= 0) & (scores >= p.least - slack)
            crowded = hit.all(axis=1) & (ids.shape[1] < len(g.x))
            a, b = np.nonzero(hit & ~crowded[:, None])
            i, j = own[a], ids[a, b]
            ok = np.einsum("nd,nd->n", exact_q[i], exact_x[j]) >= p.least if len(i) else np.zeros(0, bool)
            yield i[ok], j[ok], own[crowded]

    rows = np.arange(len(q))
    if not len(g.x) or not len(rows):
        return
    order, seen = rng.permutation(len(rows)), 0
    truth: set = set()
    while seen < len(order) and len(truth) < p.evidence:  # in full, and so answered
        part = order[seen : seen + max(p.audit, seen)]
        seen += len(part)
        for a, b in full(part):
            yield a, b
            truth |= {(int(i), int(j)) for i, j in zip(a, b, strict=True) if not (same and i == j)}
    audit, rows = order[:seen], np.sort(order[seen:])
    if 2 * seen >= len(order):  # the rest costs no more than its audit
        yield from full(rows)
        return
    beam = p.beam
    while beam < len(g.x):
        got: set = set()
        for a, b, crowded in beams(audit, beam):
            got |= {(int(i), int(j)) for i, j in zip(a, b, strict=True)}
            crowd = set(crowded.tolist())
            got |= {t for t in truth if t[0] in crowd}
        if len(got & truth) >= p.recall * len(truth):
            break
        beam *= 2
    if beam >= len(g.x):
        yield from full(rows)
        return
    while len(rows):  # widen where beams are full, then compare in full
        left = []
        for a, b, crowded in beams(rows, beam):
            yield a, b
            left.append(crowded)
        rows, beam = np.concatenate(left), beam * 4
        if beam > 8 * p.beam or beam >= len(g.x):
            yield from full(rows)
            return


# ------------------------------------------------------------------------ tasks


def _unit(vectors: list) -> np.ndarray:
    x = np.array(vectors, dtype=np.float64)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _joined(n: int, i: np.ndarray, j: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Labels (least index) after links i-j, by min-label hops and jumps."""
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, label[i], low)
        np.minimum.at(new, label[j], low)
        new = np.minimum(new, new[new])
        while (new != new[new]).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            return label
        label = new


def _answer(g: Graph, xid, xw, ex, qid, qw, eq, same: bool, p: Hnsw):
    """(id, n_links, to) rows: links of each vector by weight of the other, and a spanning link of its component.

    Links are made symmetric: a pair counts for both of its ends once, from whichever it was found.
    """
    q = eq.astype(np.float32)
    n, m = len(qid), len(xid)
    links_q, links_x = np.zeros(n, np.int64), np.zeros(m, np.int64)
    label = np.arange(m if same else m + n)
    offset = 0 if same else m
    held: list[np.ndarray] = []
    for a, b in range_links(g, q, eq, ex, p, same):
        if same:
            keep = a != b
            a, b = a[keep], b[keep]
            held.append(np.minimum(a, b) * m + np.maximum(a, b))
            if sum(map(len, held)) > 4_000_000:
                held = [np.unique(np.concatenate(held))]
        else:
            np.add.at(links_q, a, xw[b])
            np.add.at(links_x, b, qw[a])
        if len(a):
            label = _joined(len(label), a + offset, b, label)
    if same and held:
        pair = np.unique(np.concatenate(held))
        a, b = pair // m, pair % m
        np.add.at(links_x, a, xw[b])
        np.add.at(links_x, b, xw[a])
    ids = xid if same else np.concatenate([xid, qid])
    links = links_x if same else np.concatenate([links_x, links_q])
    some = (links > 0) | (label != np.arange(len(label)))
    return ids[some], links[some], ids[label[some]]


OUT = "id long, links long, to long"


def _batch(ids, links, to):
    return pa.table({"id": pa.array(ids, pa.int64()), "links": pa.array(links, pa.int64()), "to": pa.array(to, pa.int64())})


SUBS = 1 << 32  # numbers of a region's shards


def _placed(held: DataFrame, p: Hnsw) -> DataFrame:
    """held with region, near (earlier regions that can hold links), sub, subs (shard within the region, and how many),
    shard, and more: other shards may ask this one.

    Centres are vectors picked by a hash of the id, one for about shard_rows vectors, p.regions of all labels at most; labels
    of fewer vectors, and ones whose pick is empty, are one region.
    """
    sizes = held.groupBy("label", "dims").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > p.shard_rows)
    wanted = (sizes.agg(F.sum("n")).first()[0] or 0) / p.shard_rows
    centres: dict[tuple, np.ndarray] = {}
    if wanted:
        share = min(1.0, p.regions / wanted) / p.shard_rows
        picked = held.join(sizes, ["label", "dims"], "left_semi").where(F.pmod(F.xxhash64(F.lit(p.seed), "id"), F.lit(1 << 40)) < F.lit(int((1 << 40) * share)))
        rows = sorted(picked.select("label", "dims", "id", "v").collect())
        for key in sorted({(r.label, r.dims) for r in rows}):
            centres[key] = _unit([r.v for r in rows if (r.label, r.dims) == key])
    shared = held.sparkSession.sparkContext.broadcast(centres)  # some p.regions vectors
    reach = 2 * np.arccos(p.least) + 1e-6

    def run(batches):
        for batch in batches:
            label, dims, v = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(4)
            region, near = np.zeros(batch.num_rows, np.int32), [[]] * batch.num_rows
            rows: dict[tuple, list[int]] = {}
            for n, key in enumerate(zip(label, dims, strict=True)):
                if key in shared.value:
                    rows.setdefault(key, []).append(n)
            for key, own in rows.items():
                c = shared.value[key]
                for lo in range(0, len(own), 256):
                    some = own[lo : lo + 256]
                    angle = np.arccos(np.clip(_unit(v.take(pa.array(some)).to_pylist()) @ c.T, -1, 1))
                    at = angle.argmin(axis=1)
                    within = angle <= angle[np.arange(len(some)), at][:, None] + reach
                    for n, a, w in zip(some, at, within, strict=True):
                        region[n], near[n] = a, np.flatnonzero(w[:a]).tolist()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(region), pa.array(near, pa.list_(pa.int32()))], names=["label", "dims", "id", "weight", "v", "region", "near"])

    placed = C.cut(held.select("label", "dims", "id", "weight", "v").mapInArrow(run, "label string, dims int, id long, weight long, v array<double>, region int, near array<int>"))
    subs = placed.groupBy("label", "dims", "region").agg(F.ceil(F.count(F.lit(1)) / F.lit(p.shard_rows)).alias("subs"))
    several = subs.groupBy("label", "dims").agg((F.sum("subs") > 1).alias("more"))
    out = placed.join(subs.join(several, ["label", "dims"]), ["label", "dims", "region"]).withColumn("sub", F.pmod(F.xxhash64("id"), F.col("subs")))
    return out.withColumn("shard", F.col("region").cast("long") * F.lit(SUBS) + F.col("sub"))


def groups(vectors: DataFrame, p: Hnsw = Hnsw()) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for each row of vectors (vec_id, embedding, label).

    Vectors are compared only within a label that is not null. Null, empty and zero vectors, and ones
    with null or non-finite components, link with nothing, nor do vectors of different lengths.
    Vectors with equal components are one class whose members link with each other; n_links counts
    members. Ids are taken as unique: rows that repeat one each count as a vector of that id. Other
    columns are ignored. An empty table gives an empty result.
    """
    doubles = F.transform("embedding", lambda x: x.cast("double"))
    bad = F.exists(doubles, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), doubles.alias("v"), F.col("label").alias("label"), bad.alias("bad"))
    fit = F.col("label").isNotNull() & F.col("v").isNotNull() & ~F.coalesce("bad", F.lit(True)) & F.exists("v", lambda x: x != 0)
    plain = F.transform("v", lambda x: F.when(x == 0, F.lit(0.0)).otherwise(x))  # -0 is 0
    rows = C.cut(rows.select("vec_id", F.when(fit, F.col("label").cast("string")).alias("label"), F.when(fit, F.size("v")).alias("dims"), F.when(fit, F.md5(F.array_join(plain, " ").cast("binary"))).alias("key"), F.when(fit, F.col("v")).alias("v")))
    usable = rows.where("key is not null and vec_id is not null")
    classes = usable.groupBy("label", "dims", "key").agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("weight"))
    held = usable.join(classes, ["label", "dims", "key"]).where("vec_id = id").dropDuplicates(["id", "label", "dims", "key"]).select("label", "dims", "id", "weight", "v")
    held = C.cut(_placed(held, p))
    parts = max(1, held.select("label", "dims", "shard").distinct().count())
    spread = held.repartition(parts, "label", "dims", "shard")

    def build(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids, w, e = t["id"].to_numpy(), t["weight"].to_numpy(), _unit(t["v"].to_pylist())
        g = Graph(e.astype(np.float32), p)
        out = _batch(*_answer(g, ids, w, e, ids, w, e, True, p))
        n = out.num_rows
        blob = pickle.dumps((g.layers, g.entry, ids, w, e)) if t["more"][0].as_py() else None
        none = pa.array([None], pa.int64())
        fill = lambda i, kind: pa.array([key[i].as_py()] * (n + 1), kind)
        return pa.table({"id": pa.concat_arrays([*out["id"].chunks, none]), "links": pa.concat_arrays([*out["links"].chunks, none]), "to": pa.concat_arrays([*out["to"].chunks, none]), "label": fill(0, pa.string()), "dims": fill(1, pa.int32()), "shard": fill(2, pa.int64()), "graph": pa.array([None] * n + [blob], pa.binary())})

    built = C.cut(spread.groupBy("label", "dims", "shard").applyInArrow(build, f"{OUT}, label string, dims int, shard long, graph binary"))
    found = built.where("id is not null").select("id", "links", "to")
    graphs = built.where("graph is not null").select("label", "dims", "shard", "graph")
    if not graphs.isEmpty():
        subs = held.select("label", "dims", F.col("region").alias("at"), F.col("subs").alias("n")).distinct()
        row = ["label", "dims", "id", "weight", "v"]
        number = lambda region, sub: (region.cast("long") * F.lit(SUBS) + sub).alias("shard")
        same = held.where("sub > 0").select(*row, F.col("region").alias("at"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("sub") - 1)).alias("t"))
        other = held.select(*row, F.explode("near").alias("at")).join(subs, ["label", "dims", "at"]).select(*row, "at", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("t"))
        asks = same.union(other).select(*row, number(F.col("at"), F.col("t")))
        load = C.cut(asks.groupBy("label", "dims", "shard").agg(F.ceil(F.count(F.lit(1)) / F.lit(p.shard_rows)).alias("chunks")))
        left = graphs.join(load, ["label", "dims", "shard"]).withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)))
        right = asks.join(load, ["label", "dims", "shard"]).withColumn("chunk", F.pmod(F.xxhash64("id"), F.col("chunks")))

        def cross(key: tuple, x: pa.Table, y: pa.Table) -> pa.Table:
            if not x.num_rows or not y.num_rows:
                return _batch([], [], [])
            layers, entry, ids, w, e = pickle.loads(x["graph"][0].as_py())
            g = Graph.__new__(Graph)
            g.x, g.p, g.layers, g.entry = e.astype(np.float32), p, layers, entry
            y = y.sort_by("id")
            return _batch(*_answer(g, ids, w, e, y["id"].to_numpy(), y["weight"].to_numpy(), _unit(y["v"].to_pylist()), False, p))

        keys = ["label", "dims", "shard", "chunk"]
        found = C.cut(found.union(left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(cross, OUT)))
    component = C.components(found.where("id <> to").select(F.col("id").alias("a"), F.col("to").alias("b")))
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    named = classes.join(links, "id", "left").join(component, "id", "left").select("label", "dims", "key", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component_id", "id").alias("component_id"))
    out = rows.drop("v").join(named, ["label", "dims", "key"], "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op10_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of all vectors at cosine 0.98 within a label."""
    return groups(C.table(spark, sf_dir, "embeddings"))
