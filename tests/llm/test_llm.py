"""The training-data operators on small cases: nulls, empty tables, ties, repeats, long texts, clashing names, brute force."""

import base64
import hashlib
import io
import re

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from vecengine.llm import chat, common, embedding_dedup, fingerprints, html_extract, mixing, near_dedup, pieces, sharding, toxicity, warc
from vecengine.llm.queries import ORACLES, QUERIES

WORD = re.compile("[^\x20\x09-\x0d]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
MODEL = f"{pieces.TOKENIZERS}/piece_bpe_32k.model"


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size string, kept string, id string, score string")


def doc(i, text, source="s"):
    return (i, text, "en", source, len(text or ""), "x", "y", "z", "w")


@pytest.fixture(scope="module")
def documents(spark, sf):
    return [(r.doc_id, r.text or "") for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()]


def union_find(ids, links):
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


# ------------------------------------------------------------------------- 1


@pytest.fixture(scope="module")
def weights():
    return html_extract.default_weights()


LONG = "A long paragraph of many words goes here and on and on."
PAGES = {
    "parts and wrappers": (
        """<html><head><title>T</title><style>p{}</style></head><body class="has-sidebar"><header><h1>Site</h1></header>
    <div class="cookie-notice"><p>We use cookies to improve your experience on this site please accept</p></div>
    <div class="post-body"><h1>Title here</h1><p>Para one with many words in the text goes here.</p><div class="ad-box">Buy now this great thing</div>
    <p>Second&nbsp;para  with <b>bo</b>ld text &amp; a <a href=x>link</a>.</p><script>var t="</p>";</script></div>
    <aside>Related stuff you may like to read today</aside><section id="comments"><p>I liked this article very much thanks for posting it.</p></section><footer>Copyright</footer></body></html>""",
        "Title here Para one with many words in the text goes here. Second para with bold text & a link.",
    ),
    "no article, short blocks and a list first": (f"<div><p>Short intro.</p><ul><li>one two</li></ul><h2>Head</h2><p>{LONG}</p></div>", f"Short intro. one two Head {LONG}"),
    "misleading name": (f'<nav><a href=x>a</a></nav><div class="popular-science"><p>{LONG}</p><p>And a second one.</p></div><footer>foot words</footer>', f"{LONG} And a second one."),
    "references and line breaks": ("<p>A&nbsp;B C<br>D and E words go on</p>", "A B C D and E words go on"),
    "form around the page": (f"<form id=f><div class=menu><a href=x>a</a> <a href=y>b</a></div><div class=content><p>{LONG}</p><p>More text.</p></div></form>", f"{LONG} More text."),
    "wrapper named after a part": (f"<div class='content-sidebar-wrap'><div class='post'><h1 class=page-header>Title words</h1><p>{LONG}</p></div><div class=sidebar><p>Side text that is not wanted</p></div></div>", f"Title words {LONG}"),
    "more comments than article": ("<article><h1>T</h1><p>Short article of words.</p></article><div class=comments><p>" + "long comment words " * 40 + "</p></div>", "T Short article of words."),
    "overflow is visible": (f"<div style='overflow:hidden' class=overflow-hidden><p>{LONG}</p></div>", LONG),
    "link first": (f"<article><p><a href=a>Linked words</a></p><p>{LONG}</p></article>", f"Linked words {LONG}"),
}


@pytest.mark.parametrize("name", PAGES)
def test_html_layouts(weights, name):
    page, want = PAGES[name]
    assert html_extract.extract(page, weights) == want


@pytest.mark.parametrize("page", [None, "", " ", "</p></p>", "<script>x", "<nav>a b c</nav>", "<html></html>", "<nav><a href=x>a</a></nav>", "<p", "<!-- x", "<script>var a = 1;", "</p></div>", "<div hidden><p>words not to be seen</p></div>"])
def test_html_without_content(weights, page):
    assert html_extract.extract(page, weights) == ""


def brute_run(scores):
    best, at = 0.0, (0, 0)
    for i in range(len(scores)):
        total = 0.0
        for j in range(i, len(scores)):
            total += scores[j]
            if total > best + 1e-9:
                best, at = total, (i, j + 1)
    return best, at


def test_html_best_run_is_brute_force(weights):
    rng = np.random.default_rng(0)
    for _ in range(200):
        s = [float(x) for x in rng.integers(-4, 4, rng.integers(0, 12))]
        i, j = html_extract.best_run(s)
        assert sum(s[i:j]) == brute_run(s)[0]
    for page in list(html_extract.labelled_layouts(20, 5)):  # whole pages
        scores = html_extract.scored(html_extract.parse(page), weights)[1]
        i, j = html_extract.best_run(scores)
        assert sum(scores[i:j]) == pytest.approx(brute_run(scores)[0])


def test_html_text_is_the_run(weights, monkeypatch):
    """The run decides: words outside of it are lost, and without it so is the text."""
    page = f"<article><p>{LONG}</p></article><div>{'<hr>' * 40}</div><p>Far words.</p>"
    assert html_extract.extract(page, weights) == LONG
    monkeypatch.setattr(html_extract, "best_run", lambda scores: (len(scores) - 3, len(scores) - 1))
    assert html_extract.extract(page, weights) == "Far words."


def test_html_weights(weights):
    assert all(weights.tokens[k] > 0 for k in ("word:plain", "word:head", "word:item", "word:linked")) and weights.tokens["word:link"] < 0
    assert all(v < 0 for k, v in weights.tokens.items() if not k.startswith("word:")) and weights.other < 0
    assert weights.marks["name:comments"] < -3 < 0 < weights.marks["name:content"]


def test_html_held_out_layouts(weights):
    """Layouts that were not fitted on: nine in ten to the letter."""
    right = 0
    for page in html_extract.labelled_layouts(200, 99):
        text, (i, j) = html_extract.labelled_by_mark(page)
        parsed = html_extract.parse(text)
        want = "".join((t[1] if t[0].startswith("word:") else " " * (t[0].lstrip("/") not in html_extract.INLINE)) for t in parsed.tokens[i:j] if not t[3])
        right += html_extract.extract(text, weights) == " ".join(want.split())
    assert right >= 180


def test_html_query(spark, sf):
    rows = spark.read.parquet(f"{sf}/pages.parquet").collect()
    got = {r.page_id: r for r in QUERIES["op1_extract_html"](spark, sf).collect()}
    assert len(got) == len(rows)
    import html

    for r in rows:
        inner = re.sub(r"<[^>]*>", lambda m: "" if m.group().strip("</>") in ("a", "b") else " ", re.search(r"<article>(.*)</article>", r.html, re.S)[1])
        assert got[r.page_id].text == " ".join(html.unescape(inner).split()) and got[r.page_id].n_chars == len(got[r.page_id].text)


def test_html_odd_tables(spark, weights):
    long = "<article>" + f"<p>{LONG}</p>" * 20_000 + "</article>"
    rows = [(1, "u", PAGES["link first"][0], "c"), (1, "u", PAGES["link first"][0], "c"), (2, None, None, "c"), (None, "u", "", None), (3, "u", long, "c")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = html_extract.extract_pages(df, weights).collect()
    assert sorted((r.page_id or 0, r.n_chars) for r in got) == [(0, 0), (1, 13 + len(LONG)), (1, 13 + len(LONG)), (2, 0), (3, 20_000 * (len(LONG) + 1) - 1)]
    assert html_extract.extract_pages(df.limit(0), weights).collect() == [] and html_extract.labelled_sample(df.limit(0), 8) == []


# ------------------------------------------------------------------------- 2


def test_pieces_equal_the_library(documents):
    import sentencepiece

    lib, e = sentencepiece.SentencePieceProcessor(model_file=MODEL), pieces.Encoder(pieces.load(MODEL))
    texts = [t for _, t in documents[:60]] + ["", " ", "   ", "a\n\n b\t", "  two  spaces   x", "日本語🙂 x", "x" * 900 + " y", "12345 1.5,", "a▁b", "ÀÉ́", "Hello, world! internationalization antidisestablishmentarianism"]
    raw, off = common.utf8_buffer(pa.array(texts))
    ids, b = e.encode(raw, off)
    back, place = pieces.decode(e.v, ids, b)
    for i, t in enumerate(texts):
        assert ids[b[i] : b[i + 1]].tolist() == lib.encode(t)
        assert back[place[i] : place[i + 1]].tobytes().decode() == t.replace("▁", " ")
    again, _ = e.encode(raw, off)  # from the kept units
    assert np.array_equal(ids, again)


def test_unigram_paths_are_best():
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    with open(MODEL, "rb") as f:
        m.ParseFromString(f.read())
    m.trainer_spec.model_type = 1
    for p in m.pieces:
        p.score = p.score / 1000 - 5 if p.type == 1 else p.score
    v = pieces.build(m)
    e = pieces.Encoder(v)
    score = {v.data[v.bounds[i] : v.bounds[i + 1]].decode(): float(v.scores[i]) for i in v.ids}
    for t in ("therehouse", "unbelievable", "é日x"):
        raw, off = common.utf8_buffer(pa.array([t]))
        ids, _ = e.encode(raw, off)
        want = pieces.best_path(" " + t, score, float(v.floor), v.longest)
        flat = [x for p in want for x in ([v.ids[[k for k in range(len(v.ids)) if v.data[v.bounds[v.ids[k]] : v.bounds[v.ids[k] + 1]].decode() == p]][0]] if p in score else v.byte_ids[list(p.encode())].tolist())]
        assert ids.tolist() == flat


def test_pieces_frames(spark):
    rows = docs_of(spark, [doc(1, "a b"), doc(1, "a b"), doc(2, None), doc(None, "x" * 5000)])
    out = pieces.encode_texts(rows, MODEL).collect()
    assert len(out) == 4 and all(r.round_trip for r in out) and sorted(r.n_tokens for r in out)[0] == 0
    assert sorted(r.text for r in pieces.decode_ids(pieces.encode_texts(rows, MODEL), MODEL).collect()) == ["", "a b", "a b", "x" * 5000]
    assert pieces.encode_texts(rows.limit(0), MODEL).collect() == []


# ------------------------------------------------------------------------- 3


def test_toxicity_learns(spark):
    rng = np.random.default_rng(0)
    rows, labels = [], []
    for i in range(600):
        words = [f"w{rng.integers(200)}" for _ in range(30)]
        bad = i % 5 == 1
        if bad:
            words[rng.integers(30)] = ["grumble", "snarlix", f"vexo{rng.integers(1000)}"][rng.integers(3)]
        rows.append(doc(i, " ".join(words) + "."))
        labels.append((i, int(bad)))
    labels += [(1, None), (99999, 1), (None, 1)]
    docs = docs_of(spark, [*rows, doc(None, None), doc(700, ""), doc(3, "w1 w2")])
    out = toxicity.judge(docs, spark.createDataFrame(labels, "doc_id long, toxic int")).collect()
    assert len(out) == 603 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in out)
    known = dict(labels[:600])
    held = [r for r in out if r.held_out and r.doc_id in known and r.doc_id != 3]
    assert sum(r.predicted == known[r.doc_id] for r in held) >= 0.97 * len(held)
    assert all(not r.predicted for r in out if r.doc_id in (None, 700))
    import zlib

    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in out if r.doc_id is not None)
    again = {r.doc_id: r.score for r in toxicity.judge(docs, spark.createDataFrame(labels, "doc_id long, toxic int")).collect() if r.doc_id != 3}
    assert all(again[r.doc_id] == pytest.approx(r.score, abs=1e-9) for r in out if r.doc_id != 3)


def test_toxicity_without_labels(spark):
    docs = docs_of(spark, [doc(1, "you are an idiot"), doc(2, "good day")])
    out = {r.doc_id: r.predicted for r in toxicity.judge(docs, spark.createDataFrame([], "doc_id long, toxic int")).collect()}
    assert out == {1: 1, 2: 0}
    assert toxicity.judge(docs.limit(0), spark.createDataFrame([(1, 1)], "doc_id long, toxic int")).collect() == []


def voters(n=4000, seed=1):
    rng = np.random.default_rng(seed)
    y = rng.random(n) < 0.3
    say = lambda acc: np.where(rng.random(n) < acc, y, ~y) * 2 - 1
    fair = say(0.8)
    copy = np.where(rng.random(n) < 0.95, fair, -fair)
    return y, np.stack([say(0.95), fair, copy, say(0.85), rng.integers(-1, 2, n)], axis=1)


def test_label_model_finds_accuracies_and_dependences():
    y, votes = voters()
    believed = np.where(np.random.default_rng(2).random(len(y)) < 0.9, y, ~y)  # a tenth of the labels is wrong
    m = toxicity.fit_label_model(votes, 0.3, believed, trust=1.0)
    assert (((m.posterior(votes) > 0.5) == y).mean()) > 0.95
    assert m.leans[2] == 1 or m.leans[1] == 2  # a voter and its copy
    right = toxicity.fit_label_model(votes, 0.3, y).accuracy()
    assert right[:4] == pytest.approx([0.95, 0.8, 0.77, 0.85], abs=0.03)
    pair = np.array([[0, 1, 1, 0, 0], [0, 1, 0, 0, 0]])
    naive = np.log(m.posterior(pair) / (1 - m.posterior(pair)))
    assert abs(naive[0] - naive[1]) < 1.0  # the copy adds little


def test_label_model_is_brute_force():
    _, votes = voters(60, 5)
    votes, believed = votes[:, :4], np.arange(60) % 4 == 0
    m = toxicity.fit_label_model(votes, 0.3, believed, trust=2.0, rounds=3, trees=1, least=0.0)
    rows, n_voters = votes.tolist(), 4

    def tables(q, leans, trust):
        says = {}
        for j in range(n_voters):
            for y in (0, 1):
                for u in (-1, 0, 1):
                    share = []
                    for v in (-1, 0, 1):
                        fits = [i for i, r in enumerate(rows) if r[j] == v and (leans[j] < 0 or r[leans[j]] == u)]
                        share.append(0.5 + sum((q[i] if y else 1 - q[i]) + trust * (believed[i] == y) for i in fits))
                    says[j, y, u] = [x / sum(share) for x in share]
        return says

    def beliefs(says, leans, prior):
        out = []
        for r in rows:
            p = [1 - prior, prior]
            for y in (0, 1):
                for j in range(n_voters):
                    p[y] *= says[j, y, r[leans[j]] if leans[j] >= 0 else 0][r[j] + 1]
            out.append(p[1] / (p[0] + p[1]))
        return out

    zero = [0.0] * 60
    alone = [-1] * n_voters
    first = {}
    for j in range(n_voters):  # labels only
        for y in (0, 1):
            share = [0.5 + 2.0 * sum(r[j] == v for i, r in enumerate(rows) if believed[i] == y) for v in (-1, 0, 1)]
            for u in (-1, 0, 1):
                first[j, y, u] = [x / sum(share) for x in share]
    q, prior = beliefs(first, alone, 0.3), 0.3
    del zero
    for leans in (alone, m.leans.tolist()):
        for _ in range(3):
            says, prior = tables(q, leans, 2.0), (2.0 * 0.3 * 60 + sum(q)) / 180
            q = beliefs(says, leans, prior)
    assert m.posterior(votes) == pytest.approx(q, abs=1e-9)

    import itertools

    shared = toxicity.dependence(2.0 * toxicity.pair_counts(votes, believed.astype(float)) + 0.5)
    weight = lambda edges: sum(shared[a, b] for a, b in edges)
    trees = [t for t in itertools.combinations(itertools.combinations(range(4), 2), 3) if len(set(union_find(range(4), t).values())) == 1]
    tree = toxicity.spanning_tree(shared, -1.0)
    assert weight([(j, up) for j, up in enumerate(tree) if up >= 0]) == pytest.approx(max(map(weight, trees)))


def test_toxicity_does_not_depend_on_batches(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    odd = docs.select("doc_id", "text").union(docs.selectExpr("doc_id + 100000", "'THIS IS A SHOUTED TEXT! YOU ALL'").limit(2)).union(docs.selectExpr("doc_id + 200000", "'plain \u00e9 \u0130STANBUL'").limit(1))
    size, got = "spark.sql.execution.arrow.maxRecordsPerBatch", []
    before = spark.conf.get(size)
    try:
        for rows in ("1", "7", "10000"):
            spark.conf.set(size, rows)
            got.append(sorted((r.doc_id, r.score) for r in toxicity.judge(odd, labels).collect()))
    finally:
        spark.conf.set(size, before)
    assert got[0] == got[1] == got[2]
    shape = lambda *texts: [toxicity.text_features(*t)[3][:, 3].tolist() for _, _, t in toxicity.slices(pa.array(texts))][0]
    assert shape("ABC def", "plain") == shape("ABC def", "plain \u00e9") == [0.5, 0.0]


def test_toxicity_held_out(spark):
    from pyspark.sql import functions as F

    sf = "/root/testdata/sf0.01"
    out = QUERIES["op3_toxicity"](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out and toxic is not null").select("score", F.col("toxic") > 0).collect()
    pairs = [(a > b) + 0.5 * (a == b) for a, y in out if y for b, z in out if not z]
    assert sum(pairs) / len(pairs) > 0.85 and not any(a >= 0.5 for a, y in out if not y)


def test_toxicity_very_long_text(spark):
    long = "calm words in a row " * 200_000
    docs = docs_of(spark, [doc(1, long), doc(2, long + " idiot moron"), doc(3, "x" * 3_000_000)])
    assert len(toxicity.judge(docs, spark.createDataFrame([], "doc_id long, toxic int")).collect()) == 3


# ------------------------------------------------------------------------- 4


def test_shards(spark, tmp_path):
    store = sharding.ShardStore(spark, f"file://{tmp_path}/s", small=2000, target=20_000, fan=3)
    df = spark.range(0, 3000, 1, 8).selectExpr("id as doc_id", "sha2(cast(id as string), 256) as text", "cast(null as string) as n")
    assert store.append(df) == 1
    before = len(store.shards()[1])
    store.append(df.limit(10))
    version = store.compact(final=True)
    live = store.shards()[1]
    assert version > 2 and len(live) < before and sum(s.rows for s in live) == 3010
    got = store.read()
    assert got.count() == 3010 and got.select("doc_id", "text").exceptAll(df.union(df.limit(10)).select("doc_id", "text")).isEmpty()
    with pytest.raises(sharding.Conflict):
        store.commit(version - 1, [], "late writer")
    assert store.shards()[0] == version
    with pytest.raises(sharding.Conflict):
        store.change([], {"gone"}, "merge")
    assert store.versions() == list(range(1, version + 1))


def test_shards_of_odd_tables(spark):
    rows = docs_of(spark, [doc(None, None), doc(1, ""), doc(1, ""), doc(2, "x" * 100_000)]).drop("size", "kept", "id", "score")
    out = sharding.shard_documents(rows)
    assert sorted((r.doc_id or 0, len(r.text or "")) for r in out.collect()) == [(0, 0), (1, 0), (1, 0), (2, 100_000)]
    assert sharding.shard_documents(rows.limit(0)).collect() == []
    with pytest.raises(ValueError):
        sharding.shard_documents(rows.withColumn("Shard", F.lit(1)))


def test_shards_sql(spark, sf):
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    out = QUERIES["op4_sharding"](spark, sf)
    rows = con.sql(ORACLES["op4_sharding"])
    key = lambda r: tuple(map(str, r))
    assert sorted(map(tuple, out.select(*rows.columns).collect()), key=key) == sorted(rows.fetchall(), key=key)
    assert all(callable(q) for q in QUERIES.values()) and all(isinstance(q, str) for q in ORACLES.values())


def test_vacuum_by_age(spark, tmp_path):
    import os
    import time

    store = sharding.ShardStore(spark, f"file://{tmp_path}/s", small=2000, target=20_000, fan=3)
    df = spark.range(0, 3000, 1, 8).selectExpr("id as doc_id", "sha2(cast(id as string), 256) as text")
    store.append(df)
    first, files = store.shards()[0], lambda: {f for f in os.listdir(tmp_path / "s" / "data") if f.endswith(".parquet")}
    store.compact(final=True)
    assert store.vacuum() == 0 and store.read(first).count() == 3000  # young versions and their files stay
    (tmp_path / "s" / "data" / "shard-orphan.parquet").write_bytes(b"x")  # of a writer that died long ago
    old = time.time() - 30 * 86_400
    for name in ("shard-orphan.parquet", *(s.name for s in store.shards(first)[1])):
        os.utime(tmp_path / "s" / "data" / name, (old, old))
    assert store.vacuum() == 1 and "shard-orphan.parquet" not in files()  # an old version's manifest is young still
    os.utime(tmp_path / "s" / "manifest" / f"v{first:09d}.json", (old, old))
    gone = len(store.shards(first)[1])
    assert store.vacuum() == gone and files() >= {s.name for s in store.shards()[1]} and store.read().count() == 3000
    assert first not in store.versions()


# ------------------------------------------------------------------------- 5


def test_mixing_budgets(spark):
    rows = [doc(i, "w " * (i % 7), f"s{i % 4}" if i % 9 else None) for i in range(300)] + [doc(5, "a b", "s1"), doc(None, None, None), doc(900, "x" * 9, "tiny")]
    out = mixing.mix(docs_of(spark, rows)).collect()
    assert len(out) == 303
    total = sum(r.size for r in out)
    by = {}
    for r in out:
        assert 0 <= r.taken <= 2 * r.size and r.target <= 2 * r.source_size + 1e-9
        by.setdefault((r.source_size, r.target), []).append(r.taken)
    assert all(abs(sum(v) - k[1]) < 1 for k, v in by.items())
    assert sum(k[1] for k in by) == pytest.approx(1.5 * total)
    key = lambda r: (r.doc_id or -1, r.size, r.taken)
    assert sorted(map(key, out)) == sorted(map(key, mixing.mix(docs_of(spark, rows[::-1])).collect()))
    assert mixing.mix(docs_of(spark, rows).limit(0)).collect() == []


def test_mixing_sql(spark, sf):
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    want = sorted(con.sql(ORACLES["op5_mix_sources"]).fetchall())
    assert want == sorted(tuple(r) for r in QUERIES["op5_mix_sources"](spark, sf).collect())


# ------------------------------------------------------------------------- 6


def brute_groups(rows, words, percent):
    sets = {}
    for i, t in rows:
        w = WORD.findall((t or "").translate(LOW))
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    ids = sorted(sets)
    links = [(a, b) for x, a in enumerate(ids) for b in ids[x + 1 :] if sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    return {i: len(s) for i, s in sets.items()}, union_find(ids, links)


@pytest.mark.parametrize("words", [2, 5])
def test_near_dedup_is_brute_force(spark, words):
    rng = np.random.default_rng(words)
    base = [f"w{rng.integers(500)}" for _ in range(120)]
    rows = [(i, " ".join(f"v{rng.integers(900)}" for _ in range(rng.integers(1, 80)))) for i in range(60)]
    for i in range(60, 130):  # a chain of near copies around the threshold
        own = list(base)
        for _ in range(rng.integers(0, 9)):
            own[rng.integers(120)] = f"x{rng.integers(10**6)}"
        rows.append((i, " ".join(own)))
    rows += [(200, "A b  C"), (201, "a\tB c"), (202, None), (203, ""), (204, " \n"), (205, "one"), (206, "ONE"), (207, "é É"), (208, "é é")]
    sizes, roots = brute_groups(rows, words, 80)
    df = docs_of(spark, [doc(i, t) for i, t in rows])
    got = near_dedup.groups(df, near_dedup.NearDup(words=words)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in got} == {i: (sizes[i], roots[i], roots[i] == i) for i in sizes}


def test_near_dedup_odd_tables(spark):
    rows = docs_of(spark, [doc(3, "a b c"), doc(3, "a b c"), doc(None, "a b c"), doc(1, "A B C")])
    got = sorted((r.doc_id or 0, r.component_id) for r in near_dedup.groups(rows, near_dedup.NearDup(words=2)).collect())
    assert got == [(0, 1), (1, 1), (3, 1), (3, 1)]
    assert near_dedup.groups(rows.limit(0), near_dedup.NearDup()).collect() == []
    one, two = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    rows = docs_of(spark, [doc(1, one), doc(1, two), doc(2, one + " x"), doc(3, two + " y"), doc(4, "z " * 3_000_000)])  # an id of two texts
    got = sorted((r.doc_id, r.n_shingles, r.component_id) for r in near_dedup.groups(rows, near_dedup.NearDup(words=2)).collect())
    assert got == [(1, 59, 1), (1, 59, 1), (2, 60, 1), (3, 60, 1), (4, 1, 4)]


def test_sketches_tell_near_from_far():
    p = near_dedup.NearDup(words=1)
    texts = [" ".join(f"w{i}" for i in range(400)), " ".join(f"w{i}" for i in range(40, 440)), " ".join(f"u{i}" for i in range(400))]
    value, bounds = near_dedup.shingle_sets(*common.utf8_buffer(pa.array(texts)), 1)
    _, sketch = near_dedup.signatures(value, bounds, p)
    flips = lambda a, b: int(np.bitwise_count(sketch[a] ^ sketch[b]).sum())
    assert flips(0, 1) <= near_dedup.most_flips(p) < flips(0, 2)


@pytest.mark.parametrize("one_task", [0, 1000])
def test_components(spark, one_task):
    rng = np.random.default_rng(3)
    links = [(int(a), int(b)) for a, b in rng.integers(0, 300, (200, 2))] + [(i, i + 1) for i in range(500, 560)] + [(7, 7)]
    want = union_find(range(600), links)
    got = {r.id: r.component_id for r in common.components(spark.createDataFrame(links, "a long, b long"), one_task=one_task).collect()}
    assert all(want[k] == v for k, v in got.items()) and {x for a, b in links if a != b for x in (a, b)} == set(got)


# ------------------------------------------------------------------------- 7


def records(n=4, size=100):
    return [warc.encode([("WARC-Type", "response"), ("WARC-Record-ID", f"<urn:page:{i}>"), ("Content-Type", "application/http; msgtype=response")], b"HTTP/1.1 200 OK\r\n\r\n" + bytes([65 + i]) * size * i) for i in range(1, n + 1)]


def read(data):
    return [(x.begin, x.end, "gap" if isinstance(x, warc.Gap) else x.headers["warc-record-id"][10:-1]) for x in warc.read(io.BytesIO(data))]


@pytest.mark.parametrize("zipped", [True, False])
@pytest.mark.parametrize("damage", ["none", "flip", "cut", "junk", "head", "hole"])
def test_salvage(zipped, damage):
    parts = [warc.member(r) if zipped else r for r in records()]
    data, ends = bytearray(b"".join(parts)), np.cumsum([len(p) for p in parts])
    lost = set()
    if damage == "flip":
        at = int(ends[0]) + (40 if zipped else 3)
        data[at] ^= 255
        lost = {"2"}
    elif damage == "cut":
        data, lost = data[: int(ends[3]) - 60], {"4"}
    elif damage == "junk":
        data = b"garbage" + data
    elif damage == "head":
        data, lost = data[20:], {"1"}
    elif damage == "hole":
        data, lost = data[: int(ends[0])] + b"\0" * 5000 + data[int(ends[1]) :], {"2"}
    got = read(bytes(data))
    assert {x[2] for x in got} - {"gap"} == {"1", "2", "3", "4"} - lost
    assert got[0][0] == 0 and got[-1][1] == len(data) and all(a[1] == b[0] for a, b in zip(got, got[1:], strict=False))
    assert any(x[2] == "gap" for x in got) == (damage != "none")


def test_warc_round_trip(spark):
    rows = [(1, None, "a", 0), (2, "u\r\nx", "a", 0), (3, "u", None, 0), (4, "u", "", 0), (5, "v", "b", 0), (5, "v", "b", 0), (None, "w", "zz", 0), (6, "é", "ü" * 100_000, 0)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, holder long")
    got = sorted(((r.page_id or 0, r.payload_bytes, r.record_type, r.refers_to) for r in warc.round_trip(df).collect()), key=str)
    assert got == sorted([(1, 1, "revisit", 2), (2, 1, "response", None), (3, 0, "revisit", 4), (4, 0, "response", None), (5, 1, "response", None), (5, 1, "response", None), (0, 2, "response", None), (6, 200_000, "response", None)], key=str)
    digest = {r.page_id: r.payload_digest for r in warc.round_trip(df).collect()}
    assert digest[1] == digest[2] == base64.b32encode(hashlib.sha1(b"a").digest()).decode()
    assert warc.round_trip(df.limit(0)).collect() == []


# ------------------------------------------------------------------------- 8


def test_quotes(spark):
    rows = [(1, 0, "u", "Hello there\nfriend"), (1, 1, "a", "> hello THERE\n> friend\nHi back"), (1, 2, "u", ">> Hello there\n>> friend\n> Hi back\n\nthird"), (1, 3, "a", "On Monday X wrote:\n> Hello there\n> friend\n\nanswer to first"), (2, 0, "u", "> third\nother"), (1, 4, "u", "> not known\nx"), (None, None, None, None), (1, 0, "u", "Hello there\nfriend")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("depth", F.lit("clash"))
    got = {(r.conv_id, r.turn): (r.text, r.parent_turn, r.linked_by, r.depth, r.n_quotes, r.n_linked) for r in chat.conversations(df).collect()}
    assert got == {
        (1, 0): ("Hello there\nfriend", None, "root", 0, 0, 0),
        (1, 1): ("Hi back", 0, "quote", 1, 1, 1),
        (1, 2): ("third", 1, "quote", 2, 2, 2),
        (1, 3): ("answer to first", 0, "quote", 1, 1, 1),
        (1, 4): ("x", 3, "order", 2, 1, 0),
        (2, 0): ("other", None, "root", 0, 1, 1),
        (None, None): ("", None, "root", 0, 0, 0),
    }
    assert chat.conversations(df.limit(0)).collect() == []


def brute_links(messages):
    """(n_quotes, n_linked, parent, how) of each (conversation, turn), by loops over all messages."""
    parsed = {k: chat.parse(t) for k, t in messages.items()}
    own = {k: set(p[1]) for k, p in parsed.items()}
    bits = {k: set(chat.pieces(p[0])) for k, p in parsed.items()}
    turns = lambda conv: sorted(t for c, t in messages if c == conv)
    out = {}
    for conv, turn in messages:
        before = [t for t in turns(conv) if t < turn]
        others = sorted(k for k in messages if k[0] != conv)
        total = linked = 0
        answers = []
        for level, key, pieces in parsed[conv, turn][2]:
            total += 1
            author = max(((conv, t) for t in before if key in own[conv, t]), default=None)
            if author is None:
                votes = [max((t for t in before if x in bits[conv, t]), default=None) for x in set(pieces)]
                votes = [v for v in votes if v is not None]
                author = (conv, max(set(votes), key=lambda t: (votes.count(t), t))) if votes else None
            if author is None:
                author = min((k for k in others if key in own[k]), default=None)
            if author is None:
                votes = [min((k for k in others if x in bits[k]), default=None) for x in set(pieces)]
                votes = [v for v in votes if v is not None]
                author = min(set(votes), key=lambda k: (-votes.count(k), k)) if votes else None
            linked += author is not None
            if author is not None and author[0] == conv and level == 1:
                answers.append(author[1])
        parent = max(answers, default=before[-1] if before else None)
        out[conv, turn] = (total, linked, parent, "quote" if answers else "order" if before else "root")
    return out


@pytest.mark.parametrize("seed", range(3))
def test_quote_links_are_brute_force(spark, seed):
    rng = np.random.default_rng(seed)
    word = lambda: f"w{rng.integers(40)}"
    sentence = lambda: " ".join(word() for _ in range(rng.integers(2, 5))) + "."
    common = [sentence() for _ in range(4)]
    said, messages = [], {}
    for conv in range(4):
        for turn in range(int(rng.integers(1, 30 if conv else 60))):
            lines = []
            for _ in range(rng.integers(0, 3)):
                if said:
                    body = said[rng.integers(len(said))]
                    how = rng.integers(4)
                    body = body if how == 0 else body.split("\n\n")[0] if how == 1 else "[...] " + body.split(". ")[0].strip() + " ..." if how == 2 else f"{sentence()} {body.split('. ')[-1]}"
                    lines += [(">" * int(rng.integers(1, 3))) + " " + x for x in body.split("\n")] + [""] * int(rng.integers(0, 2))
            mine = ["\n\n", " "][rng.integers(2)].join(common[rng.integers(4)] if rng.random() < 0.3 else sentence() for _ in range(rng.integers(1, 4)))
            messages[conv, turn] = "\n".join([*lines, mine])
            said.append(mine)
    df = spark.createDataFrame([(c, t, "u", x) for (c, t), x in messages.items()], "conv_id long, turn long, role string, text string")
    got = {(r.conv_id, r.turn): (r.n_quotes, r.n_linked, r.parent_turn, r.linked_by) for r in chat.conversations(df).collect()}
    assert got == brute_links(messages)


def test_quotes_of_hot_and_long_messages(spark):
    """One conversation of nearly all rows, the same line in each, and a very long text."""
    rows = [(7, t, "u", f"ok\n> ok\nword{t}" if t else "ok") for t in range(1_500)] + [(8, 0, "u", "> ok\n" + "long line " * 300_000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {(r.conv_id, r.turn): r for r in chat.conversations(df).collect()}
    assert len(got) == 1_501 and all(got[7, t].parent_turn == t - 1 and got[7, t].depth == t and got[7, t].position == t + 1 for t in range(1, 1_500))
    assert got[8, 0].n_linked == 1 and got[8, 0].linked_by == "root"


def test_long_threads(spark):
    df = spark.createDataFrame([(1, i, "u", f"message {i}") for i in range(200)], "conv_id long, turn long, role string, text string")
    got = {r.turn: (r.depth, r.position, r.parent_turn, r.text) for r in chat.conversations(chat.as_mail(df)).collect()}
    assert got == {i: (i, i + 1, i - 1 if i else None, f"message {i}") for i in range(200)}


# ------------------------------------------------------------------------- 9


def brute_anchors(text, k=4, s=2):
    h64 = lambda *parts: parts

    def xx(*values):
        seed = 42
        for v in values:
            data = v.encode() if isinstance(v, str) else (v & ((1 << 64) - 1)).to_bytes(8, "little")
            seed = xxhash.xxh64_intdigest(data, seed)
        return seed - (1 << 64) if seed >= 1 << 63 else seed

    del h64
    words = [w[i : i + fingerprints.PIECE] for w in WORD.findall(text) for i in range(0, len(w), fingerprints.PIECE)]
    h = [xx(w) for w in words]
    if not h:
        return []
    if len(h) < k:
        a = 0
        for x in h:
            a = xx(a, x)
        return [(a, 1)]
    g = [xx(a, b) for a, b in zip(h, h[1:], strict=False)]
    width = k - s + 1
    return [(xx(g[i], g[i + 2]), i + 1) for i in range(len(g) - width + 1) if min(g[i], g[i + width - 1]) <= min(g[i + 1 : i + width - 1])]


def test_anchors_are_brute_force(spark, documents):
    few = [(i, t[:3000]) for i, t in documents[:40] if not re.search("[⺀-鿿가-힯豈-﫿]", t)] + [(-1, ""), (-2, "one"), (-3, "a b c"), (-4, "a b c d"), (-5, "x" * 100)]
    df = spark.createDataFrame(few, "id long, text string")
    got = {r.id: [(x.h, x.at) for x in r.a] for r in df.select("id", fingerprints.anchors(F.col("text")).alias("a")).collect()}
    assert got == {i: brute_anchors(t) for i, t in few}


def test_anchors_survive_context(spark):
    core = " ".join(f"w{i}" for i in range(50))
    df = spark.createDataFrame([("a b c " + core,), ("zz " + core + " tail words here",)], "text string")
    a, b = (dict((x.h, x.at) for x in r.a) for r in df.select(fingerprints.anchors(F.col("text")).alias("a")).collect())
    both = set(a) & set(b)
    assert len(both) > 15 and len({b[h] - a[h] for h in both}) == 1
    m = df.select(fingerprints.sketch(F.col("text")).alias("f")).collect()
    s = spark.createDataFrame([(m[0].f, m[1].f)], "a array<struct<h: long, at: int>>, b array<struct<h: long, at: int>>")
    assert {x.shift for x in s.select(fingerprints.matches(F.col("a"), F.col("b")).alias("m")).first().m} == {-2}


def test_fingerprint_query(spark, sf, documents):
    got = {r.doc_id: r for r in QUERIES["op9_closed_syncmers"](spark, sf).collect()}
    assert len(got) == len(documents)
    for n, (i, t) in enumerate(documents):
        nxt, half = documents[(n + 1) % len(documents)][1], len(t) // 2
        assert got[i].n_chars == len(t) and got[i].edited_sha256 == hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest()
        own = sorted({h: a for h, a in reversed(brute_anchors(t))}.items())[:64] if not re.search("[⺀-鿿가-힯豈-﫿]", t) else None
        if own is not None:
            assert got[i].fingerprint == " ".join(f"{h & ((1 << 64) - 1):016x}@{a}" for h, a in own)
    assert np.mean([r.near_edited for r in got.values()]) > 0.2 > np.mean([r.near_next for r in got.values()])


def test_fingerprint_odd_tables(spark):
    rows = docs_of(spark, [doc(1, "a b c d e"), doc(1, "a b c d e"), doc(None, None), doc(5, ""), doc(5, "other")])
    got = fingerprints.compare_with_next(rows).collect()
    assert len(got) == 5 and all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    one = fingerprints.compare_with_next(docs_of(spark, [doc(9, "a b c d e f")])).first()
    assert one.near_next == 1.0
    assert fingerprints.compare_with_next(rows.limit(0)).collect() == []


# ------------------------------------------------------------------------ 10


@pytest.mark.parametrize("shard_rows", [20_000, 90])
def test_embedding_groups_are_brute_force(spark, shard_rows):
    rng = np.random.default_rng(4)
    x = rng.standard_normal((400, 16)).astype(np.float32)
    x[100:200] = x[7] + 0.05 * rng.standard_normal((100, 16))
    x[200:210] = x[3]
    x[210] = 2 * x[3]
    rows = [(i, [float(v) for v in row], i % 2, "c") for i, row in enumerate(x)]
    rows += [(900, None, 1, "c"), (901, [0.0] * 16, 1, "c"), (902, [float("nan")] * 16, 1, "c"), (903, [1.0, None], 1, "c"), (904, [1.0] * 16, None, "c"), (905, [], 0, "c")]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, links string")
    e = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    near = (e @ e.T >= 0.98) & (np.arange(400)[:, None] % 2 == np.arange(400) % 2)
    np.fill_diagonal(near, False)
    roots = union_find([r[0] for r in rows], list(zip(*map(list, np.nonzero(near)), strict=True)))
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_dedup.groups(df, embedding_dedup.Hnsw(shard_rows=shard_rows)).collect()}
    assert got == {i: (int(near[i].sum()) if i < 400 else 0, roots[i], roots[i] == i) for i, *_ in rows}
    assert embedding_dedup.groups(df.limit(0)).collect() == []


@pytest.mark.parametrize("regions", [4096, 3])
def test_embedding_regions_lose_no_link(spark, regions):
    rng = np.random.default_rng(6)
    centres = rng.standard_normal((12, 24))
    x = np.concatenate([centres[rng.integers(12, size=600)] + 0.35 * rng.standard_normal((600, 24)), centres[:1] + 0.02 * rng.standard_normal((80, 24))])
    x[600:640] *= 3.0
    df = spark.createDataFrame([(i, [float(v) for v in row], "l") for i, row in enumerate(x)], "vec_id long, embedding array<double>, label string")
    p = embedding_dedup.Hnsw(shard_rows=40, regions=regions)
    e = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = e @ e.T >= 0.98
    np.fill_diagonal(near, False)
    roots = union_find(range(680), list(zip(*map(list, np.nonzero(near)), strict=True)))
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dedup.groups(df, p).collect()}
    assert got == {i: (int(near[i].sum()), roots[i]) for i in range(680)} and near.any()
    rows = embedding_dedup._placed(df.selectExpr("label", "24 as dims", "vec_id as id", "1L as weight", "embedding as v"), p).collect()
    assert len({r.region for r in rows}) > 1 and len({r.shard for r in rows}) > 10
    if regions > 100:  # most regions cannot hold links of a vector
        assert np.mean([len(r.near) for r in rows]) < 0.8 * np.mean([r.region for r in rows])


# ------------------------------------------------------------------- pipeline


def test_pipeline_is_brute_force(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    scored = {r.doc_id: r.score for r in toxicity.judge(docs, spark.read.parquet(f"{sf}/labels.parquet")).collect()}
    one = [i for i in rows if scored[i] < 0.5]
    roots = brute_groups([(i, rows[i].text) for i in one], 5, 80)[1]
    two = [i for i in one if roots[i] == i]
    kept = docs.where(F.col("doc_id").isin(two))
    epochs = {r.doc_id: -(-r.taken // r.size) for r in mixing.mix(kept).collect() if r.taken > 0}
    want = sorted(i for i, n in epochs.items() for _ in range(n))
    out = cp.run(spark, sf).collect()
    assert sorted(r.doc_id for r in out) == want and all(r.round_trip for r in out)
    assert [n for n, _ in cp.STAGES] == ["toxicity", "near_dedup", "mix_sources", "sentencepiece"]


def test_stages_take_odd_rows(spark, sf):
    import corpus_pipeline as cp

    rows = docs_of(spark, [doc(1, "a b c d e f"), doc(1, "a b c d e f"), doc(2, None), doc(None, "x y"), doc(3, "A B C D E F"), doc(4, "", None)])
    for _, stage in cp.STAGES:
        assert stage(spark, rows, sf).count() >= 1
        assert stage(spark, rows.limit(0), sf).collect() == []
    assert sorted(r.doc_id or 0 for r in cp.drop_near_copies(spark, rows, sf).collect()) == [0, 1, 1, 2, 4]
