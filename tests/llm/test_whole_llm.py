"""The training-data operators do the whole job: no caps, prefixes or samples in place of it."""

import io
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecengine.llm import chat, embedding_dedup, fingerprints, html_extract, warc


def test_fingerprints_keep_every_anchor(spark):
    a, b = ([f"{x}{i}" for i in range(9_000)] for x in "ab")
    shared = [f"s{i}" for i in range(50)]
    docs = [(1, " ".join(a[:4_000] + shared + a[4_000:])), (2, " ".join(b + shared + shared))]
    rows = fingerprints.compare_with_next(spark.createDataFrame(docs, "doc_id long, text string"))
    one, two = rows.orderBy("doc_id").collect()
    x, y = ({p.h for p in r.anchors} for r in (one, two))
    assert len(x) > 5_000 and len(x & y) > 15
    assert one.near_next == two.near_next == len(x & y) / len(x | y)
    edited = {p.h for p in one.edited_anchors}
    assert one.near_edited == len(x & edited) / len(x | edited)
    pair = rows.where("doc_id = 1").select(F.col("anchors").alias("a")).crossJoin(rows.where("doc_id = 2").select(F.col("anchors").alias("b")))
    found = pair.select(fingerprints.matches(F.col("a"), F.col("b")).alias("m")).first().m
    want = sorted((p.at, q.at) for p in one.anchors for q in two.anchors if p.h == q.h)
    assert sorted((m.at_a, m.at_b) for m in found) == want and {m.shift for m in found} >= {5_000, 5_050}


@pytest.fixture(scope="module")
def w():
    return html_extract.default_weights()


STORY = "<h1>Rivers in winter</h1><p>Ice forms first where the current is slow, then spreads from both banks.</p><p>By spring it breaks up with a great noise.</p>"
TOLD = "Rivers in winter Ice forms first where the current is slow, then spreads from both banks. By spring it breaks up with a great noise."


@pytest.mark.parametrize(
    "body",
    [
        f'<div style="overflow:hidden">{STORY}</div>',
        f'<div class="overflow-hidden" title="hidden">{STORY}</div>',
        f'<div data-x="display:none"><div style="color:red">{STORY}</div></div>',
        f'<form action="/x"><input type="hidden" name="s">{STORY}</form>',
        f'<form id="aspnetForm"><div class="menu"><a href=1>One</a></div><article>{STORY}</article></form>',
        f'<div class="content-sidebar-wrap"><div id=c>{STORY}</div><div class="sidebar"><p>Also to be read today</p></div></div>',
        f'<div class="sidebar-wrap header-wrap"><main>{STORY}</main></div><p>Small print</p>',
        f'<div class="site social share"><article>{STORY}</article></div>',
        STORY.replace("<h1>", '<h1 class="page-header">'),
        f'<article>{STORY}</article><section id="comments"><article>{"Nice one and thanks for it. " * 30}</article></section>',
        f'{STORY}<p hidden>Not seen by any reader</p><div style="visibility: hidden"><p>Nor is this one</p></div><p aria-hidden="true">Nor this</p>',
    ],
)
def test_html_wrappers_do_not_drop_the_content(body, w):
    nav = "<nav><ul><li><a href=x>Home</a></li></ul></nav>"
    assert html_extract.extract(f"<html><body>{nav}{body}<footer>All rights reserved</footer></body></html>", w) == TOLD


def test_html_link_to_hidden_words(w):
    assert "the lake" in html_extract.extract('<body><p>We walked all day to <a href="/hidden-lake">the lake</a> and back again.</p></body>', w)


def test_quotes_of_lines_and_sentences_are_linked(spark):
    first = "We walked to the lake. The water was calm\nand very cold. Then we came home."
    talk = [
        (1, 0, first),
        (1, 1, "It rained here all day."),
        (1, 2, "> The water was calm and very cold.\nHow cold?"),
        (1, 3, "Nothing new."),
        (1, 4, "> [...] We walked to the lake ...\nWhich lake?"),
        (1, 5, "> Then we came home.\n> How cold?\nGood."),
        (1, 6, "> A sentence that nobody wrote.\nWhat?"),
        (2, 0, "> Said by me later.\nHm."),
        (2, 1, "Said by me later."),
        (3, 0, "Said by me later."),
        (4, 0, "> It rained here all day.\n> Nothing new.\nSo?"),
    ]
    got = {(r.conv_id, r.turn): r for r in chat.conversations(spark.createDataFrame([(c, t, "user", x) for c, t, x in talk], "conv_id long, turn long, role string, text string")).collect()}
    assert [got[1, t].parent_turn for t in range(7)] == [None, 0, 0, 2, 0, 2, 5]
    assert [got[1, t].linked_by for t in range(7)] == ["root", "order", "quote", "order", "quote", "quote", "order"]
    assert [(got[k].n_quotes, got[k].n_linked) for k in ((1, 6), (2, 0), (4, 0))] == [(1, 0), (1, 1), (1, 1)]


def archive(n, size, digest=True):
    made = []
    for i in range(n):
        block = str(i).encode() + os.urandom(size)
        made.append(warc.encode([("WARC-Type", "resource"), ("WARC-Record-ID", f"{i}")] + [("WARC-Block-Digest", f"sha1:{warc.sha1_base32(block)}")] * digest, block))
    return made


def salvaged(data, **how):
    items = list(warc.read(io.BytesIO(data), **how))
    return [int(x.headers["warc-record-id"]) for x in items if isinstance(x, warc.Record)], [x for x in items if isinstance(x, warc.Gap)], items


def test_salvage_inside_a_member():
    parts = archive(6, 5_000)
    bad = bytearray(parts[2])
    bad[-100] ^= 255
    ids, gaps, items = salvaged(warc.member(b"".join([*parts[:2], bytes(bad), *parts[3:]])) + warc.member(archive(7, 10)[6]))
    assert ids == [0, 1, 3, 4, 5, 6] and [g.reason for g in gaps] == ["block digest differs"]
    long = parts[3].replace(b"Content-Length: 5", b"Content-Length: 9")
    assert salvaged(warc.member(b"".join([*parts[:3], long, *parts[4:]])))[0] == [0, 1, 2, 4, 5]


@pytest.mark.parametrize("damage", ["cut", "flip"])
def test_salvage_before_the_fault(damage):
    data = warc.member(b"".join(archive(6, 200_000)))
    at = len(data) * 3 // 4
    data = data[:at] if damage == "cut" else data[:at] + b"\xff" * 64 + data[at + 64 :]
    ids, gaps, items = salvaged(data + warc.member(archive(9, 10)[8]) * (damage == "flip"))
    assert ids[:4] == [0, 1, 2, 3] and len(gaps) == 1 and (damage == "cut" or ids[-1] == 8)


def test_salvage_streams_large_members():
    parts = archive(30, 1 << 20)
    data = warc.member(b"".join(parts), 1) + warc.member(archive(31, 10)[30])
    ids, gaps, items = salvaged(data, most=2 << 20)
    assert ids == list(range(31)) and not gaps
    spans = sorted({(x.begin, x.end) for x in items})
    assert spans[0][0] == 0 and spans[-1][1] == len(data) and all(a[1] == b[0] for a, b in zip(spans, spans[1:]))


def test_sparse_links_are_no_proof_of_recall():
    rng = np.random.default_rng(3)
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    x, q = unit(rng.standard_normal((2_000, 64))), unit(rng.standard_normal((2_000, 64)))
    q[:30] = unit(x[100:130] + 0.005 * rng.standard_normal((30, 64)))
    p = embedding_dedup.Hnsw(degree=3, build_beam=3, beam=1, audit=4)
    found = [np.stack(ab) for ab in embedding_dedup.range_links(embedding_dedup.Graph(x.astype(np.float32), p), q.astype(np.float32), q, x, p)]
    assert sorted(map(tuple, np.concatenate(found, axis=1).T.tolist())) == [(i, 100 + i) for i in range(30)]
