"""Main text of web pages by the maximum-scoring subsequence of tokens.

A page becomes a sequence of words and tags. Words score positive and tags negative, with weights
fitted on labelled pages; one linear scan finds the contiguous run of greatest total, and its blocks
are the text. Elements with a name (class, id, role) or a sectioning tag are judged apart by a
logistic model of the same pages: words in those that come out as page parts (menus, adverts,
comments and the like) score nothing, and are left out where they lie inside the run.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C
from vecengine.llm.layouts import labelled_layouts

#: A comment, a declaration or processing instruction, or a tag with quoted or bare attributes.
MARKUP = re.compile(r"<!--.*?(?:-->|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)", re.S)
ATTRIBUTE = re.compile(r"""([^\s"'<>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
UNSEEN = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*hidden)\b", re.I)
#: Attributes whose values name what an element is for.
HINTS = ("class", "id", "role", "itemprop", "aria-label")
NAME = re.compile(r"[A-Z]?[a-zäöüéñç]+|[A-Z]+(?![a-z])")

# Kinds of elements.
RAW = frozenset("script style noscript template textarea title iframe object xmp noembed noframes".split())
UNREAD = frozenset("head dialog button select option label svg audio video canvas map".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
SECTIONS = frozenset("article main nav header footer aside form fieldset menu section".split())
CONTENT = frozenset(("article", "main"))
OPEN_ENDED = frozenset("p li dt dd tr td th option thead tbody tfoot".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
TEXT_BLOCKS = frozenset("p blockquote dd pre figcaption".split())


def named(attributes: str) -> dict[str, str]:
    """Values by lower-case name, the first of each; an attribute without a value has an empty one."""
    out: dict[str, str] = {}
    for name, a, b, c in ATTRIBUTE.findall(attributes):
        out.setdefault(name.lower(), a or b or c)
    return out


def hidden(a: dict[str, str]) -> bool:
    """By a hidden attribute, aria-hidden=true or its own style."""
    return ("hidden" in a and not a["hidden"].lower().startswith(("false", "until"))) or a.get("aria-hidden", "").strip().lower() == "true" or bool(UNSEEN.search(a.get("style", "")))


def spans(page: str) -> Iterator[tuple]:
    """('text', run of characters), ('open'|'close'|'void', tag, attributes) in page order; raw elements' contents are skipped."""
    at, low = 0, None
    while True:
        m = MARKUP.search(page, at)
        if not m:
            break
        if m.start() > at:
            yield "text", page[at : m.start()], ""
        at = m.end()
        tag = m.group(2)
        if tag is None:
            continue
        tag = tag.lower()
        if m.group(1):
            yield "close", tag, ""
        elif tag in VOID or (m.group(3) or "").endswith("/"):
            yield "void", tag, m.group(3)
        else:
            yield "open", tag, m.group(3)
            if tag in RAW:
                low = page.lower() if low is None or len(low) != len(page) else low
                end = low.find(f"</{tag}", at)
                at = len(page) if end < 0 else end
    if at < len(page):
        yield "text", page[at:], ""


@dataclass
class Element:
    """An element that has a name or a sectioning tag, with what stands in it, elements below included."""

    up: int  # the one around it, 0 for the page
    tag: str
    names: tuple[str, ...] = ()
    words: int = 0
    linked: int = 0
    blocks: int = 0
    holds: set = field(default_factory=set)


@dataclass
class Page:
    """tokens: (kind, text, element, unread). kind of a run of characters: 'word:' and the nearest of link, linked
    (within a paragraph), head, item or plain; of a tag: its name, with '/' in front where it closes."""

    tokens: list[tuple[str, str, int, bool]]
    elements: list[Element]


def name_parts(a: dict[str, str]) -> tuple[str, ...]:
    """An element's names in lower case without digits, and the words of those that have several, in brackets."""
    out: dict[str, None] = {}
    for hint in HINTS:
        for name in a.get(hint, "").split():
            parts = [x.lower() for x in NAME.findall(name)]
            if parts:
                out["-".join(parts)] = None
            if len(parts) > 1:
                out.update(dict.fromkeys(f"({x})" for x in parts))
    return tuple(out)


def parse(page: str) -> Page:
    """Tokens and elements. Tags that nothing opened are ignored; markup that never ends runs to the end of the page."""
    tokens: list[tuple[str, str, int, bool]] = []
    elements = [Element(0, "")]
    stack: list[tuple[str, bool, int]] = []  # tag, whether its text is unread, the element around it
    depth: Counter = Counter()
    unread = links = items = heads = content = texts = at = 0

    def leave() -> None:
        nonlocal unread, links, items, heads, content, texts, at
        name, off, at = stack.pop()
        depth[name] -= 1
        unread -= off
        links -= name == "a"
        items -= name == "li"
        heads -= name in HEADINGS
        content -= name in CONTENT
        texts -= name in TEXT_BLOCKS

    for what, text, attributes in spans(page):
        if what == "text":
            kind = ("word:linked" if texts else "word:link") if links else "word:head" if heads else "word:item" if items else "word:plain"
            tokens.append((kind, text, at, unread > 0))
            if not unread and (n := len(text.split())):
                e = elements[at]
                e.words += n
                e.linked += n if links else 0
            continue
        tag = text
        if what == "open":
            if tag in OPEN_ENDED and stack and stack[-1][0] == tag:
                leave()
            off, around = tag in RAW or tag in UNREAD, at
            if not off and tag not in ("html", "body"):
                names: tuple[str, ...] = ()
                if attributes:
                    a = named(attributes)
                    off = hidden(a)
                    names = name_parts(a)
                if names or tag in SECTIONS:
                    elements.append(Element(at, f"{tag}@content" if content and tag in ("header", "footer") else tag, names))
                    at = len(elements) - 1
                if tag in TEXT_BLOCKS:
                    elements[at].blocks += 1
            stack.append((tag, off, around))
            depth[tag] += 1
            unread += off
            links += tag == "a"
            items += tag == "li"
            heads += tag in HEADINGS
            content += tag in CONTENT
            texts += tag in TEXT_BLOCKS
            tokens.append((tag, "", at, unread > 0))
        elif what == "close":
            tokens.append(("/" + tag, "", at, unread > 0))
            if depth[tag]:
                while stack[-1][0] != tag:
                    leave()
                leave()
        else:
            tokens.append((tag, "", at, unread > 0))
    for n in range(len(elements) - 1, 0, -1):  # elements below come after those around them
        e, up = elements[n], elements[elements[n].up]
        up.words += e.words
        up.linked += e.linked
        up.blocks += e.blocks
        up.holds |= e.holds | ({e.tag} & CONTENT)
    return Page(tokens, elements)


def traits(e: Element, page: Element) -> list[str]:
    """What the logistic model knows of an element besides its names and tag."""
    share, links = e.words / max(page.words, 1), e.linked / max(e.words, 1)
    return [
        "share:" + ("most" if share >= 0.5 else "some" if share >= 0.15 else "few"),
        "links:" + ("most" if links >= 0.6 else "some" if links >= 0.25 else "few"),
        "blocks:" + ("many" if e.blocks > 2 else "some" if e.blocks else "none"),
        "words:" + ("many" if e.words > 60 else "some" if e.words > 12 else "few"),
        *(f"holds:{x}" for x in sorted(e.holds)),
    ]


def marks(e: Element) -> list[str]:
    tag = "heading" if e.tag in HEADINGS else e.tag
    return [*([f"tag:{tag}"] if e.tag in SECTIONS or "@" in e.tag or tag == "heading" else []), *(f"name:{x}" for x in e.names)]


class Weights:
    """tokens: of a word by kind (positive, links apart) and of a tag (negative); unseen tags weigh `other`.

    marks: logistic weights of elements' names, tags and traits; `bias` is theirs. An element is a page part where
    its names and tag alone speak against it and all it is known for does too.
    """

    def __init__(self, tokens: dict[str, float], other: float, marks: dict[str, float], bias: float) -> None:
        self.tokens, self.other, self.marks, self.bias = tokens, other, marks, bias

    def of(self, kind: str) -> float:
        return self.tokens.get(kind, self.other)

    def parts(self, page: Page) -> list[bool]:
        """Of each element: whether it or one around it is a page part."""
        out = [False] * len(page.elements)
        for n, e in enumerate(page.elements[1:], 1):
            by_mark = sum(self.marks.get(x, 0.0) for x in marks(e))
            out[n] = out[e.up] or (by_mark < 0 and self.bias + by_mark + sum(self.marks.get(x, 0.0) for x in traits(e, page.elements[0])) < 0)
        return out


def fit(labelled: Iterable[tuple[str, tuple[int, int]]], ridge: float = 0.1, rounds: int = 25, least: int = 4) -> Weights:
    """labelled: pages and the token range [i, j) of their content.

    Words and tags weigh by the log-odds of standing in the content, each page counting as one; only what is outside
    of labelled parts counts, as parts score nothing. Names of fewer than `least` elements are left out.
    """
    inside: Counter = Counter()
    outside: Counter = Counter()
    seen: Counter = Counter()
    for text, (i, j) in labelled:
        page = parse(text)
        first, last, total = {}, {}, max(1, sum(not t[3] for t in page.tokens))
        for n, (_, _, e, _) in enumerate(page.tokens):
            while e and e not in first:
                first[e], e = n, page.elements[e].up
        for n in range(len(page.tokens) - 1, -1, -1):
            e = page.tokens[n][2]
            while e and e not in last:
                last[e], e = n, page.elements[e].up
        outer = [False] * len(page.elements)
        for n, e in enumerate(page.elements[1:], 1):
            part = n in first and (last[n] < i or first[n] >= j)
            if n in first and not outer[e.up]:
                seen[(part, frozenset([*marks(e), *traits(e, page.elements[0])]))] += 1
            outer[n] = outer[e.up] or part
        for n, (kind, run, e, off) in enumerate(page.tokens):
            size = len(run.split()) if kind.startswith("word:") else 1
            if size and not off and not outer[e]:
                (inside if i <= n < j else outside)[kind] += size / total
    tokens = {}
    for kind in {*inside, *outside}:
        odds = np.log((inside[kind] + 0.05) / (outside[kind] + 0.05))
        tokens[kind] = float(np.clip(odds / 2, -1.5, 1.0) if kind.startswith("word:") else -0.1 - 1.2 * np.clip(2 - odds, 0.0, 5.0))
    tokens.setdefault("word:linked", tokens.get("word:plain", 1.0) / 2)
    tokens |= {f"{x}{tag}": -0.1 for tag in INLINE for x in ("", "/")}  # they say nothing that their words do not
    tags = [v for k, v in tokens.items() if not k.startswith("word:") and k.lstrip("/") not in INLINE]
    often: Counter = Counter()
    for (_, found), count in seen.items():
        often.update(dict.fromkeys(found, count))
    columns = sorted(x for x, count in often.items() if count >= least)
    place = {x: k for k, x in enumerate(columns)}
    kept: Counter = Counter()
    for (part, found), count in seen.items():
        kept[part, frozenset(x for x in found if x in place)] += count
    seen = kept
    x = np.zeros((len(seen), len(columns) + 1))
    x[:, -1] = 1
    y, n = np.zeros(len(seen)), np.zeros(len(seen))
    for r, ((part, found), count) in enumerate(sorted(seen.items(), key=lambda s: (s[0][0], sorted(s[0][1])))):
        x[r, [place[f] for f in found]] = 1
        y[r], n[r] = not part, count
    w = np.zeros(x.shape[1])
    held = ridge * np.array([*(1.0 if f.startswith(("name:", "tag:")) else 4.0 for f in columns), 1.0])  # names before shapes
    for _ in range(rounds if len(seen) else 0):
        p = 1 / (1 + np.exp(-x @ w))
        step = np.linalg.solve((x * (n * p * (1 - p))[:, None]).T @ x + np.diag(held), x.T @ (n * (p - y)) + held * w)
        w -= step * min(1.0, 3 / (np.abs(step).max() + 1e-9))
        if np.abs(step).max() < 1e-4:
            break
    return Weights(tokens, sum(tags) / len(tags) if tags else -1.0, dict(zip(columns, w[:-1].tolist(), strict=True)), float(w[-1]))


def labelled_by_mark(page: str, mark: str = "<!--label-->") -> tuple[str, tuple[int, int]]:
    """A page and its content's token range from two marks around the content."""
    head, body, tail = page.split(mark)
    i = len(parse(head).tokens)
    return head + body + tail, (i, len(parse(head + body).tokens))


def labelled_by_element(page: str) -> tuple[str, tuple[int, int]] | None:
    """The inside of a lone article or main element as its page's label; None where there is no such element."""
    toks = parse(page).tokens
    for tag in ("article", "main"):
        opens = [n for n, t in enumerate(toks) if t[0] == tag]
        closes = [n for n, t in enumerate(toks) if t[0] == "/" + tag]
        if len(opens) == 1 and len(closes) == 1 and opens[0] < closes[0]:
            return page, (opens[0] + 1, closes[0])
    return None


#: A part within the run is left out of the text, so it costs the run its opening only.
PART_COST = -0.5


def best_run(scores: list[float]) -> tuple[int, int]:
    """[i, j) of the greatest total; empty where no score is positive. The first, shortest on ties."""
    best, at = 0.0, (0, 0)
    total, start = 0.0, 0
    for n, x in enumerate(scores):
        if total <= 0:
            total, start = 0.0, n
        total += x
        if total > best:
            best, at = total, (start, n + 1)
    return at


def scored(page: Page, weights: Weights) -> tuple[list[bool], list[float]]:
    """Of each token: whether it is left out as unread or in a part, and its score."""
    part = weights.parts(page)
    left = [off or part[e] for _, _, e, off in page.tokens]
    scores = []
    before = False
    for (kind, text, _, _), out in zip(page.tokens, left, strict=True):
        scores.append((0.0 if before else PART_COST) if out else weights.of(kind) * (len(text.split()) if kind.startswith("word:") else 1))
        before = out
    return left, scores


def extract(page: str | None, weights: Weights) -> str:
    """The main text: references decoded, white space within a block made one space, blocks joined by one space.

    It is the run of greatest total, out to the ends of the blocks in which it begins and ends, without page parts.
    """
    if not page:
        return ""
    parsed = parse(page)
    left, scores = scored(parsed, weights)
    i, j = best_run(scores)
    toks = parsed.tokens
    flows = lambda n: not left[n] and (toks[n][0].startswith("word:") or toks[n][0].lstrip("/") in INLINE)
    if i < j:
        while i > 0 and flows(i - 1) and flows(i):
            i -= 1
        while j < len(toks) and flows(j) and flows(j - 1):
            j += 1
    pieces = []
    for n in range(i, j):
        kind, text = toks[n][0], toks[n][1]
        if kind.startswith("word:"):
            if not left[n]:
                pieces.append(entities.unescape(text))
        elif kind.lstrip("/") not in INLINE:
            pieces.append(" ")
    return " ".join("".join(pieces).split())


def extract_pages(pages: DataFrame, weights: Weights) -> DataFrame:
    """(page_id, url, text, n_chars) for each row of pages (page_id, url, html).

    A null or empty page, or one without content, gives an empty text; markup that never ends runs to
    the end of the page. Repeated rows each give their row; other columns are ignored; an empty table
    gives an empty result.
    """

    def run(batches):
        for batch in batches:
            texts = [extract(x, weights) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", F.col("html").cast("string")).mapInArrow(run, "page_id long, url string, text string, n_chars long")


def labelled_sample(pages: DataFrame, most: int, spare: int = 64, longest: int = 50_000) -> list[str]:
    """At most `most` pages of at most `longest` characters with an article or main element: the bounded sample for fit().

    They are those of least hash of the id among about spare * most pages that a hash threshold keeps
    (all pages of a small table), so what tasks send on stays bounded however many there are.
    """
    key = F.xxhash64("page_id")
    total = pages.count()
    few = pages.select("page_id", "html")
    if total > spare * most:
        few = few.where(F.pmod(key, F.lit(1 << 40)) < F.lit(int((1 << 40) * spare * most / total)))
    marked = few.where(F.col("html").rlike("(?i)<(article|main)[\\s>]") & (F.length("html") <= longest))
    ids = C.cut(marked.select(key.alias("key")).orderBy("key").limit(most)).distinct()
    rows = few.select(key.alias("key"), "html").join(F.broadcast(ids), "key").where(F.length("html") <= longest).limit(2 * most).collect()
    return [r.html for r in sorted(rows)[:most]]


def default_weights(marked: Iterable[str] = ()) -> Weights:
    """Fitted on the generated layouts and on pages whose own article or main element marks their content."""
    own = (labelled_by_element(x) for x in marked)
    return fit([*(labelled_by_mark(x) for x in labelled_layouts()), *(x for x in own if x)])


def op1_extract_html(spark: SparkSession, sf_dir: str, labelled_pages: int = 128) -> DataFrame:
    """Main text of all pages; weights from generated labelled layouts and at most labelled_pages marked pages of the table."""
    pages = C.table(spark, sf_dir, "pages")
    return extract_pages(pages, default_weights(labelled_sample(pages, labelled_pages)))
