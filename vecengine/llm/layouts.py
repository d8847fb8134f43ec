"""Labelled pages for the extraction of main text: layouts put together by rule, with a mark around the content.

No table labels its pages, so these do: usual page parts under usual names around and inside
contents of different kinds, wrappers of the whole page, and names that mislead.
"""

from __future__ import annotations

import random
from collections.abc import Iterator

MARK = "<!--label-->"

# What page parts, contents and wrappers are usually called.
PART_NAMES = {
    "links": "nav navbar navigation menu main-menu submenu menu-bar topnav breadcrumb breadcrumbs pagination pager skip-link tags tag-list categories language-switch",
    "head": "header site-header masthead topbar top-bar toolbar banner branding logo tagline",
    "foot": "footer site-footer page-footer copyright legal disclaimer colophon imprint contentinfo",
    "side": "sidebar side-bar sidebar-left widget widgets widget-area rail complementary aside",
    "ad": "ad ads advert advertisement advertising ad-box ad-slot adbox adsense sponsor sponsored sponsored-content promo promotion banner-ad",
    "notice": "cookie cookies cookie-notice cookie-banner consent gdpr notice notification alert popup modal overlay announcement paywall",
    "share": "share sharing share-buttons social social-links social-share follow follow-us",
    "more": "related related-posts related-articles recommended recommendations trending popular popular-posts most-read read-next more-stories teaser",
    "form": "newsletter newsletter-signup subscribe subscription signup sign-up login register search search-form searchbox contact-form poll",
    "talk": "comments comment comment-list commentlist comment-form discussion respond reply replies disqus reviews user-comments",
}
CONTENT_NAMES = "content article article-body article-content post post-body post-content entry entry-content story story-body text body-text main main-content page-content single blog-post hentry document prose"
WITHIN_NAMES = "lead intro summary quote pullquote figure caption table-wrap note step section chapter list gallery example highlight code title subtitle dek paragraph"
WRAPPER_NAMES = "container wrapper wrap page site layout row col column grid inner outer has-sidebar with-sidebar no-sidebar content-sidebar-wrap site-content main-wrapper two-column app root"
FORM_NAMES = "aspnetForm mainForm form1 page-form"  # of a form around the whole page
#: Words that name parts, and subjects too.
SUBJECT_WORDS = "popular header social notice banner share reviews related comment search legal menu alert trending discussion widget login footer nav overlay"
#: Words that say nothing, which names of any kind go with.
NEUTRAL_WORDS = "box block area section list item inner top left right main bottom first module holder region container"
TAGS = {"links": "nav", "head": "header", "foot": "footer", "side": "aside", "form": "form"}


class Maker:
    def __init__(self, seed: int) -> None:
        self.r = random.Random(seed)

    def words(self, low: int, high: int) -> str:
        return " ".join("w" * self.r.randint(2, 9) for _ in range(self.r.randint(low, high)))

    def links(self, n: int, listed: bool = True) -> str:
        how = self.r.randrange(3) if listed else 1
        each = [f"<a href=/x>{self.words(1, 3)}</a>" for _ in range(n)]
        if how == 0:
            return "<ul>" + "".join(f"<li>{x}</li>" for x in each) + "</ul>"
        return (" | " if how == 1 else " ").join(each)

    def paragraphs(self, n: int, low: int = 8, high: int = 60) -> str:
        return "".join(f"<p>{self.words(low, high)}</p>" for _ in range(n))

    def named(self, tag: str, names: str, body: str) -> str:
        name = self.r.choice(names.split())
        if self.r.random() < 0.25:
            name = self.r.choice((f"{name}-{self.r.choice(NEUTRAL_WORDS.split())}", f"{self.r.choice(NEUTRAL_WORDS.split())}_{name}"))
        how = self.r.randrange(4)
        if how == 0:
            return f'<{tag} id="{name}">{body}</{tag}>'
        more = f" x{self.r.randrange(9)}" if how == 1 else ""
        return f'<{tag} class="{name}{more}">{body}</{tag}>'

    def part(self, kind: str) -> str:
        r = self.r
        body = {
            "links": lambda: self.links(r.randint(2, 9)),
            "head": lambda: r.choice((f"<h1>{self.words(1, 4)}</h1>", f"<a href=/>{self.words(1, 3)}</a>", self.words(2, 8) + self.links(3))),
            "foot": lambda: r.choice((f"<p>{self.words(4, 20)}</p>", self.words(4, 16), self.links(4) + self.words(3, 9))),
            "side": lambda: f"<h3>{self.words(1, 3)}</h3>" + r.choice((self.links(5), self.paragraphs(r.randint(1, 8), 5, 60))),
            "ad": lambda: r.choice((self.words(3, 14), self.paragraphs(r.randint(1, 3), 4, 40), f"<a href=/b>{self.words(3, 9)}</a>")),
            "notice": lambda: r.choice((self.paragraphs(r.randint(1, 3), 8, 60), self.words(6, 30))) + r.choice(("", f"<a href=/p>{self.words(1, 2)}</a>")),
            "share": lambda: r.choice((self.links(4), self.words(2, 5) + self.links(3))),
            "more": lambda: f"<h3>{self.words(1, 3)}</h3>" + r.choice((self.links(5), "".join(f"<article><h4><a href=/t>{self.words(3, 8)}</a></h4><p>{self.words(6, 20)}</p></article>" for _ in range(3)))),
            "form": lambda: r.choice(("", f"<p>{self.words(4, 25)}</p>")) + f"{self.words(1, 5)}<input name=q><button>{self.words(1, 2)}</button>",
            "talk": lambda: f"<h3>{self.words(1, 3)}</h3>" + "".join(r.choice((f"<p>{self.words(3, 50)}</p>", f"<div><b>{self.words(1, 2)}</b> {self.words(4, 60)}</div>", f"<article><p>{self.words(5, 40)}</p></article>")) for _ in range(r.randint(1, 8))),
        }[kind]()
        tag, names = TAGS.get(kind, "div"), PART_NAMES[kind]
        how = r.randrange(10)
        if how < 4 and kind in TAGS:
            return f"<{tag}>{body}</{tag}>"
        if how < 6 and kind in TAGS:
            return self.named(tag, names, body)
        return self.named(r.choice(("div", "div", "div", "section")), names, body)

    def content(self) -> str:
        r = self.r
        out = [f"<h1>{self.words(2, 12)}</h1>"] if r.random() < 0.7 else [f'<h1 class="{r.choice(("page-header", "header", "title", "post-title", "entry-title"))}">{self.words(2, 12)}</h1>']
        if r.random() < 0.2:
            out = [f"<header>{out[0]}<p>{self.words(3, 9)}</p></header>"]
        for _ in range(r.choice((0, 0, 1, 2, 4, 8, 15))):
            out.append(
                r.choice(
                    (
                        lambda: self.paragraphs(1),
                        lambda: self.paragraphs(2),
                        lambda: f"<p>{self.words(4, 30)} <a href=/i>{self.words(1, 4)}</a> <b>{self.words(1, 3)}</b>, {self.words(2, 20)}</p>",
                        lambda: f"<p>{self.words(1, 4)}</p>",
                        lambda: "<ul>" + "".join(f"<li>{self.words(1, 14)}</li>" for _ in range(r.randint(1, 6))) + "</ul>",
                        lambda: f"<ul><li><a href=/r>{self.words(2, 9)}</a></li><li>{self.words(2, 9)}</li></ul>",
                        lambda: f"<h2>{self.words(1, 8)}</h2>{self.paragraphs(1)}",
                        lambda: f"<blockquote><p>{self.words(5, 30)}</p></blockquote>",
                        lambda: f"<table><tr><td>{self.words(1, 5)}</td><td>{self.words(1, 5)}</td></tr><tr><td>{self.words(1, 5)}</td><td>{self.words(1, 5)}</td></tr></table>",
                        lambda: self.named(r.choice(("div", "p", "section", "figure")), WITHIN_NAMES, self.words(3, 30)),
                        lambda: f"{self.words(5, 40)}<br>{self.words(5, 40)}<br>",
                    )
                )()
            )
        return "".join(out)

    def page(self) -> str:
        r = self.r
        inner = self.content()
        embedded = [self.part(r.choice(("ad", "share", "notice", "form", "more"))) for _ in range(r.choice((0, 0, 0, 1)))]
        body = f"{MARK}{inner}{MARK}"
        how = r.randrange(8)
        if how < 2:
            body = f"<article>{body}</article>"
        elif how == 2:
            body = f"<main>{body}</main>"
        elif how == 3:
            name = f"{r.choice(SUBJECT_WORDS.split())}-{'s' * r.randint(3, 9)}"
            body = f'<div class="{name}">{body}{self.paragraphs(0)}</div>' if inner.count("<p>") > 2 else f"<div>{body}</div>"
        elif how < 7:
            body = self.named("div", CONTENT_NAMES, body)
        plain = lambda: f"<div>{self.links(r.randint(2, 6), False)}</div>"
        before = [self.part(k) for k in ("head", "links", "notice", "ad", "form") if r.random() < 0.45]
        after = [self.part(k) for k in ("share", "more", "talk", "side", "ad", "form", "foot") if r.random() < 0.45]
        before += [plain()] * (r.random() < 0.25)
        after += [plain()] * (r.random() < 0.25)
        r.shuffle(before)
        out = "".join(before) + body + "".join([*embedded, *after])
        wrap = r.randrange(8)
        if wrap < 3:
            out = self.named("div", WRAPPER_NAMES, out)
        elif wrap == 3:
            name = r.choice((*FORM_NAMES.split(), ""))
            out = f'<form id="{name}">{out}</form>' if name else f"<form>{out}</form>"
        return f"<html><head><title>{self.words(2, 6)}</title></head><body>{out}</body></html>"


def labelled_layouts(pages: int = 1500, seed: int = 7) -> Iterator[str]:
    """Pages with a mark before and after their content, the same ones for a seed."""
    make = Maker(seed)
    for _ in range(pages):
        yield make.page()
