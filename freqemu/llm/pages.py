"""Main text of web pages: flat text blocks, their neighbours, and a decision tree.

A page is cut at block-level tags into flat blocks. A block's features are its word count
and link density, those of the blocks before and behind, and where it stands: in an
article, inside an element that is never article text, inside an element whose class or
id names such a thing, in a list, a heading. A small labelled table trains the tree: plain
text stays wherever it stands outside such elements, unless it is a crumb between links;
linked text goes or stays by its neighbours.

Scripts, styles, templates, markup comments, the head and form controls never make text.
White space inside a block becomes one blank; blocks are joined by an empty line. Nothing
is cut or capped.

Edge cases: null or empty html, and pages without kept blocks, give the empty string;
unclosed and crossed tags end with the element that holds them; an unclosed comment or
raw-text element reaches to the end of the page; repeated rows and null ids are like others.
"""

from __future__ import annotations

import functools
import html as entities
import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from .common import annotate

_MARK = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(.*?)(?:\]\]>|\Z)|<[!?][^<>]*>|<(/?)([A-Za-z][^\s/<>]*)((?:\"[^\"]*\"|'[^']*'|[^<>\"'])*)>", re.DOTALL)
_HINT = re.compile(r"""(?:\b(?:class|id|role|aria-label)\s*=\s*)("[^"]*"|'[^']*'|[^\s"'>]+)""", re.IGNORECASE)
_QUOTED = re.compile(r"""=\s*(?:"[^"]*"|'[^']*')""")
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:[\s=/]|$)""", re.IGNORECASE)
_UNSEEN = re.compile(r"""(?:^|\s)(?:style\s*=\s*(?:"[^"]*display\s*:\s*none|'[^']*display\s*:\s*none)|aria-hidden\s*=\s*["']?true)""", re.IGNORECASE)
_SPLIT = re.compile(r"[^a-z0-9]+")

RAW = frozenset("script style textarea title noscript template iframe svg math object canvas audio video select option datalist button noframes".split())
INLINE = frozenset("a abbr b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr acronym picture source input meta link".split())
NEVER = frozenset("nav footer aside form menu dialog head fieldset".split())
HINTS = frozenset(
    "ad ads advert adverts advertisement advertising adsbygoogle banner sponsor sponsored promo promotion cookie cookies consent notice gdpr popup modal overlay alert alertdialog dialog toast "
    "newsletter subscribe comment comments commentlist disqus reply replies respond sidebar aside complementary widget related recommended share sharing social menu nav navbar navigation "
    "breadcrumb breadcrumbs footer contentinfo masthead topbar toolbar login signup search pagination pager skip copyright disclaimer".split()
)
#: A name that begins with one of these tells of the page or the article, not of what the element is.
ABOUT = frozenset("has no not with without is category cat tag type format supports".split())
#: With one of these, an element named a header is the page's, not the article's.
OF_PAGE = frozenset("site page top global main".split())
VOID = frozenset("br img hr input meta link wbr area base col embed source track param".split())
HEADINGS = frozenset(f"h{i}" for i in range(1, 7))

#: Word counts and link densities (percent) of the block before, the block and the block behind; in an article, in a never-article element, hinted as such, in a list, a heading; and the label.
LABELLED = (
    # article text: headings, paragraphs of any length, list items, lines with some links
    (0, 0, 8, 0, 60, 0, 1, 0, 0, 0, 1, 1), (8, 0, 45, 0, 70, 0, 1, 0, 0, 0, 0, 1), (45, 0, 3, 0, 30, 0, 1, 0, 0, 0, 0, 1), (3, 0, 120, 0, 0, 0, 1, 0, 0, 0, 0, 1),
    (12, 0, 1, 0, 2, 0, 1, 0, 0, 0, 0, 1), (1, 0, 2, 0, 1, 0, 1, 0, 0, 0, 0, 1), (80, 0, 20, 40, 60, 0, 1, 0, 0, 0, 0, 1), (60, 0, 12, 0, 12, 0, 1, 0, 0, 1, 0, 1),
    (12, 0, 12, 30, 50, 0, 1, 0, 0, 1, 0, 1), (1, 100, 6, 0, 40, 0, 1, 0, 0, 0, 1, 1), (15, 0, 9, 0, 25, 0, 1, 0, 0, 0, 0, 1), (25, 0, 300, 2, 30, 0, 1, 0, 0, 0, 0, 1),
    (0, 0, 6, 0, 0, 0, 1, 0, 0, 0, 1, 1), (0, 0, 1, 0, 0, 0, 1, 0, 0, 0, 0, 1), (1, 100, 1, 0, 9, 0, 1, 0, 0, 0, 0, 1), (2, 0, 5, 0, 2, 0, 1, 0, 0, 1, 0, 1),
    # article paragraphs that are mostly a link: kept between plain text, dropped beside other links
    (30, 0, 9, 100, 40, 0, 1, 0, 0, 0, 0, 1), (30, 0, 12, 90, 0, 0, 1, 0, 0, 0, 0, 1), (0, 0, 9, 100, 40, 0, 1, 0, 0, 0, 0, 1), (8, 0, 14, 95, 25, 5, 1, 0, 0, 0, 0, 1),
    (30, 0, 7, 100, 7, 100, 1, 0, 0, 0, 0, 0), (7, 100, 9, 100, 30, 0, 1, 0, 0, 0, 0, 0), (6, 100, 12, 95, 8, 100, 1, 0, 0, 0, 0, 0), (40, 0, 9, 100, 9, 100, 1, 0, 0, 0, 0, 0),
    (9, 100, 9, 100, 0, 0, 1, 0, 0, 0, 0, 0), (5, 100, 12, 95, 0, 0, 1, 0, 0, 0, 0, 0), (9, 100, 8, 100, 9, 100, 1, 0, 0, 0, 0, 0),
    (12, 0, 9, 100, 9, 100, 1, 0, 0, 0, 0, 0), (8, 0, 9, 100, 9, 100, 1, 0, 0, 0, 0, 0), (0, 0, 9, 100, 9, 100, 1, 0, 0, 0, 0, 0), (60, 0, 9, 100, 40, 0, 1, 0, 0, 0, 0, 1), (90, 0, 12, 95, 70, 0, 1, 0, 0, 0, 0, 1),
    (12, 0, 9, 100, 12, 0, 1, 0, 0, 0, 0, 1), (25, 0, 9, 100, 12, 0, 1, 0, 0, 0, 0, 1), (50, 0, 10, 90, 15, 0, 1, 0, 0, 0, 0, 1), (12, 0, 11, 100, 30, 0, 1, 0, 0, 0, 0, 1),
    (50, 0, 10, 90, 12, 100, 1, 0, 0, 0, 0, 0), (25, 0, 10, 90, 12, 100, 1, 0, 0, 0, 0, 0), (9, 100, 9, 100, 12, 0, 1, 0, 0, 0, 0, 0), (9, 100, 9, 100, 9, 100, 1, 0, 0, 0, 0, 0),
    (30, 0, 2, 100, 2, 100, 1, 0, 0, 1, 0, 0), (2, 100, 2, 100, 2, 100, 1, 0, 0, 1, 0, 0), (40, 0, 3, 100, 0, 0, 1, 0, 0, 0, 0, 0), (2, 100, 4, 100, 30, 0, 1, 0, 0, 0, 0, 0),
    (40, 0, 3, 100, 60, 0, 1, 0, 0, 0, 0, 0), (40, 0, 9, 100, 60, 0, 1, 0, 0, 1, 0, 0), (0, 0, 2, 100, 30, 0, 1, 0, 0, 0, 0, 0),
    # elements that never hold article text
    (2, 100, 1, 100, 1, 100, 0, 1, 0, 1, 0, 0), (1, 100, 1, 100, 14, 0, 0, 1, 0, 1, 0, 0), (60, 0, 12, 0, 0, 0, 0, 1, 0, 0, 0, 0), (90, 0, 30, 10, 0, 0, 0, 1, 0, 0, 0, 0),
    (0, 0, 5, 0, 8, 0, 0, 1, 0, 0, 1, 0), (40, 0, 60, 0, 20, 0, 0, 1, 0, 0, 0, 0), (40, 0, 60, 0, 20, 0, 1, 1, 0, 0, 0, 0), (20, 0, 5, 0, 20, 0, 1, 1, 0, 0, 0, 0),
    (20, 0, 8, 0, 20, 0, 1, 1, 0, 0, 1, 0), (10, 0, 150, 0, 20, 0, 1, 1, 0, 0, 0, 0), (1, 100, 1, 100, 80, 0, 0, 1, 0, 1, 0, 0), (0, 0, 5, 0, 200, 0, 0, 1, 0, 0, 0, 0),
    (30, 0, 10, 0, 90, 0, 1, 1, 0, 0, 0, 0), (0, 0, 70, 0, 90, 0, 0, 1, 0, 0, 0, 0), (90, 0, 70, 0, 90, 0, 1, 1, 0, 0, 0, 0), (20, 0, 6, 0, 120, 0, 0, 1, 0, 0, 1, 0), (0, 0, 2, 0, 0, 0, 0, 1, 0, 0, 0, 0),
    # elements named as such a thing
    (1, 100, 15, 0, 9, 0, 0, 0, 1, 0, 0, 0), (1, 100, 40, 0, 9, 0, 0, 0, 1, 0, 0, 0), (60, 0, 25, 0, 25, 0, 0, 0, 1, 0, 0, 0), (50, 0, 18, 0, 40, 0, 1, 0, 1, 0, 0, 0),
    (30, 0, 60, 0, 30, 0, 1, 0, 1, 0, 0, 0), (30, 0, 4, 0, 30, 0, 1, 0, 1, 0, 0, 0), (20, 0, 5, 0, 20, 0, 1, 0, 1, 0, 1, 0), (9, 0, 120, 3, 9, 0, 0, 0, 1, 0, 0, 0),
    (3, 0, 12, 0, 90, 0, 0, 0, 1, 0, 0, 0), (90, 0, 70, 0, 90, 0, 1, 0, 1, 0, 0, 0), (0, 0, 70, 0, 90, 0, 0, 0, 1, 0, 0, 0), (12, 0, 1, 0, 0, 0, 0, 0, 1, 0, 0, 0), (0, 0, 9, 0, 0, 0, 0, 0, 1, 0, 0, 0),
    # plain text of pages without an article element
    (8, 0, 50, 5, 60, 0, 0, 0, 0, 0, 0, 1), (60, 0, 40, 0, 80, 0, 0, 0, 0, 0, 0, 1), (7, 0, 25, 0, 30, 0, 0, 0, 0, 0, 0, 1), (40, 0, 14, 0, 35, 0, 0, 0, 0, 0, 0, 1),
    (50, 0, 90, 10, 3, 100, 0, 0, 0, 0, 0, 1), (0, 0, 7, 0, 45, 0, 0, 0, 0, 0, 1, 1), (35, 0, 5, 0, 40, 0, 0, 0, 0, 0, 1, 1), (45, 0, 4, 0, 50, 0, 0, 0, 0, 0, 0, 1),
    (30, 0, 8, 0, 30, 0, 0, 0, 0, 0, 0, 1), (40, 0, 15, 0, 15, 0, 0, 0, 0, 1, 0, 1), (15, 0, 12, 20, 14, 0, 0, 0, 0, 1, 0, 1), (0, 0, 40, 0, 0, 0, 0, 0, 0, 0, 0, 1),
    (0, 0, 12, 0, 1, 0, 0, 0, 0, 0, 0, 1), (60, 0, 9, 0, 0, 0, 0, 0, 0, 0, 0, 1), (60, 0, 12, 0, 2, 0, 0, 0, 0, 0, 0, 1), (4, 0, 5, 0, 3, 0, 0, 0, 0, 0, 0, 1), (4, 0, 6, 0, 0, 0, 0, 0, 0, 0, 0, 1),
    (0, 0, 2, 0, 0, 0, 0, 0, 0, 0, 0, 1), (0, 0, 1, 0, 1, 0, 0, 0, 0, 0, 0, 1), (60, 0, 1, 0, 60, 0, 0, 0, 0, 0, 0, 1), (2, 100, 9, 0, 1, 0, 0, 0, 0, 0, 0, 1), (2, 100, 12, 0, 2, 100, 0, 0, 0, 0, 0, 1),
    (2, 100, 6, 0, 60, 0, 0, 0, 0, 0, 1, 1), (60, 0, 7, 0, 3, 100, 0, 0, 0, 0, 0, 1), (1, 100, 2, 0, 40, 0, 0, 0, 0, 0, 1, 1), (3, 0, 2, 0, 3, 0, 0, 0, 0, 1, 0, 1), (30, 0, 12, 90, 30, 0, 0, 0, 0, 0, 0, 1),
    (12, 0, 1, 0, 1, 100, 0, 0, 0, 0, 0, 1), (60, 0, 1, 0, 1, 100, 0, 0, 0, 0, 0, 1), (5, 0, 3, 0, 1, 100, 0, 0, 0, 0, 0, 1), (1, 100, 1, 0, 40, 0, 0, 0, 0, 0, 0, 1), (1, 100, 2, 0, 8, 0, 0, 0, 0, 0, 0, 1), (3, 0, 2, 0, 1, 100, 0, 0, 0, 0, 0, 1), (2, 0, 4, 0, 3, 100, 0, 0, 0, 0, 0, 1),
    # crumbs between links, and links
    (2, 100, 3, 0, 2, 100, 0, 0, 0, 0, 0, 0), (1, 100, 1, 0, 1, 100, 0, 0, 0, 0, 0, 0), (1, 100, 2, 0, 1, 100, 0, 0, 0, 0, 1, 0), (1, 100, 1, 0, 1, 100, 0, 0, 0, 1, 0, 0), (4, 100, 5, 0, 3, 100, 0, 0, 0, 0, 0, 0),
    (2, 0, 4, 50, 3, 100, 0, 0, 0, 0, 0, 0), (3, 100, 4, 100, 4, 100, 0, 0, 0, 1, 0, 0), (50, 0, 6, 80, 4, 100, 0, 0, 0, 0, 0, 0), (3, 100, 30, 90, 3, 100, 0, 0, 0, 0, 0, 0), (1, 100, 1, 100, 60, 0, 0, 0, 0, 1, 0, 0),
    (20, 0, 4, 100, 120, 0, 0, 0, 0, 0, 0, 0), (0, 0, 1, 100, 30, 0, 0, 0, 0, 0, 0, 0), (40, 0, 2, 100, 0, 0, 0, 0, 0, 0, 0, 0), (0, 0, 1, 100, 1, 100, 0, 0, 0, 0, 0, 0),
)


def grow(x: np.ndarray, y: np.ndarray, depth: int = 16):
    """A tree of (feature, threshold, low side, high side) with shares of label 1 as leaves, split by Gini gain."""
    share = float(y.mean())
    if depth == 0 or share in (0.0, 1.0):
        return share
    best = (1e-9, None, None)
    for f in range(x.shape[1]):
        values = np.unique(x[:, f])
        for at in (values[:-1] + values[1:]) / 2:
            low = x[:, f] <= at
            gain = share * (1 - share) - sum(m.mean() * y[m].mean() * (1 - y[m].mean()) for m in (low, ~low))
            if gain > best[0]:
                best = (gain, f, at)
    if best[1] is None:
        return share
    _, f, at = best
    low = x[:, f] <= at
    return f, float(at), grow(x[low], y[low], depth - 1), grow(x[~low], y[~low], depth - 1)


@functools.lru_cache(1)
def trained():
    table = np.array(LABELLED, float)
    return grow(table[:, :-1], table[:, -1])


def is_text(tree, features: tuple) -> bool:
    while isinstance(tree, tuple):
        f, at, low, high = tree
        tree = low if features[f] <= at else high
    return tree >= 0.5


def hinted(attributes: str) -> bool:
    for m in _HINT.finditer(attributes):
        for name in m[1].strip("\"'").lower().split():
            parts = [x for x in _SPLIT.split(name) if x]
            if not parts or (len(parts) > 1 and parts[0] in ABOUT):
                continue
            if HINTS.intersection(parts) or "header" in parts and OF_PAGE.intersection(parts):
                return True
    return False


def unseen(attributes: str) -> bool:
    return bool(_UNSEEN.search(attributes) or _HIDDEN.search(_QUOTED.sub("", attributes)))


def blocks(page: str) -> list[tuple[str, int, int, bool, bool, bool, bool, bool]]:
    """(text, words, link percent, in article, never, hinted, in list, heading) of each flat block."""
    out, parts, linked = [], [], 0
    stack: list[tuple[str, bool, bool, bool, bool, bool]] = []
    state = (False, False, False, False, False)
    in_link = 0
    opened: Counter[str] = Counter()  # names on the stack

    def close(depth: int):
        opened.subtract(x[0] for x in stack[depth:])
        del stack[depth:]

    def flush():
        nonlocal parts, linked
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                n = text.count(" ") + 1
                out.append((text, n, min(100, 100 * linked // n), *state))
            parts, linked = [], 0

    def take(raw: str):
        nonlocal linked
        parts.append(raw)
        if in_link:
            linked += len(raw.split())

    at, size = 0, len(page)
    while at < size:
        m = _MARK.search(page, at)
        if m is None:
            take(page[at:])
            break
        if m.start() > at:
            take(page[at : m.start()])
        at = m.end()
        if m[1] is not None:
            take(entities.escape(m[1]))
        name = m[3]
        if name is None:
            continue
        name, closing = name.lower(), bool(m[2])
        if name in RAW:
            if not closing and not m[4].endswith("/"):
                end = re.compile(rf"</{re.escape(name)}\s*>", re.IGNORECASE).search(page, at)
                at = end.end() if end else size
            if name not in ("button", "option", "select"):
                parts.append(" ")
            continue
        if name in INLINE:
            if name == "a":
                in_link = 0 if closing else 1
            elif name in ("br", "wbr", "img"):
                parts.append(" " if name == "br" else "")
            continue
        flush()
        if closing:
            if opened[name] > 0:
                close(next(k for k in range(len(stack) - 1, -1, -1) if stack[k][0] == name))
                in_link = 0
        elif name not in VOID and not m[4].endswith("/"):
            article, never, hint, listed, heading = stack[-1][1:] if stack else (False,) * 5
            own = hinted(m[4])
            if name in ("p", "li", "dt", "dd", "tr", "td", "th", *HEADINGS) and stack and stack[-1][0] == name:
                close(len(stack) - 1)
                article, never, hint, listed, heading = stack[-1][1:] if stack else (False,) * 5
            is_article = name in ("article", "main") and not own
            hint = hint and not is_article  # a wrapper may be named after a part of it
            never = never or name in NEVER or (name == "header" and not article) or unseen(m[4])
            opened[name] += 1
            stack.append((name, article or is_article, never, hint or (own and name not in ("body", "html")), listed or name in ("ul", "ol", "dl"), name in HEADINGS))
        state = stack[-1][1:] if stack else (False,) * 5
    flush()
    return out


def main_text(page: bytes | str | None, tree=None) -> str:
    if not page:
        return ""
    found = blocks(page.decode("utf-8", "replace") if isinstance(page, bytes) else page)
    tree = tree or trained()
    edge = ("", 0, 0)
    kept = []
    for k, b in enumerate(found):
        before, behind = (found[k - 1] if k else edge), (found[k + 1] if k + 1 < len(found) else edge)
        if is_text(tree, (*before[1:3], *b[1:3], *behind[1:3], *map(int, b[3:]))):
            kept.append(b[0])
    return "\n\n".join(kept)


def extract(pages: DataFrame, html: str = "html", keep=None) -> DataFrame:
    """Rows of ``pages`` with text and n_chars (code points)."""

    def start():
        tree = trained()

        def work(htmls):
            texts = [main_text(h, tree) for h in htmls]
            return texts, [len(t) for t in texts]

        return work

    return annotate(pages, [html], [("text", T.StringType()), ("n_chars", T.LongType())], start, keep)


def op4_main_text(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return extract(pages, keep=["page_id", "url"])
