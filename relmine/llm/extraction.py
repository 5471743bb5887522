"""Main text of web pages: flat text blocks and a decision tree.

A page is scanned once into flat blocks of text, the runs between block-level
tags. Each block has its word count and link density, those of its neighbours,
and what the page declares around it: containers for navigation, notices,
adverts, forms or comments, or for an article. A small decision tree, grown on
the blocks of the labelled pages below, keeps or drops each block.

Defined cases: null, empty or textless html gives empty text; broken nesting,
unclosed tags, comments and quotes are read as far as they go, an open bracket that
begins no tag is text; very long pages take time in proportion to their length;
scripts, styles and templates are never text; repeated rows give repeated results; null ids and
urls are kept; extra columns are ignored.
"""

from __future__ import annotations

import html as html_
import re
from bisect import bisect_left
from collections import Counter
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Element names by their part in a page.
RAW = {"script", "style", "noscript", "template", "iframe", "object", "svg", "math", "textarea", "select", "title", "head"}
BREAKING = set("address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
               "h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
BAD_TAGS = {"nav", "footer", "aside", "form", "button", "menu", "dialog", "fieldset"}
BAD_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
BAD_NAMES = set("ad ads adv advert adverts advertisement advertising adsense banner breadcrumb breadcrumbs cc comment comments commentlist consent cookie cookies copyright "
                "disclaimer disqus feedback footer foot gdpr hidden legal login masthead menu meta modal nav navbar navigation newsletter notice notification overlay pager pagination "
                "popup promo promoted promotion rail recommended related replies reply respond search share sharing sidebar signup skip social sponsor sponsored subscribe tagcloud tags "
                "teaser toolbar topbar warning widget alert header".split())
GOOD_NAMES = set("article articlebody body content entry main maincontent post postbody story text prose".split())
_TAG = re.compile(r"<!--.*?(?:--!?>|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?]|<(/?)([a-zA-Z][^\s/>]*)", re.S)
_MARKS = re.compile("[>\"']")
_ATTR = re.compile(r"([a-zA-Z_:][\w:.-]*)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.S)
_NAME = re.compile(r"[a-z]+")


@lru_cache(32)
def _closing(tag: str) -> re.Pattern:
    return re.compile(rf"</{tag}\b[^>]*>", re.I)


class Block(NamedTuple):
    text: str
    words: int
    links: float  # share of the words inside links
    bad: bool
    article: bool
    heading: bool


@lru_cache(4096)
def _marks(tag: str, attributes: str) -> tuple[bool, bool]:
    """(declared as no main text, declared as main text)."""
    bad, good = tag in BAD_TAGS, tag in ("article", "main")
    if attributes.strip():
        names: list[str] = []
        for k, *v in _ATTR.findall(attributes):
            k, v = k.lower(), "".join(v).lower()
            if k in ("class", "id"):
                names += _NAME.findall(v)
            elif k == "role":
                bad |= v in BAD_ROLES
                good |= v in ("main", "article")
            elif k == "hidden" or k == "aria-hidden" and v == "true" or k == "style" and re.search(r"display\s*:\s*none", v):
                bad = True
        if tag not in ("html", "body", "article", "main"):
            bad |= any(n in BAD_NAMES for n in names)
        good |= any(n in GOOD_NAMES for n in names)
    return bad, good and not bad


class TagEnds:
    """Where tags of a page end: at the first > outside quotation marks, found for all places in one pass from the back."""

    def __init__(self, page: str):
        self.at = [m.start() for m in _MARKS.finditer(page)]
        self.end = [-1] * (len(self.at) + 1)
        later = {'"': -1, "'": -1}
        for i in range(len(self.at) - 1, -1, -1):
            c = page[self.at[i]]
            if c == ">":
                self.end[i] = self.at[i] + 1
            else:
                self.end[i] = self.end[later[c] + 1] if later[c] >= 0 else -1
                later[c] = i

    def __call__(self, start: int) -> int:
        """The end of a tag whose attributes begin at ``start``; -1 if it has none."""
        return self.end[bisect_left(self.at, start)]


def blocks(page: str | None) -> list[Block]:
    """The blocks of a page, in time that grows with its length whatever is left open in it."""
    out: list[Block] = []
    page = page or ""
    stack: list[tuple[str, bool, bool]] = [("", False, False)]
    opened: Counter[str] = Counter()
    endless: set[str] = set()
    ends, last = TagEnds(page), page.rfind(">")
    parts: list[str] = []
    linked, link_depth, heading, at = 0, 0, False, 0

    def close() -> None:
        nonlocal linked
        if parts:
            words = html_.unescape("".join(parts)).split()
            parts.clear()
            if words:
                out.append(Block(" ".join(words), len(words), min(1.0, linked / len(words)), stack[-1][1], stack[-1][2], heading))
            linked = 0

    def take(piece: str) -> None:
        nonlocal linked
        if piece:
            parts.append(piece)
            if link_depth:
                linked += len(piece.split())

    n = len(page)
    while at < n:
        m = _TAG.search(page, at)
        if m is None:
            take(page[at:])
            break
        stop = ends(m.end()) if m[2] is not None else m.end() if m.end() - m.start() > 2 else page.find(">", m.end()) + 1 if m.end() <= last else -1
        if stop < 0:  # no tag: an open bracket as text
            take(page[at:m.start() + 1])
            at = m.start() + 1
            continue
        take(page[at:m.start()])
        at = stop
        if m[2] is None:
            continue
        tag, ending, attributes = m[2].lower(), bool(m[1]), page[m.end():stop - 1]
        if tag in RAW and not ending:
            if tag == "head":
                continue
            if not attributes.endswith("/"):
                found = None if tag in endless else _closing(tag).search(page, at)
                if found is None:
                    endless.add(tag)
                at = found.end() if found else (n if tag in ("script", "style", "title", "textarea") else at)
            if tag in BREAKING:
                close()
            continue
        if tag == "br":
            take(" ")
        elif tag == "a":
            link_depth = max(0, link_depth - 1) if ending else link_depth + 1
        elif tag in BREAKING:
            close()
            heading = not ending and len(tag) == 2 and tag[0] == "h" and tag[1].isdigit()
            if ending:
                while opened[tag]:
                    last = stack.pop()[0]
                    opened[last] -= 1
                    if last == tag:
                        break
            elif tag != "hr":
                if stack[-1][0] in ("p", "h1", "h2", "h3", "h4", "h5", "h6") or stack[-1][0] == tag == "li":
                    opened[stack.pop()[0]] -= 1
                bad, good = _marks(tag, attributes)
                inside = stack[-1]
                # a page's header is none of its text, an article's header is its title
                bad |= tag == "header" and not inside[2]
                stack.append((tag, inside[1] or bad, (inside[2] or good) and not bad))
                opened[tag] += 1
            link_depth = 0
    close()
    return out


def features(found: list[Block]) -> np.ndarray:
    """bad, article, heading, words, link density, those of the block before and after, and whether it ends a sentence."""
    if not found:
        return np.zeros((0, 10))
    own = np.array([(b.bad, b.article, b.heading, min(b.words, 100), b.links) for b in found], float)
    side = np.zeros((len(found) + 2, 2))
    side[1:-1] = own[:, 3:5]
    ends = np.array([[b.text[-1] in ".!?…:;\"”»)"] for b in found], float)
    return np.hstack([own, side[:-2], side[2:], ends])


class Tree:
    """A decision tree by Gini impurity."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 6, least: int = 1):
        self.value = float(y.mean()) if len(y) else 0.0
        self.cut = None
        if depth and 0 < self.value < 1 and len(y) >= 2 * least:
            best = min(((self._impurity(x[:, j] <= t, y), j, t) for j in range(x.shape[1]) for t in self._places(x[:, j])), default=None)
            if best is not None and best[0] < len(y) * self.value * (1 - self.value) - 1e-12:
                _, j, t = best
                low = x[:, j] <= t
                if least <= low.sum() <= len(y) - least:
                    self.cut = (j, t, Tree(x[low], y[low], depth - 1, least), Tree(x[~low], y[~low], depth - 1, least))

    @staticmethod
    def _places(v: np.ndarray) -> np.ndarray:
        u = np.unique(v)
        return (u[1:] + u[:-1]) / 2

    @staticmethod
    def _impurity(low: np.ndarray, y: np.ndarray) -> float:
        return sum(len(s) * s.mean() * (1 - s.mean()) for s in (y[low], y[~low]) if len(s))

    def predict(self, x: np.ndarray) -> np.ndarray:
        if self.cut is None:
            return np.full(len(x), self.value)
        j, t, a, b = self.cut
        low = x[:, j] <= t
        out = np.empty(len(x))
        out[low], out[~low] = a.predict(x[low]), b.predict(x[~low])
        return out


#: The labelled table: small pages; a block is main text where it begins with "M ".
_S = "M The committee met on Tuesday and agreed that the plan should go ahead, with two members against it and one absent from the vote."
_L = ("We and our partners keep and read details on a device, such as cookies, and process them for the purposes that are described in the policy, which you should read before you go on, "
      "and which may change from time to time without any further word from us.")
LABELLED = (
    f"<body><nav><ul><li><a href=/>Home</a></li><li><a href=/n>News</a></li></ul></nav><article><h1>M Title of it</h1><p>{_S}</p><p>M Short.</p><p>{_S}</p><p>M Also short.</p></article><footer>All rights reserved by the owner of this site.</footer></body>",
    f"<body><div class=header>Daily News</div><div class=menu><a href=1>One</a> <a href=2>Two</a></div><div class=content><h2>M A heading</h2><p>{_S}</p><p>M Yes.</p><ul><li>M first point of it</li><li>M second point</li></ul></div><div class=sidebar><h3>Most read</h3><p>A teaser of some other story that is long enough to look like text, and ends here.</p></div><div id=comments><p>I do not agree with this at all, it was quite different when I was there in May.</p><p>Nice one!</p></div></body>",
    f"<body><header><a href=/>Site</a> A slogan about the site that runs for some words.</header><main><h1>M Main title here</h1><p>{_S} <a href=x>M link</a></p><blockquote>M A quotation of eight words stands right here.</blockquote></main><aside>Follow us for more, every day, wherever you are and whatever you do.</aside><form><label>Your name</label><p>Fill in this form to hear from us about offers and news.</p></form></body>",
    f"<body><div class=cookie-notice>We use cookies to make this site better for you, please accept them.</div><div><p>{_S}</p><p>{_S}</p><p>{_S}</p></div><div><a href=1>Related one</a> <a href=2>Related two</a> <a href=3>Related three</a></div><div>Copyright</div></body>",
    f"<body><table><tr><td><a href=1>Home</a></td><td><a href=2>About us</a></td></tr></table><div>Menu</div><p>{_S}</p><p>M It was late, and they all went home soon after that.</p><p>{_S}</p><div><a href=4>Next page</a></div><div>Imprint</div></body>",
    f"<body><div class=ad>Buy now the best of all products that money can buy you today.</div><article><header><h1>M Name of story</h1></header><section><p>{_S}</p><p>M One.</p><ol><li>M <a href=r>M reference text in a list</a></li></ol></section><div class=share><a href=t>Share it</a></div><section class=comments><p>What a story, I have read it twice and sent it to my friends too.</p></section></article><footer><p>The publisher, its address and a long legal text that nobody ever reads.</p></footer></body>",
    f"<body><div class=post><h1>M Post title</h1><p>{_S}</p><p>M So.</p><pre>M some code here</pre></div><div class=promo><p>Subscribe today and get the first month for nothing, then pay each month.</p></div><div class=widget><ul><li><a href=1>January</a></li><li><a href=2>February</a></li></ul></div></body>",
    f"<body><div>Menu</div><div>Search</div><article><h1>M Storms</h1><p>M No.</p><p>M Why?</p><p>{_S}</p><p>M Rain.</p><p>M <a href=w>M Wind</a></p><p>M Indeed.</p></article><div>Imprint</div><div>Top</div></body>",
    f"<body><div>Login</div><div>Page 3 of 7</div><main><h2>M Prices</h2><p>M 12</p><p>M Up.</p><p>{_S}</p><p>M Down</p></main><div>Contact</div><div>Version 2</div></body>",
    f"<body><div class=consent><p>{_L}</p><p>{_L}</p></div><h1>M Harbour to close</h1><p>{_S}</p><p>{_S}</p><p>{_S}</p><div id=comments><p>{_L}</p><p>{_L}</p></div><footer><p>{_L}</p></footer></body>",
    f"<body><aside><p>{_L}</p></aside><article><p>{_S}</p><p>{_L.replace('We', 'M We', 1)}</p><div class=comments><p>{_L}</p><p>Quite.</p><p>{_L}</p></div></article><form><p>{_L}</p></form><div class=disclaimer>{_L}</div></body>",
    f"<body><ul><li><a href=1>Sports</a></li><li><a href=2>Weather</a></li></ul><h1>M A headline</h1><p>{_S}</p><p>{_S}</p><p>M He left.</p><p>{_S}</p><p><a href=1>Privacy</a> <a href=2>Terms</a></p></body>",
)


@lru_cache(1)
def tree() -> Tree:
    found = [blocks(p) for p in LABELLED]
    return Tree(np.vstack([features(f) for f in found]), np.array([b.text.startswith("M ") for f in found for b in f], float))


def main_text(page: str | None) -> str:
    found = blocks(page)
    keep = tree().predict(features(found)) >= 0.5
    return "\n".join(b.text for b, k in zip(found, keep) if k)


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars), a row for each row of ``pages``."""
    def run(batches):
        for b in batches:
            text = [main_text(t) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(
        run, "page_id long, url string, text string, n_chars long")
