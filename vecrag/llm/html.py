"""Main-text extraction: flat text blocks, shallow features of each block and its neighbours, a decision tree.

A page is cut into blocks at block-level tags. A block has its word count and link density (share of words
inside links), those of the blocks before and after it, and what its open elements say about it (article or
main body, heading, list item, page furniture by tag, role, class or id). A decision tree, grown in numpy on
the small labelled pages below, keeps or drops each block; kept blocks are joined by a newline. Shallow text
features come first among equal gains; elements decide where they tell, and pages without them, or whose main
element holds little of the text, are judged by words, links and neighbours.

Defined results: null or empty html gives the empty text; truncated markup is read as far as it goes (an open
head ends at the first element or text that belongs to a body); very long pages are taken whole; repeated pages
give repeated rows; a null page id or url is passed on.
"""

from __future__ import annotations

import html as entities
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import map_slices

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(/?)([A-Za-z][A-Za-z0-9:-]*+)((?:[^>\"']|\"[^\"]*+\"|'[^']*+')*+)>"
    r"|<(/?)([A-Za-z][A-Za-z0-9:-]*+)([^>]*+)(?:>|\Z)",
    re.S,
)
ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|aria-hidden|style)\b\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+))?", re.I)

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is never text of the page.
UNSEEN = frozenset("script style noscript template iframe object svg math head title audio video canvas select option datalist textarea button".split())
RAW = frozenset("script style title textarea iframe noscript xmp noembed noframes".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var br wbr img".split())

#: Elements that a head may hold; any other one, or text, ends an open head.
IN_HEAD = frozenset("base basefont bgsound link meta title style script noscript template".split())

MAIN, NAV, HEADER, FOOTER, ASIDE, ADVERT, NOTICE, FORM, COMMENT, LINK, HIDDEN = (1 << k for k in range(11))
FURNITURE = NAV | HEADER | FOOTER | ASIDE | ADVERT | NOTICE | FORM | COMMENT
TAG_BITS = {"article": MAIN, "main": MAIN, "nav": NAV, "menu": NAV, "header": HEADER, "footer": FOOTER, "aside": ASIDE, "form": FORM, "fieldset": FORM, "dialog": NOTICE, "a": LINK}
#: Words of class, id and role attributes, and what they mean (fixed values).
NAME_BITS = {
    NAV: "nav navbar navigation menu breadcrumb breadcrumbs pagination pager toc tabs topbar toolbar",
    HEADER: "header masthead banner site-header page-header",
    FOOTER: "footer colophon contentinfo copyright site-footer page-footer",
    ASIDE: "sidebar aside widget widgets related recommended complementary share sharing social trending promo tags",
    ADVERT: "ad ads advert adverts advertisement advertising sponsor sponsored ad-slot adbox dfp",
    NOTICE: "cookie cookies consent gdpr notice alert popup modal overlay newsletter subscribe subscription disclaimer paywall",
    FORM: "form search login signin signup",
    COMMENT: "comment comments disqus respond reply replies reader-comments user-comments",
    MAIN: "article post entry story main content article-body post-content entry-content story-body main-content",
}
BITS_OF = {word: bit for bit, words in NAME_BITS.items() for word in words.split()}
#: Parts of a hyphenated name that say nothing by themselves: such a name counts if all its other parts are furniture.
NEUTRAL = frozenset("site page top bottom left right upper lower inner outer wrap wrapper container box bar area list item section block slot zone unit col column row primary secondary global mobile desktop fixed sticky big small text link links".split())
PART = re.compile(r"[a-z]+")


def _name_bits(word: str, name: str) -> int:
    """What one word of a class, id or role says."""
    word = word.replace("_", "-")
    bits = BITS_OF.get(word, 0)
    if not bits and "-" in word and name in ("div", "section", "ul", "ol", "aside", "p", "span", "header", "footer"):
        told = [BITS_OF.get(piece, 0) for piece in PART.findall(word) if piece not in NEUTRAL]
        if told and all(b & FURNITURE for b in told):
            for b in told:
                bits |= b
    return bits


def _own_bits(name: str, attributes: str, inherited: int) -> int:
    bits = TAG_BITS.get(name, 0)
    if attributes.strip():
        for key, value in ATTRIBUTE.findall(attributes):
            key, value = key.lower(), value.strip("\"'").lower()
            if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
                bits |= HIDDEN
            elif key in ("class", "id", "role"):
                for word in value.split():
                    bits |= _name_bits(word, name)
    if bits & FURNITURE and name in ("body", "html", "main", "article"):
        bits &= ~FURNITURE
    if name == "header" and inherited & MAIN:  # an article's own heading group
        bits &= ~HEADER
    return bits


@dataclass
class Block:
    text: str
    words: int
    linked: int
    bits: int
    tag: str
    gold: bool = False


@dataclass
class _Open:
    name: str
    bits: int
    unseen: bool
    gold: bool = False


@dataclass
class _Page:
    blocks: list[Block] = field(default_factory=list)
    stack: list[_Open] = field(default_factory=lambda: [_Open("", 0, False)])
    pieces: list[tuple[str, bool]] = field(default_factory=list)

    def flush(self) -> None:
        if not self.pieces:
            return
        top = next((x for x in reversed(self.stack) if x.name not in INLINE), self.stack[0])
        text = " ".join("".join(p for p, _ in self.pieces).split())
        if text:
            words = text.count(" ") + 1
            linked = sum(len(p.split()) for p, link in self.pieces if link)
            self.blocks.append(Block(text, words, min(linked, words), self.stack[-1].bits & ~LINK | top.bits, top.name, any(x.gold for x in self.stack)))
        self.pieces.clear()

    def add(self, raw: str) -> None:
        if raw and self.stack[-1].name == "head" and not raw.isspace():
            self.end_head()
        top = self.stack[-1]
        if raw and not top.unseen:
            self.pieces.append((entities.unescape(raw) if "&" in raw else raw, bool(top.bits & LINK)))

    def end_head(self) -> None:
        at = next((k for k in range(len(self.stack) - 1, 0, -1) if self.stack[k].name == "head"), 0)
        if at:
            del self.stack[at:]

    def close(self, name: str) -> None:
        at = next((k for k in range(len(self.stack) - 1, 0, -1) if self.stack[k].name == name), 0)
        if at:
            del self.stack[at:]


#: An opening tag on the left ends an open element named on the right.
IMPLIED = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th")}


def blocks_of(page: str) -> list[Block]:
    """The text blocks of a page, in page order."""
    out, at, end = _Page(), 0, len(page)
    while at < end:
        m = TOKEN.search(page, at)
        if m is None:
            tail = page[at:]
            out.add(tail)
            break
        out.add(page[at : m.start()])
        at = m.end()
        name = (m[2] or m[5] or "").lower()
        if not name:
            continue
        closing, attributes = bool(m[1] or m[4]), m[3] or m[6] or ""
        if name in ("br", "wbr", "hr", "img"):
            out.add(" ")
        if name not in INLINE and name not in UNSEEN:
            out.flush()
        if closing:
            out.close(name)
            continue
        if out.stack[-1].name == "head" and name not in IN_HEAD:
            out.end_head()
        if name in VOID:
            continue
        if name not in INLINE and name not in UNSEEN and any(x.name == "p" for x in out.stack[1:]):
            k = max(k for k, x in enumerate(out.stack) if x.name == "p")
            if all(x.name in INLINE for x in out.stack[k + 1 :]):
                del out.stack[k:]
        for other in IMPLIED.get(name, ()):
            for k in range(len(out.stack) - 1, 0, -1):
                if out.stack[k].name in ("ul", "ol", "dl", "table"):
                    break
                if out.stack[k].name == other:
                    del out.stack[k:]
                    break
        top = out.stack[-1]
        bits = _own_bits(name, attributes, top.bits)
        if not attributes.rstrip().endswith("/") or name not in ("svg", "path"):
            out.stack.append(_Open(name, top.bits | bits, top.unseen or name in UNSEEN or bool(bits & HIDDEN), top.gold or "data-gold" in attributes))
        if name in RAW:
            stop = re.compile(rf"</{name}\b", re.I).search(page, at)
            if stop is None:  # never closed: nothing readable follows
                at = end
            else:
                at = stop.start()
    out.flush()
    return out.blocks


FEATURES = ("words", "link_density", "words_before", "link_density_before", "words_after", "link_density_after", "page_links", "furniture", "in_main", "main_share", "heading", "list_item")


def features_of(blocks: list[Block]) -> np.ndarray:
    """One row of FEATURES for each block; outside the page a neighbour has no words and no links.

    main_share is the share of the page's words, furniture left out, that the main element (or what is named so) holds.
    """
    n = len(blocks)
    words = np.array([0, *(b.words for b in blocks), 0], float)
    density = np.array([0, *(b.linked / b.words for b in blocks), 0], float)
    main = np.array([bool(b.bits & MAIN) for b in blocks], bool)
    furniture = np.array([bool(b.bits & FURNITURE) for b in blocks], bool)
    linked = sum(b.linked for b in blocks) / max(1, sum(b.words for b in blocks))
    own = words[1:-1][~furniture].sum()
    share = words[1:-1][main & ~furniture].sum() / own if own else 0.0
    return np.column_stack([
        words[1:-1], density[1:-1], words[:-2], density[:-2], words[2:], density[2:], np.full(n, linked),
        furniture, main, np.full(n, share),
        np.array([b.tag in ("h1", "h2", "h3", "h4", "h5", "h6") for b in blocks], float),
        np.array([b.tag in ("li", "dt", "td", "th") for b in blocks], float),
    ]).reshape(n, len(FEATURES))


def _gini(y: np.ndarray) -> float:
    p = y.mean() if len(y) else 0.0
    return 2 * p * (1 - p)


def grow(x: np.ndarray, y: np.ndarray, depth: int = 6, least: int = 1) -> list[tuple]:
    """A decision tree by Gini impurity: rows (feature, threshold, left, right, share); feature -1 is a leaf.

    Equal gains go to the feature listed first, then to the smaller threshold.
    """
    tree: list[tuple] = []

    def node(rows: np.ndarray, left: int) -> int:
        at = len(tree)
        tree.append((-1, 0.0, -1, -1, float(y[rows].mean()) if len(rows) else 0.0))
        best = (1e-12, -1, 0.0)
        if left and 0 < y[rows].mean() < 1:
            for f in ORDER:
                values = np.unique(x[rows, f])
                for t in (values[1:] + values[:-1]) / 2:
                    side = x[rows, f] <= t
                    if min(side.sum(), (~side).sum()) >= least:
                        gain = _gini(y[rows]) - side.mean() * _gini(y[rows][side]) - (~side).mean() * _gini(y[rows][~side])
                        if gain > best[0] + 1e-12:
                            best = (gain, f, t)
        if best[1] >= 0:
            side = x[rows, best[1]] <= best[2]
            a, b = node(rows[side], left - 1), node(rows[~side], left - 1)
            tree[at] = (best[1], best[2], a, b, tree[at][4])
        return at

    node(np.arange(len(y)), depth)
    return tree


#: Shallow text features are tried before what elements say, so that they win equal gains.
ORDER = list(range(len(FEATURES)))


def predict(tree: list[tuple], x: np.ndarray) -> np.ndarray:
    """Share of kept training blocks in the leaf each row falls into."""
    feature, threshold, left, right, share = (np.array(c) for c in zip(*tree, strict=True))
    at = np.zeros(len(x), int)
    while (inner := feature[at] >= 0).any():
        go = np.flatnonzero(inner)
        f = feature[at[go]]
        at[go] = np.where(x[go, f] <= threshold[at[go]], left[at[go]], right[at[go]])
    return share[at]


_SENTENCE = "The council met on Monday evening to talk about the new bridge and its cost."
_LINKS = "".join(f'<li><a href="/{w}">{w}</a></li>' for w in ("home", "world", "sport", "travel"))
_BARE = " ".join(f'<a href="/{w}">{w}</a>' for w in ("home", "news", "sport", "about", "contact"))
_TEASER = '<a href="/t">The long story of the old mill that the town wants to keep for good</a>'
_G = " data-gold"
#: The labelled table's pages: blocks under an element with data-gold are article text. The first pages have elements that
#: tell the article from the rest; the others have none, or ones that mislead, so that words, links and neighbours must.
LABELLED_PAGES = (
    f"<html><body><nav><ul>{_LINKS}</ul></nav><div class='ad'>Buy the finest boots in town at half the price today and tomorrow only.</div>"
    f"<article><h1{_G}>Bridge talks</h1><p{_G}>{_SENTENCE}</p><p{_G}>Yes.</p><p{_G}>{_SENTENCE * 4}</p></article><footer>&copy; The Paper, all rights reserved by its owners since 1901.</footer></body></html>",
    f"<body><header><h1>The Paper</h1><p>News that you can read every day of the week.</p></header><main><h2{_G}>One</h2><p{_G}>{_SENTENCE} See <a href='/x'>the plan</a>.</p>"
    f"<ul><li{_G}>first point of the plan</li><li{_G}>second</li></ul><blockquote{_G}>{_SENTENCE}</blockquote></main><aside><p>{_SENTENCE * 2}</p></aside><section class='comments'><p>I agree with every word of this long and careful report, thanks.</p></section></body>",
    f"<body><div id='cookie-notice'><p>We use cookies to make this site better for you and for our partners.</p></div><article><header><h1{_G}>Rain</h1></header><p{_G}>By a writer</p><p{_G}>{_SENTENCE * 3}</p>"
    f"<form><label>Your mail</label><p>Get our letter each week in your box.</p></form><div class='advert'>Great cars, great prices, call us now for a drive in your street.</div><p{_G}>End.</p>"
    f"<div id='comments'><p>{_SENTENCE}</p><p>no</p></div></article><div class='sidebar'><ul>{_LINKS}</ul><p>Most read this week</p></div></body>",
    f"<body><ul>{_LINKS}</ul><article><h1{_G}>{_SENTENCE}</h1><p{_G}><b>{_SENTENCE * 2}<br></p><p{_G}>{_SENTENCE}</p></article><div><p>Read more stories from the same town in our other paper.</p><ul>{_LINKS}</ul></div></body>",
    f"<div class='menu'>{_LINKS}</div><article><p{_G}>In.</p></article><footer>Contact us.</footer>",
    f"<article><h1{_G}>{_SENTENCE}</h1><p{_G}>{_SENTENCE}</p></article><div>Copyright of the publisher and its writers.</div>",
    f"<p>Skip to the text</p><article><p{_G}>{_SENTENCE}</p><p{_G}>Ends here.</p></article><ul>{_LINKS}</ul>",
    f"<ul>{_LINKS}</ul><main><p{_G}>Begins here.</p><p{_G}>{_SENTENCE}</p><p{_G}><a href='/s'>source of the story</a></p></main><ul>{_LINKS}</ul><p>Last changed on Monday.</p>",
    f"<main><p{_G}>{_SENTENCE}</p><p{_G}><a href='/q'>A whole paragraph inside a link</a></p><p{_G}>Done.</p></main><p>{_SENTENCE}</p>",
    # no element tells
    f"<body><div>{_BARE}</div><p{_G}>{_SENTENCE * 2}</p><p{_G}>{_SENTENCE} <a href='/m'>More</a> of it was said later that day.</p><p{_G}>{_SENTENCE * 3}</p><div><a href='/t'>terms of use</a> <a href='/p'>privacy</a></div></body>",
    f"<body><p{_G}>Short note.</p></body>",
    f"<body><h1{_G}>A list of facts</h1><p{_G}>{_SENTENCE}</p><p{_G}>Two.</p></body>",
    f"<table><tr><td><a href='/a'>one</a></td><td><a href='/b'>two</a></td><td><a href='/c'>three</a></td></tr><tr><td{_G}>{_SENTENCE * 3}</td></tr></table><p><a href='/top'>back to the top of the page</a></p>",
    f"<div>{_BARE}</div><div>Sign in to your account</div><div>{_BARE}</div><h1{_G}>Bridge talks go on</h1><p{_G}>{_SENTENCE * 2}</p><p{_G}>Yes.</p><p{_G}>{_SENTENCE * 3}</p><div>{_TEASER}</div><div>All rights reserved</div><div>{_BARE}</div>",
    f"<div>{_BARE}</div><div>Today in the town</div><div>{_TEASER}</div><div>Most read</div><div>{_TEASER} {_TEASER}</div><p{_G}>{_SENTENCE * 3}</p><p{_G}>He said no.</p><p{_G}>{_SENTENCE}</p><p{_G}>{_SENTENCE * 2}</p><div>More on this</div><div>{_TEASER}</div>",
    f"<p{_G}>{_SENTENCE * 2}</p><p{_G}>Not now.</p><p{_G}>{_SENTENCE * 2} <a href='/w'>See the plan of the work</a> for what comes next.</p><p{_G}>{_SENTENCE}</p><div>Share this</div><div>{_BARE}</div>",
    # a main element that holds little of the text
    f"<div id='main'><p{_G}>In short</p></div><p{_G}>{_SENTENCE * 3}</p><p{_G}>{_SENTENCE * 2}</p><p{_G}>So be it.</p><p{_G}>{_SENTENCE * 2}</p><div>{_BARE}</div><div>All rights reserved</div>",
    f"<div>{_BARE}</div><div class='content'><p{_G}>From our writer</p></div><div{_G}>{_SENTENCE * 4}</div><div{_G}>{_SENTENCE}</div><div>{_TEASER}</div>",
)


def labelled_table(pages: tuple[str, ...] = LABELLED_PAGES) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of every block of the labelled pages."""
    parts = [blocks_of(p) for p in pages]
    return np.vstack([features_of(b) for b in parts]), np.array([x.gold for b in parts for x in b], float)


def train(pages: tuple[str, ...] = LABELLED_PAGES) -> list[tuple]:
    return grow(*labelled_table(pages))


def main_text(page: str | None, tree: list[tuple]) -> str:
    blocks = blocks_of(page) if page else []
    if not blocks:
        return ""
    keep = predict(tree, features_of(blocks)) >= 0.5
    return "\n".join(b.text for b, k in zip(blocks, keep, strict=True) if k)


def extract(df: DataFrame, html: str = "html", keep: tuple[str, ...] = ("page_id", "url"), pages: tuple[str, ...] = LABELLED_PAGES) -> DataFrame:
    """Main text of every row: the `keep` columns, text and n_chars (code points)."""
    tree = train(pages)

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(p, tree) for p in piece.column("html").to_pylist()]
        kept = [piece.column(f"k{i}") for i in range(len(keep))]
        return pa.RecordBatch.from_arrays([*kept, pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*(f"k{i}" for i in range(len(keep))), "text", "n_chars"])

    given = df.select(*(F.col(c).alias(f"k{i}") for i, c in enumerate(keep)), F.col(html).cast("string").alias("html"))
    kinds = ", ".join(f"k{i} {df.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = map_slices(given, "html", work, f"{kinds + ', ' if keep else ''}text string, n_chars long")
    return out.select(*(F.col(f"k{i}").alias(c) for i, c in enumerate(keep)), "text", "n_chars")
