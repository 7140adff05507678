"""Main text of web pages: boosted trees over DOM-node features, decoded along the tree.

A tolerant scanner makes a tree of the block-level elements. Each gets features of its subtree (text, links, tags, punctuation), its attribute
tokens and its ancestors', its depth and its siblings. The trees give each element the log-odds that it holds main text; decoding
picks the likeliest labelling in which nothing is kept below what is dropped. The model is trained on generated pages of many layouts
and, weakly labelled by their semantic elements, on a bounded sample of the table's own pages.
"""

from __future__ import annotations

import html
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .boosting import BoostedTrees

# Fixed values of the HTML language: elements without content, raw-text elements, block-level elements, and what an open paragraph ends before.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template noscript textarea iframe title".split())
#: Without an end tag these reach to the end of the page, as HTML has it; what follows the start tag of another unclosed raw element is read as usual.
_CODE = frozenset(("script", "style"))
#: Block-level elements that may stand in a select; any other ends one that isn't closed.
_IN_SELECT = frozenset(("option", "hr", "legend"))
BLOCK = frozenset(
    "html body address article aside blockquote caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header "
    "hgroup hr legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
ENDS_P = BLOCK - {"html", "body", "head", "caption", "legend", "option", "tbody", "td", "tfoot", "th", "thead", "tr", "figcaption", "dd", "dt", "li", "summary"}
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "tbody": {"tbody", "thead", "tr", "td", "th"}}
_SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": set(), "tbody": {"table"}}

_TAG = re.compile(r"<(?:(!--)|([!?])|(/?)([a-zA-Z][^\s/>]*))")
_PLAIN = re.compile(r"[^>\"']*")
#: Deeper elements stand beside their parent instead of below it, as browsers have it, so that no token walks far.
MOST_OPEN = 512
_NAMES = re.compile(r"(?:class|id|role|itemprop|aria-label|data-component)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
_SPLIT = re.compile(r"[^a-z]+|(?<=[a-z])(?=[A-Z])")
#: Attribute words by what they hint at.
HINTS = {
    "main": "article content main post entry story text body prose blog news page",
    "nav": "nav navigation menu navbar breadcrumb breadcrumbs pagination pager toc tabs skip",
    "ad": "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner adsense dfp outbrain taboola",
    "foot": "footer foot copyright legal colophon bottom",
    "head": "header masthead top topbar logo branding hero",
    "side": "sidebar side aside widget rail related recommend recommended more trending popular tags teaser",
    "talk": "comment comments discussion disqus reply replies respond reviews thread feedback",
    "notice": "notice cookie cookies consent gdpr alert modal popup overlay newsletter subscribe signup paywall warning disclaimer message toast",
    "form": "form search login register input contact",
    "share": "share sharing social follow like tweet author byline meta date",
}
_HINT_OF = {w: i for i, words in enumerate(HINTS.values()) for w in words.split()}
_TAGS = ("body", "div", "section", "article", "main", "p", "h1", "h2", "h3", "ul", "ol", "li", "table", "td", "blockquote", "pre", "nav", "aside", "header", "footer", "form", "figure", "figcaption", "dl")
_TAG_AT = {t: i for i, t in enumerate(_TAGS)}
_UNDER = ("article", "main", "nav", "aside", "header", "footer", "form")
_UNDER_BIT = {t: 1 << i for i, t in enumerate(_UNDER)}
N_HINTS = len(HINTS)


class Node:
    __slots__ = ("tag", "hints", "parent", "children", "parts", "depth", "inputs", "gold", "counts")

    def __init__(self, tag: str, attrs: str, parent: "Node | None"):
        self.tag, self.parent, self.depth = tag, parent, parent.depth + 1 if parent else 0
        self.children: list[Node] = []
        self.parts: list = []  # Node, or (text, in a link)
        self.inputs, self.gold, self.counts = 0, None, None
        self.hints = 0
        if attrs:
            for m in _NAMES.finditer(attrs):
                for w in _SPLIT.split(m[1].strip("\"'")):
                    at = _HINT_OF.get(w.lower())
                    if at is not None:
                        self.hints |= 1 << at
            if "data-gold" in attrs:
                self.gold = "data-gold=1" in attrs
        if parent:
            parent.children.append(self)
            parent.parts.append(self)


def _attributes_end(page: str, at: int, unmatched: set[str]) -> int:
    """Where the > of a tag stands (or the page ends). A quote after = hides what is between it and the next such quote; one that nothing closes hides nothing."""
    while True:
        at = _PLAIN.match(page, at).end()
        if at >= len(page) or page[at] == ">":
            return at
        quote, before = page[at], at - 1
        while page[before].isspace():
            before -= 1
        close = page.find(quote, at + 1) if page[before] == "=" and quote not in unmatched else -1
        if close < 0 and page[before] == "=":
            unmatched.add(quote)
        at = close + 1 if close >= 0 else at + 1


def parse(page: str | None) -> Node:
    """The tree of block-level elements of a page; inline elements are dissolved into their block. Anything is accepted, in time linear in its length."""
    page = page or ""
    root = Node("html", "", None)
    open_: list[tuple[str, Node | None, Node]] = [("html", root, root)]  # tag, its node if it is a block, the block that text goes to
    at = 0
    select = False  # one may be open
    endless: set[str] = set()  # raw elements without an end tag from here on
    unmatched: set[str] = set()  # quotes that don't occur from here on

    now_open = Counter()  # how often a tag is among the open elements

    def close(i: int) -> None:
        for t, _, _ in open_[i:]:
            now_open[t] -= 1
        del open_[i:]

    while at < len(page):
        m = _TAG.search(page, at)
        end = m.start() if m else len(page)
        now = open_[-1][2]
        if end > at:
            now.parts.append((page[at:end], now_open["a"] > 0))
        if not m:
            break
        if m[1]:
            end = page.find("-->", m.end())
            at = end + 3 if end >= 0 else len(page)
            continue
        if m[2]:
            end = page.find(">", m.end())
            at = end + 1 if end >= 0 else len(page)
            continue
        end = _attributes_end(page, m.end(), unmatched)
        attrs, at, tag = page[m.end() : end], min(len(page), end + 1), m[4].lower()
        closed_itself = attrs.rstrip().endswith("/")
        if m[3]:
            if now_open[tag]:
                close(next(i for i in range(len(open_) - 1, 0, -1) if open_[i][0] == tag))
        elif tag in RAW:
            if tag == "textarea":
                now.inputs += 1
            if closed_itself and (now_open["svg"] or now_open["math"]):
                continue
            last = None if tag in endless else re.compile(rf"</{tag}(?=[\s/>])[^>]*(?:>|\Z)", re.I).search(page, at)
            if last:
                at = last.end()
            else:
                endless.add(tag)
                at = len(page) if tag in _CODE else at
        elif tag in VOID:
            if tag == "br":
                now.parts.append((" ", False))
            elif tag == "hr":
                Node("hr", "", now)
            elif tag == "input":
                now.inputs += 1
        elif tag != "html":
            if select and tag in BLOCK and tag not in _IN_SELECT:
                close(next((i for i, x in enumerate(open_) if x[0] == "select"), len(open_)))
                select = False
            first = len(open_)
            if tag in ENDS_P and now_open["p"]:
                for i in range(len(open_) - 1, 0, -1):
                    if open_[i][0] == "p":
                        first = i
                        break
                    if open_[i][1] is not None:
                        break
            elif tag in ENDS and any(now_open[t] for t in ENDS[tag]):
                for i in range(len(open_) - 1, 0, -1):
                    if open_[i][0] in _SCOPE[tag]:
                        break
                    if open_[i][0] in ENDS[tag]:
                        first = i
            close(first)
            if not closed_itself or tag in BLOCK:
                if len(open_) >= MOST_OPEN:
                    close(len(open_) - 1)
                now = open_[-1][2]
                node = Node(tag, attrs, now) if tag in BLOCK else None
                open_.append((tag, node, node or now))
                now_open[tag] += 1
                select = select or tag == "select"
                if tag in ("button", "select"):
                    now.inputs += 1
    return root


def nodes_of(root: Node) -> list[Node]:
    out, todo = [], [root]
    while todo:
        n = todo.pop()
        out.append(n)
        todo.extend(reversed(n.children))
    return out


def features(nodes: list[Node]) -> np.ndarray:
    """One row a node: subtree, attribute, ancestor, depth and sibling features. ``nodes`` may be those of several pages, one after the other as nodes_of() lists them."""
    n = len(nodes)
    at: dict[int, int] = {}
    text, link, elements, paras, marks, inputs, items, blocks = ([0] * n for _ in range(8))
    parent, above, under, inside, tag_no, same, top = [-1] * n, [0] * n, [0] * n, [0] * n, [-1] * n, [0.0] * n, [0] * n
    hints = [x.hints for x in nodes]
    root = 0
    for i, x in enumerate(nodes):
        at[id(x)] = i
        if x.parent is None:
            root = i
        else:
            p = parent[i] = at[id(x.parent)]
            above[i] = above[p] | hints[p]
            under[i] = under[p] | _UNDER_BIT.get(x.parent.tag, 0)
            same[i] = _share(x)
        top[i] = root
        tag_no[i] = _TAG_AT.get(x.tag, -1)
        for part in x.parts:
            if part.__class__ is tuple:
                t = part[0]
                text[i] += len(t)
                if part[1]:
                    link[i] += len(t)
                marks[i] += t.count(",") + t.count(".")
        elements[i], paras[i], inputs[i], items[i], blocks[i] = 1, x.tag == "p", x.inputs, x.tag == "li", text[i] > 0
    own = np.array(text, np.float64)
    for i in range(n - 1, -1, -1):
        p = parent[i]
        if p >= 0:
            text[p] += text[i]
            link[p] += link[i]
            elements[p] += elements[i]
            paras[p] += paras[i]
            marks[p] += marks[i]
            inputs[p] += inputs[i]
            items[p] += items[i]
            blocks[p] += blocks[i]
            inside[p] |= inside[i] | _UNDER_BIT.get(nodes[i].tag, 0)
    text, link, elements, paras, marks, inputs, items, blocks = (np.array(c, np.float64) for c in (text, link, elements, paras, marks, inputs, items, blocks))
    up, top = np.array(parent), np.array(top)
    has = up >= 0
    start = np.cumsum(own) - own
    start -= start[top]
    size, total = np.maximum(1.0, text), np.maximum(1.0, text[top])
    above_size = np.where(has, size[up], 1.0)
    cols = [
        np.log1p(text), np.log1p(own), link / size, text / elements, np.log1p(elements), np.log1p(paras), marks / size, np.log1p(inputs), np.array([x.depth for x in nodes]),
        np.array([len(x.parent.children) if x.parent else 0 for x in nodes]), np.array(same), np.where(has, text / above_size, 0), np.where(has, link[up] / above_size, 0),
        text / total, start / total, items / elements, text / np.maximum(1.0, blocks), paras / elements,
    ]
    bits = lambda masks, k: (np.array(masks)[:, None] >> np.arange(k) & 1).astype(np.float64)
    one_hot = (np.array(tag_no)[:, None] == np.arange(len(_TAGS))).astype(np.float64)
    return np.hstack([np.stack(cols, axis=1), one_hot, bits(hints, N_HINTS), bits(above, N_HINTS), bits(under, len(_UNDER)), bits(inside, len(_UNDER))])


def _share(x: Node) -> float:
    """The share of siblings with the node's tag, counted once for a long list of siblings."""
    p = x.parent
    if p.counts is None:
        p.counts = Counter(s.tag for s in p.children)
    return p.counts[x.tag] / len(p.children)


def decode(nodes: list[Node], odds: np.ndarray) -> list[bool]:
    """The likeliest labels of one page in which no element is kept below a dropped one; head is dropped, and the root kept, always."""
    at = {id(x): i for i, x in enumerate(nodes)}
    best, drop = (-np.logaddexp(0, -odds)).tolist(), (-np.logaddexp(0, odds)).tolist()  # of whole subtrees
    parent = [at[id(x.parent)] if x.parent else -1 for x in nodes]
    kept = [True] * len(nodes)
    for i in range(len(nodes) - 1, 0, -1):
        kept[i] = best[i] > drop[i] and nodes[i].tag != "head"
        p = parent[i]
        drop[p] += drop[i]
        best[p] += best[i] if kept[i] else drop[i]
    for i in range(1, len(nodes)):
        kept[i] = kept[i] and kept[parent[i]]
    return kept


def render(nodes: list[Node], kept: list[bool]) -> str:
    """The text of kept elements: references decoded, white space of a block made one space, blocks in page order joined by two line feeds."""
    keep = {id(x) for x, k in zip(nodes, kept) if k}
    blocks, run = [], []

    def flush():
        text = " ".join("".join(run).split())
        if text:
            blocks.append(text)
        run.clear()

    todo: list = [nodes[0]]
    while todo:
        x = todo.pop()
        if x is None:
            flush()
        elif x.__class__ is tuple:
            run.append(html.unescape(x[0]))
        else:
            flush()
            if id(x) in keep:
                todo.append(None)
                todo.extend(reversed(x.parts))
    flush()
    return "\n\n".join(blocks)


# Generated training pages.


def _sentence(r: random.Random, least: int, most: int) -> str:
    words = ["".join(r.choice("bcdfghlmnprstvw") + r.choice("aeiouéüó") for _ in range(r.randint(1, 4))) for _ in range(r.randint(least, most))]
    return (" ".join(words)).capitalize().replace(" ", ", ", r.random() < 0.4) + r.choice(".. !?")[:1]


def _el(r: random.Random, tags: str, names: str, body: str, gold: int | None = None) -> str:
    tag, name = r.choice(tags.split()), r.choice(names.split() + [""]) if names else ""
    attr = f' {r.choice(["class", "class", "id"])}="{name.replace("+", " ")}"' if name and name != "-" else ""
    mark = "" if gold is None else f" data-gold={gold}"
    return f"<{tag}{attr}{mark}>{body}</{tag}>"


def _prose(r: random.Random, gold: int) -> str:
    g = f" data-gold={gold}"
    kind = r.random()
    if kind < 0.66:
        open_ = r.random() < 0.15
        return f"<p{g}>" + ("<b>" if open_ else "") + " ".join(_sentence(r, 1, 18) for _ in range(r.choice([1, 1, 2, 4, 9]))) + (r.choice(["</p>", "<br>"]) if open_ else "</p>")
    if kind < 0.76:
        return f"<h2{g}>{_sentence(r, 1, 7)}</h2>"
    if kind < 0.84:
        return f"<ul{g}>" + "".join(f"<li{g}>{_sentence(r, 2, 14)}</li>" for _ in range(r.randint(2, 6))) + "</ul>"
    if kind < 0.9:
        return f"<blockquote{g}><p{g}>{_sentence(r, 5, 30)}</p></blockquote>"
    if kind < 0.94:
        return f"<pre{g}>{_sentence(r, 3, 20)}</pre>"
    if kind < 0.97:
        return f"<table{g}>" + "".join(f"<tr{g}><td{g}>{_sentence(r, 1, 3)}</td><td{g}>{_sentence(r, 1, 5)}</td></tr>" for _ in range(3)) + "</table>"
    return f'<figure{g}><img src="x.png"><figcaption{g}>{_sentence(r, 2, 9)}</figcaption></figure>'


def _links(r: random.Random, n: int) -> str:
    item = lambda: f'<a href="/{r.randint(1, 99)}">{_sentence(r, 1, r.choice([1, 1, 3, 8]))}</a>'
    return "<ul>" + "".join(f"<li>{item()}</li>" for _ in range(n)) + "</ul>" if r.random() < 0.8 else " ".join(item() for _ in range(n))


def _extra(r: random.Random) -> str:
    return r.choice([
        lambda: _el(r, "div aside section", "ad ads advert ad-slot sponsored promo banner advertisement", r.choice(["", "<p>"]) + _sentence(r, 2, 16), 0),
        lambda: _el(r, "aside div section", "sidebar related widget rail recommended more-stories trending", f"<h3>{_sentence(r, 1, 3)}</h3>" + _links(r, r.randint(2, 7)), 0),
        lambda: _el(r, "aside", "", f"<p>{_sentence(r, 3, 20)}</p>" * r.randint(1, 2), 0),
        lambda: _el(r, "div section p", "notice cookie-notice consent alert cookie-banner gdpr newsletter disclaimer message", f"{_sentence(r, 4, 25)} " + r.choice(["<button>Ok</button>", "", "<a href=#>Info</a>"]), 0),
        lambda: _el(r, "form", "search login newsletter signup -", f"<label>{_sentence(r, 1, 4)}</label><input name=q><p>{_sentence(r, 2, 9)}</p><button>{_sentence(r, 1, 2)}</button>", 0),
        lambda: _el(r, "div ul", "share social share-buttons follow", _links(r, 4), 0),
        lambda: _el(r, "nav div ul ol", "breadcrumb breadcrumbs pagination menu", _links(r, r.randint(2, 8)), 0),
    ])()


def _comments(r: random.Random) -> str:
    one = lambda: _el(r, "div li article section", "comment reply comment-body -", f"<b>{_sentence(r, 1, 2)}</b><p>{_sentence(r, 2, 20)} {_sentence(r, 3, 25)}</p>")
    tag = r.choice(["div", "section", "ol", "aside"])
    name = r.choice(["comments", "comment-list", "discussion", "replies", "reader-comments", "respond"])
    return f'<{tag} {r.choice(["class", "id"])}="{name}" data-gold=0><h3>{_sentence(r, 1, 3)}</h3>' + "".join(one() for _ in range(r.randint(1, 8))) + f"</{tag}>"


def generated_page(r: random.Random) -> str:
    """A page of a random layout, its elements marked with what they hold: data-gold=1 main text, 0 none, for the whole subtree unless marked again."""
    body = [_prose(r, 1) for _ in range(r.choice([1, 2, 4, 8, 14]))]
    head = f"<h1 data-gold=1>{_sentence(r, 1, 9)}</h1>" if r.random() < 0.8 else ""
    for _ in range(r.choice([0, 0, 0, 1, 2])):
        body.insert(r.randint(0, len(body)), _extra(r))
    if head and r.random() < 0.15:
        head = f"<header data-gold=1>{head}</header>"
    if r.random() < 0.15:
        body.append(_comments(r))
    kind = r.random()
    text = head + "".join(body)
    if kind < 0.5:
        text = _el(r, "article", "post entry article story -", text, 1)
    elif kind < 0.8:
        text = _el(r, "div section main td", "content main article-body post-content entry-content story-text body text prose", text, 1)
    if r.random() < 0.25:
        text = _el(r, "main div", "main content page -", text, 1)
    before, after = [], []
    if r.random() < 0.6:
        before.append(_el(r, "header div", "header masthead site-header top branding", f"<p>{_sentence(r, 1, 5)}</p>" + (_links(r, 4) if r.random() < 0.5 else ""), 0))
    if r.random() < 0.8:
        before.append(_el(r, "nav nav div ul", "nav menu navbar main-nav navigation", _links(r, r.randint(3, 9)), 0))
    for _ in range(r.choice([0, 1, 1, 2])):
        (before if r.random() < 0.5 else after).append(_extra(r))
    if r.random() < 0.3:
        after.append(_comments(r))
    if r.random() < 0.85:
        after.append(_el(r, "footer footer div", "footer site-footer copyright colophon", f"&copy; {_sentence(r, 1, 3)} &middot; {_sentence(r, 3, 14)}" + (_links(r, 3) if r.random() < 0.4 else ""), 0))
    r.shuffle(before)
    inner = "".join(before) + text + "".join(after)
    for _ in range(r.choice([0, 0, 1, 2])):
        inner = _el(r, "div", "wrapper container page row layout site -", inner, 1)
    return f"<!DOCTYPE html><html><head><title>{_sentence(r, 1, 8)}</title><style>p{{margin:0}}</style><script>x('</p>')</script></head><body data-gold=1>{inner}</body></html>"


def _gold(nodes: list[Node]) -> np.ndarray:
    out = np.zeros(len(nodes))
    at = {id(x): i for i, x in enumerate(nodes)}
    for i, x in enumerate(nodes):
        out[i] = 1.0 if not i else 0.0 if x.tag == "head" else float(x.gold) if x.gold is not None else out[at[id(x.parent)]]
    return out


_WEAK_NO = frozenset(("nav", "aside", "footer", "form", "head"))


def weak_labels(nodes: list[Node]) -> np.ndarray | None:
    """Labels of a page that has one article or main element: inside it, but for navigation, asides, forms and what its attributes call otherwise. None if it has none."""
    tops = [x for x in nodes if x.tag == "article"]
    tops = tops if len(tops) == 1 else [x for x in nodes if x.tag == "main"]
    if len(tops) != 1:
        return None
    at = {id(x): i for i, x in enumerate(nodes)}
    inside, out = np.zeros(len(nodes), bool), np.zeros(len(nodes))
    bad = sum(1 << i for i, k in enumerate(HINTS) if k in ("nav", "ad", "foot", "side", "talk", "notice", "form"))
    for i, x in enumerate(nodes):
        p = at[id(x.parent)] if x.parent else -1
        inside[i] = x is tops[0] or (p >= 0 and inside[p] and x.tag not in _WEAK_NO and not x.hints & bad)
        out[i] = inside[i]
    x = tops[0].parent
    while x is not None:
        out[at[id(x)]] = 1
        x = x.parent
    return out


def train(pages: DataFrame | None = None, generated: int = 1000, sample: int = 150, seed: int = 9, **how) -> BoostedTrees:
    """``generated``: number of generated pages; ``sample``: bound of the table's own pages (drawn by a hash of page_id, of at most 100,000 characters each) that
    are added with weak labels."""
    r = random.Random(seed)
    xs, ys = [], []
    for _ in range(generated):
        nodes = nodes_of(parse(generated_page(r)))
        xs.append(features(nodes))
        ys.append(_gold(nodes))
    if pages is not None:
        key = F.xxhash64(F.lit(seed), F.col("page_id").cast("string"))
        drawn = pages.select(key.alias("o"), F.col("html").cast("string").alias("html")).where(F.length("html") <= 100_000)
        n = pages.count()
        rate = min(1.0, 2.0 * sample / max(1, n))
        few = drawn.where(F.col("o").bitwiseAND(F.lit((1 << 53) - 1)) / float(1 << 53) < rate).orderBy("o", "html").limit(sample).collect()
        for row in sorted(few, key=lambda row: (row["o"], row["html"])):
            nodes = nodes_of(parse(row["html"]))
            if (labels := weak_labels(nodes)) is not None:
                xs.append(features(nodes))
                ys.append(labels)
    return BoostedTrees(**how).fit(np.vstack(xs), np.concatenate(ys))


def extract_text(page: str | None, model: BoostedTrees) -> str:
    nodes = nodes_of(parse(page))
    return render(nodes, decode(nodes, model.predict(features(nodes))))


def extract(pages: DataFrame, model: BoostedTrees) -> DataFrame:
    """pages (page_id, url, html) -> one row per page: (page_id, url, text, n_chars), n_chars in code points. Null, empty and textless pages give ''.
    What browsers that run scripts don't show counts as markup: noscript, template, iframe and title; the text of svg and math elements is text of their
    block. Repeated rows and null ids pass through; no rows give no rows; other columns are ignored."""
    ship(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    shared = pages.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 100):
                part = batch.slice(at, 100)
                trees = [nodes_of(parse(h.as_py())) for h in part.column(2)]
                odds = m.predict(features([x for t in trees for x in t]))
                ends = np.cumsum([len(t) for t in trees])
                texts = [render(t, decode(t, odds[e - len(t) : e])) for t, e in zip(trees, ends)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
