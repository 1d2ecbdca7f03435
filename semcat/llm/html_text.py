"""Main text of web pages: gradient-boosted trees over DOM nodes, decoded from the top down.

Each element that can hold blocks gets features of its subtree, its attributes and its place. Boosted trees give the
probability that it belongs to the main text. Along a path from the root the states can only go from outside to main to
excluded; the best such labelling of the tree is found by dynamic programming, so no descendant contradicts an ancestor.
"""

from __future__ import annotations

import html
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

#: A quote opens a value only after an equals sign, and only if it is closed somewhere; elsewhere it is an ordinary sign.
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*\"[^\"]*\"|=\s*'[^']*'|[^>])*+)(?:>|\Z)", re.S)
_ATTR = re.compile(r"\b(?:class|id|role|aria-label|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"[a-z]+")
#: Fixed values of HTML: elements without content, with raw text, inside a line of text.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
RAW = frozenset("script style template svg iframe textarea select title".split())
#: Raw elements that, left open, take the rest of the page; of the others only the start tag is dropped.
OPEN_RAW = frozenset("script style textarea title".split())
INLINE = frozenset("a abbr b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr img math mi mn mo mrow msup msub mfrac msqrt mtext semantics".split())
#: A start tag that ends an open paragraph, and open elements that the same start tag ends.
ENDS_P = frozenset("address article aside blockquote center details dialog div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
SELF = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "p": ("p",)}
#: Groups of tags and of attribute words that become features.
TAGS = [("article", "main"), ("nav", "menu"), ("header",), ("footer",), ("aside",), ("form", "button", "fieldset"), ("p", "pre", "blockquote"), ("h1", "h2", "h3", "h4", "h5", "h6"), ("ul", "ol", "dl", "li", "dt", "dd"), ("div", "section"), ("table", "tr", "td", "th", "tbody", "thead"), ("body", "html")]
WORDS = ["article content main post entry story body text page prose", "nav navigation menu breadcrumb breadcrumbs toc pagination pager links tabs", "header masthead topbar banner branding hero", "footer foot bottom copyright legal colophon", "sidebar side aside widget rail secondary complementary", "ad ads advert adverts advertisement sponsor sponsored promo promotion promoted", "cookie cookies consent notice gdpr alert warning popup modal overlay toast disclaimer", "comment comments reply replies respond discussion disqus reviews feedback", "form search newsletter subscribe signup login register", "share social related recommended more tags author byline meta"]
_TAG = {t: i for i, g in enumerate(TAGS) for t in g}
_GROUP = {w: i for i, g in enumerate(WORDS) for w in g.split()}
FEATURES = 2 * len(TAGS) + 2 * len(WORDS) + 12


class Node:
    __slots__ = ("attrs", "children", "depth", "index", "links", "order", "parent", "size", "tag", "text")

    def __init__(self, tag: str, parent: Node | None, attrs: int = 0):
        self.tag, self.parent, self.attrs = tag, parent, attrs
        self.children: list[Node] = []
        self.text: list[tuple[int, str | None]] = []  # (place among the page's pieces, text or None for a break)
        self.links = self.size = self.index = 0
        self.depth = parent.depth + 1 if parent else 0
        self.order = 0
        if parent:
            self.order = len(parent.children)
            parent.children.append(self)


def _attr_groups(raw: str) -> int:
    out = 0
    for m in _ATTR.finditer(raw):
        for w in _WORD.findall((m[1] or m[2] or m[3] or "").lower()):
            if w in _GROUP:
                out |= 1 << _GROUP[w]
    return out


def parse(page: str) -> list[Node]:
    """The page's block nodes in document order, the root first; line-level elements are dissolved into them."""
    root = Node("html", None)
    nodes, stack, at, place, in_link = [root], [root], 0, 0, 0
    opened: dict[str, int] = {}  # how many elements of a tag are open, so that a stray end tag costs nothing
    unclosed: set[str] = set()
    page = page.replace("\0", "")

    def leave(k: int) -> None:
        for x in stack[k:]:
            opened[x.tag] -= 1
        del stack[k:]

    while at < len(page):
        m = _TOKEN.search(page, at)
        text = page[at : m.start() if m else len(page)]
        if text:
            top = stack[-1]
            if "&" in text:
                text = html.unescape(text)
            top.text.append((place, text))
            size = len(text.strip())
            top.size += size
            if in_link:
                top.links += size
            place += 1
        if not m:
            break
        at = m.end()
        tag = (m[2] or "").lower()
        if not tag:
            continue
        if m[1]:
            if tag == "a":
                in_link = max(0, in_link - 1)
            elif opened.get(tag):
                k = next(k for k in range(len(stack) - 1, 0, -1) if stack[k].tag == tag)
                stack[k - 1].text.append((place, None))
                place += 1
                leave(k)
                in_link = 0
            continue
        if tag in RAW:
            if not m[0].endswith("/>"):
                end = None if tag in unclosed else re.compile(rf"</{tag}\s*>", re.I).search(page, at)
                if end:
                    at = end.end()
                elif tag in OPEN_RAW:
                    at = len(page)
                else:
                    unclosed.add(tag)
            continue
        if tag == "br":
            stack[-1].text.append((place, " "))
            place += 1
        elif tag == "a":
            in_link += not m[0].endswith("/>")
        elif tag in VOID:
            if tag == "hr":
                stack[-1].text.append((place, None))
                place += 1
        elif tag not in INLINE and tag not in ("html", "head"):
            close = SELF.get(tag, ()) + (("p",) if tag in ENDS_P else ())
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in close:
                    leave(k)
                    in_link = 0
                    break
                if stack[k].tag not in ("p", "li", "dt", "dd", "td", "th") or stack[k].tag == "li" and tag not in ("li",):
                    break
            top = stack[-1]
            top.text.append((place, None))
            place += 1
            node = Node(tag, top, _attr_groups(m[3]) if m[3] else 0)
            nodes.append(node)
            if not m[0].endswith("/>"):
                stack.append(node)
                opened[tag] = opened.get(tag, 0) + 1
    return nodes


def parents(nodes: list[Node]) -> list[int]:
    for i, x in enumerate(nodes):
        x.index = i
    return [x.parent.index if x.parent else -1 for x in nodes]


def features(nodes: list[Node]) -> np.ndarray:
    """One row per node: own and ancestors' tags and attribute words, subtree density, depth, sibling statistics."""
    n, parent = len(nodes), parents(nodes)
    own = [x.size for x in nodes]
    chars, links, size, paras = own[:], [x.links for x in nodes], [1] * n, [x.tag == "p" for x in nodes]
    for i in range(n - 1, 0, -1):
        p = parent[i]
        chars[p] += chars[i]
        links[p] += links[i]
        size[p] += size[i]
        paras[p] += paras[i]
    t, w = len(TAGS), len(WORDS)
    tags, words = [1 << _TAG[x.tag] if x.tag in _TAG else 0 for x in nodes], [x.attrs for x in nodes]
    for i in range(1, n):  # ancestors' bits stand above the own ones
        p = parent[i]
        tags[i] |= (tags[p] & ((1 << t) - 1) << t) | (tags[p] & (1 << t) - 1) << t
        words[i] |= (words[p] & ((1 << w) - 1) << w) | (words[p] & (1 << w) - 1) << w
    bits = np.column_stack([np.array(tags)[:, None] >> np.arange(2 * t) & 1, np.array(words)[:, None] >> np.arange(2 * w) & 1])
    up = np.maximum(np.array(parent), 0)
    c, k, z, q, o = (np.array(v, np.float64) for v in (chars, links, size, paras, own))
    order, depth = np.array([x.order for x in nodes], float), np.array([x.depth for x in nodes], float)
    same = np.array([1, *[len(x.parent.children) for x in nodes[1:]]], float)
    share = k / np.maximum(1, c)
    above = share[up]
    above[0] = 0
    return np.column_stack([bits, np.log1p(c), c / z / 100, share, c / max(1, c[0]), depth, order, same, np.log1p(q), np.log1p(o), np.log1p(z), order / same, above]).astype(np.float32)


def decode(nodes: list[Node], p: np.ndarray) -> np.ndarray:
    """Best labelling with states outside, main, excluded that never go back along a path; True where main."""
    n, parent = len(nodes), parents(nodes)
    yes, no = np.log(np.clip(p, 1e-6, 1)).tolist(), np.log(np.clip(1 - p, 1e-6, 1)).tolist()
    out, main, cut = no[:], yes, no[:]  # of a node with its best subtree
    for i in range(n - 1, 0, -1):
        q = parent[i]
        out[q] += max(out[i], main[i])
        main[q] += max(main[i], cut[i])
        cut[q] += cut[i]
    state = [0] * n
    state[0] = int(main[0] > out[0])
    for i in range(1, n):
        up = state[parent[i]]
        state[i] = 2 if up == 2 or up == 1 and cut[i] >= main[i] else int(up == 1 or main[i] > out[i])
    return np.array(state) == 1


def blocks_of(nodes: list[Node], main: np.ndarray) -> str:
    """The text of the main nodes: white space inside a block is one space, blocks in page order are joined by one."""
    pieces = sorted(((place, i, text) for i, x in enumerate(nodes) if main[i] for place, text in x.text), key=lambda r: r[0])
    out, line, owner = [], [], -1
    for _, i, text in pieces:
        if text is None or i != owner:
            out.append(" ".join("".join(line).split()))
            line, owner = [], i
        if text is not None:
            line.append(text)
    out.append(" ".join("".join(line).split()))
    return " ".join(x for x in out if x)


class Boosted:
    """Gradient-boosted regression trees on the logistic loss; features are cut at quantiles of the training rows."""

    def __init__(self, rounds: int = 60, depth: int = 5, rate: float = 0.3, cuts: int = 16):
        self.rounds, self.depth, self.rate, self.cuts = rounds, depth, rate, cuts
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        """All cuts of all features are judged together, a level of the tree at a time, by one product of matrices."""
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.cuts + 1)[1:-1], method="lower")) for f in range(x.shape[1])]
        cuts = [(f, e) for f, es in enumerate(edges) for e in es if (x[:, f] > e).any()]
        below = np.column_stack([x[:, f] <= e for f, e in cuts]).astype(np.float32)
        feature_of, edge_of = np.array([f for f, _ in cuts]), np.array([e for _, e in cuts])
        z = np.zeros(len(y))
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-z))
            g, h = p - y, p * (1 - p) + 1e-6
            size = 2 ** (self.depth + 1) - 1
            feature, cut = np.full(2**self.depth - 1, -1), np.zeros(2**self.depth - 1)
            where = np.zeros(len(y), np.int64)
            for level in range(self.depth):
                first, m = 2**level - 1, 2**level
                here = np.flatnonzero(where >= first)  # rows whose node stopped growing stay above
                at = where[here] - first
                gh = np.zeros((len(y), 2 * m), np.float32)
                gh[here, at], gh[here, m + at] = g[here], h[here]
                left = (below.T @ gh).astype(np.float64)
                gl, hl = left[:, :m], left[:, m:]
                gs, hs, n = np.bincount(at, g[here], m), np.bincount(at, h[here], m), np.bincount(at, minlength=m)
                gain = gl**2 / (hl + 1) + (gs - gl) ** 2 / (np.maximum(hs - hl, 0) + 1) - gs**2 / (hs + 1)
                best = gain.argmax(0)
                grows = (n >= 20) & (gain[best, np.arange(m)] > 1e-3)
                feature[first : first + m] = np.where(grows, feature_of[best], -1)
                cut[first : first + m] = edge_of[best]
                go = here[grows[at]]
                node = where[go] - first
                where[go] = 2 * where[go] + 1 + (below[go, best[node]] == 0)
            leaf = -self.rate * np.bincount(where, g, size) / (np.bincount(where, h, size) + 1.0)
            self.trees.append((feature, cut, leaf))
            z += leaf[where]
        return self

    def _one(self, tree, x: np.ndarray) -> np.ndarray:
        feature, cut, leaf = tree
        at = np.zeros(len(x), np.int64)
        for _ in range(self.depth):
            f = feature[np.minimum(at, len(feature) - 1)]
            live = (at < len(feature)) & (f >= 0)
            at = np.where(live, 2 * at + 1 + (x[np.arange(len(x)), np.maximum(f, 0)] > cut[np.minimum(at, len(feature) - 1)]), at)
        return leaf[at]

    def predict(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-sum(self._one(t, x) for t in self.trees)))


#: Opens a made-up page whose root is the main element.
ROOT_IS_MAIN = "<!--main-->"


def sample_page(rng: random.Random) -> str:
    """A made-up page for training; main-text elements carry data-y. Of many layouts: the main text in paragraphs, directly in
    its element, in a cell, deep in wrappers, in the body or in no element at all."""
    text = "".join(rng.choices("etaoinshrdlu    ", k=2000)).split()
    word = lambda: text[rng.randrange(len(text))]
    say = lambda a, b: " ".join(text[(i := rng.randrange(len(text) - b)) : i + rng.randint(a, b)])
    pick = rng.choice
    link = lambda: f'<a href="/{word()}">{say(1, 3)}</a>'
    links = lambda a, b: "<ul>" + "".join(f"<li>{link()}</li>" for _ in range(rng.randint(a, b))) + "</ul>"
    para = lambda: f"<p>{say(1, 90)}" + (f" {link()} {say(2, 9)}" if rng.random() < 0.2 else "") + ("<br>" if rng.random() < 0.1 else "") + ("</p>" if rng.random() < 0.7 else "")
    around = {
        "nav": lambda: pick([f"<nav>{links(3, 9)}</nav>", f'<div class="{pick(["menu", "main-nav", "breadcrumbs"])}">{links(2, 8)}</div>', f'<ul class="nav">{links(3, 7)}</ul>']),
        "header": lambda: pick([f"<header><h1>{say(1, 4)}</h1>{links(2, 5)}</header>", f'<div class="{pick(["header", "masthead", "topbar"])}"><p>{say(2, 8)}</p></div>', f"<header>{say(1, 5)}</header>"]),
        "notice": lambda: f'<{(t := pick(["div", "section", "aside"]))} class="{pick(["cookie-notice", "consent", "notice", "alert", "gdpr-popup"])}"><p>{say(5, 40)}</p><button>{word()}</button></{t}>',
        "ad": lambda: f'<{(t := pick(["div", "aside", "section"]))} class="{pick(["ad", "ads", "advert", "sponsored", "promo"])}">{pick([say(3, 60), f"<p>{say(4, 60)}</p>"])}</{t}>',
        "side": lambda: pick([f"<aside><h3>{say(1, 4)}</h3>{pick([links(2, 6), f'<p>{say(5, 50)}</p>'])}</aside>", f'<div class="{pick(["sidebar", "widget", "right-rail"])}"><p>{say(4, 50)}</p></div>', f'<div id="sidebar">{links(2, 6)}<p>{say(3, 30)}</p></div>']),
        "form": lambda: f'<form class="{pick(["search", "newsletter", "", "login"])}"><p>{say(2, 15)}</p><label>{word()}</label><input name="q"><button>{word()}</button></form>',
        "comments": lambda: f'<{(t := pick(["section", "div"]))} {pick(["id", "class"])}="{pick(["comments", "comment-list", "discussion", "replies"])}"><h2>{say(1, 3)}</h2>' + "".join(pick([f'<div class="comment"><p>{say(3, 60)}</p></div>', f"<p>{say(3, 60)}</p>", f'<article class="comment"><p>{say(3, 50)}</p></article>']) for _ in range(rng.randint(1, 5))) + f"</{t}>",
        "footer": lambda: pick([f"<footer>{say(3, 30)}</footer>", f"<footer><p>{say(3, 20)}</p>{links(2, 5)}</footer>", f'<div class="footer"><p>{say(3, 25)}</p></div>']),
        "related": lambda: f'<div class="{pick(["related", "share", "social"])}">{links(2, 5)}</div>',
    }
    mark = lambda s: re.sub(r"<(p|h1|h2|h3|ul|ol|li|blockquote|pre|table|tr|td|figure|figcaption|div|section|article|main)\b", r"<\1 data-y", s)
    parts = [mark(f"<h1>{say(2, 9)}</h1>")] if rng.random() < 0.8 else []
    bare = lambda: pick([say(3, 90), f"{say(2, 40)} <b>{say(1, 5)}</b> {say(1, 40)}", f"{say(2, 30)} {link()} {say(2, 30)}"]) + pick(["<br>", "<br><br>", ""])
    direct = rng.choices([0, 0.3, 1], [6, 2, 2])[0]  # how much of the main text stands in the main element itself
    for _ in range(rng.randint(1, 14)):
        parts.append(bare() if rng.random() < direct else mark(pick([para, para, para, para, lambda: f"<h2>{say(1, 6)}</h2>", lambda: "<ul>" + "".join(f"<li>{say(2, 25)}</li>" for _ in range(rng.randint(2, 6))) + "</ul>", lambda: f"<blockquote><p>{say(4, 40)}</p></blockquote>", lambda: f"<pre>{say(4, 30)}</pre>", lambda: f"<table><tr><td>{say(1, 5)}</td><td>{say(1, 5)}</td></tr></table>", lambda: f"<div><p>{say(5, 60)}</p></div>"])()))
        if rng.random() < 0.08:
            parts.append(around[pick(["ad", "form", "notice", "related", "side", "nav"])]())
    if rng.random() < 0.25:
        parts.append(around["comments"]())
    if rng.random() < 0.1:
        parts.insert(0, around["header"]())
    if rng.random() < 0.1:
        parts.append(around["footer"]())
    body = "".join(parts)
    t, c = pick([("article", ""), ("article", ""), ("article", ' class="post"'), ("main", ""), ("div", ' class="content"'), ("div", ' id="article-body"'), ("section", ' class="entry"'), ("div", ' class="post-text"'), ("div", ' id="main"'), ("div", ""), ("section", ""), ("td", ' class="story"')])
    if rng.random() < 0.1:
        deep = rng.randint(1, 30)
        body = "<div data-y>" * deep + body + "</div>" * deep
    main = f"<{t} data-y{c}>{body}</{t}>"
    if t == "td":
        main = f"<table><tr><td>{around['nav']()}</td>{main}</tr></table>"
    if t == "article" and rng.random() < 0.3:
        main = f"<main data-y>{main}</main>"
    first = [around[k]() for k in ("nav", "header", "notice", "ad", "side", "form") if rng.random() < 0.45]
    last = [around[k]() for k in ("comments", "side", "ad", "form", "related", "notice", "nav") if rng.random() < 0.35] + ([around["footer"]()] if rng.random() < 0.85 else [])
    if rng.random() < 0.2:  # nothing but the text
        first, last = [], last[-1:] if rng.random() < 0.5 else []
    rng.shuffle(first)
    wrap = pick(["{}", "{}", '<div class="wrapper">{}</div>', '<div id="page">{}</div>'])
    head = "<!DOCTYPE html><html><head><title>x</title></head>"
    if rng.random() < 0.06:  # a fragment: without a body element the root stands for it
        return f"{ROOT_IS_MAIN}{''.join(first)}{body}{''.join(last)}" if rng.random() < 0.5 else "".join(first) + main + "".join(last)
    if rng.random() < 0.15:  # a plain page whose body is the main element
        return f"{head}<body data-y>{''.join(first)}{body}{''.join(last)}</body></html>"
    return f"{head}<body>" + wrap.format("".join(first) + main + "".join(last)) + "</body></html>"


def labelled(page: str) -> tuple[list[Node], np.ndarray]:
    """The nodes of a made-up page, and which of them are main."""
    flags = [bool(re.match(r"<[a-z0-9]+ data-y", m[0])) for m in _TOKEN.finditer(page) if m[2] and not m[1] and (t := m[2].lower()) not in RAW | VOID | INLINE and t not in ("html", "head")]
    return parse(page.replace(" data-y", "")), np.array([page.startswith(ROOT_IS_MAIN), *flags], float)


@lru_cache
def trained(pages: int = 2000, seed: int = 11) -> Boosted:
    """The model, fitted to made-up pages with known main text (a fixed number of them; deterministic)."""
    rng = random.Random(seed)
    xs, ys = [], []
    for _ in range(pages):
        nodes, flags = labelled(sample_page(rng))
        xs.append(features(nodes))
        ys.append(flags)
    return Boosted().fit(np.concatenate(xs), np.concatenate(ys))


def main_text(page: str, model: Boosted) -> str:
    """Main text of one page."""
    nodes = parse(page)
    return blocks_of(nodes, decode(nodes, model.predict(features(nodes))))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(id, url, text, n_chars) for every row, from the whole html. A null or empty page, or one without main text, gives the
    empty text and 0. Repeated rows give repeated results; an empty input gives none; other columns are ignored."""
    model = trained()
    source = pages.select(F.col(id_col).alias("id_"), F.col(url_col).alias("url_"), F.col(html_col).cast("string").alias("html_"))

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for k in range(0, b.num_rows, 64):
            trees = [parse(h or "") for h in b.column("html_").slice(k, 64).to_pylist()]
            p = model.predict(np.concatenate([features(t) for t in trees]))
            at = 0
            for t in trees:
                out.append(blocks_of(t, decode(t, p[at : at + len(t)])))
                at += len(t)
        return pa.RecordBatch.from_arrays([b.column("id_"), b.column("url_"), pa.array(out, pa.string()), pa.array(list(map(len, out)), pa.int64())], ["id_", "url_", "text", "n_chars"])

    types = {f.name: f.dataType.simpleString() for f in source.schema.fields}
    out = map_batches(source, run, f"id_ {types['id_']}, url_ {types['url_']}, text string, n_chars long")
    return out.select(F.col("id_").alias(id_col), F.col("url_").alias(url_col), "text", "n_chars")
