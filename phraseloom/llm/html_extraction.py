"""Main-text extraction with gradient-boosted trees over DOM nodes and hierarchical decoding.

A page is parsed into its block elements. Each gets features of its tag and attribute words (its own and its
ancestors'), subtree text and link density, depth and sibling statistics. Boosted trees give the probability that a
node holds article text. Decoding is a dynamic programme over the tree: a node that is dropped takes its whole subtree
along, a node that stays may drop or keep each child, and the labelling of highest likelihood wins; so no kept block
stands under a dropped ancestor.

The trees are fitted here, on generated pages whose nodes carry their true labels: many layouts, with semantic tags or
named or unnamed containers, for menus, headers, footers, sidebars, notices, adverts, forms and reader comments.

Text of kept nodes is cut into blocks at block elements; character references are decoded, white space inside a block
becomes one space, blocks are trimmed and joined by a line break. Scripts, styles, and markup never give text. Elements
of ``RAW`` are dropped up to the end tag that matches them; self-closing svg and math are empty, an option ends where its
end tag may be left out, and where there is no matching end tag only scripts, styles, text areas and titles run to the
page's end: of the others the start tag is ignored and the content read.

Defined cases: null and empty pages, and pages without kept text, give an empty string; pages of any length and nesting
are read whole; repeated rows are read each on its own; columns besides key, URL and markup never enter.
"""

from __future__ import annotations

import html as html_lib
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TOKEN = re.compile(r"<!--.*?(?:-->|$)|<(?:[!?])[^>]*(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)(?:>|$)", re.S)
ATTRIBUTE = re.compile(r"(class|id|role|itemprop|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
HEAD_END = re.compile(r"</head\s*>|(?=<body[\s>])", re.I)
SPACE = re.compile(r"\s+")
NAME = re.compile(r"[a-z]+")

#: Fixed values of the markup language.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var br wbr".split())
#: Their content is characters up to their end tag, or to the end of the page.
TEXT_ONLY = frozenset("script style textarea title".split())
FOREIGN = frozenset(("svg", "math"))
#: Elements whose content gives no text.
RAW = frozenset("script style noscript template iframe textarea select svg math object audio video canvas title head button option".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
IMPLIED = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "tbody": ("tr", "td", "th", "thead")}
SCOPES = frozenset("ul ol dl table body html article section div main nav aside".split())

TAGS = "html body main article section div nav header footer aside form ul ol li dl dt dd p h1 h2 h3 h4 h5 h6 blockquote pre table tr td th figure figcaption address hr".split()
#: Attribute words by group.
GROUPS = {
    "content": "article content post entry story main body text prose",
    "menu": "nav navbar navigation menu breadcrumb breadcrumbs topbar tabs toc pagination pager",
    "head": "header masthead banner hero logo branding",
    "foot": "footer foot copyright colophon legal bottom",
    "side": "sidebar aside side widget widgets related recommended popular trending rail more teaser",
    "advert": "ad ads advert adverts advertisement sponsor sponsored promo promoted promotion",
    "notice": "notice notices cookie cookies consent gdpr alert popup modal overlay disclaimer announcement message",
    "talk": "comment comments reply replies discussion respond disqus reader readers thread feedback review reviews",
    "form": "form search login signup subscribe subscription newsletter contact input",
    "share": "share sharing social follow tags meta byline author",
}
_GROUP_OF = {w: g for g, ws in enumerate(GROUPS.values()) for w in ws.split()}
ROLES = {"navigation": "menu", "banner": "head", "contentinfo": "foot", "complementary": "side", "search": "form", "main": "content", "alert": "notice", "dialog": "notice"}


@dataclass
class Node:
    tag: str
    parent: int
    depth: int
    groups: int
    end: int = 0
    text: list[str] = field(default_factory=list)  # own characters, to measure
    chars: int = 0
    linked: int = 0
    links: int = 0
    stops: int = 0
    index: int = 0


def _groups(attributes: str) -> int:
    mask = 0
    for kind, a, b, c in ATTRIBUTE.findall(attributes):
        value = (a or b or c).lower()
        if kind.lower() == "role":
            value = ROLES.get(value, "")
            mask |= 1 << list(GROUPS).index(value) if value in GROUPS else 0
            continue
        for word in NAME.findall(value):
            g = _GROUP_OF.get(word)
            if g is not None:
                mask |= 1 << g
    return mask


@lru_cache(maxsize=64)
def _text_end(name: str) -> re.Pattern:
    return re.compile(f"</{name}(?=[\\s/>])[^>]*>", re.I)


def _matches(page: str, at: int) -> dict[int, int]:
    """End of a start tag of ``RAW`` -> end of the end tag that matches it, for all that follow ``at``."""
    out: dict[int, int] = {}
    open_: dict[str, list[int]] = {}
    while found := TOKEN.search(page, at):
        at = found.end()
        closing, name, attributes = found.groups()
        name = (name or "").lower()
        if name not in RAW:
            continue
        if closing:
            if open_.get(name):
                out[open_[name].pop()] = at
        elif attributes.endswith("/") and (name in FOREIGN or any(open_.get(x) for x in FOREIGN)):
            continue
        elif name in TEXT_ONLY:
            end = _text_end(name).search(page, at)
            at = end.end() if end else len(page)
        else:
            open_.setdefault(name, []).append(at)
    return out


def _option_end(page: str, at: int, around: set[str]) -> int | None:
    """Where an option ends: after its end tag, or before the next option, block element, or end tag of what it stands in."""
    while found := TOKEN.search(page, at):
        closing, name, _ = found.groups()
        at = found.end()
        name = (name or "").lower()
        if closing and name == "option":
            return at
        if name and (name in around or name == "optgroup" if closing else name not in INLINE):
            return found.start()
    return None


def parse(page: str) -> tuple[list[Node], list[tuple[int, str]]]:
    """Block elements in page order, and text blocks as ``(node, text)``; node 0 is the page itself."""
    nodes = [Node("html", -1, 0, 0)]
    blocks: list[tuple[int, str]] = []
    stack: list[tuple[str, int]] = [("#", 0)]  # (tag, node that holds its text); inline elements share their block's
    pending: list[str] = []
    memory: dict[str, int] = {}
    matches: dict[int, int] | None = None
    in_link = 0

    def flush() -> None:
        if pending:
            text = SPACE.sub(" ", html_lib.unescape("".join(pending))).strip()
            pending.clear()
            if text:
                at = stack[-1][1]
                blocks.append((at, text))
                nodes[at].chars += len(text)
                nodes[at].stops += text.count(". ") + text.count(", ") + (text[-1] in ".!?:;…")

    def pop(to: int) -> None:
        nonlocal in_link
        while len(stack) > to:
            tag, at = stack[-1]
            if tag == "a":
                in_link = max(0, in_link - 1)
            if tag not in INLINE:
                flush()
                nodes[at].end = len(nodes)
            stack.pop()

    def close(tags: tuple[str, ...], stop: frozenset[str]) -> None:
        for k in range(len(stack) - 1, 0, -1):
            if stack[k][0] in tags:
                pop(k)
                return
            if stack[k][0] in stop:
                return

    at, size = 0, len(page)
    while at < size:
        found = TOKEN.search(page, at)
        piece = page[at : found.start()] if found else page[at:]
        if piece:
            pending.append(piece)
            if in_link:
                nodes[stack[-1][1]].linked += len(piece.strip())
        if not found:
            break
        at = found.end()
        closing, name, attributes = found.groups()
        if name is None:
            continue
        name = name.lower()
        if closing:
            if name in INLINE:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k][0] == name:
                        pop(k)
                        break
                    if stack[k][0] not in INLINE:
                        break
            else:
                close((name,), frozenset() if name in SCOPES else SCOPES - {name})
            continue
        if name in RAW:
            if name not in INLINE:
                flush()
            if name == "head":
                end = HEAD_END.search(page, at)
                at = end.end() if end else at
            elif name in FOREIGN and attributes.endswith("/"):
                pass
            elif name in TEXT_ONLY:
                end = _text_end(name).search(page, at)
                at = end.end() if end else size
            elif name == "option":
                at = _option_end(page, at, {tag for tag, _ in stack}) or at
            else:
                if matches is None:
                    matches = _matches(page, found.start())
                at = matches.get(at, at)
            continue
        if name in INLINE or name in VOID:
            if name == "br":
                pending.append(" ")
            elif name in ("hr",):
                flush()
            elif name == "a":
                in_link += 1
                nodes[stack[-1][1]].links += 1
                stack.append((name, stack[-1][1]))
            elif name not in VOID:
                stack.append((name, stack[-1][1]))
            continue
        if name in CLOSES_P:
            close(("p",), SCOPES)
        if name in IMPLIED:
            close(IMPLIED[name], frozenset(("ul", "ol", "dl", "table")))
        flush()
        if name == "html":
            continue
        groups = memory.get(attributes)
        if groups is None:
            groups = memory[attributes] = _groups(attributes) if "=" in attributes else 0
        parent = stack[-1][1]
        nodes.append(Node(name, parent, nodes[parent].depth + 1, groups))
        stack.append((name, len(nodes) - 1))
    flush()
    pop(1)
    nodes[0].end = len(nodes)
    return nodes, blocks


_TAG_AT = {t: k for k, t in enumerate(TAGS)}


def node_features(nodes: list[Node]) -> np.ndarray:
    """One row of numbers per node."""
    n = len(nodes)
    parent = np.array([max(0, x.parent) for x in nodes])
    end = np.array([max(x.end, k + 1) for k, x in enumerate(nodes)])
    tag = np.array([_TAG_AT.get(x.tag, len(TAGS)) for x in nodes])
    groups = np.array([x.groups for x in nodes])
    above = groups.copy()
    kinds = 1 << tag
    over = np.zeros(n, np.int64)
    for k in range(1, n):
        above[k] |= above[parent[k]]
        over[k] = over[parent[k]] | kinds[parent[k]]
    own = np.array([(x.chars, x.linked, x.links, x.stops) for x in nodes], dtype=np.float64)
    sums = np.concatenate([np.zeros((1, 4)), np.cumsum(own, axis=0)])
    tree = sums[end] - sums[np.arange(n)]
    paragraphs = np.concatenate([[0], np.cumsum(np.isin(tag, [_TAG_AT["p"], _TAG_AT["blockquote"], _TAG_AT["pre"]]))])
    items = np.concatenate([[0], np.cumsum(tag == _TAG_AT["li"])])
    size = end - np.arange(n)
    depth = np.array([x.depth for x in nodes])
    siblings = np.bincount(parent[1:], minlength=n)[parent] if n > 1 else np.zeros(n)
    rank = np.zeros(n)
    alike = np.zeros(n)
    seen: dict[int, int] = {}
    kinds_below: dict[tuple[int, int], int] = {}
    for k in range(1, n):
        p = int(parent[k])
        rank[k] = seen[p] = seen.get(p, 0) + 1
        kinds_below[p, int(tag[k])] = kinds_below.get((p, int(tag[k])), 0) + 1
    for k in range(1, n):
        alike[k] = kinds_below[int(parent[k]), int(tag[k])]
    chars = tree[:, 0]
    total = max(1.0, chars[0])
    before = sums[np.arange(n), 0] / total
    numbers = [
        np.log1p(chars), chars / total, tree[:, 1] / np.maximum(chars, 1), np.log1p(tree[:, 2]), tree[:, 3] / np.maximum(chars, 1) * 100, chars / size, np.log1p(size), np.log1p(own[:, 0]),
        np.log1p(paragraphs[end] - paragraphs[:-1]), np.log1p(items[end] - items[:-1]), depth, rank, siblings, alike, before, chars[parent] / total, tree[parent, 1] / np.maximum(chars[parent], 1), tag, tag[parent],
    ]
    flags = [((mask >> g) & 1) for mask in (groups, above) for g in range(len(GROUPS))]
    inside = [((over >> _TAG_AT[t]) & 1) for t in ("article", "main", "nav", "header", "footer", "aside", "form", "ul", "ol", "li", "p", "table")]
    is_tag = [tag == _TAG_AT[t] for t in ("p", "li", "div", "section", "h1", "h2", "nav", "header", "footer", "aside", "form", "article", "main", "ul", "ol", "blockquote", "pre", "table")]
    return np.stack([np.asarray(x, np.float32) for x in (*numbers, *flags, *inside, *is_tag)], axis=1)


@dataclass
class Trees:
    """Boosted regression trees of a fixed depth, as flat arrays (feature, threshold; leaves)."""

    features: np.ndarray
    cuts: np.ndarray
    leaves: np.ndarray
    base: float

    def probability(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.base)
        rows = np.arange(len(x))
        depth = int(np.log2(self.leaves.shape[1]))
        for f, c, leaf in zip(self.features, self.cuts, self.leaves, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(depth):
                at = 2 * at + 1 + (x[rows, f[at]] > c[at])
            total += leaf[at - (len(leaf) - 1)]
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 60, depth: int = 5, rate: float = 0.2, bins: int = 32, ridge: float = 1.0) -> Trees:
    """Second-order boosting on the logistic loss with histograms over quantile bins."""
    n, width = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
    base = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    score = np.full(n, base)
    inner = (1 << depth) - 1
    out_f, out_c, out_l = [], [], []
    offset = np.arange(width) * bins
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-score))
        g, h = p - y, np.maximum(p * (1 - p), 1e-9)
        feature, cut, cut_bin = np.zeros(inner, np.int64), np.full(inner, np.inf), np.full(inner, bins)
        at = np.zeros(n, np.int64)
        for level in range(depth):
            low, count = (1 << level) - 1, 1 << level
            slot = ((at - low)[:, None] * (width * bins) + offset + binned).ravel()
            hist_g = np.bincount(slot, np.repeat(g, width), minlength=count * width * bins).reshape(count, width, bins)
            hist_h = np.bincount(slot, np.repeat(h, width), minlength=count * width * bins).reshape(count, width, bins)
            left_g, left_h = hist_g.cumsum(axis=2), hist_h.cumsum(axis=2)
            all_g, all_h = left_g[:, :1, -1:], left_h[:, :1, -1:]
            gain = left_g**2 / (left_h + ridge) + (all_g - left_g) ** 2 / (all_h - left_h + ridge) - all_g**2 / (all_h + ridge)
            gain[(left_h < 1) | (all_h - left_h < 1)] = 0
            best = gain.reshape(count, -1).argmax(axis=1)
            for k in range(count):
                j, b = divmod(int(best[k]), bins)
                if gain[k, j, b] > 1e-6 and b < len(edges[j]):
                    feature[low + k], cut[low + k], cut_bin[low + k] = j, edges[j][b], b
            at = 2 * at + 1 + (binned[np.arange(n), feature[at]] > cut_bin[at])
        leaf = at - inner
        sum_g, sum_h = np.bincount(leaf, g, minlength=inner + 1), np.bincount(leaf, h, minlength=inner + 1)
        value = -rate * sum_g / (sum_h + ridge)
        score += value[leaf]
        out_f.append(feature)
        out_c.append(cut)
        out_l.append(value)
    return Trees(np.array(out_f), np.array(out_c, np.float32), np.array(out_l), base)


def decode(nodes: list[Node], p: np.ndarray) -> np.ndarray:
    """Labels of highest likelihood under which a dropped node's subtree is dropped; the page itself stays."""
    keep, drop = np.log(np.clip(p, 1e-6, 1)), np.log(np.clip(1 - p, 1e-6, 1))
    for k in range(len(nodes) - 1, 0, -1):  # children stand behind their parents
        parent = nodes[k].parent
        keep[parent] += max(keep[k], drop[k])
        drop[parent] += drop[k]
    stays = np.ones(len(nodes), dtype=bool)
    for k in range(1, len(nodes)):
        stays[k] = stays[nodes[k].parent] and (keep[k] > drop[k] or nodes[k].tag == "body")
    return stays


class PageMaker:
    """Generated pages with labels: text that starts with ``KEEP`` is the article's."""

    KEEP = "\x02"

    def __init__(self, seed: int) -> None:
        self.r = random.Random(seed)

    def words(self, low: int, high: int) -> str:
        r = self.r
        out = ["".join(r.choice("bcdfghlmnprstv") + r.choice("aeiou") for _ in range(r.randint(1, 4))) for _ in range(r.randint(low, high))]
        for k in range(len(out)):
            if k and r.random() < 0.08:
                out[k - 1] += r.choice(",,,;")
            if k and r.random() < 0.08:
                out[k - 1] += "."
                out[k] = out[k].capitalize()
        return " ".join(out).capitalize() + r.choice([".", ".", ".", "", "!"])

    def box(self, inside: str, tags: list[str], names: list[str], plain: float = 0.15) -> str:
        r = self.r
        tag = r.choice(tags)
        semantic = tag not in ("div", "section", "ul", "p", "span")
        if (semantic and r.random() < 0.6) or r.random() < plain:
            return f"<{tag}>{inside}</{tag}>"
        name = r.choice(names)
        name = r.choice([name, name, f"{name}-{r.choice(['box', 'wrap', 'inner', 'top', 'x1', 'area'])}", f"site-{name}", f"{r.choice(['c', 'js', 'l'])}-{name} {r.choice(['clear', 'col', 'row'])}"])
        return f'<{tag} {r.choice(["class", "class", "id"])}="{name}">{inside}</{tag}>'

    def links(self, low: int, high: int) -> str:
        r = self.r
        many = [f'<a href="/{k}">{self.words(1, 3)}</a>' for k in range(r.randint(low, high))]
        if r.random() < 0.75:
            return "<ul>" + "".join(f"<li>{a}</li>" for a in many) + "</ul>"
        return r.choice([" | ", " ", " &middot; "]).join(many)

    def boilerplate(self, kind: str) -> str:
        r, box, words = self.r, self.box, self.words
        if kind == "menu":
            return box(self.links(3, 9), ["nav", "nav", "div", "ul"], ["nav", "menu", "navbar", "breadcrumb"], 0.1)
        if kind == "head":
            inside = r.choice([f"<h1>{words(1, 3)}</h1>", f'<div class="logo">{words(1, 2)}</div>', f"<p>{words(3, 8)}</p>", f"<a href='/'>{words(1, 3)}</a>"]) + (self.boilerplate("menu") if r.random() < 0.5 else "")
            return box(inside, ["header", "header", "div"], ["header", "masthead", "banner", "topbar"], 0.05)
        if kind == "foot":
            inside = r.choice([f"&copy; {words(1, 2)} &middot; {words(4, 20)}", f"<p>&copy; 2024 {words(3, 12)}</p>", self.links(2, 6) + f"<p>{words(3, 9)}</p>", f"<div>{words(4, 15)}</div>"])
            return box(inside, ["footer", "footer", "div"], ["footer", "copyright", "legal", "colophon"], 0.05)
        if kind == "side":
            inside = f"<h{r.randint(2, 4)}>{words(1, 3)}</h3>" + r.choice([self.links(3, 7), "".join(f"<p>{words(4, 16)}</p>" for _ in range(r.randint(1, 3)))])
            return box(inside, ["aside", "aside", "div", "section"], ["sidebar", "widget", "related", "side", "popular", "recommended"], 0.05)
        if kind == "advert":
            return box(r.choice([words(3, 25), f"<p>{words(4, 25)}</p>", f"<a href='#'>{words(3, 9)}</a>", f"<div><span>{words(5, 20)}</span></div>"]), ["div", "div", "aside", "section", "p"], ["ad", "ads", "advert", "sponsored", "promo", "advertisement"], 0)
        if kind == "notice":
            inside = r.choice([words(6, 30), f"<p>{words(6, 30)}</p>"]) + r.choice(["", "<button>OK</button>", f"<a href='#'>{words(1, 2)}</a>"])
            return box(inside, ["div", "div", "section", "p", "aside"], ["cookie", "notice", "consent", "alert", "popup", "cookie-banner", "gdpr", "disclaimer"], 0)
        if kind == "talk":
            one = lambda: box(r.choice([f"<p>{words(4, 40)}</p>", f"<div class='author'>{words(1, 2)}</div><p>{words(5, 60)}</p>", f"<b>{words(1, 2)}</b> {words(4, 40)}"]), ["li", "div", "article"], ["comment", "reply", "item"], 0.3)
            inside = (f"<h{r.randint(2, 4)}>{words(1, 3)}</h3>" if r.random() < 0.6 else "") + "".join(one() for _ in range(r.randint(1, 6)))
            return box(inside, ["div", "section", "ol", "ul", "aside"], ["comments", "comment-list", "discussion", "replies", "respond", "reader-comments"], 0)
        if kind == "form":
            inside = f"<label>{words(1, 4)}</label><input name=q>" + r.choice(["", f"<p>{words(3, 15)}</p>", f"<div>{words(3, 12)}</div>"]) + "<button>go</button>"
            return box(f"<form action='/s'>{inside}</form>" if r.random() < 0.7 else inside, ["form", "form", "div", "section"], ["search", "newsletter", "subscribe", "login", "signup", "form"], 0)
        return box(r.choice([self.links(2, 5), words(2, 8)]), ["div", "ul", "p"], ["share", "social", "tags", "byline", "follow"], 0)

    def article(self) -> str:
        r, k = self.r, self.KEEP
        words = lambda a, b: k + self.words(a, b)
        parts = [f"<h1>{words(2, 12)}</h1>"] if r.random() < 0.8 else []
        if parts and r.random() < 0.2:
            parts[0] = f"<header>{parts[0]}</header>"
        for _ in range(r.choice([1, 1, 2, 3, 4, 6, 9, 14])):
            roll = r.random()
            if roll < 0.62:
                text = words(3, r.choice([12, 40, 120, 250]))
                text = r.choice([text, text, f"<b>{text}</b>", f"{text} <a href='#'>{self.words(1, 3)}</a> {self.words(2, 20)}", f"<b>{text}<br>"])
                parts.append(f"<p>{text}" + ("</p>" if r.random() < 0.9 else ""))
            elif roll < 0.72:
                parts.append(f"<h{r.randint(2, 4)}>{words(1, 8)}</h2>".replace("</h2>", "</h2>"))
            elif roll < 0.82:
                tag = r.choice(["ul", "ol"])
                parts.append(f"<{tag}>" + "".join(f"<li>{words(1, 25)}</li>" for _ in range(r.randint(2, 6))) + f"</{tag}>")
            elif roll < 0.87:
                parts.append(f"<blockquote>{words(4, 40)}</blockquote>" if r.random() < 0.5 else f"<blockquote><p>{words(4, 40)}</p></blockquote>")
            elif roll < 0.9:
                parts.append(f"<pre>{words(3, 30)}</pre>")
            elif roll < 0.93:
                parts.append("<table>" + "".join("<tr>" + "".join(f"<td>{words(1, 4)}</td>" for _ in range(3)) + "</tr>" for _ in range(r.randint(2, 4))) + "</table>")
            elif roll < 0.96:
                parts.append(f"<figure><img src=x><figcaption>{words(2, 12)}</figcaption></figure>")
            else:
                parts.append(f"<div>{words(4, 60)}</div>")
        for kind, chance in (("advert", 0.3), ("share", 0.2), ("form", 0.08), ("side", 0.1), ("notice", 0.08)):
            if r.random() < chance:
                parts.insert(r.randint(0, len(parts)), self.boilerplate(kind))
        if r.random() < 0.15:
            parts.append(self.boilerplate("talk"))
        inside = "".join(parts)
        if r.random() < 0.25:
            inside = self.box(inside, ["div", "section"], ["content", "entry", "body", "text", "inner", "x"], 0.3)
        return self.box(inside, ["article", "article", "main", "div", "section"], ["article", "content", "post", "entry", "story", "main", "page", "wrap"], 0.15)

    def page(self) -> str:
        r, b = self.r, self.boilerplate
        top = [b(kind) for kind, chance in (("notice", 0.25), ("head", 0.5), ("menu", 0.7), ("advert", 0.5), ("form", 0.15), ("side", 0.15)) if r.random() < chance]
        tail = [b(kind) for kind, chance in (("share", 0.2), ("talk", 0.35), ("side", 0.35), ("form", 0.2), ("advert", 0.3), ("menu", 0.15), ("foot", 0.8), ("notice", 0.1)) if r.random() < chance]
        if r.random() < 0.5:
            r.shuffle(top)
        middle = self.article()
        if r.random() < 0.3:
            at = r.randint(0, len(tail))
            middle, tail = self.box(middle + "".join(tail[:at]), ["div", "main", "section"], ["container", "wrapper", "page", "layout", "main"], 0.3), tail[at:]
        return f"<!DOCTYPE html><html><head><title>{self.words(2, 6)}</title><style>p{{}}</style></head><body>" + "".join(top) + middle + "".join(tail) + ("</body></html>" if r.random() < 0.9 else "")


def labelled_pages(pages: int, seed: int) -> list[tuple[list[Node], list[tuple[int, str]], np.ndarray]]:
    maker, out = PageMaker(seed), []
    for _ in range(pages):
        nodes, blocks = parse(maker.page())
        truth = np.zeros(len(nodes), dtype=bool)
        for at, text in blocks:
            if PageMaker.KEEP in text:
                while at >= 0 and not truth[at]:
                    truth[at] = True
                    at = nodes[at].parent
        out.append((nodes, blocks, truth))
    return out


@lru_cache(maxsize=2)
def default_trees(pages: int = 700, seed: int = 20) -> Trees:
    made = labelled_pages(pages, seed)
    return boost(np.concatenate([node_features(n) for n, _, _ in made]), np.concatenate([t for _, _, t in made]).astype(float))


def extract(pages: list[str | None], trees: Trees) -> list[str]:
    parsed = [parse(p) if p else ([], []) for p in pages]
    full = [x for x in parsed if x[1]]
    p = trees.probability(np.concatenate([node_features(n) for n, _ in full])) if full else np.zeros(0)
    out, at = [], 0
    for nodes, blocks in parsed:
        if not blocks:
            out.append("")
            continue
        stays = decode(nodes, p[at : at + len(nodes)])
        at += len(nodes)
        out.append("\n".join(text for k, text in blocks if stays[k]))
    return out


def extract_pages(pages: DataFrame, trees: Trees | None = None, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """``(page_id, url, text, n_chars)`` per row."""
    sent = pages.sparkSession.sparkContext.broadcast(trees or default_trees())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                texts = extract(part.column(2).to_pylist(), sent.value)
                yield pa.record_batch([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col(key).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.col(html).cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
