"""Main text of web pages: gradient-boosted trees over DOM nodes, decoded along the tree.

A page is read into block elements and the text segments between their borders.  Every block gets features of its own
tag and attribute tokens, its ancestors', its depth, its siblings, and its subtree's text, links and element density.
Boosted trees, fitted on generated pages whose parts are known, give each block the log-odds of holding main text.
Decoding chooses for the whole tree at once: a dropped block drops everything in it, so no kept block lies in a
dropped one, and of all such choices the one with the highest sum of log-odds is found from the leaves up.
"""

from __future__ import annotations

import html
import json
import random
import re
from collections import defaultdict
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm.texthash import bounded, small, tidy

# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template textarea title iframe noembed noframes object svg canvas math select noscript".split())
BLOCKS = frozenset(
    "html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup"
    " head hr li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption legend button".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
CLOSES_P = BLOCKS - {"html", "body", "head", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "button", "legend"}
CLOSED_BY = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "tbody": {"tr", "td", "th", "thead", "tbody"}, "tfoot": {"tr", "td", "th", "tbody"}, "option": {"option"}}
FENCES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "tbody": {"table"}, "tfoot": {"table"}}

AWAY = frozenset(
    "nav navbar navigation menu menubar breadcrumb breadcrumbs header masthead topbar banner footer bottom colophon copyright legal sidebar aside rail widget related recommended popular trending"
    " ad ads adv advert adverts advertisement sponsor sponsored promo promotion cookie cookies consent notice notification alert gdpr popup modal overlay newsletter subscribe signup login form search share sharing"
    " social follow comment comments reply replies respond discussion disqus feedback pagination pager tags tagcloud categories author bio toolbar skip hidden print outbrain taboola".split()
)
HOME = frozenset("article content main post entry story text body page maincontent articlebody blogpost prose copy read single hentry".split())
TALK = frozenset("comment comments reply replies respond discussion disqus feedback commentlist".split())

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>", re.S)
_TOKENS = re.compile(r"\b(?:class|id|role|itemprop|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_CAMEL = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
_COMMENT = re.compile(r"<!--.*", re.S)  # after the last >, only an unclosed comment is markup
_UNSEEN = re.compile(r"(?:^|\s)hidden(?=[\s/=]|$)(?!\s*=\s*[\"']?(?:until|false))|\baria-hidden\s*=\s*[\"']?true|\bstyle\s*=\s*[\"'][^\"']*display\s*:\s*none", re.I)
INLINE, HIDDEN, GAP = -1, -2, -3
_GONE = re.compile(r"\b(?:hidden\b(?!\s*=\s*[\"']?(?:until|false))|aria-hidden\s*=\s*[\"']?true)|display\s*:\s*none", re.I)

TAG_KINDS = {
    "p": 1, "h1": 2, "h2": 3, "h3": 3, "h4": 3, "h5": 3, "h6": 3, "li": 4, "ul": 5, "ol": 5, "dl": 5, "dir": 5, "menu": 5, "div": 6, "center": 6, "section": 7, "article": 8, "main": 9, "nav": 10, "header": 11, "footer": 12,
    "aside": 13, "form": 14, "fieldset": 14, "button": 14, "legend": 14, "table": 15, "tr": 15, "td": 15, "th": 15, "tbody": 15, "thead": 15, "blockquote": 16, "pre": 17, "figure": 18, "figcaption": 18, "dialog": 19, "address": 20,
}
N_FEATURES = 41


class Page:
    """Blocks of a page in document order, and its text segments with the block each belongs to."""

    __slots__ = ("parent", "tag", "own", "chars", "links", "anchors", "inputs", "inline", "segments")

    def __init__(self) -> None:
        self.parent, self.tag, self.own = [-1], ["html"], [(0, 0, 0, 0)]
        self.chars, self.links, self.anchors, self.inputs, self.inline = [0], [0], [0], [0], [0]
        self.segments: list[tuple[int, str]] = []


_token_memory: dict[str, tuple[int, int, int, int]] = {}


def _attribute_counts(attributes: str) -> tuple[int, int, int, int]:
    """Tokens of boilerplate, of main text and of comments in class, id, role; and whether the element is hidden."""
    got = _token_memory.get(attributes)
    if got is None:
        words = [w.lower() for m in _TOKENS.finditer(attributes) for w in _CAMEL.findall(m[1] or m[2] or m[3] or "")]
        got = (sum(w in AWAY for w in words), sum(w in HOME for w in words), sum(w in TALK for w in words), int(bool(_GONE.search(attributes))))
        if len(_token_memory) > 1 << 16:
            _token_memory.clear()
        _token_memory[attributes] = got
    return got


def characters(text: str) -> str:
    """Character references decoded once."""
    if "&" not in text:
        return text
    n = text.count("&")
    return text.replace("&amp;", "&") if n == text.count("&amp;") else html.unescape(text)


def read(source: str) -> Page:
    """The blocks and segments of a page; unclosed and stray tags are mended as browsers do in the common cases.

    The text of raw elements, of noscript and of hidden inline elements is left out.  Every tag takes constant time: where the nearest open
    element of a name is, is kept by name, and an inline element that is closed out of order leaves a gap.
    """
    page = Page()
    parent, tags, own, chars, links, anchors, inputs, inline = page.parent, page.tag, page.own, page.chars, page.links, page.anchors, page.inputs, page.inline
    stack: list[tuple[str, int]] = [("html", 0)]  # open elements; the block's index, or one of INLINE, HIDDEN and GAP
    places: dict[str, list[int]] = defaultdict(list)  # where in the stack each name is open, without the root
    blocks: list[int] = [0]  # where in the stack blocks are open
    block, in_link, hidden, buffer = 0, 0, 0, []
    lower, absent = None, set()
    at, n = 0, len(source)
    last = source.rfind(">")

    def flush() -> None:
        text = " ".join("".join(buffer).split())
        buffer.clear()
        if text:
            page.segments.append((block, text))

    def forget(name: str, i: int) -> None:
        nonlocal in_link, hidden
        if i != GAP:
            places[name].pop()
            in_link -= name == "a"
            hidden -= i == HIDDEN

    def pop_to(depth: int) -> None:
        nonlocal block
        flush()
        while len(stack) > depth:
            name, i = stack.pop()
            if i >= 0:
                blocks.pop()
            forget(name, i)
        block = stack[blocks[-1]][1]

    def take_out(d: int) -> None:
        """Close the inline element at d, which is the nearest of its name."""
        forget(*stack[d])
        stack[d] = ("", GAP)
        while stack[-1][1] == GAP:
            stack.pop()

    def nearest(names) -> int:
        return max((places[x][-1] for x in names if places[x]), default=0)

    def opened(names, fences) -> int:
        d = nearest(names)
        return d if d > nearest(fences) else 0

    search = _TAG.search
    while at < n:
        m = search(source, at) if at <= last else _COMMENT.search(source, at)
        end = m.start() if m else n
        if end > at and not hidden:
            text = characters(source[at:end])
            buffer.append(text)
            size = len(text) - text.count(" ")
            chars[block] += size
            if in_link:
                links[block] += size
        if not m:
            break
        at = m.end()
        name = (m[2] or m[5]) if m.re is _TAG else None
        if not name:
            continue
        name = name.lower()
        if m[1] or m[4]:
            if name == "br":
                buffer.append(" ")
                continue
            d = nearest(HEADINGS if name in HEADINGS else (name,))
            if d and name in BLOCKS:
                pop_to(d)
            elif d > blocks[-1]:
                take_out(d)
            continue
        if name in RAW:
            lower = lower or source.lower()
            stop = -1 if name in absent else lower.find(f"</{name}", at)
            if stop < 0:
                absent.add(name)
                if name in ("object", "select", "svg", "math", "canvas", "noscript"):
                    continue
            if name in ("select", "textarea"):
                inputs[block] += 1
            at = source.find(">", stop) + 1 if stop >= 0 else n
            at = at or n
            continue
        if name in VOID:
            if name == "br":
                buffer.append(" ")
            elif name == "hr":
                flush()
            elif name == "input":
                inputs[block] += 1
            continue
        attributes = m[3] or m[6] or ""
        if attributes.endswith("/") and name not in BLOCKS:
            continue
        if name not in BLOCKS:
            inline[block] += 1
            if name == "a":
                if in_link:  # links don't nest
                    take_out(nearest(("a",)))
                anchors[block] += 1
                in_link += 1
            gone = bool(attributes and _UNSEEN.search(attributes))
            hidden += gone
            places[name].append(len(stack))
            stack.append((name, HIDDEN if gone else INLINE))
            continue
        if name == "html" or name == "body" and "body" in tags[:4]:  # opened once
            continue
        if name in CLOSES_P:
            if stack[blocks[-1]][0] == "p":
                pop_to(blocks[-1])
        if name == "body":
            d = nearest(("head",))
            if d:
                pop_to(d)
        if name in HEADINGS and stack[-1][0] in HEADINGS:
            pop_to(len(stack) - 1)
        if name in CLOSED_BY:
            while d := opened(CLOSED_BY[name], FENCES.get(name, ())):
                pop_to(d)
        flush()
        parent.append(block)
        block = len(tags)
        tags.append(name)
        own.append(_attribute_counts(attributes) if attributes else (0, 0, 0, 0))
        for x in (chars, links, anchors, inputs, inline):
            x.append(0)
        places[name].append(len(stack))
        blocks.append(len(stack))
        stack.append((name, block))
    flush()
    return page


def levels(parent: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Depth of each block, roots at 0, and the blocks of each depth; parents come before their children."""
    depth = [0] * len(parent)
    for i, p in enumerate(parent.tolist()):
        if p != i:
            depth[i] = depth[p] + 1
    depth = np.array(depth, np.int64)
    order = np.argsort(depth, kind="stable")
    cuts = np.searchsorted(depth[order], np.arange(int(depth.max()) + 1 if len(depth) else 0))
    return depth, np.split(order, cuts[1:]) if len(depth) else []


def features(pages: list[Page]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature rows of all blocks of all pages, the index of each block's parent (its own for roots), and where pages start."""
    sizes = np.array([len(p.tag) for p in pages])
    first = np.concatenate([[0], np.cumsum(sizes)])
    total = int(first[-1])
    join = lambda name, kind=np.float64: np.array([v for p in pages for v in getattr(p, name)], kind)
    kind = np.array([TAG_KINDS.get(t, 0) for p in pages for t in p.tag])
    tag = np.array([hash_tag(t) for p in pages for t in p.tag])
    parent = np.concatenate([np.array(p.parent) + a for p, a in zip(pages, first, strict=False)]) if pages else np.zeros(0, np.int64)
    root = np.zeros(total, bool)
    root[first[:-1]] = True
    parent[root] = np.flatnonzero(root)
    own = np.array([v for p in pages for v in p.own], np.float64).reshape(-1, 4)
    words, stops, segs, longest = (np.zeros(total) for _ in range(4))
    for p, a in zip(pages, first, strict=False):
        for b, text in p.segments:
            words[a + b] += text.count(" ") + 1
            stops[a + b] += text.count(".") + text.count(",") + text.count("!") + text.count("?") + text.count(";")
            segs[a + b] += 1
            longest[a + b] = max(longest[a + b], len(text))
    chars, links, anchors, inputs, inline = (join(x) for x in ("chars", "links", "anchors", "inputs", "inline"))
    flags = np.stack([kind == 1, kind == 2, kind == 4, np.ones(total), kind == 3], axis=1).astype(np.float64)
    sums = np.concatenate([np.stack([chars, links, anchors, inputs, inline, words, stops, segs], axis=1), flags], axis=1)
    sub, deep = sums.copy(), longest.copy()
    depth, rows = levels(parent)
    for at in reversed(rows[1:]):
        np.add.at(sub, parent[at], sub[at])
        np.maximum.at(deep, parent[at], deep[at])
    page_of = np.repeat(np.arange(len(pages)), sizes)
    whole = sub[first[:-1]][page_of] if total else sub
    tagged = np.stack([own[:, 0], own[:, 1], own[:, 2], own[:, 3], np.isin(kind, (10, 11, 12, 13, 14, 19)), np.isin(kind, (8, 9)), kind == 14, np.isin(kind, (4, 5))], axis=1)
    above = np.zeros_like(tagged)
    for at in rows[1:]:
        above[at] = np.maximum(above[parent[at]], tagged[parent[at]])
    # siblings: order by parent, then by place
    order = np.lexsort((np.arange(total), parent))
    order = order[~root[order]]
    par = parent[order]
    new = np.ones(len(order), bool)
    new[1:] = par[1:] != par[:-1]
    group = np.cumsum(new) - 1
    start = np.flatnonzero(new)
    count = np.diff(np.append(start, len(order)))
    place, siblings, alike = np.zeros(total), np.ones(total), np.zeros(total)
    place[order] = np.arange(len(order)) - start[group] if len(order) else 0
    siblings[order] = count[group] if len(order) else 0
    if len(order):
        _, pair, n_pair = np.unique(np.stack([par, tag[order]]), axis=1, return_inverse=True, return_counts=True)
        alike[order] = n_pair[pair.ravel()] / count[group]
    density = sub[:, 1] / np.maximum(1, sub[:, 0])
    before, after = np.full(total, -1.0), np.full(total, -1.0)
    text_before, text_after = np.zeros(total), np.zeros(total)
    if len(order) > 1:
        a, b = order[:-1][~new[1:]], order[1:][~new[1:]]
        before[b], after[a] = density[a], density[b]
        text_before[b], text_after[a] = sub[a, 0], sub[b, 0]
    # text before a block's start, as a share of the page's
    running = np.cumsum(chars) - chars
    running = running - running[first[:-1]][page_of] if total else running
    share = lambda x, y: x / np.maximum(1, y)
    x = np.stack(
        [
            kind, own[:, 0], own[:, 1], own[:, 2], own[:, 3], *above.T,
            np.minimum(depth, 30), np.minimum(place, 50), np.minimum(siblings, 50), share(place, siblings), alike, before, after, np.log1p(text_before), np.log1p(text_after),
            np.log1p(sub[:, 0]), density, share(sub[:, 2], sub[:, 5]), np.minimum(sub[:, 3], 9), share(sub[:, 4], sub[:, 5]), np.log1p(sub[:, 5]), share(sub[:, 6], sub[:, 5]), share(sub[:, 5], sub[:, 7]),
            np.minimum(sub[:, 8], 50), np.minimum(sub[:, 9], 9), np.minimum(sub[:, 10], 50), share(sub[:, 11], sub[:, 5]), np.minimum(sub[:, 12], 9), np.log1p(deep), share(sub[:, 0], whole[:, 0]),
            share(running, whole[:, 0]), share(sub[:, 8], sub[:, 11]), np.log1p(whole[:, 0]), kind[parent] if total else kind,
        ],
        axis=1,
    ) if total else np.zeros((0, N_FEATURES))
    return x.astype(np.float32), parent, first


_tag_numbers: dict[str, int] = {t: i for i, t in enumerate(sorted(BLOCKS))}


def hash_tag(tag: str) -> int:
    return _tag_numbers.get(tag, -1)


class Trees:
    """Gradient-boosted trees of one depth for a yes or no label, on quantile bins."""

    def __init__(self, rounds: int = 60, depth: int = 4, rate: float = 0.25, bins: int = 32, smooth: float = 4.0) -> None:
        self.rounds, self.depth, self.rate, self.bins, self.smooth = rounds, depth, rate, bins, smooth

    def fit(self, x: np.ndarray, y: np.ndarray) -> Trees:
        rows, width = x.shape
        self.edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.bins + 1)[1:-1])) for f in range(width)]
        code = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(self.edges)], axis=1)
        self.start = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
        score = np.full(rows, self.start)
        nodes = (1 << self.depth) - 1
        self.feature, self.edge, self.leaf = np.zeros((self.rounds, nodes), np.int64), np.full((self.rounds, nodes), np.inf, np.float32), np.zeros((self.rounds, nodes + 1))
        for r in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            g, h = y - p, p * (1 - p)
            node = np.zeros(rows, np.int64)
            for level in range(self.depth):
                n = 1 << level
                best, pick = np.full(n, 1e-6), np.full((n, 2), -1)
                total_g, total_h = np.bincount(node, g, n), np.bincount(node, h, n)
                for f, e in enumerate(self.edges):
                    if not len(e):
                        continue
                    at = node * (len(e) + 1) + code[:, f]
                    left_g = np.bincount(at, g, n * (len(e) + 1)).reshape(n, -1).cumsum(axis=1)[:, :-1]
                    left_h = np.bincount(at, h, n * (len(e) + 1)).reshape(n, -1).cumsum(axis=1)[:, :-1]
                    right_g, right_h = total_g[:, None] - left_g, total_h[:, None] - left_h
                    gain = left_g**2 / (left_h + self.smooth) + right_g**2 / (right_h + self.smooth) - (total_g**2 / (total_h + self.smooth))[:, None]
                    k = gain.argmax(axis=1)
                    v = gain[np.arange(n), k]
                    better = v > best
                    best[better], pick[better] = v[better], np.stack([np.full(n, f), k], axis=1)[better]
                right = np.zeros(rows, bool)
                for i, (f, k) in enumerate(pick):
                    if f >= 0:
                        self.feature[r, n - 1 + i], self.edge[r, n - 1 + i] = f, self.edges[f][k]
                        mine = node == i
                        right[mine] = code[mine, f] > k
                node = node * 2 + right
            n = 1 << self.depth
            self.leaf[r] = self.rate * np.bincount(node, g, n) / (np.bincount(node, h, n) + self.smooth)
            score += self.leaf[r][node]
        return self

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for feature, edge, leaf in zip(self.feature, self.edge, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for level in range(self.depth):
                at = (1 << level) - 1 + node
                node = node * 2 + (x[rows, feature[at]] > edge[at])
            out += leaf[node]
        return out


def decode(log_odds: np.ndarray, parent: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Best consistent choice: which blocks are kept, with every kept block's ancestors kept too; roots always are."""
    s = np.clip(log_odds, -6, 6)
    root = parent == np.arange(len(parent))
    _, rows = levels(parent)
    keep, drop = s.copy(), -s
    for at in reversed(rows[1:]):
        np.add.at(drop, parent[at], drop[at])
        np.add.at(keep, parent[at], np.maximum(keep[at], drop[at]))
    chosen = root.copy()
    for at in rows[1:]:
        chosen[at] = chosen[parent[at]] & (keep[at] > drop[at])
    return chosen


# --- generated pages whose parts are known ---


class _Writer:
    """A generated page: html pieces; blocks that hold main text are marked by the attribute data-keep, taken out before training."""

    def __init__(self, r: random.Random) -> None:
        self.r, self.out = r, []
        self.named = r.random() < 0.75  # telling class names

    def word(self) -> str:
        return "".join(self.r.choice(("th", "on", "er", "an", "la", "de", "que", "ich", "os", "ar", "me", "in", "ou", "st", "ver", "é")) for _ in range(self.r.randint(1, 4)))

    def words(self, a: int, b: int) -> str:
        return " ".join(self.word() for _ in range(self.r.randint(a, b)))

    def sentences(self, a: int, b: int) -> str:
        odd = self.r.random() < 0.1
        return " ".join(" ".join(w + self.r.choice(("", "###", "&amp;&amp;", "***", "%")) * odd for w in self.words(3, 18).split()).capitalize() + self.r.choice("...!?") for _ in range(self.r.randint(a, b)))

    def mark(self, kind: str) -> str:
        """Class or id for a region, telling or not."""
        names = {
            "nav": ("nav", "main-menu", "navbar", "site-navigation", "menu"), "header": ("header", "site-header", "masthead", "top-bar", "banner"), "footer": ("footer", "site-footer", "colophon", "bottom"),
            "side": ("sidebar", "widget-area", "right-rail", "secondary", "related-posts"), "ad": ("ad", "ads", "advert", "sponsored", "promo-box", "ad-slot"), "note": ("cookie-notice", "gdpr-consent", "alert", "notice", "popup"),
            "form": ("newsletter", "search-form", "subscribe", "login", "signup"), "talk": ("comments", "comment-list", "discussion", "respond", "disqus_thread"), "one": ("comment", "reply", "comment-body", "c-item"), "share": ("share", "social", "share-buttons", "follow-us"),
            "main": ("content", "main", "main-content", "page-body"), "article": ("article", "post", "entry-content", "story", "article-body", "post-content", "text"), "wrap": ("container", "wrapper", "inner", "row", "layout", "site"),
        }[kind]
        if self.r.random() < 0.12:
            return ""
        name = self.r.choice(names) if self.named else "".join(self.r.choice("abcdefgkxyz0123456789") for _ in range(6))
        return f' {self.r.choice(("class", "class", "id"))}="{name}"'

    def links(self, a: int, b: int, flat: bool = False) -> None:
        n = self.r.randint(a, b)
        if flat:
            self.out.append(" | ".join(f'<a href="/{i}">{self.words(1, 3)}</a>' for i in range(n)))
        else:
            self.out.append("<ul>" + "".join(f'<li><a href="/{i}">{self.words(1, 3)}</a></li>' for i in range(n)) + "</ul>")

    def boiler(self, kind: str) -> None:
        r, o = self.r, self.out
        tag = {"nav": ("nav", "nav", "div"), "header": ("header", "div"), "footer": ("footer", "footer", "div"), "side": ("aside", "div", "section"), "note": ("div", "section", "dialog"), "talk": ("section", "div"), "form": ("form", "div", "section")}.get(kind, ("div", "aside"))
        tag = r.choice(tag)
        o.append(f"<{tag}{self.mark(kind)}>")
        if kind == "nav":
            self.links(2, 9, r.random() < 0.25)
        elif kind == "header":
            o.append(r.choice((f"<h1>{self.words(1, 3)}</h1>", f"<p>{self.words(2, 6)}</p>", f'<a href="/">{self.words(1, 2)}</a>', f"<div>{self.words(1, 4)}</div>")))
            if r.random() < 0.6:
                self.boiler("nav")
        elif kind == "footer":
            o.append(r.choice((f"<p>&copy; 20{r.randint(10, 29)} {self.words(1, 4)}. All rights reserved.</p>", f"&copy; {self.words(2, 6)}", self.words(2, 9), f"<p>{self.sentences(1, 2)}</p>")))
            if r.random() < 0.5:
                self.links(2, 6, r.random() < 0.5)
        elif kind == "side":
            for _ in range(r.randint(1, 3)):
                o.append(f"<h3>{self.words(1, 3)}</h3>")
                self.links(2, 7) if r.random() < 0.7 else o.append(f"<p>{self.sentences(1, 2)}</p>")
        elif kind == "ad":
            o.append(r.choice((self.sentences(1, 2), f"<p>{self.sentences(1, 3)}</p>", f'<a href="/buy">{self.words(2, 6)}</a>', f"<p>{self.words(2, 5)}</p><a href='/x'>{self.words(1, 2)}</a>")))
        elif kind == "note":
            o.append(f"<p>{self.sentences(1, 2)}</p><button>{self.words(1, 2)}</button>" if r.random() < 0.7 else self.sentences(1, 2))
        elif kind == "form":
            inner = f"<label>{self.words(1, 3)}</label><input name=q><button>{self.words(1, 2)}</button>"
            o.append(f"<p>{self.words(3, 9)}</p>" * (r.random() < 0.5) + (inner if tag == "form" else f"<form>{inner}</form>"))
        elif kind == "talk":
            o.append(f"<h{r.choice('234')}>{self.words(1, 3)}</h3>" if r.random() < 0.7 else "")
            one = r.choice(("div", "li", "article"))
            o.append("<ol>" if one == "li" else "")
            for _ in range(r.randint(1, 6)):
                o.append(f"<{one}{self.mark('one')}>" + (f"<b>{self.words(1, 2)}</b>" if r.random() < 0.5 else f"<div>{self.words(1, 2)}</div>") + r.choice((f"<p>{self.sentences(1, 4)}</p>", f"<div>{self.sentences(1, 3)}</div>", self.sentences(1, 3))) + f"</{one}>")
            o.append("</ol>" if one == "li" else "")
            if r.random() < 0.4:
                self.boiler("form")
        elif kind == "share":
            self.links(2, 5, r.random() < 0.5)
        o.append(f"</{tag}>")

    def block(self) -> None:
        r, o = self.r, self.out
        k, x = r.random(), r.random()
        if k < 0.68:
            text = self.sentences(1, 6) if r.random() < 0.8 else self.words(1, 5).capitalize() + r.choice(("", ".", "."))
            if x < 0.25:
                text = f"<b>{text}<br>" if x < 0.06 else f"{self.sentences(1, 2)} <a href='/z'>{self.words(1, 3)}</a> {text}"
            o.append(f"<p data-keep>{text}" + "</p>" * (r.random() < 0.93))
        elif k < 0.78:
            o.append(f"<h{r.choice('23')} data-keep>{self.words(1, 6)}</h2>")
        elif k < 0.86:
            t = r.choice(("ul", "ol"))
            o.append(f"<{t} data-keep>" + "".join(f"<li data-keep>{self.words(2, 14) if x < 0.5 else self.sentences(1, 2)}</li>" for _ in range(r.randint(2, 6))) + f"</{t}>")
        elif k < 0.91:
            o.append(f"<blockquote data-keep><p data-keep>{self.sentences(1, 3)}</p></blockquote>" if x < 0.6 else f"<blockquote data-keep>{self.sentences(1, 2)}</blockquote>")
        elif k < 0.94:
            o.append(f"<pre data-keep>{self.words(4, 20)}</pre>")
        elif k < 0.97:
            o.append("<table data-keep>" + "".join("<tr data-keep>" + "".join(f"<td data-keep>{self.words(1, 4)}</td>" for _ in range(3)) + "</tr>" for _ in range(r.randint(2, 4))) + "</table>")
        else:
            o.append(f"<figure data-keep><img src=x><figcaption data-keep>{self.words(3, 10)}</figcaption></figure>")

    def page(self) -> str:
        r, o = self.r, self.out
        o.append(f'<!DOCTYPE html><html><head><meta charset="utf-8"><title>{self.words(2, 6)}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head><body>')
        wraps = r.randint(0, 2)
        if r.random() < 0.3:
            self.boiler("note")
        if r.random() < 0.55:
            self.boiler("header")
        if r.random() < 0.7:
            self.boiler("nav")
        if r.random() < 0.3:
            self.boiler("ad")
        for _ in range(wraps):
            o.append(f"<div data-keep{self.mark('wrap')}>")
        if r.random() < 0.25:
            self.boiler("side")
        outer = r.choice(("", "", "main", "div", "section"))
        if outer:
            o.append(f"<{outer} data-keep{self.mark('main')}>")
        inner = r.choice(("article", "article", "div", "section"))
        o.append(f"<{inner} data-keep{self.mark('article') if inner != 'article' or r.random() < 0.4 else ''}>")
        if r.random() < 0.85:
            h = f"<h1 data-keep>{self.words(1, 9) if r.random() < 0.7 else self.word().capitalize() + "."}</h1>"
            o.append(f"<header data-keep>{h}" + f"<p data-keep>{self.words(2, 6)}</p>" * (r.random() < 0.2) + "</header>" if r.random() < 0.15 else h)
        n = r.choice((1, 1, 2, 3, 4, 6, 9, 14))
        for i in range(n):
            self.block()
            if r.random() < 0.07:
                self.boiler(r.choice(("ad", "ad", "form", "share", "side", "note")))
        if r.random() < 0.15:
            self.boiler("share")
        if r.random() < 0.1:
            self.boiler("talk")
        o.append(f"</{inner}>")
        if r.random() < 0.35:
            self.boiler("talk")
        if r.random() < 0.25:
            self.boiler(r.choice(("side", "ad", "form", "share")))
        if outer:
            o.append(f"</{outer}>")
        if r.random() < 0.35:
            self.boiler("side")
        o.append("</div>" * wraps)
        if r.random() < 0.8:
            self.boiler("footer")
        if r.random() < 0.15:
            self.boiler("note")
        o.append("</body></html>")
        return "".join(o)


def generated(n: int, seed: int) -> list[str]:
    r = random.Random(seed)
    return [_Writer(r).page() for _ in range(n)]


def labelled(source: str) -> tuple[Page, np.ndarray]:
    """A generated page as extraction sees it, and which of its blocks hold main text."""
    marks: list[bool] = []
    for m in _TAG.finditer(re.sub(r"<script>.*?</script>", "", source)):
        if m[2] and not m[1] and m[2].lower() in BLOCKS and m[2] not in VOID and m[2] != "html":
            marks.append("data-keep" in m[3])
    page = read(source.replace(" data-keep", ""))
    keep = np.array([True, *marks])
    for i, t in enumerate(page.tag):
        if t == "body":
            keep[i] = True
    assert len(keep) == len(page.tag)
    return page, keep


TRAINING_PAGES, TRAINING_SEED = 2000, 11
FITTED = Path(__file__).with_name("html_trees.json")
_model: list[Trees] = []


def fit() -> Trees:
    """Trees fitted on TRAINING_PAGES generated pages; half a minute of one core."""
    pairs = [labelled(s) for s in generated(TRAINING_PAGES, TRAINING_SEED)]
    x, _, _ = features([p for p, _ in pairs])
    return Trees().fit(x, np.concatenate([k for _, k in pairs]).astype(float))


def store(trees: Trees, path: Path = FITTED) -> None:
    """Write fitted trees; ``python -m corridor.llm.htmlextract`` does it for those of ``fit``."""
    values = {"depth": trees.depth, "start": trees.start, "feature": trees.feature.tolist(), "edge": [[None if np.isinf(v) else float(v) for v in row] for row in trees.edge], "leaf": [[round(v, 9) for v in row] for row in trees.leaf.tolist()]}
    path.write_text(json.dumps(values))


def model() -> Trees:
    """The fitted trees that come with the package."""
    if not _model:
        values = json.loads(FITTED.read_text())
        trees = Trees(rounds=len(values["leaf"]), depth=values["depth"])
        trees.start, trees.feature, trees.leaf = values["start"], np.array(values["feature"]), np.array(values["leaf"])
        trees.edge = np.array([[np.inf if v is None else v for v in row] for row in values["edge"]], np.float32)
        _model.append(trees)
    return _model[0]


def main_texts(sources: list[str | None], trees: Trees) -> list[str]:
    """Main text of each page: its kept blocks in order, one line each; empty for null and empty pages."""
    pages = [read(s or "") for s in sources]
    x, parent, first = features(pages)
    keep = decode(trees.log_odds(x), parent, first)
    out = []
    for p, a in zip(pages, first, strict=False):
        head = {i for i, t in enumerate(p.tag) if t == "head"}
        out.append("\n".join(text for b, text in p.segments if keep[a + b] and b not in head))
    return out


def extract(pages: DataFrame, trees: Trees | None = None, step: int = 512) -> DataFrame:
    """page_id, url, text and n_chars of every row of ``pages(page_id, url, html)``, from the whole html.

    Character references are decoded, white space inside a block becomes one space, blocks are joined by a line feed.  A null or empty
    html, or one without main text, gives an empty text.  Ids and urls are passed on as they are, null or repeated.  An empty table gives
    an empty one; other columns are left out, whatever their names.
    """
    fitted = trees or model()

    def run(batches):
        for batch in small(batches):
            sources = batch.column(2).to_pylist()
            texts: list[str] = []
            for a in range(0, len(sources), step):
                texts += main_texts(sources[a : a + step], fitted)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = bounded(pages).select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(tidy(run), "page_id long, url string, text string, n_chars long")


if __name__ == "__main__":
    store(fit())
