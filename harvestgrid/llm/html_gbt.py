"""Main text of web pages by gradient-boosted trees over the nodes of the page.

A tolerant parser builds the tree (void and raw-text elements, implied end tags,
unclosed and cut-off markup). Every block-level node gets features of its subtree
(text, links, densities, punctuation), of its attributes (learned weights of the tokens of class, id and role,
its own and its ancestors'), of its depth and of its siblings. Boosted trees give the
log-odds that main text lies in the node. Decoding is hierarchical: by
dynamic programming over the tree it picks the likeliest labelling in which no node
below a rejected one is accepted and no accepted node is left without text of its
own or an accepted child.

The trees are trained here, on pages that a generator composes from invented words
in many layouts; there is no table of labelled pages to learn from. The model is
the same in every run.

Defined results: null, empty and text-free pages give the empty string; a page
without markup is its own main text. Character references are decoded, white space
inside a block becomes one space, blocks are joined in page order by a newline.
"""

from __future__ import annotations

import html as _html
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: What follows a tag's name. A quote opens a value only right after the equals sign, and a value in quotes has any length; a
#: quote that is never closed has no other of its kind behind it, so it costs one scan to the end and then counts as a plain sign.
_INSIDE = r"(?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+'|[^\s>]*+))*+"
_MARK = re.compile(rf"<!--(?:.*?-->|>)|<[!?][^>]*+>|<(/?)([a-zA-Z][^\s/>]*+)({_INSIDE})>", re.DOTALL)
_ATTR = re.compile(r"(class|id|role|itemprop|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.IGNORECASE)
_TOKEN = re.compile(r"[a-z]+")
#: Element sets of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe xmp noembed noframes".split())
_TO_THE_END = frozenset(("script", "style", "textarea", "title"))
#: Ordinary nested elements whose text is not shown as text of the page.
HIDDEN = frozenset("svg template select button noscript".split())
_PAIRS = re.compile(rf"<(/?)(svg|template|select|button|noscript)(?=[\s/>])({_INSIDE})>", re.IGNORECASE)
BLOCK = frozenset(
    "html body address article aside blockquote center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hgroup hr li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption ins".split()
)
_CLOSES_P = BLOCK - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "ins"}
_SAME = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}}
#: Start tags that end a drawing, unless they are in one of its elements for text.
_OUT_OF_SVG = BLOCK | frozenset("b big br code em i img font s small span strike strong sub sup tt u var".split())
_IN_SVG = frozenset(("foreignobject", "desc", "title"))
_HEADS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))


def _closed(source: str) -> set[int]:
    """Places of the start tags of hidden elements that have an end tag of their own; only drawings and templates nest."""
    found, open_ = set(), {name: [] for name in HIDDEN}
    for m in _PAIRS.finditer(source):
        name = m[2].lower()
        if m[1]:
            if open_[name]:
                found.add(open_[name].pop())
        elif not m[3].endswith("/"):
            if name not in ("svg", "template"):
                open_[name].clear()
            open_[name].append(m.start())
    return found


class Page:
    """Block nodes of one page in order, and its text runs."""

    __slots__ = ("tag", "parent", "attr", "depth", "runs", "tags", "links")

    def __init__(self, source: str | None):
        self.tag, self.parent, self.attr, self.depth = ["html"], [-1], [""], [0]
        #: [node, text, text inside links] of each run of text between block boundaries
        self.runs: list[list] = []
        self.tags, self.links = [0], [0]
        self._parse(source or "")

    def _parse(self, source: str) -> None:
        stack = [("html", 0)]  # open elements: name, nearest block node; -1 for what is inside a hidden element
        hidden: list[tuple[int, bool]] = []  # open hidden elements: place on the stack, whether an end tag follows
        closed: set[int] | None = None
        run: list[str] = []
        linked = at = link_open = 0
        runs = self.runs

        def flush():
            nonlocal linked
            if run:
                text = " ".join(_html.unescape("".join(run)).split())
                run.clear()
                if text:
                    runs.append([next(n for _, n in reversed(stack) if n >= 0), text, min(linked, len(text))])
            linked = 0

        def close(k):
            nonlocal link_open
            if any(n in BLOCK and node >= 0 for n, node in stack[k:]):
                flush()
            link_open -= sum(n == "a" and node >= 0 for n, node in stack[k:])
            del stack[k:]
            while hidden and hidden[-1][0] >= k:
                hidden.pop()

        last = source.rfind(">")
        while True:
            m = _MARK.search(source, at) if at <= last else None
            text = source[at : m.start()] if m else source[at:]
            if not m:  # what a cut-off page leaves of a tag is no text
                cut = re.search(r"<(?:/?[a-zA-Z]|!)[^<]*$", text)
                text = text[: cut.start()] if cut else text
            if text and not hidden:
                run.append(text)
                if link_open:
                    linked += len(text.strip())
            if not m:
                break
            at = m.end()
            if m[2] is None:
                continue
            name = m[2].lower()
            # Nothing inside a hidden element that has its end tag reaches what is around it.
            wall = next((k for k, ends in reversed(hidden) if ends), 0)
            if m[1]:
                k = next((k for k in range(len(stack) - 1, max(wall, 1) - 1, -1) if stack[k][0] == name), 0)
                if k:
                    close(k)
                continue
            if wall and stack[wall][0] == "svg" and name in _OUT_OF_SVG and not any(n in _IN_SVG for n, _ in stack[wall:]):
                close(wall)
                wall = next((k for k, ends in reversed(hidden) if ends), 0)
            if hidden and not wall and (name in BLOCK or name == stack[hidden[-1][0]][0]):
                close(hidden[0][0])  # a hidden element without end tag ends where a block begins
            drawn = any(stack[k][0] == "svg" for k, _ in hidden)
            if name in RAW and not (drawn and (m[3].endswith("/") or name == "title")):
                end = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>", re.IGNORECASE).search(source, at)
                if end or name in _TO_THE_END:
                    at = end.end() if end else len(source)
                if not hidden:
                    self.tags[stack[-1][1]] += 1
                continue
            if hidden:
                if name not in VOID and not m[3].endswith("/"):
                    if name in HIDDEN:
                        hidden.append((len(stack), m.start() in closed))
                    stack.append((name, -1))
                continue
            if name == "br":
                run.append(" ")
            if name in HIDDEN:
                self.tags[stack[-1][1]] += 1
                if not m[3].endswith("/"):
                    closed = _closed(source) if closed is None else closed
                    hidden.append((len(stack), m.start() in closed))
                    stack.append((name, -1))
                continue
            if name in _CLOSES_P:
                k = next((k for k in range(len(stack) - 1, 0, -1) if stack[k][0] == "p"), 0)
                if k:
                    flush()
                    close(k)
            if name in _SAME:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k][0] in _SCOPE.get(name, ()):
                        break
                    if stack[k][0] in _SAME[name]:
                        flush()
                        close(k)
                        break
            node = stack[-1][1]
            if name in BLOCK:
                flush()
                if name in ("html", "body") and any(n == name for n, _ in stack[1:]):
                    continue
                self.tag.append(name)
                self.parent.append(node)
                self.depth.append(self.depth[node] + 1)
                attr = m[3]
                self.attr.append(" ".join(a[1] or a[2] or a[3] for a in _ATTR.findall(attr)).lower() if "=" in attr else "")
                self.tags.append(0)
                self.links.append(0)
                node = len(self.tag) - 1
            else:
                self.tags[node] += 1
                self.links[node] += name == "a"
            if name not in VOID and not m[3].endswith("/"):
                stack.append((name, node))
                link_open += name == "a"
        flush()


#: Node kinds that are told apart; what they and the attribute tokens mean is learned.
KINDS = "html body div section article main nav header footer aside ul ol li p h1 h2 h3 form table td blockquote pre figure figcaption dl ins".split()
_KIND = {k: i for i, k in enumerate(KINDS)}
_NUMERIC = 24
#: Least and most of the weights of a node's own attribute tokens, and of those of the nodes above it.
_ATTRS = 2
N_FEATURES = _NUMERIC + 2 * len(_KIND) + 2 * _ATTRS
#: Pages that a token has to be met in to get a weight.
TOKEN_PAGES = 5


def token_weights(pages: list[Page], truth: list[np.ndarray]) -> dict[str, float]:
    """Log-odds that main text lies in a node, for each token of class, id, role and label, by pages."""
    seen: dict[str, list[int]] = {}
    base = [0, 0]
    for page, hit in zip(pages, truth):
        met = {(t, bool(h)) for attr, h in zip(page.attr, hit) if attr for t in _TOKEN.findall(attr)}
        for t, h in met:
            seen.setdefault(t, [0, 0])[h] += 1
            base[h] += 1
    prior = np.log((base[1] + 1) / (base[0] + 1))
    return {t: float(np.log((yes + 1) / (no + 1)) - prior) for t, (no, yes) in sorted(seen.items()) if no + yes >= TOKEN_PAGES}


def node_features(page: Page, tokens: dict[str, float]) -> np.ndarray:
    """One row per block node; ``tokens`` are the learned weights of attribute tokens."""
    n = len(page.tag)
    x = np.zeros((n, N_FEATURES), dtype=np.float32)
    own, linked, runs, commas, ends, longest, words = (np.zeros(n) for _ in range(7))
    start = np.full(n, np.inf)
    seen = 0
    for node, text, link in page.runs:
        own[node] += len(text)
        linked[node] += link
        runs[node] += 1
        commas[node] += text.count(",")
        ends[node] += text.count(".") + text.count("!") + text.count("?")
        longest[node] = max(longest[node], len(text))
        words[node] += text.count(" ") + 1
        start[node] = min(start[node], seen)
        seen += len(text)
    total, t_link, t_runs, t_comma, t_end, t_words = (a.copy() for a in (own, linked, runs, commas, ends, words))
    tags, links = np.array(page.tags, float) + 1, np.array(page.links, float)
    parent = page.parent
    kids, place = np.zeros(n), np.zeros(n)
    for k in range(1, n):
        place[k] = kids[parent[k]]
        kids[parent[k]] += 1
    paras = np.array([t == "p" for t in page.tag], float)
    for k in range(n - 1, 0, -1):
        p = parent[k]
        for a in (total, t_link, t_runs, t_comma, t_end, t_words, tags, links, paras):
            a[p] += a[k]
        longest[p] = max(longest[p], longest[k])
        start[p] = min(start[p], start[k])
    up = np.array(parent)
    up[0] = 0
    all_text = max(1.0, total[0])
    depth = np.array(page.depth, float)
    numbers = [
        np.log1p(total), np.log1p(own), np.log1p(longest), t_link / np.maximum(1, total), total / tags, np.log1p(t_runs), np.log1p(links),
        np.log1p(t_words), t_comma / np.maximum(1, t_words), t_end / np.maximum(1, t_words), total / all_text, total / np.maximum(1, total[up]),
        depth, place, kids[up], kids, np.where(np.isfinite(start), start, all_text) / all_text, np.log1p(paras), np.log1p(total[up]), t_link[up] / np.maximum(1, total[up]),
        np.log1p(longest[up]), np.log1p(total / np.maximum(1, t_runs)), place / np.maximum(1, kids[up]), np.log1p(own / np.maximum(1, runs)),
    ]
    x[:, :_NUMERIC] = np.stack(numbers, axis=1)
    a, b = _NUMERIC, _NUMERIC + len(_KIND)
    c, d = b + len(_KIND), b + len(_KIND) + _ATTRS
    for k in range(n):
        p = parent[k]
        if k:  # what any ancestor is
            x[k, b:c] = x[p, b:c]
            x[k, d] = min(x[p, c], x[p, d])
            x[k, d + 1] = max(x[p, c + 1], x[p, d + 1])
            kind = _KIND.get(page.tag[p])
            if kind is not None:
                x[k, b + kind] = 1
        kind = _KIND.get(page.tag[k])
        if kind is not None:
            x[k, a + kind] = 1
        if page.attr[k]:
            known = [tokens[t] for t in _TOKEN.findall(page.attr[k]) if t in tokens]
            if known:
                x[k, c], x[k, c + 1] = min(0.0, *known), max(0.0, *known)
    return x


class BoostedTrees:
    """Logistic boosting of complete binary trees over quantile-binned features."""

    def __init__(self, trees: int = 120, depth: int = 5, rate: float = 0.25, bins: int = 24, ridge: float = 1.0, share: float = 0.35):
        self.trees, self.depth, self.rate, self.bins, self.ridge, self.share = trees, depth, rate, bins, ridge, share

    def _binned(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(x.shape, dtype=np.uint8)
        for f, cuts in enumerate(self.cuts):
            if len(cuts):
                out[:, f] = np.searchsorted(cuts, x[:, f], side="right")
        return out

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None) -> BoostedTrees:
        weight = np.ones(len(y)) if weight is None else weight
        self.cuts = []
        for f in range(x.shape[1]):
            values = np.unique(x[:, f])
            if len(values) > self.bins:
                values = np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.bins + 1)[1:-1]))
                self.cuts.append(values)
            else:
                self.cuts.append((values[1:] + values[:-1]) / 2)
        used = np.array([f for f, c in enumerate(self.cuts) if len(c)])
        binned = self._binned(x)[:, used]
        width = int(binned.max()) + 1
        flat = binned.astype(np.int64) + np.arange(len(used)) * width
        p0 = (weight * y).sum() / weight.sum()
        self.base = float(np.log(p0 / (1 - p0)))
        score = np.full(len(y), self.base)
        self.feature, self.cut, self.leaf = [], [], []
        rng = np.random.default_rng(5)
        every, every_flat = binned, flat
        for _ in range(self.trees):
            # Each tree sees a share of the rows.
            rows = np.nonzero(rng.random(len(y)) < self.share)[0]
            binned, flat = every[rows], every_flat[rows]
            p = 1 / (1 + np.exp(-score[rows]))
            g, h = weight[rows] * (y[rows] - p), weight[rows] * p * (1 - p)
            node = np.zeros(len(rows), dtype=np.int64)
            features, cuts = np.zeros(2**self.depth - 1, dtype=np.int64), np.full(2**self.depth - 1, 255)
            for level in range(self.depth):
                count = 2**level
                size = len(used) * width
                slot = (node[:, None] * size + flat).ravel()
                sums = [np.bincount(slot, np.repeat(v, len(used)), minlength=count * size).reshape(count, len(used), width) for v in (g, h)]
                left = [np.cumsum(s, axis=2) for s in sums]
                whole = [s[:, :, -1:] for s in left]
                gain = sum((a**2) / (b + self.ridge) for a, b in ((left[0], left[1]), (whole[0] - left[0], whole[1] - left[1]))) - whole[0] ** 2 / (whole[1] + self.ridge)
                gain = gain.reshape(count, -1)
                best = gain.argmax(axis=1)
                for k in range(count):
                    if gain[k, best[k]] > 1e-6:
                        features[count - 1 + k], cuts[count - 1 + k] = used[best[k] // width], best[k] % width
                own = node + count - 1
                f_at = np.searchsorted(used, features[own])
                f_at = np.minimum(f_at, len(used) - 1)
                node = node * 2 + (binned[np.arange(len(rows)), f_at] > cuts[own])
            leaves = 2**self.depth
            value = self.rate * np.bincount(node, g, minlength=leaves) / (np.bincount(node, h, minlength=leaves) + self.ridge)
            node = np.zeros(len(y), dtype=np.int64)
            for level in range(self.depth):
                own = node + 2**level - 1
                node = node * 2 + (every[np.arange(len(y)), np.minimum(np.searchsorted(used, features[own]), len(used) - 1)] > cuts[own])
            score += value[node]
            self.feature.append(features)
            self.cut.append(cuts)
            self.leaf.append(value)
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        """Log-odds of each row."""
        binned = self._binned(x)
        rows = np.arange(len(x))
        out = np.full(len(x), self.base)
        for features, cuts, value in zip(self.feature, self.cut, self.leaf):
            node = np.zeros(len(x), dtype=np.int64)
            for level in range(self.depth):
                own = node + 2**level - 1
                node = node * 2 + (binned[rows, features[own]] > cuts[own])
            out += value[node]
        return out


def decode(page: Page, odds: np.ndarray) -> np.ndarray:
    """The likeliest labelling without contradictions: accepted nodes form a tree from the root down."""
    n = len(page.tag)
    has_text = np.zeros(n, dtype=bool)
    for node, _, _ in page.runs:
        has_text[node] = True
    children: list[list[int]] = [[] for _ in range(n)]
    for k in range(1, n):
        children[page.parent[k]].append(k)
    # The outermost nodes hold every page, so what they are says nothing.
    odds = np.where([t in ("html", "body") for t in page.tag], 0.0, odds) if len(page.tag) > 1 else odds
    value = np.zeros(n)
    chosen: list[list[int]] = [[] for _ in range(n)]
    for k in range(n - 1, -1, -1):
        good = [c for c in children[k] if value[c] > 0]
        if not good and not has_text[k]:
            able = [c for c in children[k] if np.isfinite(value[c])]
            if not able:
                value[k] = -np.inf  # nothing to accept inside
                continue
            good = [max(able, key=lambda c: (value[c], -c))]
        chosen[k] = good
        value[k] = odds[k] + sum(value[c] for c in good)
    keep = np.zeros(n, dtype=bool)
    if value[0] > 0:
        open_ = [0]
        while open_:
            k = open_.pop()
            keep[k] = True
            open_ += chosen[k]
    return keep


# ---- pages to train on -------------------------------------------------------------------

_SYLLABLES = "an ber co da el fin gar hu in jo ka lem mo ner os pa qui ra st tu ur vel wo xi yo zen th ing ou ex il ma".split()


def compose(rng: random.Random) -> tuple[str, list[str]]:
    """A page and the blocks of its main text."""

    def word():
        return "".join(rng.choice(_SYLLABLES) for _ in range(rng.choice((1, 1, 2, 2, 3))))

    def sentence(lo=1, hi=18):
        w = [word() for _ in range(rng.randint(lo, hi))]
        if len(w) > 6 and rng.random() < 0.5:
            w[rng.randrange(len(w) - 1)] += ","
        return " ".join(w).capitalize() + rng.choice((".", ".", ".", "!", "?", ""))

    def prose(lo=1, hi=8):
        return " ".join(sentence() for _ in range(rng.randint(lo, hi)))

    # Some pages have class names that say nothing, on everything.
    obscure = rng.random() < 0.15

    def attrs(*names):
        if obscure:
            return f' class="{word()[:2]}-{rng.randint(16, 4095):x}"' if rng.random() < 0.7 else ""
        if not names or rng.random() < 0.1:
            return ""
        name = rng.choice(names)
        extra = rng.choice(("", "", f" {word()}", f"-{rng.randint(1, 9)}", f" {word()}-{word()}"))
        return f' {rng.choice(("class", "class", "id"))}="{name}{extra}"'

    def links(n, sep="li"):
        one = lambda: f'<a href="/{word()}">{" ".join(word() for _ in range(rng.randint(1, 4)))}</a>'
        if sep == "li":
            return "<ul>" + "".join(f"<li>{one()}</li>" for _ in range(n)) + "</ul>"
        return sep.join(one() for _ in range(n))

    def boiler(kind):
        tag = rng.choice(("div", "div", "section"))
        if kind == "menu":
            form = rng.randrange(4)
            if form == 0:
                return f"<nav{attrs('menu', 'main-nav', 'navbar')}>{links(rng.randint(2, 9))}</nav>"
            if form == 1:
                return f"<div{attrs('menu', 'nav', 'navigation', 'top-menu', 'breadcrumb', 'breadcrumbs')}>{links(rng.randint(2, 9), rng.choice((' | ', ' &gt; ', ' ')))}</div>"
            if form == 2:
                return links(rng.randint(2, 12)).replace("<ul>", f"<ul{attrs('menu', 'nav', 'pagination', 'pager')}>")
            return f'<div role="navigation">{links(rng.randint(2, 9))}</div>'
        if kind == "header":
            inner = rng.choice((f"<h1><a href='/'>{word()}</a></h1>", f"<p>{sentence(1, 5)}</p>", f"<div>{word()} {word()}</div>", f"<h2>{sentence(1, 4)}</h2><p>{sentence(2, 8)}</p>"))
            if rng.random() < 0.5:
                return f"<header{attrs('site-header', 'masthead', 'header', 'top')}>{inner}{links(3) if rng.random() < 0.5 else ''}</header>"
            return f"<div{attrs('header', 'site-header', 'masthead', 'top-bar')}>{inner}</div>"
        if kind == "ad":
            return f"<{tag}{attrs('ad', 'ads', 'advert', 'advertisement', 'sponsored', 'promo', 'banner', 'ad-slot', 'sponsor', 'partner', 'promotion')}>{rng.choice((prose(1, 2), sentence(), links(1, ''), f'<p>{prose(1, 3)}</p>'))}</{tag}>"
        if kind == "notice":
            return f"<{tag}{attrs('cookie', 'cookie-notice', 'consent', 'notice', 'alert', 'gdpr-banner', 'newsletter', 'subscribe', 'popup', 'modal')}><p>{prose(1, 2)}</p>{rng.choice(('', '<button>ok</button>', links(1, '')))}</{tag}>"
        if kind == "sidebar":
            inner = "".join(rng.choice((f"<h3>{sentence(1, 3)}</h3>{links(rng.randint(2, 7))}", f"<p>{prose(1, 3)}</p>", f"<div{attrs('widget')}>{prose(1, 2)}</div>")) for _ in range(rng.randint(1, 4)))
            if rng.random() < 0.5:
                return f"<aside{attrs('sidebar', 'related', 'widget')}>{inner}</aside>"
            return f"<div{attrs('sidebar', 'aside', 'secondary', 'related', 'recommended', 'widget-area', 'side')}>{inner}</div>"
        if kind == "form":
            return f"<form{attrs('search', 'login', 'signup', 'search-form', 'subscribe')}><p>{sentence(1, 8)}</p><label>{word()}</label><input type=text name=q><div>{sentence(1, 4)}</div><button>{word()}</button></form>"
        if kind == "comments":
            body = "".join(
                rng.choice((
                    f"<div{attrs('comment', 'comment-body', 'reply')}><p>{prose(1, 5)}</p></div>", f"<li{attrs('comment')}><b>{word()}</b><p>{prose(1, 4)}</p></li>",
                    f"<article{attrs('comment')}><h4>{word()}</h4><p>{prose(1, 4)}</p></article>",
                ))
                for _ in range(rng.randint(1, 6))
            )
            return f"<{tag}{attrs('comments', 'comment-list', 'discussion', 'comments-area', 'respond', 'disqus', 'reviews', 'feedback')}><h3>{sentence(1, 3)}</h3>{body}</{tag}>"
        if kind == "share":
            return f"<{tag}{attrs('share', 'social', 'tags', 'post-meta', 'share-buttons')}>{links(rng.randint(2, 5), ' ')}</{tag}>"
        inner = rng.choice((f"&copy; {word()} &middot; {prose(1, 2)}", f"<p>&copy; 2020 {prose(1, 2)}</p>{links(4)}", prose(1, 3), f"{links(5, ' | ')}"))
        if rng.random() < 0.7:
            return f"<footer{attrs('footer', 'site-footer', 'colophon')}>{inner}</footer>"
        return f"<div{attrs('footer', 'site-footer', 'bottom', 'copyright', 'legal')}>{inner}</div>"

    def code():
        return rng.choice(("", f"<style>.{word()}{{color:#{rng.randint(100, 999)}}}</style>", f"<script>{word()}({rng.randint(0, 9)} &lt; 2)</script>", f"<link rel=icon href=/{word()}.ico>"))

    blocks: list[str] = []

    def keep(text):
        text = " ".join(_html.unescape(re.sub(r"<br>|<[^>]*>", lambda m: " " if m[0] == "<br>" else "", text)).split())
        if text:
            blocks.append(text)

    def styled(text):
        w = text.split(" ")
        if len(w) > 3 and rng.random() < 0.4:
            k = rng.randrange(len(w) - 1)
            name = rng.choice(("b", "i", "em", "strong", "span", 'a href="/x"', "code"))
            w[k] = f"<{name}>{w[k]}</{name.split(' ')[0]}>"
        if rng.random() < 0.1:
            w.insert(len(w) // 2, "<br>")
        return " ".join(w).replace(" et ", " &amp; ")

    def content():
        form = rng.random()
        if form < 0.68:
            t = styled(prose(1, rng.choice((1, 2, 8, 20))))
            keep(t)
            return f"<p{attrs('text', 'intro') if obscure or rng.random() < 0.1 else ''}>{t}" + ("</p>" if rng.random() < 0.9 else "")
        if form < 0.76:
            t = sentence(1, 8)
            keep(t)
            return _head(rng, t)
        if form < 0.84:
            items = [styled(rng.choice((sentence(), prose(1, 2)))) for _ in range(rng.randint(2, 6))]
            for t in items:
                keep(t)
            name = rng.choice(("ul", "ol"))
            return f"<{name}>" + "".join(f"<li>{t}</li>" for t in items) + f"</{name}>"
        if form < 0.90:
            t = styled(prose(1, 3))
            keep(t)
            return f"<blockquote>{t}</blockquote>" if rng.random() < 0.5 else f"<blockquote><p>{t}</p></blockquote>"
        if form < 0.93:
            t = sentence(2, 9)
            keep(t)
            return f'<figure><img src="/{word()}.png" alt="{word()}"><figcaption>{t}</figcaption></figure>'
        if form < 0.95:
            t = styled(prose(1, 4))
            keep(t)
            return f"<div>{t}</div>"
        if form < 0.965:
            pairs = [(sentence(1, 3), styled(prose(1, 2))) for _ in range(rng.randint(1, 5))]
            for t in (x for pair in pairs for x in pair):
                keep(t)
            return "<dl>" + "".join(f"<dt>{x}<dd>{y}" for x, y in pairs) + "</dl>"
        if form < 0.975:
            t = prose(1, 4)
            keep(t)
            return f"<pre>{t}</pre>"
        cells = [[sentence(1, 4) for _ in range(3)] for _ in range(rng.randint(2, 4))]
        for r in cells:
            for t in r:
                keep(t)
        return "<table>" + "".join("<tr>" + "".join(f"<td>{t}</td>" for t in r) + "</tr>" for r in cells) + "</table>"

    def article():
        parts = []
        if rng.random() < 0.8:
            t = sentence(1, 12)
            keep(t)
            parts.append(f"<h1>{t}</h1>")
            if rng.random() < 0.3:
                t = sentence(1, 12)
                keep(t)
                parts.append(rng.choice((f"<h2>{t}</h2>", f"<div>{t}</div>", f"<p><strong>{t}</strong></p>", f"<p><em>{t}</em>")))
        for _ in range(rng.choice((1, 2, 4, 8, 20))):
            parts.append(content())
            if rng.random() < 0.12:
                parts.append(boiler(rng.choice(("ad", "ad", "notice", "share", "form", "sidebar"))))
        if len(parts) > 1 and rng.random() < 0.3:  # the text in parts of its own
            cut = rng.randrange(1, len(parts))
            name = rng.choice(("div", "div", "section"))
            parts = [*parts[:cut], f"<{name}{attrs() if rng.random() < 0.5 else ''}>{''.join(parts[cut:])}</{name}>"]
        body = "".join(parts)
        wrap = rng.random()
        if wrap < 0.06:
            return body
        if wrap < 0.45:
            return f"<article{attrs('post', 'entry', 'article', 'story', 'hentry') if rng.random() < 0.5 else ''}>{body}</article>"
        if wrap < 0.60:
            return f"<main{attrs('content', 'main')}>{body}</main>"
        if wrap < 0.90:
            return f"<div{attrs('content', 'article', 'post', 'entry-content', 'article-body', 'story', 'main', 'text', 'post-content')}>{body}</div>"
        if wrap < 0.95:
            return f"<section{attrs('content', 'post', 'article')}>{body}</section>"
        return f"<table><tr><td>{body}</td></tr></table>"

    kind = rng.random()
    if kind < 0.03:
        t = prose(1, 6)
        keep(t)
        return t, blocks
    if kind < 0.08:  # a fragment: content alone
        return "".join(content() for _ in range(rng.randint(1, 6))), blocks
    if kind < 0.11:  # a page without main text
        return "".join(boiler(rng.choice(("menu", "header", "ad", "footer", "form", "notice"))) for _ in range(rng.randint(1, 4))), blocks
    before = [boiler(k) for k in ("header", "menu", "notice", "ad", "form", "menu") if rng.random() < 0.45]
    main = article()
    after = [boiler(k) for k in ("share", "comments", "sidebar", "ad", "form", "menu", "footer", "footer") if rng.random() < 0.45]
    if rng.random() < 0.15:
        before.append(boiler("sidebar"))
    rng.shuffle(before)
    if rng.random() < 0.3:
        main = f"<div{attrs('container', 'wrapper', 'page', 'site', 'primary')}>{main}{after.pop(0) if after and rng.random() < 0.4 else ''}</div>"
    head = f"<head><meta charset=utf-8><title>{sentence(1, 8)}</title>{code()}</head>" if rng.random() < 0.8 else ""
    page = f"<!DOCTYPE html><html>{head}<body>{''.join(before)}{'<!-- x -->' if rng.random() < 0.5 else ''}{main}{''.join(after)}" + ("</body></html>" if rng.random() < 0.8 else "")
    return page, blocks


def _head(rng: random.Random, text: str) -> str:
    level = rng.choice((2, 2, 3, 4))
    return f"<h{level}>{text}</h{level}>"


def _targets(page: Page, blocks: list[str]) -> np.ndarray:
    """Nodes in whose subtree main text lies; runs are matched to blocks in order."""
    hit = np.zeros(len(page.tag), dtype=bool)
    at = 0
    for node, text, _ in page.runs:
        if at < len(blocks) and text == blocks[at]:
            at += 1
            while node >= 0 and not hit[node]:
                hit[node] = True
                node = page.parent[node]
    return hit


class Model:
    """Weights of attribute tokens, and the trees."""

    def __init__(self, tokens: dict[str, float], trees: BoostedTrees):
        self.tokens, self.trees = tokens, trees


@lru_cache(maxsize=2)
def trained(pages: int = 2400, seed: int = 11) -> Model:
    rng = random.Random(seed)
    held = [compose(rng) for _ in range(pages)]
    parsed = [Page(source) for source, _ in held]
    truth = [_targets(page, blocks) for page, (_, blocks) in zip(parsed, held)]
    tokens = token_weights(parsed, truth)
    x = np.concatenate([node_features(page, tokens) for page in parsed])
    return Model(tokens, BoostedTrees().fit(x, np.concatenate(truth).astype(float), (1 + x[:, 0]) / 4))


def extract(sources: list[str | None], model: Model) -> list[str]:
    """Main text of each page."""
    pages = [Page(s) for s in sources]
    if not pages:
        return []
    rows = [node_features(p, model.tokens) for p in pages]
    odds = model.trees.score(np.concatenate(rows))
    out, at = [], 0
    for p, x in zip(pages, rows):
        keep = decode(p, odds[at : at + len(x)])
        at += len(x)
        out.append("\n".join(text for node, text, _ in p.runs if keep[node]))
    return out


def _extract_batches(shared):
    def run(batches):
        model = shared.value
        for batch in slices(batches, 64):
            texts = extract(batch.column(2).to_pylist(), model)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"]
            )

    return run


def main_text(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """page_id, url, text, n_chars (code points) of every page."""
    shared = pages.sparkSession.sparkContext.broadcast(model or trained())
    picked = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return picked.mapInArrow(_extract_batches(shared), "page_id long, url string, text string, n_chars long")
