"""Main text of pages by a tree-structured graphical model over the page's elements.

A page becomes a tree: its block-level elements, and the runs of text between their borders as leaves. Every node
has a label, content or not, with a potential from its features (tag, class and id words; for text its
length, words, share in links). Each child is tied to its parent by a potential of both labels. Messages
passed from the leaves upward and from the root downward (sum-product) give the exact marginal of every node; text runs
of marginal a half or more are the page's text. Trees of a whole batch are worked on together, level by
level, as arrays.

The potentials maximise the likelihood of labelled pages. The labelled pages are made here from a seed
(``labelled_pages``): articles in varied containers among menus, headers, footers, side columns, notices,
adverts, forms and reader comments. Pages with labels of one's own can be given instead: ``data-y`` on an element labels all that it holds.

Cases: null, empty and text-free pages give empty text; markup that is never closed is closed at the end; scripts, styles,
comments and heads never give text; a page of any length is read once; repeated rows each get a row; an empty
table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import html
import math
import re
import zlib
from bisect import insort

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from commlens.llm.common import column_text, map_batches

FEATURES = 1 << 12
TRAIN_PAGES, TRAIN_STEPS = 160, 80
#: Nodes a level, on average, below which messages pass node by node instead of level by level.
THIN_LEVEL = 8

# Elements by their role in the HTML standard.
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_INLINE = {
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark",
    "q", "ruby", "rt", "rp", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr",
}
_UNREAD = ("script", "style", "title", "template", "noscript", "textarea", "iframe", "svg", "math", "object", "select")
#: A start tag of the key ends an open element of the values, up to the next element of the last set.
_ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_SCOPE = {"ul", "ol", "dl", "table", "tbody", "thead", "select", "body", "html", "article", "section", "div"}

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    rf"|<({'|'.join(_UNREAD)})\b[^>]*>.*?(?:</\1\s*>|\Z)"
    r"|<[!?][^>]*>?"
    r"|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+>|[^>]*>?)",
    re.S | re.I,
)
_NAMES = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_LABEL = re.compile(r"""\bdata-y\s*=\s*["']?([01])""", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


def _feature(name: str) -> int:
    return zlib.crc32(name.encode()) % FEATURES


_known: dict[str, list[int]] = {}


def _element_features(tag: str, attributes: str) -> list[int]:
    key = f"{tag} {attributes}"
    got = _known.get(key)
    if got is None:
        names = {"tag=" + tag}
        for m in _NAMES.finditer(attributes):
            names |= {"name=" + p.lower() for p in _PARTS.findall(m[2] or m[3] or m[4] or "")}
        if len(_known) > 50_000:
            _known.clear()
        got = _known[key] = [_feature(x) for x in sorted(names)]
    return got


def _text_features(text: str, linked: int, parent: str) -> list[int]:
    words = text.count(" ") + 1
    return [
        _feature(f"size={min(len(text).bit_length(), 10)}"),
        _feature(f"words={min(words.bit_length(), 7)}"),
        _feature(f"links={min(4, 4 * linked // len(text))}"),
        _feature(f"stop={text[-1] in '.!?'}"),
        _feature(f"under={parent}"),
    ]


class Page:
    """The tree of a page: ``parent`` of each node (parents come first), ``features``, ``text`` (none for elements) and given ``label``."""

    def __init__(self, source: str) -> None:
        self.parent, self.features, self.text, self.label = [-1], [[_feature("tag=#page")]], [None], [-1]
        self.depth = [0]
        self._stack = [(0, "#page", -1)]
        self._places: dict[str, list[int]] = {}
        self._run: list[str] = []
        self._linked = self._links = 0
        at = 0
        for m in _TOKEN.finditer(source):
            if m.start() > at:
                self._read(source[at : m.start()])
            at = m.end()
            tag = m[3]
            if tag:
                (self._close if m[2] else self._open)(tag.lower(), m[4])
            elif m[1]:
                self._run.append(" ")
        self._read(source[at:])
        self._flush()

    def _read(self, raw: str) -> None:
        self._run.append(raw)
        if self._links:
            self._linked += len(raw)

    def _flush(self) -> None:
        if self._run:
            raw = "".join(self._run)
            self._run = []
            text = " ".join((html.unescape(raw) if "&" in raw else raw).split())
            if text and not self._places.get("head"):
                at, tag, label = self._stack[-1]
                self._add(at, _text_features(text, min(self._linked, len(text)), tag), text, label)
        self._linked = 0

    def _add(self, parent: int, features: list[int], text: str | None, label: int) -> int:
        self.parent.append(parent)
        self.depth.append(self.depth[parent] + 1)
        self.features.append(features)
        self.text.append(text)
        self.label.append(label)
        return len(self.parent) - 1

    def _innermost(self, tags: set[str]) -> int:
        """The place of the innermost open element of some tags, -1 if none is open."""
        return max((at[-1] for t in tags if (at := self._places.get(t))), default=-1)

    def _cut(self, place: int) -> None:
        """Ends the open elements from a place on."""
        while len(self._stack) > place:
            self._places[self._stack.pop()[1]].pop()

    def _end_head(self) -> None:
        """A body ends an open head; one that other open elements stand in stays above them without its meaning."""
        for place in reversed(self._places.pop("head", [])):
            if place == len(self._stack) - 1:
                self._stack.pop()
            else:
                at, _, label = self._stack[place]
                self._stack[place] = (at, "#head", label)
                insort(self._places.setdefault("#head", []), place)

    def _open(self, tag: str, attributes: str) -> None:
        if tag in _INLINE:
            self._links += tag == "a"
            return
        if tag == "br":
            self._run.append(" ")
            return
        self._flush()
        if tag in _VOID:
            return
        if tag == "body":
            self._end_head()
        if self._stack[-1][1] == "p":
            self._cut(len(self._stack) - 1)
        if tag in _ENDS:
            scope = self._innermost(_SCOPE)
            while (place := self._innermost(_ENDS[tag])) > scope:
                self._cut(place)
        given = _LABEL.search(attributes) if "data-y" in attributes else None
        label = int(given[1]) if given else self._stack[-1][2]
        self._places.setdefault(tag, []).append(len(self._stack))
        self._stack.append((self._add(self._stack[-1][0], _element_features(tag, attributes), None, label), tag, label))

    def _close(self, tag: str, _: str) -> None:
        if tag in _INLINE:
            self._links -= tag == "a" and self._links > 0
            return
        if tag == "br":
            self._run.append(" ")
            return
        self._flush()
        place = self._innermost({tag})
        if place > 0:
            self._cut(place)


class Forest:
    """The trees of many pages as arrays, nodes by depth; ``kind`` of an edge is 1 to a text, else 0."""

    def __init__(self, pages: list[Page]) -> None:
        base = np.cumsum([0, *(len(p.parent) for p in pages)])
        self.base = base
        self.parent = np.concatenate([np.where(np.array(p.parent) < 0, -1, np.array(p.parent) + b) for p, b in zip(pages, base, strict=False)])
        flat = [f for p in pages for f in p.features]
        self.counts = np.array([len(f) for f in flat])
        self.flat = np.fromiter((x for f in flat for x in f), dtype=np.int64)
        self.kind = np.array([t is not None for p in pages for t in p.text], dtype=np.int64)
        depth = np.concatenate([np.array(p.depth) for p in pages])
        order = np.argsort(depth, kind="stable")
        self.levels = np.split(order, np.cumsum(np.bincount(depth))[:-1])

    def scores(self, weights: np.ndarray) -> np.ndarray:
        """The log potential of label 1 of each node (label 0 has zero)."""
        return np.add.reduceat(weights[self.flat], np.cumsum(self.counts) - self.counts)

    def marginals(self, weights: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """P(label 1) of each node, and P(parent's label, label) of each node but roots. ``edges`` (kind, parent's label, label)."""
        n = len(self.parent)
        if len(self.levels) * THIN_LEVEL > n:
            return self._one_by_one(weights, edges)
        up = np.zeros((n, 2))
        up[:, 1] = self.scores(weights)
        sent = np.zeros((n, 2))
        for level in self.levels[:0:-1]:
            joint = edges[self.kind[level]] + up[level][:, None, :]
            sent[level] = np.logaddexp(joint[:, :, 0], joint[:, :, 1])
            np.add.at(up, self.parent[level], sent[level])
        down = np.zeros((n, 2))
        pair = np.zeros((n, 2, 2))
        for level in self.levels[1:]:
            above = self.parent[level]
            outer = (down[above] + up[above] - sent[level])[:, :, None] + edges[self.kind[level]]
            down[level] = np.logaddexp(outer[:, 0], outer[:, 1])
            joint = outer + up[level][:, None, :]
            joint -= joint.max(axis=(1, 2), keepdims=True)
            pair[level] = np.exp(joint) / np.exp(joint).sum(axis=(1, 2), keepdims=True)
        belief = up + down
        return 1.0 / (1.0 + np.exp(np.clip(belief[:, 0] - belief[:, 1], -500, 500))), pair


    def _one_by_one(self, weights: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for trees of few nodes a level, node after node: parents come before their children."""
        n = len(self.parent)
        parent, kind, own, table = self.parent.tolist(), self.kind.tolist(), self.scores(weights).tolist(), edges.tolist()
        exp, log1p = math.exp, math.log1p

        def join(a: float, b: float) -> float:
            return a + log1p(exp(b - a)) if a >= b else b + log1p(exp(a - b))

        up = [[0.0, s] for s in own]
        sent: list = [(0.0, 0.0)] * n
        for i in range(n - 1, -1, -1):
            a = parent[i]
            if a >= 0:
                (e00, e01), (e10, e11) = table[kind[i]]
                u0, u1 = up[i]
                m0, m1 = sent[i] = (join(e00 + u0, e01 + u1), join(e10 + u0, e11 + u1))
                up[a][0] += m0
                up[a][1] += m1
        down: list = [(0.0, 0.0)] * n
        pair = np.zeros((n, 2, 2))
        for i in range(n):
            a = parent[i]
            if a >= 0:
                (e00, e01), (e10, e11) = table[kind[i]]
                o0, o1 = (down[a][y] + up[a][y] - sent[i][y] for y in (0, 1))
                u0, u1 = up[i]
                down[i] = (join(o0 + e00, o1 + e10), join(o0 + e01, o1 + e11))
                four = (o0 + e00 + u0, o0 + e01 + u1, o1 + e10 + u0, o1 + e11 + u1)
                top = max(four)
                w = [exp(x - top) for x in four]
                pair[i] = np.array(w).reshape(2, 2) / sum(w)
        belief = np.array(up) + np.array(down)
        return 1.0 / (1.0 + np.exp(np.clip(belief[:, 0] - belief[:, 1], -500, 500))), pair


class ContentModel:
    def __init__(self, weights: np.ndarray, edges: np.ndarray) -> None:
        self.weights, self.edges = weights, edges

    @classmethod
    def train(cls, sources: list[str], steps: int = TRAIN_STEPS, rate: float = 0.2, decay: float = 2e-4) -> ContentModel:
        """Maximises the likelihood of the labels; each step compares observed with expected features."""
        pages = [Page(s) for s in sources]
        forest = Forest(pages)
        y = np.array([max(0, v) for p in pages for v in p.label], dtype=float)
        inner = forest.parent >= 0
        above = y[forest.parent].astype(int)
        seen = np.zeros((2, 2, 2))
        np.add.at(seen, (forest.kind[inner], above[inner], y[inner].astype(int)), 1.0)
        weights, edges = np.zeros(FEATURES), np.zeros((2, 2, 2))
        square_w, square_e = np.full(FEATURES, 1e-6), np.full((2, 2, 2), 1e-6)
        for _ in range(steps):
            p, pair = forest.marginals(weights, edges)
            grad = np.bincount(forest.flat, np.repeat(y - p, forest.counts), FEATURES) / len(sources) - decay * weights
            expected = np.stack([pair[inner & (forest.kind == k)].sum(axis=0) for k in (0, 1)])
            grad_e = (seen - expected) / len(sources) - decay * edges
            square_w = 0.9 * square_w + 0.1 * grad**2
            square_e = 0.9 * square_e + 0.1 * grad_e**2
            weights += rate * grad / (np.sqrt(square_w) + 1e-3)
            edges += rate * grad_e / (np.sqrt(square_e) + 1e-3)
        return cls(weights, edges)

    def texts(self, sources: list[str]) -> list[str]:
        if not sources:
            return []
        pages = [Page(s) for s in sources]
        forest = Forest(pages)
        keep = (forest.marginals(self.weights, self.edges)[0] >= 0.5).tolist()
        return ["\n".join(t for t, k in zip(p.text, keep[a:b], strict=True) if k and t is not None) for p, a, b in zip(pages, forest.base[:-1], forest.base[1:], strict=True)]


# Names that pages commonly give to their parts.
_CONTENT_NAMES = "content post entry-content article-body story text main-content post-body page-content entry article".split()
_OTHER_NAMES = (
    "menu navbar nav header masthead footer sidebar ad ads advert advertisement banner cookie-notice notice popup newsletter breadcrumbs share social"
    " related promo widget comments comment-list comment copyright login search subscribe sponsor toolbar legal alert modal"
).split()


def labelled_pages(n: int = TRAIN_PAGES, seed: int = 11) -> list[str]:
    """Pages of seeded words with ``data-y`` labels."""
    rng = np.random.default_rng(seed)
    pick = lambda xs: xs[int(rng.integers(len(xs)))]
    chance = lambda p: rng.random() < p

    def word() -> str:
        return "".join(chr(97 + int(c)) for c in rng.integers(0, 26, int(rng.integers(1, 10)))) + pick(["", "", "", "", "###", "!!", ","])

    def words(low: int, high: int) -> str:
        return " ".join(word() for _ in range(int(rng.integers(low, high)))) + pick([".", ".", "", "?"])

    def link() -> str:
        return f'<a href="/{word()}">{words(1, 4)}</a>'

    def block(low: int, high: int) -> str:
        kind = pick(["p", "p", "p", "p", "li", "quote", "table", "head", "bare"])
        text = words(low, high) + (" " + link() if chance(0.15) else "")
        if kind == "li":
            return f"<ul>{''.join(f'<li>{words(1, 12)}</li>' for _ in range(3))}</ul>"
        if kind == "quote":
            return f"<blockquote>{text}</blockquote>"
        if kind == "table":
            return f"<table><tr><td>{words(1, 5)}<td>{words(1, 5)}</table>"
        if kind == "head":
            return f"<h2>{words(1, 8)}</h2>"
        if kind == "bare":
            return f"<div>{text}</div>"
        return f"<p>{text}" + ("</p>" if chance(0.8) else "")

    def content() -> str:
        tag = pick(["article", "article", "article", "main", "div", "div", "section"])
        name = "" if tag in ("article", "main") and chance(0.6) else f' {pick(["class", "id"])}="{pick(_CONTENT_NAMES)}"'
        inner = (f"<h1>{words(1, 10)}</h1>" if chance(0.8) else "") + "".join(block(1, pick([4, 30, 120])) for _ in range(int(rng.integers(1, 9))))
        if chance(0.2):
            inner += other()
        return f'<{tag}{name} data-y="1">{inner}</{tag}>'

    def other() -> str:
        tag = pick(["nav", "header", "footer", "aside", "form", "div", "div", "div", "section", "ul"])
        name = "" if tag in ("nav", "header", "footer", "aside", "form") and chance(0.6) else f' {pick(["class", "class", "id"])}="{pick(_OTHER_NAMES)}"'
        if tag == "ul":
            inner = "".join(f"<li>{link()}</li>" for _ in range(4))
        elif tag == "nav" or chance(0.3):
            inner = f"<ul>{''.join(f'<li>{link()}</li>' for _ in range(int(rng.integers(1, 7))))}</ul>"
        elif chance(0.4):
            inner = "".join(f"<p>{words(1, pick([4, 40]))}</p>" for _ in range(int(rng.integers(1, 4))))
        else:
            inner = words(1, pick([4, 15, 60]))
        return f'<{tag}{name} data-y="0">{inner}</{tag}>'

    out = []
    for _ in range(n):
        before, after = "".join(other() for _ in range(int(rng.integers(0, 4)))), "".join(other() for _ in range(int(rng.integers(0, 4))))
        inner = f"{before}{content()}{after}"
        if chance(0.3):
            inner = f'<div class="{pick(["wrapper", "container", "page", "row", "layout"])}">{inner}</div>'
        out.append(f'<html><head><title>{words(1, 5)}</title></head><body data-y="0">{inner}</body></html>')
    return out


def extract_pages(pages: DataFrame, model: ContentModel | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""
    model = model or ContentModel.train(labelled_pages())

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = model.texts(column_text(batch, "html"))
            return pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

        return step

    kinds = {f.name: f.dataType.simpleString() for f in pages.schema.fields}
    return map_batches(pages.select("page_id", "url", "html"), make, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars bigint", "html")
