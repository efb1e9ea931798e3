"""Main-text extraction from HTML by gradient-boosted trees over DOM nodes.

A page is parsed into block elements.  Features of a block are its tag, the
hashed tokens of its attributes and of its ancestors', text and link density of
its subtree, depth, position and its siblings' statistics.  What a token tells
is learned: its bucket's log-odds, counted on pages that the trees are not
fitted on.  Trees and odds are fitted here on generated pages with known labels,
part of which have meaningless class names; then a dynamic programme over the
tree picks the labels of largest likelihood in which nothing below a rejected
block is kept, so an ancestor and its descendants never contradict each other.

Defined results: null and empty pages and pages without main text give the
empty text; unclosed and stray tags are handled as browsers do in the common
cases (a head without an end tag ends at the first tag or text that it cannot
hold); text outside any tag counts as a block of the body; ``<br>`` is white
space; pages of any length and depth are handled whole, in linear time; repeated
rows repeat their result; extra columns are ignored.
"""

from __future__ import annotations

import pickle
import re
import zlib
from collections.abc import Iterator
from functools import cache
from html import unescape

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

# Fixed values of HTML: block elements, elements whose text is no page text,
# elements without content, and which open elements a start tag closes.
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 header hgroup hr html label legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
SILENT = frozenset("head script style template noscript iframe object svg math canvas audio video select datalist textarea button".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_CLOSES = {"li": ("li",), "dd": ("dd", "dt"), "dt": ("dd", "dt"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th")}
_SCOPE = frozenset("body div article section aside nav main header footer table ul ol dl form blockquote td th li fieldset details".split())
_CLOSE_P = BLOCKS - frozenset("html body caption label legend summary tbody td tfoot th thead tr".split())

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>"
    r"""|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>""",
    re.S,
)
_ATTR = re.compile(r"""\b(?:class|id|role|itemprop|aria-label)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HEAD = frozenset("head base basefont bgsound link meta noscript script style template title".split())
_WORDS = regex.compile(r"\p{Lu}?\p{Ll}+|\p{Lu}+")
#: Buckets of hashed attribute tokens, and the letters of the stem hashed besides.
BUCKETS = 1 << 13
STEM = 5

TAGS = "article aside blockquote body dd div dl dt figcaption figure footer form header li main nav ol p pre section table td tr ul".split()
_TAG = {t: i for i, t in enumerate(TAGS)}


class Page:
    """Blocks of a page in document order; text units belong to blocks."""

    def __init__(self, source: str):
        self.tag: list[str] = ["body"]
        self.parent: list[int] = [-1]
        self.attrs: list[str] = [""]
        self.units: list[tuple[int, str]] = []  # block, text
        self.link_chars: dict[int, int] = {}
        self.links: dict[int, int] = {}
        self._parse(source)

    def _parse(self, s: str) -> None:
        stack: list[tuple[str, int]] = [("body", 0)]  # open elements and their block
        places: dict[str, list[int]] = {}  # where each name is open, so no search walks the stack
        blocks: list[int] = []
        silent = links = 0
        buffer: list[str] = []

        def flush():
            if buffer:
                text = " ".join(unescape("".join(buffer)).split())
                if text:
                    self.units.append((stack[-1][1], text))
                buffer.clear()

        def push(name: str, block: int):
            places.setdefault(name, []).append(len(stack))
            if name in BLOCKS:
                blocks.append(len(stack))
            stack.append((name, block))

        def pop_to(k: int):
            nonlocal silent, links
            if blocks and blocks[-1] >= k:
                flush()
            while len(stack) > k:
                t, _ = stack.pop()
                places[t].pop()
                if t in BLOCKS:
                    blocks.pop()
                silent -= t in SILENT
                links -= t == "a"

        def last(names) -> int:
            return max((places[t][-1] for t in names if places.get(t)), default=-1)

        def find(names, scope) -> int:
            k = last(names)
            return k if k > last(scope) else -1

        at = 0
        while True:
            m = _TOKEN.search(s, at)
            text = s[at : m.start() if m else len(s)]
            if silent and places.get("head") and text.strip() and len(stack) - 1 == places["head"][-1]:
                pop_to(places["head"][-1])
            if text and not silent:
                buffer.append(text)
                if links:
                    b = stack[-1][1]
                    self.link_chars[b] = self.link_chars.get(b, 0) + len(text)
            if not m:
                break
            at = m.end()
            name = (m[2] or m[5] or "").lower()
            if not name:
                if m[0].startswith("<![CDATA[") and not silent:
                    buffer.append(m[0][9:].removesuffix("]]>").replace("&", "&amp;").replace("<", "&lt;"))
                continue
            if m[1] or m[4]:
                k = last((name,))
                if k > 0 and (name in BLOCKS or name in SILENT or not (blocks and blocks[-1] > k)):
                    pop_to(k)
                elif name in BLOCKS:
                    flush()
                continue
            if name not in _HEAD and places.get("head") and not silent - 1:
                pop_to(places["head"][-1])
            if name in ("html", "body"):
                continue
            if name in _CLOSE_P:
                k = find(("p",), _SCOPE)
                if k > 0:
                    pop_to(k)
            if name in _CLOSES:
                k = find(_CLOSES[name], _SCOPE - set(_CLOSES[name]))
                if k > 0:
                    pop_to(k)
            attrs = m[3] or m[6] or ""
            if name in RAW:
                end = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>", re.I).search(s, at)
                inner = s[at : end.start() if end else len(s)]
                at = end.end() if end else len(s)
                if name not in SILENT and name != "title" and not silent:
                    buffer.append(inner.replace("<", "&lt;"))
                continue
            if name in VOID or attrs.endswith("/") and name not in BLOCKS:
                if name == "br":
                    buffer.append(" ")
                elif name == "hr":
                    flush()
                continue
            if name in BLOCKS:
                flush()
                self.tag.append(name)
                self.parent.append(stack[-1][1])
                self.attrs.append(" ".join(a or b or c for a, b, c in _ATTR.findall(attrs)) if "=" in attrs else "")
                push(name, len(self.tag) - 1)
            else:
                push(name, stack[-1][1])
                if name == "a":
                    self.links[stack[-1][1]] = self.links.get(stack[-1][1], 0) + 1
            silent += name in SILENT
            links += name == "a"
        flush()

    def tokens(self, i: int) -> list[int]:
        """Buckets of the words, and of their stems, in a block's attributes."""
        if not self.attrs[i]:
            return []
        words = {w.lower() for w in _WORDS.findall(self.attrs[i])}
        return [zlib.crc32(w.encode()) % BUCKETS for w in words | {f"{w[:STEM]}-" for w in words}]

    def features(self, odds: np.ndarray) -> np.ndarray:
        n = len(self.tag)
        parent = np.array(self.parent)
        own = np.zeros((n, 7))  # characters, words, commas and stops, link characters, links, paragraphs, their characters
        for b, t in self.units:
            own[b, :3] += len(t), t.count(" ") + 1, t.count(",") + t.count(".")
        for b, c in self.link_chars.items():
            own[b, 3] = c
        for b, c in self.links.items():
            own[b, 4] = c
        own[:, 5] = [t == "p" for t in self.tag]
        own[:, 6] = own[:, 5] * own[:, 0]
        sub, nodes, depth = own.copy(), np.ones(n), np.zeros(n)
        for i in range(n - 1, 0, -1):
            sub[parent[i]] += sub[i]
            nodes[parent[i]] += nodes[i]
        told, low, up_low, up_high, up_bad, up_main = (np.zeros(n) for _ in range(6))
        index, children, alike = np.zeros(n), np.zeros(n), np.zeros(n)
        tags = np.zeros((n, len(TAGS) + 1))
        twins: dict[tuple[int, str, str], list[int]] = {}
        for i in range(n):
            t, p = self.tag[i], self.parent[i]
            seen = [odds[k] for k in self.tokens(i)]
            if seen:
                told[i], low[i] = sum(seen), min(seen)
            if t[0] == "h" and t[1:].isdigit():
                tags[i, len(TAGS)] = 1
            elif t in _TAG:
                tags[i, _TAG[t]] = 1
            if p >= 0:
                depth[i] = depth[p] + 1
                index[i] = children[p]
                children[p] += 1
                twins.setdefault((p, t, self.attrs[i]), []).append(i)
                up_low[i] = min(up_low[p], low[p])
                up_high[i] = max(up_high[p], told[p])
                up_bad[i] = max(up_bad[p], self.tag[p] in ("nav", "header", "footer", "aside", "form"))
                up_main[i] = max(up_main[p], self.tag[p] in ("article", "main"))
        for same in twins.values():
            alike[same] = len(same)
        start = np.concatenate(([0], np.cumsum(own[:-1, 0])))
        total = max(sub[0, 0], 1)
        p = np.maximum(parent, 0)
        density = sub[:, 0] / nodes
        return np.column_stack(
            [
                tags, told, low, up_low, up_high, up_bad, up_main, depth, index, children[p], children, alike,
                [bool(a) for a in self.attrs], np.log1p(sub[:, 0]), np.log1p(own[:, 0]), sub[:, 0] / total, start / total,
                sub[:, 3] / np.maximum(sub[:, 0], 1), sub[:, 4] / np.maximum(sub[:, 1], 1), sub[:, 2] / np.maximum(sub[:, 1], 1),
                np.log1p(density), np.log1p(sub[:, 5]), sub[:, 6] / max(sub[0, 6], 1), nodes, sub[:, 0] / np.maximum(sub[p, 0], 1),
                density / np.maximum(density[p], 1), sub[p, 3] / np.maximum(sub[p, 0], 1), np.log1p(sub[p, 0]),
            ]
        )

    def decode(self, score: np.ndarray) -> np.ndarray:
        """Labels of largest likelihood without a kept block below a rejected one."""
        yes, no = -np.logaddexp(0, -score), -np.logaddexp(0, score)
        keep, drop = yes.copy(), no.copy()
        for i in range(len(score) - 1, 0, -1):
            keep[self.parent[i]] += max(keep[i], drop[i])
            drop[self.parent[i]] += drop[i]
        out = np.zeros(len(score), bool)
        out[0] = True
        for i in range(1, len(score)):
            out[i] = out[self.parent[i]] and keep[i] >= drop[i]
        return out

    def text(self, kept: np.ndarray) -> str:
        return "\n".join(t for b, t in self.units if kept[b])


class Trees:
    """Gradient-boosted regression trees for the logistic loss."""

    def __init__(self, x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 4, rate: float = 0.3, bins: int = 24):
        cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
        binned = np.column_stack([np.searchsorted(k, c, side="left") for k, c in zip(cuts, x.T, strict=True)])
        self.bias = float(np.log(y.mean() / (1 - y.mean())))
        self.trees: list[list[tuple[np.ndarray, ...]]] = []
        f = np.full(len(y), self.bias)
        width = bins + 1
        for _ in range(trees):
            p = 1 / (1 + np.exp(-f))
            g, h = y - p, p * (1 - p)
            at = np.zeros(len(y), np.int64)
            levels = []
            for d in range(depth):
                size = 1 << d
                best = np.full(size, 1e-9)
                feature, cut = np.zeros(size, np.int64), np.full(size, np.inf)
                for j in range(x.shape[1]):
                    slot = at * width + binned[:, j]
                    gs = np.bincount(slot, g, size * width).reshape(size, width).cumsum(1)
                    hs = np.bincount(slot, h, size * width).reshape(size, width).cumsum(1)
                    gt, ht = gs[:, -1:], hs[:, -1:]
                    gain = gs**2 / (hs + 1) + (gt - gs) ** 2 / (ht - hs + 1) - gt**2 / (ht + 1)
                    gain = gain[:, : len(cuts[j])]
                    if not gain.shape[1]:
                        continue
                    k = gain.argmax(1)
                    v = gain[np.arange(size), k]
                    up = v > best
                    best[up], feature[up], cut[up] = v[up], j, cuts[j][k[up]]
                levels.append((feature, cut))
                at = 2 * at + (x[np.arange(len(x)), feature[at]] > cut[at])
            n = 1 << depth
            leaf = rate * np.bincount(at, g, n) / (np.bincount(at, h, n) + 1)
            f += leaf[at]
            self.trees.append((levels, leaf))

    def score(self, x: np.ndarray) -> np.ndarray:
        out, rows = np.full(len(x), self.bias), np.arange(len(x))
        for levels, leaf in self.trees:
            at = np.zeros(len(x), np.int64)
            for feature, cut in levels:
                at = 2 * at + (x[rows, feature[at]] > cut[at])
            out += leaf[at]
        return out


class Model:
    """Token odds and trees."""

    def __init__(self, odds: np.ndarray, trees: Trees):
        self.odds, self.trees = odds, trees

    def texts(self, sources: list[str]) -> list[str]:
        pages = [Page(s) for s in sources]
        score = self.trees.score(np.concatenate([p.features(self.odds) for p in pages]))
        out, at = [], 0
        for p in pages:
            out.append(p.text(p.decode(score[at : at + len(p.tag)])))
            at += len(p.tag)
        return out


# Fixed: names that authors give to the parts of a page, used to write training
# pages.  No feature refers to them; their weight is learned like any token's.
NAMES = {
    "main": "article content main post entry story text body news artikel beitrag inhalt contenu contenido articulo cuerpo texto",
    "plain": "wrapper container row col box inner outer block item grid left right top panel region",
    "menu": "nav navbar navigation menu breadcrumb pagination toc tabs toolbar navigationsleiste menue ariane migas",
    "head": "header masthead topbar banner logo branding kopfzeile entete cabecera",
    "foot": "footer copyright colophon legal imprint bottom fusszeile impressum pied pie",
    "side": "sidebar aside widget related recommended trending popular tags rail more stories next also seitenleiste verwandte mehr similaires relacionados",
    "note": "notice cookie consent gdpr popup modal overlay alert toast disclaimer hinweis avis aviso",
    "ad": "ad ads advert advertisement sponsor sponsored promo promotion werbung anzeige publicite publicidad anuncio",
    "form": "form login search contact register poll survey newsletter subscribe suche anmeldung recherche buscar",
    "talk": "comment comments respond reply discussion thread reviews kommentar kommentare leserbriefe commentaires comentarios opiniones",
    "share": "share sharing social follow teilen partager compartir",
}
NAMES = {k: v.split() for k, v in NAMES.items()}


class _Maker:
    """Pages with known labels, to fit on."""

    def __init__(self, seed: int):
        self.r = np.random.default_rng(seed)
        self.rows: list[int] = []  # label of each block in document order
        self.clear = True  # whether class names tell anything on this page

    def pick(self, *xs):
        return xs[int(self.r.integers(len(xs)))]

    def chance(self, p: float) -> bool:
        return self.r.random() < p

    def words(self, lo: int, hi: int) -> str:
        n = int(self.r.integers(lo, hi))
        w = ["".join(self.pick(*"aeioulnrstdmkp") for _ in range(int(self.r.integers(2, 9)))) for _ in range(n)]
        return " ".join(x + (self.pick(",", ".") if self.chance(0.12) else "") for x in w) + "."

    def named(self, kind: str) -> str:
        """A class or id attribute for a part, meaningless on some pages."""
        word = self.pick(*NAMES[kind])
        if not self.clear:
            word = "".join(self.pick(*"bcdfghjklmnpqrstvwxyz") for _ in range(int(self.r.integers(3, 9))))
        other = self.pick(*NAMES["plain"])
        name = self.pick(word, word, f"{word}-{other}", f"site-{word}", f"{other} {word}", f"{word}{self.r.integers(9)}", f"{other}{word.title()}")
        return f' {self.pick("class", "class", "id")}="{name}"'

    def block(self, tag: str, label: int, inner, attrs: str = "") -> str:
        self.rows.append(label)
        body = inner() if callable(inner) else inner
        return f"<{tag}{attrs}>{body}</{tag}>"

    def link(self) -> str:
        return f'<a href="/{self.r.integers(999)}">{self.words(1, self.pick(3, 12))}</a>'

    def menu(self, label: int = 0) -> str:
        items = int(self.r.integers(1, 9))
        if self.chance(0.3):
            return " ".join(self.link() for _ in range(items))
        return self.block(self.pick("ul", "ul", "ol"), label, lambda: "".join(self.block("li", label, self.link()) for _ in range(items)))

    def prose(self) -> str:
        out = []
        for _ in range(int(self.r.integers(0, 9))):
            k = self.r.random()
            if k < 0.75:
                out.append(self.block("p", 1, self.words(1, self.pick(6, 30, 120, 300)), self.named("plain") if self.chance(0.05) else ""))
            elif k < 0.82:
                out.append(self.block(self.pick("h2", "h3"), 1, self.words(1, 8)))
            elif k < 0.88:
                out.append(self.block(self.pick("ul", "ol"), 1, lambda: "".join(self.block("li", 1, self.words(2, 15)) for _ in range(3))))
            elif k < 0.92:
                out.append(self.block("blockquote", 1, lambda: self.block("p", 1, self.words(5, 40))))
            elif k < 0.935:
                out.append(self.block("p", 1, f"{self.words(3, 30)} {self.link()} {self.words(3, 30)}"))
            elif k < 0.945:
                row = lambda: "".join(self.block("td", 1, self.words(1, 6)) for _ in range(3))
                out.append(self.block("table", 1, lambda: "".join(self.block("tr", 1, row) for _ in range(3))))
            elif k < 0.95:
                out.append(self.block("pre", 1, self.words(3, 40)))
            elif k < 0.955:
                out.append(self.block("figure", 1, lambda: "<img src=x>" + self.block("figcaption", 1, self.words(2, 15))))
            elif k < 0.965:
                out.append(self.block(self.pick("div", "section"), 1, lambda: self.block("p", 1, self.words(5, 80)), self.named("plain") if self.chance(0.5) else ""))
            elif k < 0.975:
                out.append("<br>".join(self.words(5, 60) for _ in range(3)))
            else:
                out.append(self.clutter(inside=True))
        return "".join(out)

    def comments(self) -> str:
        """Readers' remarks: much alike, with a name or a date, and answers."""
        tag, attrs = self.pick("div", "li", "p", "article"), self.named("talk") if self.chance(0.6) else ""

        def one():
            if tag == "p" or self.chance(0.3):
                return self.words(2, 60)
            who = self.block(self.pick("div", "p", "h4"), 0, self.words(1, 4)) if self.chance(0.6) else ""
            return who + self.block(self.pick("p", "div"), 0, self.words(2, 60))

        several = lambda: "".join(self.block(tag, 0, one, attrs) for _ in range(int(self.r.integers(1, 6))))
        head = self.block(self.pick("h2", "h3", "h4"), 0, self.words(1, 4)) if self.chance(0.5) else ""
        return head + (self.block(self.pick("ol", "ul"), 0, several) if tag == "li" else several())

    def clutter(self, inside: bool = False) -> str:
        kind = self.pick("ad", "note", "share", "form", "talk", "side") if inside else self.pick(*(k for k in NAMES if k not in ("main", "plain")))
        tag = {"menu": "nav", "head": "header", "foot": "footer", "side": "aside", "form": "form"}.get(kind)
        if tag is None or self.chance(0.5):
            tag = self.pick("div", "div", "section", "p") if kind == "ad" else self.pick("div", "div", "section")
            attrs = self.named(kind)
        else:
            attrs = self.named(kind) if self.chance(0.4) else ""

        def inner():
            if tag == "p":
                return self.words(1, 30)
            k = self.r.random()
            if kind in ("menu", "share"):
                return self.menu()
            if kind == "talk":
                return self.comments()
            if kind == "side" and k < 0.75:
                return self.block(self.pick("h2", "h3", "h4", "div", "p"), 0, self.words(1, 5)) + self.menu()
            if kind == "head" and k < 0.5:
                return self.block(self.pick("h1", "div"), 0, self.words(1, 4)) + self.menu()
            if kind == "form":
                return f"{self.words(1, 6)}<input name=q>" + self.block("p", 0, self.words(1, 8))
            if k < 0.5:
                return self.words(1, self.pick(8, 40))
            return self.block("p", 0, self.words(1, self.pick(8, 60)))

        return self.block(tag, 0, inner, attrs)

    def page(self) -> tuple[str, np.ndarray]:
        self.rows, self.clear = [1], self.chance(0.8)
        before = int(self.r.integers(0, 5))
        after = int(self.r.integers(0, 5))

        def article():
            head = self.block("h1", 1, self.words(2, 12)) if self.chance(0.8) else ""
            return head + self.prose()

        def middle():
            k = self.r.random()
            if k < 0.5:
                return self.block("article", 1, article, self.named("main") if self.chance(0.3) else "")
            if k < 0.65:
                return self.block("main", 1, article)
            if k < 0.85:
                return self.block("div", 1, article, self.named("main"))
            return article()

        def around(inner) -> str:
            """A wrapper, whose name may be that of any part or tell nothing."""
            return self.block("div", 1, inner, self.named(self.pick("plain", "plain", "plain", "main", *NAMES)) if self.chance(0.6) else "")

        def body():
            out = [self.clutter() for _ in range(before)]
            if self.chance(0.1):  # no main text at all
                return "".join(out + [self.clutter() for _ in range(after + 1)])
            wrapped = lambda: middle() + (self.clutter() if self.chance(0.4) else "")
            out.append(around(wrapped) if self.chance(0.4) else middle())
            return "".join(out + [self.clutter() for _ in range(after)])

        inside = around(body) if self.chance(0.4) else body()
        return f"<html><head><title>{self.words(1, 5)}</title></head><body>{inside}</body></html>", np.array(self.rows)


def generated(pages: int, seed: int) -> list[tuple[Page, np.ndarray]]:
    make, out = _Maker(seed), []
    while len(out) < pages:
        source, labels = make.page()
        page = Page(source)
        if len(page.tag) == len(labels):
            out.append((page, labels))
    return out


def token_odds(data: list[tuple[Page, np.ndarray]]) -> np.ndarray:
    """Smoothed log-odds of main text for every bucket; 0 if it never came."""
    seen = np.zeros((2, BUCKETS))
    for page, y in data:
        for i in range(len(page.tag)):
            for k in page.tokens(i):
                seen[int(y[i]), k] += 1
    return np.log((seen[1] + 1) / (seen[0] + 1))


@cache
def trained(pages: int = 1_200, seed: int = 5) -> Model:
    """Fitted on ``pages`` generated pages, half for the odds and half for the
    trees; deterministic."""
    data = generated(pages, seed)
    odds, rest = token_odds(data[: pages // 2]), data[pages // 2 :]
    return Model(odds, Trees(np.concatenate([p.features(odds) for p, _ in rest]), np.concatenate([y for _, y in rest]).astype(float), trees=60))


def main_text(source: str | None, model: Model) -> str:
    return model.texts([source])[0] if source else ""


def extract(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """page_id, url, text, n_chars of every row of ``pages``."""
    spark = pages.sparkSession
    common.tune_arrow(spark)
    sent = spark.sparkContext.broadcast(pickle.dumps(model or trained()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(sent.value)
        for b in batches:
            texts: list[str] = []
            sources = b.column(2).to_pylist()
            for lo in range(0, len(sources), 64):  # trees score the blocks of many pages at once
                texts += m.texts([s or "" for s in sources[lo : lo + 64]])
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    return pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(
        run, "page_id long, url string, text string, n_chars long"
    )
