"""Main text of web pages: boosted trees over DOM nodes, decoded so that ancestors and descendants agree.

Every block element gets features of its subtree (text, link and tag density), its attribute tokens and
tag, its depth and ancestors, and its siblings. Gradient-boosted trees give the probability that it
lies in the main article. Each path from the root then runs through three states: outside (above the
article), inside, and dropped (page furniture, also within the article); nothing under a dropped
element comes back. The most probable assignment under that rule is found from the leaves upwards.

The trees are fitted on pages that are composed here: articles of many shapes between menus, headers,
sidebars, notices, adverts, forms, comments and footers, marked up by meaning or by class names only.
"""

from __future__ import annotations

import random
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dom import INLINE, RAW, Node, parse
from .runtime import ship

#: Pages composed for fitting.
FIT_PAGES = 700
#: Elements whose contents never are article text.
NEVER = RAW | frozenset("head form button select option input object embed canvas audio video dialog map datalist".split())
_WORD = re.compile(r"[a-z]+|\d+")
_MARKS = re.compile(r"[.,;:!?]")


def attribute_tokens(node: Node) -> list[str]:
    """Tokens of class, id and role; camel case and separators split."""
    if not node.attributes:
        return []
    named = node.named()
    text = " ".join(named.get(k, "") for k in ("class", "id", "role", "itemprop"))
    return _WORD.findall(re.sub(r"([a-z])([A-Z])", r"\1 \2", text).lower()) if text.strip() else []


class Page:
    """Blocks of a page in document order with their feature rows."""

    def __init__(self, html: str):
        self.root = parse(html)
        self.blocks: list[Node] = []
        self.parents: list[int] = []
        self.depth: list[int] = []
        self._collect()

    def _collect(self) -> None:
        stack = [(self.root, -1, 0)]
        while stack:
            node, parent, depth = stack.pop()
            if node.tag in NEVER:
                continue
            if node.tag not in INLINE:
                node.index = len(self.blocks)
                self.blocks.append(node)
                self.parents.append(parent)
                self.depth.append(depth)
                parent, depth = node.index, depth + 1
            stack.extend((x, parent, depth) for x in reversed(node.items) if isinstance(x, Node))

    def counts(self) -> np.ndarray:
        """Own sums per block: text, link text, marks, words, links, pieces, paragraphs, items, headings, images."""
        own = np.zeros((len(self.blocks), 10))

        for i, node in enumerate(self.blocks):
            row, stack = own[i], [(node, False)]
            while stack:
                inline, in_link = stack.pop()
                for x in inline.items:
                    if isinstance(x, str):
                        size = len(x) if not x.isspace() else 0
                        if size:
                            row[0] += size
                            row[1] += size * in_link
                            row[2] += len(_MARKS.findall(x))
                            row[3] += x.count(" ") + 1
                            row[5] += 1
                    elif x.tag in INLINE:
                        row[4] += x.tag == "a"
                        row[9] += x.tag == "img"
                        stack.append((x, in_link or x.tag == "a"))
            own[i, 6] = node.tag == "p"
            own[i, 7] = node.tag == "li"
            own[i, 8] = node.tag in ("h1", "h2", "h3", "h4", "h5", "h6")
        return own

    def features(self, tag_code: dict[str, float], token_code: dict[str, float]) -> np.ndarray:
        n = len(self.blocks)
        parents = np.array(self.parents)
        own = self.counts()
        total = np.column_stack([own, np.ones(n)])
        for i in range(n - 1, 0, -1):
            total[parents[i]] += total[i]
        tag = np.array([tag_code.get(b.tag, 0.0) for b in self.blocks])
        token = np.zeros(n)
        for i, b in enumerate(self.blocks):
            codes = [token_code[t] for t in attribute_tokens(b) if t in token_code]
            token[i] = max(codes, key=abs, default=0.0)
        low_tag, high_tag, low_token, high_token = tag.copy(), tag.copy(), token.copy(), token.copy()
        children = np.bincount(parents[1:], minlength=n)
        place = np.zeros(n)
        seen = np.zeros(n, int)
        previous, following = np.zeros(n), np.zeros(n)
        last = np.full(n, -1)
        before = np.concatenate([[0], np.cumsum(own[:, 0])[:-1]])
        text = total[:, 0]
        for i in range(1, n):
            p = parents[i]
            low_tag[i], high_tag[i] = min(low_tag[i], low_tag[p]), max(high_tag[i], high_tag[p])
            low_token[i], high_token[i] = min(low_token[i], low_token[p]), max(high_token[i], high_token[p])
            place[i] = seen[p] / max(1, children[p] - 1)
            seen[p] += 1
            if last[p] >= 0:
                previous[i] = text[last[p]]
                following[last[p]] = text[i]
            last[p] = i
        up = np.maximum(parents, 0)
        whole = max(text[0], 1.0) if n else 1.0
        safe = np.maximum(text, 1.0)
        return np.column_stack([
            np.array(self.depth), np.log1p(text), np.log1p(own[:, 0]), total[:, 1] / safe, np.log1p(total[:, 10]), np.log1p(text / total[:, 10]),
            children, place, children[up], text / np.maximum(text[up], 1.0), text / whole, before / whole, total[:, 2] / safe * 100,
            total[:, 3] / np.maximum(total[:, 5], 1), np.log1p(total[:, 4]), np.log1p(total[:, 6]), np.log1p(total[:, 7]), np.log1p(total[:, 8]),
            np.log1p(previous), np.log1p(following), tag, tag[up], low_tag, high_tag, token, token[up], low_token, high_token, np.log1p(total[:, 9]),
        ])


class BoostedTrees:
    """Second-order boosting of depth-limited trees on binned features, logistic loss."""

    def __init__(self, trees: int = 60, depth: int = 4, rate: float = 0.2, bins: int = 48, least: float = 4.0):
        self.trees, self.depth, self.rate, self.bins, self.least = trees, depth, rate, bins, least

    def _bin(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(self.edges)]).astype(np.int64)

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        self.edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.bins + 1)[1:-1])) for f in range(x.shape[1])]
        b = self._bin(x)
        n, m = b.shape
        self.base = float(np.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6)))
        score = np.full(n, self.base)
        nodes = (1 << self.depth) - 1
        self.feature = np.zeros((self.trees, nodes), np.int64)
        self.cut = np.full((self.trees, nodes), 1 << 30)
        self.leaf = np.zeros((self.trees, 1 << self.depth))
        width = self.bins + 1
        for t in range(self.trees):
            p = 1 / (1 + np.exp(-score))
            g, h = p - y, np.maximum(p * (1 - p), 1e-6)
            at = np.zeros(n, np.int64)
            for level in range(self.depth):
                first, k = (1 << level) - 1, 1 << level
                best = np.full(k, 1e-3)
                for f in range(m):
                    cell = at * width + b[:, f]
                    gs = np.bincount(cell, g, k * width).reshape(k, width).cumsum(1)
                    hs = np.bincount(cell, h, k * width).reshape(k, width).cumsum(1)
                    ga, ha = gs[:, -1:], hs[:, -1:]
                    gain = gs**2 / (hs + 1) + (ga - gs) ** 2 / (ha - hs + 1) - ga**2 / (ha + 1)
                    gain[(hs < self.least) | (ha - hs < self.least)] = 0
                    j = gain.argmax(1)
                    better = gain[np.arange(k), j] > best
                    best[better] = gain[better, j[better]]
                    self.feature[t, first : first + k][better] = f
                    self.cut[t, first : first + k][better] = j[better]
                at = at * 2 + (b[np.arange(n), self.feature[t, first + at]] > self.cut[t, first + at])
            gs, hs = np.bincount(at, g, 1 << self.depth), np.bincount(at, h, 1 << self.depth)
            self.leaf[t] = -self.rate * gs / (hs + 1)
            score += self.leaf[t][at]
        return self

    def margins(self, x: np.ndarray) -> np.ndarray:
        b = self._bin(x)
        rows = np.arange(len(b))
        out = np.full(len(b), self.base)
        for t in range(self.trees):
            at = np.zeros(len(b), np.int64)
            for level in range(self.depth):
                node = (1 << level) - 1 + at
                at = at * 2 + (b[rows, self.feature[t, node]] > self.cut[t, node])
            out += self.leaf[t][at]
        return out


def decode(parents: list[int], margin: np.ndarray) -> np.ndarray:
    """0 outside, 1 inside, 2 dropped per block: the best assignment in which outside may turn to inside
    and inside to dropped on the way down, and nothing else changes; the root is outside or inside."""
    n = len(parents)
    inside, not_inside = -np.logaddexp(0, -margin), -np.logaddexp(0, margin)
    value = np.column_stack([not_inside, inside, not_inside])
    pick = np.zeros((n, 2), np.int8)  # of a child of an outside, of an inside parent
    for i in range(n - 1, 0, -1):
        v = value[i]
        pick[i, 0] = 0 if v[0] >= v[1] else 1
        pick[i, 1] = 1 if v[1] >= v[2] else 2
        p = parents[i]
        value[p, 0] += v[pick[i, 0]]
        value[p, 1] += v[pick[i, 1]]
        value[p, 2] += v[2]
    state = np.zeros(n, np.int8)
    for i in range(1, n):
        up = state[parents[i]]
        state[i] = 2 if up == 2 else pick[i, up]
    return state


def text_of(page: Page, state: np.ndarray) -> str:
    """Text of the inside blocks: white space to one space, blocks joined by an empty line."""
    out: list[str] = []
    held: list[str] = []

    def close() -> None:
        text = " ".join("".join(held).split())
        if text:
            out.append(text)
        held.clear()

    stack: list[tuple[Node | str | None, bool]] = [(page.root, False)]
    while stack:
        x, inside = stack.pop()
        if x is None:
            close()
        elif isinstance(x, str):
            if inside:
                held.append(x)
        elif x.tag in NEVER:
            if x.tag not in INLINE:
                held.append(" ")
        elif x.tag in INLINE:
            if x.tag == "br":
                held.append(" ")
            stack.extend((y, inside) for y in reversed(x.items))
        else:
            close()
            stack.append((None, inside))
            here = state[x.index] == 1
            stack.extend((y, here) for y in reversed(x.items))
    close()
    return "\n\n".join(out)


# -- pages to fit on ---------------------------------------------------------------------------------

#: Class names seen around page furniture and around articles; each composed page draws a few.
FURNITURE = {
    "nav": "nav menu navbar navigation topnav breadcrumbs links tabs",
    "header": "header masthead banner top logo branding",
    "footer": "footer bottom copyright legal colophon foot",
    "aside": "sidebar aside widget related recommended rail popular trending side",
    "ad": "ad ads advert sponsored promo banner adsense sponsor advertisement",
    "notice": "cookie consent notice alert popup modal newsletter subscribe paywall gdpr",
    "comments": "comments comment reply discussion respond thread disqus",
    "share": "share social tags meta toolbar buttons follow byline",
}
ARTICLE = "article content post entry story main body text prose markdown page"
SEMANTIC = {"nav": "nav", "header": "header", "footer": "footer", "aside": "aside", "comments": "section"}


def compose(seed: int) -> tuple[str, list[tuple[str, bool]]]:
    """A page and its marker words: each block's first word is unique and known to be article or not."""
    rng = random.Random(seed)
    marks: list[tuple[str, bool]] = []
    semantic = rng.random() < 0.65
    vocabulary = ["".join(rng.choice("bcdfglmnprst") + rng.choice("aeiouéü") for _ in range(rng.randint(1, 4))) for _ in range(150)]

    def words(n: int) -> str:
        out = [rng.choice(vocabulary) for _ in range(n)]
        for i in range(rng.randint(5, 12), n, rng.randint(6, 14)):
            out[i] += rng.choice(".,.;:")
        text = " ".join(out)
        return (text[:1].upper() + text[1:] + rng.choice([".", ".", ".", "", "!"])) if n > 3 else text

    def marked(inside: bool, text: str) -> str:
        word = f"Zq{len(marks)}x{seed}"
        marks.append((word, inside))
        return f"{word} {text}"

    def attrs(kind: str, sure: float) -> str:
        if rng.random() > sure:
            return ""
        names = (ARTICLE if kind == "article" else FURNITURE[kind]).split()
        name = rng.choice(names) + rng.choice(["", "", "-" + rng.choice(["box", "wrap", "list", "inner", "area", "1"]), " " + rng.choice(names)])
        return f' {rng.choice(["class", "class", "id"])}="{name}"'

    def opened(kind: str) -> tuple[str, str]:
        tag = SEMANTIC.get(kind) if semantic and rng.random() < 0.9 else None
        tag = tag or rng.choice(["div", "div", "div", "section", "ul" if kind == "nav" else "div"])
        sure = 0.3 if tag in ("nav", "footer", "aside", "header") else 0.95
        return f"<{tag}{attrs(kind, sure)}>", f"</{tag}>"

    def links(n: int, inside: bool = False) -> str:
        return "<ul>" + "".join(f'<li><a href="/{rng.choice(vocabulary)}">{marked(inside, words(rng.randint(0, 3)))}</a></li>' for _ in range(n)) + "</ul>"

    def furniture(kind: str) -> str:
        a, b = opened(kind)
        if kind == "nav":
            return a + links(rng.randint(3, 9)) + b
        if kind == "comments":
            return a + f"<h3>{marked(False, 'comments')}</h3>" + "".join(f"<div{attrs('comments', 0.7)}><p>{marked(False, words(rng.randint(4, 45)))}</p></div>" for _ in range(rng.randint(1, 6))) + b
        if kind == "aside":
            inner = rng.choice([f"<h4>{marked(False, words(2))}</h4>" + links(rng.randint(2, 6)), f"<p>{marked(False, words(rng.randint(5, 40)))}</p>"])
            return a + inner + b
        body = marked(False, words(rng.randint(2, 25)))
        return a + rng.choice([body, f"<p>{body}</p>", f"<span>{body}</span>", f"&copy; {body} &middot; {marked(False, words(3))}"]) + b

    def paragraph() -> str:
        text = marked(True, words(rng.choice([1, 2, 4, 8, 15, 30, 60, 100])))
        if rng.random() < 0.2:
            text += f' <a href="#">{words(2)}</a> ' + words(3)
        kind = rng.random()
        if kind < 0.72:
            return f"<p>{text}" + ("</p>" if rng.random() < 0.85 else "")
        if kind < 0.8:
            return f"<p><b>{text}<br>"
        if kind < 0.86:
            level = rng.randint(2, 4)
            return f"<h{level}>{marked(True, words(4))}</h{level}>"
        if kind < 0.9:
            return "<ul>" + "".join(f"<li>{marked(True, words(rng.randint(2, 14)))}</li>" for _ in range(rng.randint(2, 5))) + "</ul>"
        if kind < 0.93:
            return f"<blockquote>{text}</blockquote>"
        if kind < 0.96:
            return "<table>" + "".join(f"<tr><td>{marked(True, words(2))}</td><td>{words(2)}</td></tr>" for _ in range(3)) + "</table>"
        return f"<div>{text}</div>" if rng.random() < 0.6 else f"<pre>{text}</pre>"

    parts = [paragraph() for _ in range(rng.choice([0, 1, 1, 2, 3, 5, 8, 14, 25]))]
    if rng.random() < 0.2:
        parts = [f"<section{attrs('article', 0.3)}>{''.join(parts[i : i + 3])}</section>" for i in range(0, len(parts), 3)]
    for kind, chance in (("ad", 0.25), ("share", 0.2), ("aside", 0.1), ("notice", 0.1)):
        if rng.random() < chance:
            parts.insert(rng.randint(0, len(parts)), furniture(kind))
    inner = (f"<h1>{marked(True, words(rng.choice([0, 1, 2, 4, 6, 9])))}</h1>" if rng.random() < 0.8 or not parts else "") + "".join(parts)
    tag = rng.choice(["article", "article", "article", "main"]) if semantic else "div"
    article = f"<{tag}{attrs('article', 0.25 if tag != 'div' else 0.95)}>{inner}</{tag}>"
    before = [furniture(k) for k, c in (("notice", 0.3), ("header", 0.5), ("nav", 0.85), ("ad", 0.5)) if rng.random() < c]
    after = [furniture(k) for k, c in (("share", 0.3), ("comments", 0.35), ("aside", 0.45), ("ad", 0.25), ("footer", 0.85)) if rng.random() < c]
    if rng.random() < 0.15:
        after.append(f"<form{attrs('notice', 0.5)}><label>{words(2)}</label><input></form>")
    body = "".join(before) + article + "".join(after)
    for _ in range(rng.choice([0, 0, 1, 2])):
        body = f"<div{rng.choice(['', ' class=wrap', ' id=page', ' class=container'])}>{body}</div>"
    return f"<!DOCTYPE html><html><head><title>{words(4)}</title><style>p{{}}</style></head><body>{body}</body></html>", marks


class Extractor:
    def __init__(self, tag_code: dict[str, float], token_code: dict[str, float], model: BoostedTrees):
        self.tag_code, self.token_code, self.model = tag_code, token_code, model

    def texts(self, pages: list[str]) -> list[str]:
        parsed = [Page(p) for p in pages]
        rows = [p.features(self.tag_code, self.token_code) for p in parsed]
        margins = self.model.margins(np.concatenate(rows)) if rows else np.zeros(0)
        out, at = [], 0
        for page, r in zip(parsed, rows):
            out.append(text_of(page, decode(page.parents, margins[at : at + len(r)])))
            at += len(r)
        return out


def _code(seen: list[tuple[str, bool]], least: int = 3) -> dict[str, float]:
    """Smoothed log-odds of each name."""
    names, inverse = np.unique([n for n, _ in seen], return_inverse=True)
    inside = np.array([x for _, x in seen], float)
    n, k = np.bincount(inverse), np.bincount(inverse, inside)
    base = inside.mean()
    odds = np.log((k + 2 * base) / (n + 2)) - np.log((n - k + 2 * (1 - base)) / (n + 2)) - np.log(base / (1 - base))
    return {str(a): float(o) for a, o, c in zip(names, odds, n) if c >= least}


@lru_cache(maxsize=2)
def train(pages: int = FIT_PAGES) -> Extractor:
    """Fit on composed pages; deterministic."""
    made = []
    for seed in range(pages):
        html, marks = compose(seed)
        page, inside = Page(html), dict(marks)
        n = len(page.blocks)
        got = np.zeros((n, 2))  # article and other blocks of text at or below

        def words_of(node: Node) -> list[str]:
            return [w for x in node.items for w in (re.findall(r"Zq\d+x\d+", x) if isinstance(x, str) else words_of(x) if x.tag in INLINE else [])]

        for i, b in enumerate(page.blocks):
            for w in words_of(b):
                got[i, 0 if inside[w] else 1] += 1
        for i in range(n - 1, 0, -1):
            got[page.parents[i]] += got[i]
        label = np.zeros(n, bool)
        whole = got[0, 0]
        for i in range(n):
            p = page.parents[i]
            # inside: below the smallest block that holds all article text, and not without any of it
            holds_all = got[i, 0] == whole and not any(got[c, 0] == whole for c in range(i + 1, n) if page.parents[c] == i)
            label[i] = got[i, 0] > 0 and ((p >= 0 and label[p]) or (holds_all and got[i, 0] > 0))
        made.append((page, label))
    tags = _code([(b.tag, bool(x)) for page, label in made for b, x in zip(page.blocks, label)])
    tokens = _code([(t, bool(x)) for page, label in made for b, x in zip(page.blocks, label) for t in attribute_tokens(b)])
    x = np.concatenate([page.features(tags, tokens) for page, _ in made])
    y = np.concatenate([label for _, label in made]).astype(float)
    return Extractor(tags, tokens, BoostedTrees().fit(x, y))


def _extract(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    tool: Extractor = shared.value
    for batch in batches:
        at = 0
        while at < batch.num_rows:
            part, size = [], 0
            while at + len(part) < batch.num_rows and len(part) < 128 and size < 1 << 21:
                part.append(batch.column(2)[at + len(part)].as_py() or "")
                size += len(part[-1])
            texts = tool.texts(part)
            here = batch.slice(at, len(part))
            yield pa.RecordBatch.from_arrays(
                [here.column(0), here.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"]
            )
            at += len(part)


def main_text(pages: DataFrame, extractor: Extractor | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of every row of ``pages`` (page_id, url, html); one narrow pass.

    Null or empty html and pages without article text give an empty text. Repeated rows come back each.
    """
    spark = pages.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(extractor or train())
    picked = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return picked.mapInArrow(lambda it: _extract(it, shared), "page_id long, url string, text string, n_chars long")
