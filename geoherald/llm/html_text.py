"""Main text of web pages: a linear-chain conditional random field over the leaf blocks of the DOM.

A lenient parser cuts a page into leaf blocks, runs of inline content between block-level tags, each with
its ancestors. Features are ancestor tags, words of their classes and ids, and traits of the text; the
chain has two labels. Weights are trained on labelled pages by stochastic ascent of the conditional
likelihood (forward-backward), and a page is decoded by Viterbi. ``labelled_pages`` generates pages of
many layouts with known labels; any iterable of (blocks, labels) can be trained on instead.

Results for odd rows: a null or empty page, or one without text, gives an empty text. Cut-off markup is
read to its end. A page of any length is one chain. Repeated rows give equal texts. Only the named
columns are read; a column named like an output column is replaced.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from math import log1p

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<close>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<rest>(?:\"[^\"]*\"|'[^']*'|[^>\"'])*)(?:>|\Z)"
    # a quote that never closes: up to the next >
    r"|<(?P<shut>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<tail>[^>]*)>"
    r"|</?[a-zA-Z][^>]*\Z",
    re.S,
)
#: A slash that ends an element at once, not the last character of an unquoted value.
SLASH = re.compile(r"(?:^|[\s\"'])/$")
ATTRIBUTE = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))", re.I)
# Element names.
RAW = frozenset("script style textarea title noscript template iframe noembed xmp".split())
UNSEEN = frozenset("svg select button object canvas math datalist".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var".split()
)
ENDS_ITSELF = {"li": "li", "p": "p", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "option": "option"}
WHITE = re.compile(r"\s+")
PARTS = re.compile(r"[a-z]+")
STOP = re.compile(r"[.!?…:;»”\"')]$")
SAYS = {
    "rights": re.compile(r"©|\(c\)|copyright|all rights|imprint|privacy", re.I),
    "cookie": re.compile(r"cookie|consent|gdpr", re.I),
    "account": re.compile(r"\b(sign in|log ?in|sign up|subscribe|newsletter|register)\b", re.I),
    "answer": re.compile(r"\b(repl(y|ies)|comments?|posted by|upvote)\b", re.I),
    "more": re.compile(r"\b(read more|related|share|tweet|follow us|advert|sponsored|previous|next)\b", re.I),
    "dots": re.compile(r"[·•›»|]"),
}


@dataclass
class Block:
    text: str
    path: list[tuple[str, tuple[str, ...]]]
    linked: int = 0


def blocks_of(page: str | None) -> list[Block]:
    """Leaf blocks of a page in order, with their open elements."""
    out: list[Block] = []
    stack: list[tuple[str, tuple[str, ...]]] = []
    parts: list[str] = []
    linked = hidden = links = 0

    def flush() -> None:
        nonlocal linked
        text = WHITE.sub(" ", "".join(parts)).strip()
        if text:
            out.append(Block(text, list(stack), linked))
        parts.clear()
        linked = 0

    def add(raw: str) -> None:
        nonlocal linked
        if raw and not hidden:
            text = html.unescape(raw)
            parts.append(text)
            if links:
                linked += len(text.strip())

    def pop() -> None:
        nonlocal hidden, links
        name, _ = stack.pop()
        hidden -= name in UNSEEN
        links -= name == "a"

    page, at = page or "", 0
    while True:
        m = TAG.search(page, at)
        if m is None:
            break
        add(page[at : m.start()])
        at = m.end()
        name, rest = m["name"] or m["tag"], m["rest"] or m["tail"] or ""
        if name is None:
            continue
        name = name.lower()
        if m["close"] or m["shut"]:
            if name not in INLINE:
                flush()
            if any(n == name for n, _ in stack):
                while stack[-1][0] != name:
                    pop()
                pop()
            continue
        if name == "br":
            parts.append(" ")
            continue
        if name in RAW:
            end = re.compile(rf"</{re.escape(name)}\b[^>]*>?", re.I).search(page, at)
            at = end.end() if end else len(page)
            continue
        if name not in INLINE and name not in VOID:
            flush()
            ends = ENDS_ITSELF.get(name, "p" if stack and stack[-1][0] == "p" else "").split()
            if stack and stack[-1][0] in ends:
                pop()
        if name in VOID or SLASH.search(rest):
            continue
        words = tuple(w for a in ATTRIBUTE.finditer(rest) for w in PARTS.findall(next(x for x in a.groups() if x is not None).lower()))
        stack.append((name, words))
        hidden += name in UNSEEN
        links += name == "a"
    add(page[at:])
    flush()
    return out


def _bucket(x: float) -> int:
    return int(log1p(x) * 1.5)


def block_features(blocks: list[Block]) -> list[list[str]]:
    """Names of the features that hold for each block."""
    out, titled = [], False
    for k, b in enumerate(blocks):
        names = [n for n, _ in b.path]
        solid = [n for n in names if n not in INLINE]
        f = ["bias", f"in:{solid[-1] if solid else ''}", f"depth:{min(len(solid), 8)}"]
        f += {f"tag:{n}" for n in names if n not in ("html", "body")}
        f += {f"word:{w}" for _, words in b.path for w in words}
        f += {f"near:{w}" for w in (b.path[-1][1] if b.path else ())}
        n, words = len(b.text), b.text.count(" ") + 1
        f.append(f"chars:{_bucket(n)}")
        f.append(f"linked:{int(4 * min(1.0, b.linked / n))}")
        f.append("ends" if STOP.search(b.text) else "open")
        if words < 4:
            f.append("brief")
        f += [f"says:{name}" for name, pattern in SAYS.items() if n < 400 and pattern.search(b.text)]
        f.append(f"place:{4 * k // len(blocks)}")
        titled = titled or "h1" in names
        f.append("titled" if titled else "untitled")
        out.append(f)
    return out


@dataclass
class ChainField:
    """Weights of a two-label chain: per feature, for neighbours, and for the first block."""

    weights: dict[str, tuple[float, float]] = field(default_factory=dict)
    steps: tuple[tuple[float, float], tuple[float, float]] = ((0.0, 0.0), (0.0, 0.0))

    def emissions(self, features: list[list[str]]) -> list[tuple[float, float]]:
        get, none = self.weights.get, (0.0, 0.0)
        out = []
        for names in features:
            a = b = 0.0
            for name in names:
                x, y = get(name, none)
                a += x
                b += y
            out.append((a, b))
        return out

    def viterbi(self, features: list[list[str]]) -> list[int]:
        """The most likely labels."""
        if not features:
            return []
        (s00, s01), (s10, s11) = self.steps
        emitted = self.emissions(features)
        a, b = emitted[0]
        back = []
        for x, y in emitted[1:]:
            from_a, from_b = int(b + s10 > a + s00), int(b + s11 > a + s01)
            a, b = (b + s10 if from_a else a + s00) + x, (b + s11 if from_b else a + s01) + y
            back.append((from_a, from_b))
        label = int(b > a)
        out = [label]
        for step in reversed(back):
            label = step[label]
            out.append(label)
        return out[::-1]


def train_chain(pages: Iterable[tuple[list[list[str]], list[int]]], rounds: int = 8, rate: float = 0.3, ridge: float = 1e-4, seed: int = 5) -> ChainField:
    """Adaptive stochastic ascent of the conditional log likelihood, page by page."""
    data = [(f, y) for f, y in pages if f]
    index: dict[str, int] = {}
    coded = [([np.array([index.setdefault(n, len(index)) for n in names]) for names in f], np.array(y)) for f, y in data]
    w, gw = np.zeros((len(index), 2)), np.full((len(index), 2), 1e-2)
    t, gt = np.zeros((2, 2)), np.full((2, 2), 1e-2)
    rng = random.Random(seed)
    for _ in range(rounds):
        rng.shuffle(coded)
        for rows, y in coded:
            e = np.stack([w[r].sum(axis=0) for r in rows])
            n = len(e)
            before, after = np.zeros((n, 2)), np.zeros((n, 2))
            before[0] = e[0]
            for k in range(1, n):
                before[k] = e[k] + np.logaddexp(before[k - 1, 0] + t[0], before[k - 1, 1] + t[1])
            for k in range(n - 2, -1, -1):
                x = t + e[k + 1] + after[k + 1]
                after[k] = np.logaddexp(x[:, 0], x[:, 1])
            whole = np.logaddexp(*before[-1])
            node = np.exp(before + after - whole)
            target = np.zeros((n, 2))
            target[np.arange(n), y] = 1.0
            delta = target - node
            for r, d in zip(rows, delta, strict=True):
                g = d - ridge * w[r]
                gw[r] += g * g
                w[r] += rate * g / np.sqrt(gw[r])
            if n > 1:
                pair = np.exp(before[:-1, :, None] + t[None] + (e + after)[1:, None, :] - whole).sum(axis=0)
                seen = np.zeros((2, 2))
                np.add.at(seen, (y[:-1], y[1:]), 1.0)
                g = seen - pair - ridge * t
                gt += g * g
                t += rate * g / np.sqrt(gt)
    return ChainField({n: (float(w[k, 0]), float(w[k, 1])) for n, k in index.items()}, tuple(tuple(map(float, r)) for r in t))


MARK = "\ue000"


class _PageMaker:
    """Pages of many layouts. Main text carries a mark, from which the labels are read off."""

    SYLLABLES = "an ber ca de er fo ga hi in jo ka lo mi no or pa qu re sa ti un ver wa xi ya zu".split()

    def __init__(self, rng: random.Random):
        self.rng = rng

    def word(self) -> str:
        return "".join(self.rng.choice(self.SYLLABLES) for _ in range(self.rng.randint(1, 4)))

    def words(self, low: int, high: int) -> str:
        return " ".join(self.word() for _ in range(self.rng.randint(low, high)))

    def prose(self, low: int = 1, high: int = 80) -> str:
        text = self.words(low, high).capitalize() + "."
        style = self.rng.random()
        if style < 0.08:
            text = text.replace(" ", self.rng.choice(["%%% ", " | ", "!! ", "&amp;&amp; "]))
        elif style < 0.12:
            text = text.upper()
        elif style < 0.3:
            text = text.replace(" ", " <b>x</b> ", 1).replace(" ", ' <a href="/x">y</a> ', 1)
        return text

    def main(self, text: str) -> str:
        return MARK + text

    def pick(self, *options):
        return self.rng.choice(options)

    def links(self, low: int = 3, high: int = 8) -> str:
        items = "".join(f'<li><a href="/{self.word()}">{self.words(1, 3)}</a></li>' for _ in range(self.rng.randint(low, high)))
        return f"<ul>{items}</ul>"

    def junk(self) -> str:
        r, name = self.rng, self.word()
        kind = r.randrange(13)
        if kind == 0:
            name, rest = self.pick(("nav", ""), ("div", " class=menu"), ("header", ""), ("div", " id=navigation"))
            return f"<{name}{rest}>{self.links()}</{name}>"
        if kind == 1:
            return f'<div class="{self.pick("ad", "advert", "ads banner", "sponsored", "promo")}">{self.prose(2, 25)}</div>'
        if kind == 2:
            return f'<{(s := self.pick("aside", "div"))} class="{self.pick("sidebar", "widget", "related", "side column")}"><h3>{self.words(1, 4)}</h3>{self.links()}<p>{self.prose(3, 30)}</p></{s}>'
        if kind == 3:
            return f'<div class="{self.pick("cookie notice", "notice", "consent banner", "alert")}"><p>We use cookies. {self.prose(3, 20)}</p><button>Accept</button></div>'
        if kind == 4:
            return f'<form action="/s"><label>{self.words(1, 4)}</label><input name="q"><p>{self.prose(2, 12)}</p><select><option>{name}</option></select></form>'
        if kind == 5:
            people = "".join(f'<div class="comment"><span class="author">{self.word()}</span><p>{self.prose(3, 60)}</p></div>' for _ in range(r.randint(1, 5)))
            return f'<{(s := self.pick("section", "div"))} {self.pick("id=comments", "class=comments", "class=responses")}><h2>{r.randint(1, 30)} comments</h2>{people}</{s}>'
        if kind == 6:
            return f"<footer>{self.pick('&copy; ', '', 'Copyright ')}{name}.com {self.pick('&middot;', '|', '')} {self.prose(2, 25)}</footer>"
        if kind == 7:
            return f'<div class="{self.pick("share", "social", "breadcrumb", "tags", "pagination")}"><a href="/">{name}</a> &gt; <a href="/b">{self.words(1, 2)}</a></div>'
        if kind == 8:
            return f'<header><div class="{self.pick("logo", "site title", "brand")}"><a href="/">{name}</a></div><p>{self.prose(2, 10)}</p></header>'
        if kind == 9:
            return f"<div class=\"newsletter\"><h4>Subscribe</h4><p>{self.prose(4, 20)}</p></div>"
        if kind == 10:
            return f"<script>var a = '<p>{name}</p>';</script><style>p {{ margin: 0 }}</style><!-- {name} -->"
        if kind == 11:
            return f'<div class="footer" id="{self.pick("footer", "bottom", "legal")}"><p>{self.prose(3, 25)}</p>{self.links(2, 4)}</div>'
        return f"<nav>{self.links()}</nav>"

    def article(self) -> str:
        r = self.rng
        body = [f"<h1>{self.main(self.prose(2, 10))}</h1>"] if r.random() < 0.9 else []
        for _ in range(r.randint(1, 14)):
            kind = r.random()
            text = self.main(self.prose(1, 90))
            if kind < 0.6:
                body.append(f"<p>{text}" + self.pick("</p>", "</p>", ""))
            elif kind < 0.68:
                body.append(f"<p><b>{text}<br>")
            elif kind < 0.74:
                body.append(f"<h2>{self.main(self.words(1, 6))}</h2>")
            elif kind < 0.8:
                body.append(f"<blockquote><p>{text}</p></blockquote>")
            elif kind < 0.86:
                body.append("<ul>" + "".join(f"<li>{self.main(self.prose(1, 15))}</li>" for _ in range(r.randint(2, 5))) + "</ul>")
            elif kind < 0.9:
                body.append(f"<div>{text}</div>")
            elif kind < 0.93:
                body.append(f"<table><tr><td>{self.main(self.words(1, 4))}</td><td>{self.main(self.words(1, 4))}</td></tr></table>")
            else:
                body.append(f'<div class="{self.pick("ad", "promo", "related", "share", "newsletter")}">{self.prose(2, 20)}</div>')
        inner = "".join(body)
        shape = r.random()
        if shape < 0.5:
            return f"<article>{inner}</article>"
        if shape < 0.65:
            return f"<main>{inner}</main>"
        if shape < 0.75:
            return f"<main><article class=\"{self.pick('post', 'story', 'entry')}\">{inner}</article></main>"
        name = self.pick("content", "article body", "post content", "entry", "story", "main text")
        return f'<div {self.pick("class", "id")}="{name}">{inner}</div>'

    def page(self) -> str:
        r = self.rng
        top = "".join(self.junk() for _ in range(r.randint(0, 4)))
        bottom = "".join(self.junk() for _ in range(r.randint(0, 4)))
        head = f"<head><title>{self.prose(2, 8)}</title></head>"
        page = f"<!DOCTYPE html><html>{head}<body>{top}{self.article()}{bottom}</body></html>"
        return page.replace("</body></html>", "") if r.random() < 0.1 else page


def labelled_pages(n: int, seed: int = 17) -> Iterator[tuple[list[Block], list[int]]]:
    """Blocks and labels (1: main text) of ``n`` generated pages."""
    for k in range(n):
        blocks = blocks_of(_PageMaker(random.Random(seed * 1_000_003 + k)).page())
        labels = [int(MARK in b.text) for b in blocks]
        for b in blocks:
            b.text = b.text.replace(MARK, "")
        yield blocks, labels


@lru_cache(maxsize=4)
def default_chain(pages: int = 500) -> ChainField:
    return train_chain((block_features(b), y) for b, y in labelled_pages(pages))


def main_text(page: str | None, chain: ChainField) -> str:
    blocks = blocks_of(page)
    labels = chain.viterbi(block_features(blocks))
    return " ".join(b.text for b, y in zip(blocks, labels, strict=True) if y)


def text_column(page: Column, chain: ChainField) -> Column:
    @F.arrow_udf(T.StringType())
    def extract(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for pages in batches:
            yield pa.array([main_text(p, chain) for p in pages.to_pylist()], pa.string())

    return extract(page.cast("string"))


def extract_text(pages: DataFrame, page: str = "html", chain: ChainField | None = None) -> DataFrame:
    """Every row with ``text`` and ``n_chars`` (its code points) added."""
    rows = pages.select(*[F.col(f"`{c}`") for c in pages.columns if c not in {"text", "n_chars"}])
    rows = rows.withColumn("text", text_column(F.col(f"`{page}`"), chain or default_chain()))
    return rows.withColumn("n_chars", F.length("text").cast("long"))
