"""Main text of web pages: a recurrent labeller over the sequence of leaf blocks.

A forgiving scanner, linear in the page, turns it into leaf blocks, each with its path of elements, classes and ids; paths
are nodes of a tree, so deep pages share them.  A bidirectional LSTM in numpy reads, for every block, a vector of its path,
a vector of its hashed words and a few measures, and labels every block as main text or not, with the whole page as
context.  Nothing but scripts, styles and comments is dropped before it.  It is trained here on pages of many layouts made
by a seeded generator.
"""

from __future__ import annotations

import html
import random
import re
import zlib
from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PATH_ROWS, PATH_DIM = 1024, 24
WORD_ROWS, WORD_DIM = 1024, 12
MEASURES = 6
INPUT = PATH_DIM + WORD_DIM + MEASURES
HIDDEN = 20
#: Blocks times pages of one padded batch.
BATCH_CELLS = 60_000

# Elements of the HTML, SVG and MathML standards by how they take part in blocks.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr object svg g text tspan math mi mn mo ms mtext mrow msub msup msubsup mfrac msqrt mroot munder mover munderover semantics".split())
RAW = frozenset("script style".split())
RAW_TEXT = frozenset("title textarea".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())

_NAME = re.compile(r"/?[a-zA-Z][^\s/>]*")
_MARK = re.compile(r"[>\"']")
_NAMED = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_TOKEN = re.compile(r"[a-z]+")
_CLOSED_BY_START = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}


class Node:
    """An open element: its tokens, those of them that its ancestors lack, and how many tokens lie on its path."""

    __slots__ = ("name", "own", "fresh", "parent", "depth")

    def __init__(self, name: str, own: tuple[str, ...], fresh: tuple[str, ...], parent: Node | None):
        self.name, self.own, self.fresh, self.parent = name, own, fresh, parent
        self.depth = len(own) + (parent.depth if parent else 0)


class Block:
    __slots__ = ("node", "text", "linked")

    def __init__(self, node: Node | None, text: str, linked: float):
        self.node, self.text, self.linked = node, text, linked

    @property
    def path(self) -> tuple[str, ...]:
        """All tokens from the outermost element on."""
        out, node = [], self.node
        while node:
            out.append(node.own)
            node = node.parent
        return tuple(t for own in reversed(out) for t in own)


class _Tags:
    """Finds where tags end.  A > inside a quoted value ends none; quotes count after = only, and where they are closed.
    Should all that is left turn out to be inside quotes, the first > ends a tag from there on, so no text is read twice."""

    def __init__(self, page: str):
        self.page, self.plain = page, False
        self.last = {c: page.rfind(c) for c in ">\"'"}

    def end(self, at: int) -> int:
        """The place of the > that ends the tag whose name ends at ``at``, or -1."""
        page, first = self.page, at
        if at > self.last[">"]:
            return -1
        while not self.plain:
            m = _MARK.search(page, at)
            if m is None:
                self.plain = True
                break
            c, k = m.group(), m.start()
            if c == ">":
                return k
            before = k - 1
            while before > at and page[before] in " \t\n\r\f":
                before -= 1
            at = page.index(c, k + 1) + 1 if page[before] == "=" and self.last[c] > k else k + 1
        return page.find(">", first)


def blocks_of(page: str | None) -> list[Block]:
    """Leaf blocks with text, in page order.  Unclosed, unopened and crossing elements are taken as they come."""
    page = page or ""
    out: list[Block] = []
    top: Node | None = None
    named: Counter = Counter()  # open elements by name
    tokens: Counter = Counter()  # tokens on the path
    held: list[str] = []
    link = linked = all_ = 0

    def flush() -> None:
        nonlocal linked, all_
        if held:
            text = " ".join(html.unescape("".join(held)).split())
            if text:
                out.append(Block(top, text, linked / max(1, all_)))
            held.clear()
        linked = all_ = 0

    def close() -> None:
        nonlocal top
        named[top.name] -= 1
        tokens.subtract(top.own)
        top = top.parent

    def say(piece: str) -> None:
        nonlocal linked, all_
        held.append(piece)
        n = len(piece.strip())
        all_ += n
        linked += n if link else 0

    tags, at, n = _Tags(page), 0, len(page)
    lower = page.lower() if len(page.lower()) == n else None  # for ends of raw elements
    while at < n:
        lt = page.find("<", at)
        if lt != at:
            say(page[at : lt if lt >= 0 else n])
            at = lt if lt >= 0 else n
            continue
        if page.startswith("<!--", at):
            end = page.find("-->", at + 4)
            at = end + 3 if end >= 0 else n
            continue
        if page.startswith(("<!", "<?"), at):
            end = page.find(">", at + 2)
            at = end + 1 if end >= 0 else n
            continue
        m = _NAME.match(page, at + 1)
        end = tags.end(m.end()) if m else -1
        if end < 0:
            say("<")
            at += 1
            continue
        rest, at = page[m.end() : end], end + 1
        name = m.group().lower()
        ending, name = name.startswith("/"), name.removeprefix("/")
        if name == "a":
            link = 0 if ending else 1
        if name in RAW or name in RAW_TEXT:
            if ending or rest.endswith("/"):
                continue
            if lower is not None:
                stop = lower.find(f"</{name}", at)
            else:
                found = re.compile(f"</{name}", re.I).search(page, at)
                stop = found.start() if found else -1
            inside = page[at : stop if stop >= 0 else n]
            gt = page.find(">", stop) if stop >= 0 else -1
            at = gt + 1 if gt >= 0 else n
            if name in RAW_TEXT and inside.strip():
                flush()
                node = top
                top = Node(name, (name,), () if tokens[name] > 0 else (name,), node)
                say(inside)
                flush()
                top = node
            continue
        if name == "br":
            held.append(" ")
            continue
        if name in INLINE:
            continue
        flush()
        link = 0
        if name in VOID:
            continue
        if ending:
            if named[name] > 0:
                while top.name != name:
                    close()
                close()
            continue
        closes = _CLOSED_BY_START.get(name, {"p"} if name not in ("html", "body") else set())
        while top and top.name in closes:
            close()
        own = [name]
        for found in _NAMED.findall(rest):
            own += [f".{t}" for t in _TOKEN.findall("".join(found).lower())]
        top = Node(name, tuple(own), tuple(t for t in dict.fromkeys(own) if tokens[t] <= 0), top)
        named[name] += 1
        tokens.update(own)
    flush()
    return out


# --- vectors of blocks ----------------------------------------------------------------------------------------------


@lru_cache(maxsize=200_000)
def _row(token: str, rows: int) -> int:
    return zlib.crc32(token.encode("utf-8", "replace")) % rows


@dataclass
class Numbers:
    """A page for the labeller.  Path nodes stand parents first: the parent of each (-1: none), and the rows they add with
    the node of each row; for each block its node (-1: none), the row of its leaf, how many words it has (one at least) and
    its measures; and the rows of all words, block by block."""

    parent: list[int]
    add_rows: np.ndarray
    add_node: np.ndarray
    node: np.ndarray
    leaf: np.ndarray
    word_rows: np.ndarray
    counts: np.ndarray
    measures: np.ndarray


def numbers(blocks: list[Block]) -> Numbers:
    place: dict[int, int] = {}
    parent, add_rows, add_node, at, leaf, words, counts = [], [], [], [], [], [], []
    m = np.zeros((len(blocks), MEASURES), np.float32)
    for k, b in enumerate(blocks):
        chain, node = [], b.node
        while node is not None and id(node) not in place:
            chain.append(node)
            node = node.parent
        for node in reversed(chain):
            place[id(node)] = len(parent)
            add_rows += [_row(t, PATH_ROWS) for t in node.fresh]
            add_node += [len(parent)] * len(node.fresh)
            parent.append(place[id(node.parent)] if node.parent is not None else -1)
        at.append(place[id(b.node)] if b.node is not None else -1)
        leaf.append(_row(f"leaf:{b.node.own[-1]}" if b.node is not None else "leaf:", PATH_ROWS))
        w = b.text.lower().split()
        words += [_row(t, WORD_ROWS) for t in w]
        counts.append(len(w))
        depth = b.node.depth if b.node is not None else 0
        m[k] = (np.log1p(len(b.text)) / 6, b.linked, min(1.0, len(w) / 30), k / max(1, len(blocks) - 1), b.text[-1] in ".!?", min(3.0, depth / 10))
    ints = lambda v: np.array(v, np.int64)
    return Numbers(parent, ints(add_rows), ints(add_node), ints(at), ints(leaf), ints(words), ints(counts), m)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Labeller:
    """Embeddings, two LSTM directions and a logistic output; parameters live in one dictionary."""

    def __init__(self, seed: int = 3):
        r = np.random.default_rng(seed)
        d = lambda *s, k=0.1: (r.standard_normal(s) * k).astype(np.float32)
        self.p = {"path": d(PATH_ROWS, PATH_DIM), "word": d(WORD_ROWS, WORD_DIM, k=0.02), "v": d(2 * HIDDEN), "v0": np.zeros(1, np.float32)}
        for side in "fb":
            self.p |= {f"W{side}": d(INPUT, 4 * HIDDEN, k=INPUT**-0.5), f"U{side}": d(HIDDEN, 4 * HIDDEN, k=HIDDEN**-0.5), f"c{side}": np.repeat(np.array([0, 1, 0, 0], np.float32), HIDDEN)}

    def inputs(self, pages: list[Numbers]) -> tuple[np.ndarray, np.ndarray]:
        t = max(len(p.node) for p in pages)
        x, mask = np.zeros((len(pages), t, INPUT), np.float32), np.zeros((len(pages), t, 1), np.float32)
        path, word = self.p["path"], self.p["word"]
        for i, page in enumerate(pages):
            n = len(page.node)
            sums = np.zeros((len(page.parent) + 1, PATH_DIM), path.dtype)  # the last row is that of no node
            np.add.at(sums, page.add_node, path[page.add_rows])
            for k, up in enumerate(page.parent):
                if up >= 0:
                    sums[k] += sums[up]
            x[i, :n, :PATH_DIM] = sums[page.node] + path[page.leaf]
            starts = np.cumsum(page.counts) - page.counts
            x[i, :n, PATH_DIM : PATH_DIM + WORD_DIM] = np.add.reduceat(word[page.word_rows], starts) / page.counts[:, None]
            x[i, :n, -MEASURES:] = page.measures
            mask[i, :n] = 1
        return x, mask

    def _run(self, x: np.ndarray, mask: np.ndarray, side: str, keep: list | None = None) -> np.ndarray:
        n, steps, _ = x.shape
        z_in, u = x @ self.p[f"W{side}"] + self.p[f"c{side}"], self.p[f"U{side}"]
        h = c = np.zeros((n, HIDDEN), np.float32)
        out = np.zeros((n, steps, HIDDEN), np.float32)
        for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
            z = z_in[:, t] + h @ u
            s = _sigmoid(z[:, : 3 * HIDDEN])
            i, f, o, g = s[:, :HIDDEN], s[:, HIDDEN : 2 * HIDDEN], s[:, 2 * HIDDEN :], np.tanh(z[:, 3 * HIDDEN :])
            c2 = f * c + i * g
            y = np.tanh(c2)
            m = mask[:, t]
            if keep is not None:
                keep.append((t, h, c, i, f, o, g, y))
            c, h = m * c2 + (1 - m) * c, m * o * y + (1 - m) * h
            out[:, t] = h
        return out

    def _back(self, x, mask, side, keep, d_out, grad) -> np.ndarray:
        w, u = self.p[f"W{side}"], self.p[f"U{side}"]
        dz_all = np.zeros((*x.shape[:2], 4 * HIDDEN), np.float32)
        dh = dc = np.zeros((len(x), HIDDEN), np.float32)
        for t, h, c, i, f, o, g, y in reversed(keep):
            m = mask[:, t]
            dh = dh + d_out[:, t]
            d2, stay = dh * m, dh * (1 - m)
            dct = dc * m + d2 * o * (1 - y * y)
            dz = np.hstack([dct * g * i * (1 - i), dct * c * f * (1 - f), d2 * y * o * (1 - o), dct * i * (1 - g * g)])
            dz_all[:, t] = dz
            grad[f"U{side}"] += h.T @ dz
            dh = dz @ u.T + stay
            dc = dct * f + dc * (1 - m)
        flat = dz_all.reshape(-1, 4 * HIDDEN)
        grad[f"W{side}"] += x.reshape(-1, INPUT).T @ flat
        grad[f"c{side}"] += flat.sum(axis=0)
        return dz_all @ w.T

    def scores(self, pages: list[Numbers]) -> list[np.ndarray]:
        """The probability of main text for every block of every page (pages as ``numbers`` gives them, none empty)."""
        x, mask = self.inputs(pages)
        h = np.concatenate([self._run(x, mask, "f"), self._run(x, mask, "b")], axis=2)
        p = _sigmoid(h @ self.p["v"] + self.p["v0"])
        return [p[i, : len(q.node)] for i, q in enumerate(pages)]

    def step(self, pages: list[Numbers], labels: list[np.ndarray]) -> dict[str, np.ndarray]:
        """Gradients of the mean log loss of a batch."""
        x, mask = self.inputs(pages)
        kf, kb = [], []
        h = np.concatenate([self._run(x, mask, "f", kf), self._run(x, mask, "b", kb)], axis=2)
        p = _sigmoid(h @ self.p["v"] + self.p["v0"])
        y = np.zeros_like(p)
        for i, q in enumerate(labels):
            y[i, : len(q)] = q
        d = (p - y) * mask[:, :, 0] / mask.sum()
        grad = {k: np.zeros_like(v) for k, v in self.p.items()}
        grad["v"] = np.einsum("ntk,nt->k", h, d)
        grad["v0"] = d.sum(keepdims=True).reshape(1)
        dh = d[:, :, None] * self.p["v"]
        dx = self._back(x, mask, "f", kf, dh[:, :, :HIDDEN], grad) + self._back(x, mask, "b", kb, dh[:, :, HIDDEN:], grad)
        for i, page in enumerate(pages):
            n, below = len(page.node), np.zeros((len(page.parent) + 1, PATH_DIM), np.float32)
            np.add.at(below, page.node, dx[i, :n, :PATH_DIM])
            np.add.at(grad["path"], page.leaf, dx[i, :n, :PATH_DIM])
            for k in range(len(page.parent) - 1, -1, -1):
                if page.parent[k] >= 0:
                    below[page.parent[k]] += below[k]
            np.add.at(grad["path"], page.add_rows, below[page.add_node])
            each = dx[i, :n, PATH_DIM : PATH_DIM + WORD_DIM] / page.counts[:, None]
            np.add.at(grad["word"], page.word_rows, np.repeat(each, page.counts, axis=0))
        return grad


def fit(examples: list[tuple[list[Block], np.ndarray]], epochs: int = 9, rate: float = 0.01, batch: int = 40, seed: int = 3) -> Labeller:
    """Adam on the log loss of block labels."""
    net, r = Labeller(seed), random.Random(seed)
    ready = [(numbers(b), y) for b, y in examples if b]
    t = 0
    m1, m2 = ({k: np.zeros_like(v) for k, v in net.p.items()} for _ in range(2))
    for epoch in range(epochs):
        r.shuffle(ready)
        for a in range(0, len(ready), batch):
            part = ready[a : a + batch]
            grad = net.step([p for p, _ in part], [y for _, y in part])
            t += 1
            for k, g in grad.items():
                m1[k] = 0.9 * m1[k] + 0.1 * g
                m2[k] = 0.99 * m2[k] + 0.01 * g * g
                net.p[k] -= (rate * (0.8**epoch) * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.99**t)) + 1e-7)).astype(np.float32)
    return net


# --- training pages -------------------------------------------------------------------------------------------------

MAIN, OTHER = "\x01", "\x02"  # marks before each training block's text


def made_page(r: random.Random) -> str:
    """A page of a random template whose texts begin with MAIN or OTHER."""
    syllables = "th er an on in re he ed nd ha at en es or nt ea ti to it st io le is ou ar as de rt ve".split()
    word = lambda: "".join(r.choice(syllables) for _ in range(r.randint(1, 3)))
    words = lambda a, b: " ".join(word() for _ in range(r.randint(a, b)))
    line = lambda a=3, b=25: words(a, b).capitalize() + r.choice((".", ".", "!", "?"))
    other = lambda s: OTHER + s
    links = lambda n: "".join(f'<li><a href="/{word()}">{other(words(1, 2))}</a></li>' for _ in range(n))
    text = lambda: MAIN + " ".join(line() for _ in range(r.randint(1, 6)))

    def paragraph() -> str:
        pick = r.random()
        if pick < 0.12:
            return f"<p><b>{text()}<br>"  # never closed
        if pick < 0.2:
            return f"<h{r.randint(2, 4)}>{MAIN}{line(1, 6)}</h2>"
        if pick < 0.28:
            return "<ul>" + "".join(f"<li>{MAIN}{line()}" for _ in range(r.randint(2, 5))) + "</ul>"
        if pick < 0.32:
            return f"<blockquote><p>{text()}</p></blockquote>"
        if pick < 0.36:
            return f"<table><tr><td>{MAIN}{words(1, 3)}</td><td>{MAIN}{words(1, 3)}</td></tr></table>"
        if pick < 0.42:
            return f"<div>{text()}</div>"
        if pick < 0.46:
            return f"<pre>{MAIN}{words(3, 9)}</pre>"
        if pick < 0.49:
            return f"<figure><img src='x.png'><figcaption>{MAIN}{line(2, 9)}</figcaption></figure>"
        if pick < 0.51:
            return f"<p>{text()} <math><mi>x</mi></math> {words(2, 8)}.</p>"
        if pick < 0.53:
            return f"<dl><dt>{MAIN}{words(1, 2)}<dd>{MAIN}{line()}</dl>"
        if pick < 0.6:
            return f"<p>{MAIN}{line(1, 4)}</p>"
        return f"<p>{text()} <a href='/x'>{words(1, 3)}</a> {words(2, 8)}.</p>" if pick < 0.74 else f"<p>{text()}</p>"

    made = lambda: r.choice((word(), f"{word()}-{word()}", f"{word()}__{word()}", f"css-{word()}"))

    def boxed(kinds: str, body: str, tags: tuple[str, ...] = ("div", "div", "section")) -> str:
        """A box whose class or id says what it holds, often beside words that say nothing."""
        kind = r.choice(kinds.split())
        name = r.choice((kind, kind, f"{kind} {made()}", f"{made()} {kind}", f"{kind}-{word()}", f"{word()}-{kind}"))
        tag = r.choice(tags)
        return f'<{tag} {r.choice(("class", "class", "id"))}="{name}">{body}</{tag}>'

    def advert() -> str:
        return boxed("ad ads advert adslot sponsored sponsor promo promoted advertisement banner-ad outbrain", r.choice((other(line()), f"<p>{other(line())}</p>", f"<p>{other(words(1, 3))}</p><a href='/{word()}'>{other(words(1, 4))}</a>")), ("div", "aside", "section"))

    def notice() -> str:
        body = r.choice((f"<p>{other(line())}</p><button>{other(words(1, 2))}</button>", f"{other(line())} <a href='/x'>{words(1, 2)}</a>"))
        return boxed("cookie-notice notice cookie consent gdpr alert newsletter subscribe paywall popup modal overlay disclaimer announcement toast privacy", body)

    def form() -> str:
        inner = f'<label>{other(words(1, 3))}</label><input name="q"><select><option>{other(word())}<option>{other(word())}</select><p>{other(line(2, 8))}</p><textarea>{other(words(1, 3))}</textarea><button>{other(words(1, 2))}</button>'
        return r.choice((f'<form action="/s">{inner}</form>', boxed("search contact signup login", f"<form>{inner}</form>"), f"<fieldset><legend>{other(words(1, 2))}</legend>{inner}</fieldset>"))

    def sidebar() -> str:
        listed = f"<ul>{links(r.randint(2, 6))}</ul>" if r.random() < 0.7 else "".join(f"<p>{other(line(2, 8))}</p>" for _ in range(r.randint(1, 3)))
        inner = f"<h{r.randint(2, 4)}>{other(words(1, 3))}</h3>{listed}" + (f"<p>{other(line())}</p>" if r.random() < 0.5 else "")
        return f"<aside>{inner}</aside>" if r.random() < 0.35 else boxed("sidebar side rail widget related popular trending recommended secondary column-right more-stories tags archive most-read author-bio share social", inner, ("div", "div", "aside", "section"))

    def comments() -> str:
        one = lambda: f'<{(t := r.choice(("div", "li", "article")))} class="{r.choice(("comment", "comment-body", "reply", "response", "message"))}"><p>{other(line(1, 4))}</p><p>{other(line())}</p></{t}>'
        return boxed("comments comment-list discussion respond reader-comments replies responses disqus thread feedback", f"<h3>{other(words(1, 3))}</h3>" + "".join(one() for _ in range(r.randint(1, 4))), ("div", "section", "ol"))

    def menu() -> str:
        body = r.choice((f"<ul>{links(r.randint(3, 8))}</ul>", "".join(f"<a href='/{word()}'>{other(word())}</a> " for _ in range(4))))
        return f"<nav>{body}</nav>" if r.random() < 0.45 else boxed("menu nav navbar navigation breadcrumb breadcrumbs topnav tabs toolbar pagination pager", body, ("div", "nav", "div"))

    def header() -> str:
        return r.choice(("", f"<header><h1>{other(words(1, 4))}</h1>{menu()}</header>", f'<header class="site-header"><p>{other(words(1, 5))}</p></header>', boxed("header masthead topbar site-head logo branding", r.choice((f"<p>{other(line(2, 8))}</p>", other(words(1, 4)) + menu())))))

    def footer() -> str:
        sign = r.choice(("&copy; ", "(c) ", "Copyright ", "", "&#169; 2024 "))
        body = r.choice((other(sign + word() + r.choice((" &middot; ", " | ", ". ", " - ")) + line()), f"<p>{other(line())}</p><ul>{links(3)}</ul>", f"<p>{other(sign + words(1, 4))}</p>"))
        return f"<footer>{body}</footer>" if r.random() < 0.6 else boxed("footer colophon copyright legal site-info bottom credits", body)

    extras = [advert, notice, form, sidebar, comments]
    some = lambda p: "".join(f() for f in extras if r.random() < p)
    names = "content post article-body entry story main-content text entry-content post-content rich-text prose body-copy page-content markdown-body story-body single"
    wrap = r.random()
    if wrap < 0.4:
        open_, close = "<article>", "</article>"
    elif wrap < 0.52:
        open_, close = r.choice((("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<div role="main">', "</div>")))
    elif wrap < 0.85:
        tag = r.choice(("div", "div", "section", "article"))
        open_, close = f'<{tag} {r.choice(("class", "id"))}="{r.choice(names.split())}{r.choice(("", "", " " + made()))}">', f"</{tag}>"
    elif wrap < 0.95:
        open_, close = r.choice((("<div>", "</div>"), (f'<div class="{made()}">', "</div>"), ("<table><tr><td>", "</td></tr></table>")))
    else:
        open_ = close = ""
    inside = [f"<h1>{MAIN}{line(2, 9)}</h1>"] * (r.random() < 0.85) + [paragraph() for _ in range(r.randint(1, 12))]
    for f in extras:
        if r.random() < 0.08:
            inside.insert(r.randint(0, len(inside)), f())
    fallback = f"<noscript><p>{other(line(2, 9))}</p></noscript>" if r.random() < 0.1 else ""
    body = (header() + (menu() if r.random() < 0.85 else "")) + fallback + "<!-- ad 1 -->" * (r.random() < 0.5) + some(0.25) + open_ + "".join(inside) + close + some(0.3) + footer()
    if r.random() < 0.3:
        body = f'<div {r.choice(("class", "id"))}="{r.choice(("wrapper", "page", "container", "layout", "app", "root", made()))}">{body}</div>'
    head = f'<!DOCTYPE html><html lang="en"><head><meta charset="utf-8"><title>{other(words(2, 6))}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head><body>'
    return head + body + r.choice(("</body></html>", ""))


def examples(n: int, seed: int) -> list[tuple[list[Block], np.ndarray]]:
    r, out = random.Random(seed), []
    for _ in range(n):
        blocks = blocks_of(made_page(r))
        y = np.array([MAIN in b.text for b in blocks], np.float32)
        for b in blocks:
            b.text = b.text.replace(MAIN, "").replace(OTHER, "") or "."
        out.append((blocks, y))
    return out


@lru_cache(maxsize=1)
def trained(pages: int = 800, seed: int = 5) -> Labeller:
    return fit(examples(pages, seed))


# --- pages to text --------------------------------------------------------------------------------------------------


def main_texts(pages: list[str | None], net: Labeller) -> list[str]:
    """The main text of each whole page; empty where there is none."""
    split = [blocks_of(p) for p in pages]
    out = [""] * len(pages)
    order = sorted((i for i, b in enumerate(split) if b), key=lambda i: len(split[i]))
    while order:
        part = [order.pop()]
        while order and len(split[part[0]]) * (len(part) + 1) <= BATCH_CELLS and len(part) < 256:
            part.append(order.pop())
        for i, p in zip(part, net.scores([numbers(split[i]) for i in part])):
            out[i] = " ".join(b.text for b, s in zip(split[i], p) if s > 0.5)
    return out


def extract(pages: DataFrame, net: Labeller | None = None) -> DataFrame:
    """page_id, url, text and n_chars of every page, a row for each row.

    Null html counts as empty and gives an empty text; so does a page without main text.  Repeated pages give repeated rows;
    columns besides page_id, url and html are not read.  Empty table: empty result.
    """
    sent = pages.sparkSession.sparkContext.broadcast(net or trained())

    @F.pandas_udf("string")
    def main(s: pd.Series) -> pd.Series:
        out: list[str] = []
        for at in range(0, len(s), 512):
            out += main_texts([p if isinstance(p, str) else None for p in s[at : at + 512]], sent.value)
        return pd.Series(out, dtype=object)

    got = pages.select("page_id", "url", main("html").alias("text"))
    return got.withColumn("n_chars", F.length("text").cast("long"))
