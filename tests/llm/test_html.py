import collections
import html
import re
import time

import numpy as np
from helpers import SMALL

from hypertriad.llm import html_main as H


def test_blocks_of_broken_markup():
    page = """<!DOCTYPE html><title>t</title><script>var a="</p><p>no";</script><!-- <p>no</p> --><div class="Ad box">x&nbsp;y<p>one<b>two</b> &amp; <a href='>'>three</a><br>four<p>five</div>six</span><style>p{}</style><p>"""
    got = [(b.text, b.path) for b in H.blocks_of(page)]
    assert [t for t, _ in got] == ["t", "x y", "onetwo & three four", "five", "six"]
    assert got[0][1] == ("title",) and got[1][1] == ("div", ".ad", ".box") and got[2][1][-1] == "p" and got[4][1] == ()
    assert H.blocks_of(None) == H.blocks_of("") == H.blocks_of("<p></p>") == []
    assert [b.text for b in H.blocks_of("a < b <p")] == ["a < b <p"]
    assert len(H.blocks_of("<div>" * 20_000 + "x")) == 1
    page = "<article><p>Let <math><mi>x</mi></math> be <object>fallback</object> it<template><p>kept</p></template><iframe>also</iframe>"
    assert [b.text for b in H.blocks_of(page)] == ["Let x be fallback it", "kept", "also"]
    assert [b.text for b in H.blocks_of("<p title=don't>a</p><p title='>'>b</p><p title=\"x>c</p><p>d")] == ["a", "b", "c", "d"]


def test_scanner_is_linear():
    for piece in ("<a ", "<div>x", '<a b="x> ', "<a b='>' ", "<!--", "</p", "<title>", "<p class='", "<li><ul>", "&amp", "<a b=  "):
        page = piece * (1_000_000 // len(piece))
        began = time.time()
        H.blocks_of(page)
        took = time.time() - began
        assert took < 8, (piece, took)  # a quadratic scan takes many minutes
    began = time.time()
    H.numbers(H.blocks_of("<div class=c>x" * 70_000))
    assert time.time() - began < 10


def test_path_vectors_sum_distinct_tokens():
    blocks = H.blocks_of('<div class="a b"><div class="b c"><p>x<p class=a>y</p></div>z</div>w')
    net, page = H.Labeller(2), H.numbers(blocks)
    x, _ = net.inputs([page])
    for k, b in enumerate(blocks):
        rows = [H._row(t, H.PATH_ROWS) for t in dict.fromkeys(b.path)] + [H._row(f"leaf:{b.path[-1]}" if b.path else "leaf:", H.PATH_ROWS)]
        assert np.allclose(x[0, k, : H.PATH_DIM], net.p["path"][rows].sum(axis=0), atol=1e-5)


SHAPES = [
    ('<body><div id="masthead">Site name</div><div class="topnav"><a href="/">Home</a> <a href="/n">News</a></div><div class="story-text"><h1>A river floods.</h1><p>The river rose by two metres in the night.</p><p>Roads are closed.</p></div><div class="rail"><h3>Popular</h3><ul><li><a href="/1">Ten ways to cook</a></li><li><a href="/2">Cars of the year</a></li></ul></div><div class="colophon">(c) 2024 Site name. All rights reserved.</div>', "A river floods. The river rose by two metres in the night. Roads are closed."),
    ('<html><body><header><p>My blog</p></header><main><h1>On bread.</h1><p>Bread needs flour, water, salt and a lot of time.</p><ul><li>Mix the flour.<li>Let it rest.</ul><div class="newsletter-signup"><p>Get our letter every week!</p><button>Sign up</button></div><p>Bake it hot and long.</p></main><section id="comments"><h3>2 comments</h3><div class="comment"><p>Anna:</p><p>Lovely bread, thanks!</p></div></section><footer>Copyright my blog</footer>', "On bread. Bread needs flour, water, salt and a lot of time. Mix the flour. Let it rest. Bake it hot and long."),
    ('<body><div class="cookie-banner"><p>We use cookies.</p><button>OK</button></div><nav><ul><li><a href="/a">Docs</a><li><a href="/b">API</a></ul></nav><div class="markdown-body"><h2>Install.</h2><p>Fetch the archive and unpack it anywhere you like.</p><pre>tar xf archive</pre><p>Then run it.</p></div><aside><h3>Related</h3><p>Other tools that you may like.</p></aside><form><label>Search</label><input><button>Go</button></form><div id="footer">Made by us</div>', "Install. Fetch the archive and unpack it anywhere you like. tar xf archive Then run it."),
    ('<body><table><tr><td class="menu"><a href="/">Start</a> <a href="/x">Other</a></td><td class="content"><p>An old page in a table still has its text here, of a few words.</p><p>It goes on for a second paragraph.</p></td></tr></table><div class="sponsored">Buy these shoes now!</div>', "An old page in a table still has its text here, of a few words. It goes on for a second paragraph."),
]


def test_pages_of_other_shapes():
    net = H.trained()
    right = wrong = missed = 0
    for page, want in SHAPES:
        got = H.main_texts([page], net)[0].split()
        w = want.split()
        common = sum((collections.Counter(got) & collections.Counter(w)).values())
        right, wrong, missed = right + common, wrong + len(got) - common, missed + len(w) - common
    assert right / (right + wrong) >= 0.9 and right / (right + missed) >= 0.9, (right, wrong, missed)


def test_gradients_against_differences():
    net = H.Labeller(1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    pages = [H.numbers(b) for b, _ in H.examples(2, 8)]
    labels = [y for _, y in H.examples(2, 8)]

    def loss():
        x, mask = net.inputs(pages)
        p = net.scores(pages)
        return -sum(np.sum(y * np.log(q) + (1 - y) * np.log(1 - q)) for q, y in zip(p, labels)) / mask.sum()

    grad = net.step(pages, labels)
    for name, at in (("v", (3,)), ("Uf", (2, 5)), ("Wb", (7, 30)), ("cf", (25,)), ("v0", (0,))):
        kept, eps = net.p[name][at], 1e-3
        net.p[name][at] = kept + eps
        up = loss()
        net.p[name][at] = kept - eps
        down = loss()
        net.p[name][at] = kept
        assert abs((up - down) / (2 * eps) - grad[name][at]) < 2e-3 * max(1, abs(grad[name][at])), name


def test_held_out_templates():
    net = H.trained()
    made = [(b, y) for b, y in H.examples(120, 321) if b]
    right = [((p > 0.5) == (y > 0.5)).mean() for p, (_, y) in zip(net.scores([H.numbers(b) for b, _ in made]), made)]
    assert np.mean(right) > 0.99


def article(page):
    inner = re.search(r"<article>(.*)</article>", page, re.S).group(1)
    parts = (re.sub(r"<[^>]*>", " ", x) for x in re.split(r"</?(?:p|h1|li|div)[^>]*>", inner))
    return " ".join(x for x in (" ".join(html.unescape(q).split()) for q in parts) if x)


def test_given_pages(spark):
    pages = spark.read.parquet(f"{SMALL}/pages.parquet")
    want = {r["page_id"]: article(r["html"]) for r in pages.collect()}
    for r in H.extract(pages).collect():
        assert r["text"] == want[r["page_id"]] and r["n_chars"] == len(r["text"])


def test_odd_pages(spark):
    rows = [(1, "u", None, "x"), (2, None, "", "x"), (2, None, "", "x"), (None, "u", "<article><p>Long " + "word " * 50_000, "x")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = H.extract(df).collect()
    assert len(got) == 4 and [r["text"] for r in got[:3]] == ["", "", ""] and got[3]["n_chars"] > 200_000
    assert H.extract(df.where("false")).count() == 0
