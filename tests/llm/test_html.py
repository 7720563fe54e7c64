import html as html_lib
import itertools
import re

import numpy as np
import pytest
from pyspark.sql import types as T

from cdfblend.llm import html_extract as H
from cdfblend.llm import html_training as TR
from cdfblend.llm.html_tree import Kinds, read

PAGES = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("html", T.StringType()), T.StructField("text", T.StringType())])


@pytest.fixture(scope="module")
def model():
    return H.default_model()


def test_marginals_equal_enumeration():
    rng = np.random.default_rng(0)
    kinds = Kinds()
    pages = [read("<article><p>a b</p><div><ul><li>x<li>y</ul></div></article>", kinds), read("<p>one", kinds), read("", kinds)]
    f, k = H.Forest.of(pages, kinds), H.KindFeatures.of(kinds)
    m = H.TreeModel(rng.normal(size=H.FEATURES), rng.normal(size=(3, 2, 2)))
    node, edge = m.beliefs(f, k)
    own = np.array([sum(m.unary[len(H.TAGS) + b] / np.sqrt(len(names)) for b in names) + m.unary[tag] for tag, names in (kinds.rows[i] for i in f.kind)]) + f.stats @ m.unary[H.NAMED :]
    coupling = k.coupling[f.kind]
    at = 0
    for p in pages:
        n = len(p.parent)
        total, marg = 0.0, np.zeros(n)
        for s in itertools.product((0, 1), repeat=n):
            w = np.exp(sum(own[at + i] * s[i] for i in range(n)) + sum(m.pair[coupling[at + i], s[p.parent[i]], s[i]] for i in range(1, n)))
            total += w
            marg += w * np.array(s)
        assert np.allclose(node[at : at + n, 1], marg / total)
        at += n


def test_held_out_pages(model):
    kinds = Kinds()
    pages = [read(h, kinds, TR.MARK) for h, _ in TR.labelled_pages(150, 991)]
    f = H.Forest.of(pages, kinds)
    y = np.array([m == "1" for p in pages for m in p.marks])
    text = f.stats[:, 0] > 0
    assert ((model.content(f, H.KindFeatures.of(kinds)) >= 0.5) == y)[text].mean() > 0.98


PROSE = "This is the first sentence of the story, with enough words to read. Here is another one that goes on a little longer than that."


@pytest.mark.parametrize(
    "page,want",
    [
        ("<main><p>Short.</p></main>", "Short."),
        ("<article class='comment-worthy story'><h1>Title here</h1><p>One short paragraph.</p></article>", "Title here One short paragraph."),
        (f"<article><h1>T</h1><p>{PROSE}</p></article><section id='kommentare'><h2>Kommentare</h2><div><b>Anna</b> Das sehe ich anders.</div><div><b>Ben</b> Guter Text.</div></section>", f"T {PROSE}"),
        (f"<nav><ul><li><a href=a>Start</a><li><a href=b>Politik</a></ul></nav><article><h1>T</h1><p>{PROSE}</p><div class='werbung'>Jetzt kaufen und sparen.</div><p>{PROSE}</p></article>", f"T {PROSE} {PROSE}"),
        (f"<div id='contenido'><h1>T</h1><p>{PROSE}</p><p>{PROSE}</p></div><aside><h3>Ver más</h3><ul><li><a href=a>uno</a><li><a href=b>dos</a></ul></aside><div class='pie-de-pagina'>&copy; 2020</div>", f"T {PROSE} {PROSE}"),
        (f"<div class='qpz'><div class='xrk'><a href=a>One</a> <a href=b>Two</a> <a href=c>Three</a></div><div class='vbn'><h1>T</h1><p>{PROSE}</p><p>{PROSE}</p><p>{PROSE}</p></div></div>", f"T {PROSE} {PROSE} {PROSE}"),
        (f"<article><h1>T</h1><p>{PROSE}</p><p><a href=x>A paragraph that is a link</a></p><p>{PROSE}</p></article>", f"T {PROSE} A paragraph that is a link {PROSE}"),
        ("<nav><ul><li><a href=a>Home</a><li><a href=b>News</a></ul></nav><footer>&copy; Site</footer>", ""),
    ],
)
def test_other_layouts_and_languages(model, page, want):
    assert H.page_texts([f"<html><body>{page}</body></html>"], model)[0] == want


def test_markup_and_references(model):
    body = "<h1>A &amp; B</h1><p><b>First&nbsp;line<br>x</b>y  &#233;\n z<p>Unclosed <i>two</i>thirds of a long paragraph of words, and more words &lt;tag&gt;.</p><!-- <p>no</p> --><script>var a='<p>no</p>';</script><p>Last words of the text, with some more to read.</p>"
    page = f"<html><head><title>T</title></head><body><nav><ul><li><a href='/'>Home</a></li></ul></nav><article>{body}</article><footer>&copy; x</footer></body></html>"
    assert H.page_texts([page, "", "<<<", "<p title='a>b", "</div></p>"], model)[0] == "A & B First line xy é z Unclosed twothirds of a long paragraph of words, and more words <tag>. Last words of the text, with some more to read."


def test_deep_and_odd_pages(model):
    deep = "<div>" * 3000 + "word " * 50 + "</div>" * 10
    out = H.page_texts([deep, "<p>" * 2000, "<" * 5000, "<a '" * 500, "<!--" + "x" * 10000, "<ul>" + "<li>x" * 2000], model)
    assert len(out) == 6


def test_whole_table(spark, model):
    prose = "Some plain words of the article that go on for a while. " * 3
    made = lambda k: f"<body><nav><a href=x>menu</a></nav><article><h1>T{k}</h1><p>{prose}</p><div class='ad'>Buy this.</div></article><footer>foot</footer>"
    rows = [(k, "u", made(k), "old") for k in range(40)] + [(1, "u", made(1), "old"), (98, "v", None, ""), (99, None, "", ""), (None, "w", "<nav><a href=q>x</a></nav>", "")]
    got = H.extract(spark.createDataFrame(rows, PAGES)).collect()
    assert len(got) == len(rows) and got[0].asDict().keys() == {"page_id", "url", "text"}
    for r in got:
        if r.page_id is not None and r.page_id < 90:
            assert r.text == " ".join(f"T{r.page_id} {prose}".split())
        else:
            assert r.text == ""
    assert H.extract(spark.createDataFrame([], PAGES)).count() == 0


def test_against_test_pages(spark, model):
    """On the given pages the text is what stands in the article element."""
    for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect():
        inner = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        blocks = [" ".join(html_lib.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1|div|ul|li|br)[^>]*>", inner)]
        assert H.page_texts([r.html], model)[0] == " ".join(b for b in blocks if b)
