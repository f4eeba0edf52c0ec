import html
import itertools
import random
import re

import numpy as np
from divknn.llm import html_pages
from divknn.llm.common import table


def test_held_out_accuracy():
    chain, rng = html_pages.default_chain(), random.Random(99)
    right = false = missed = 0
    for _ in range(200):
        page, main = html_pages.labelled_page(rng)
        got = html_pages.main_text(page, chain).split("\n")
        want = [" ".join(x.split()) for x in main]
        right += len(set(got) & set(want))
        false += len(set(got) - set(want) - {""})
        missed += len(set(want) - set(got))
    assert right / (right + false) > 0.97 and right / (right + missed) > 0.97, (right, false, missed)


def test_given_pages(spark):
    pages = table(spark, "/root/testdata/sf0.01", "pages")
    wrong = 0
    rows = {r["page_id"]: r["html"] for r in pages.collect()}
    for r in html_pages.extract_main_text(pages).collect():
        inner = re.search(r"<article>(.*?)</article>", rows[r["page_id"]], re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"</?(?:b|a)\b[^>]*>", "", x)).split()) for x in re.split(r"</?(?:p|h1|br)>", inner)]
        wrong += r["text"] != "\n".join(x for x in parts if x)
        assert r["n_chars"] == len(r["text"])
    assert wrong == 0


def test_viterbi_is_the_best_path():
    chain, rng = html_pages.default_chain(), random.Random(5)
    blocks = html_pages.leaf_blocks(html_pages.labelled_page(rng)[0])[:9]
    f = html_pages.block_features(blocks)
    s = chain.scores(f)
    value = lambda y: sum(a * b for a, b in zip(s, y, strict=True)) + sum(chain.moves[a, b] for a, b in itertools.pairwise(y))
    assert np.isclose(value(chain.decode(f)), max(value(y) for y in itertools.product((0, 1), repeat=len(f))))


def test_awkward(spark):
    rows = [(1, "u", None, 1), (2, "u", "", 1), (3, None, "<p", 1), (4, "u", "<article><p>A &amp; B\n&nbsp;c<p>" + "word " * 50000 + ".</article>", 1), (None, "u", "<div><div>", 1), (6, "u", "<script>x</p>", 1)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text int")
    got = {r["page_id"]: r["text"] for r in html_pages.extract_main_text(df).collect()}
    assert got[1] == got[2] == got[3] == got[6] == got[None] == ""
    assert got[4] == "A & B c\n" + "word " * 49999 + "word ."
    assert html_pages.extract_main_text(df.limit(0)).count() == 0


def test_tag_soup():
    blocks = html_pages.leaf_blocks("<ul><li>a<li>b</ul><p>c<p>d <b>e</b>f<div class='x y'>g<!-- <p> --> h</div><style>p{}</style><h2>i</h2>tail")
    assert [b.text for b in blocks] == ["a", "b", "c", "d ef", "g h", "i", "tail"]
    assert {"c=x", "c=y", "in=div"} <= blocks[4].marks


P = "The quick brown fox runs over the hill, and away from all of them. " * 3


def read(page):
    return html_pages.main_text(page, html_pages.default_chain())


def test_open_and_embedded_elements():
    p = P.strip()
    assert read(f"<html><head><title>x</title><meta charset=utf-8><body><header>y</header><article><h1>Head line</h1><p>{P}</p></article></body>") == f"Head line\n{p}"
    assert read(f"<article><h1>Head line</h1><p>{P}<button>Share<p>{P}</article>") == f"Head line\n{p}\n{p}"
    assert read(f"<article><p>{P} where <math><mi>x</mi></math> is <svg><text>no</text></svg>small.</p></article>") == f"{p} where x is small."
    assert read(f"<article><p>{P}</p><script>a</SCRIPT ><p>{P}</p><style>b</p></article>") == f"{p}\n{p}"


def test_places_and_quotes():
    dots = "\u0130" * 10
    assert read(f"<article><p>{dots}<script>x='<p>'</script>Text. {P}</p></article>") == f"{dots} Text. {P.strip()}"
    assert read(f"<article><p title=it's>{P}</p><p>It's {P}</p></article>") == f"{P.strip()}\nIt's {P.strip()}"


def test_layouts_of_other_names():
    for before, after in (("<div class='wrapper'><div class='col-md-8'>", "</div></div>"), ('<article class="post meta-article">', "</article>"), ("<div><section class='xyz'>", "</section></div>")):
        page = f"<html><body><nav><ul><li><a href=x>Home</a></ul></nav>{before}<h1>Title of page</h1><p>{P}</p><p>{P}</p>{after}<div class=sidebar><p>{P}</p></div><footer>z</footer>"
        assert read(page) == f"Title of page\n{P.strip()}\n{P.strip()}"


def test_deep_pages_take_memory_in_proportion():
    deep = "".join(f"<div class=a{i}>" for i in range(30_000)) + "".join(f"<p>t{i}" for i in range(2_000))
    blocks = html_pages.leaf_blocks(deep, html_pages.default_chain().names)
    assert len(blocks) == 2_000 and max(len(b.marks) for b in blocks) < 10
