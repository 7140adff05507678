import html
import random
import re
import time

import numpy as np
import pytest

from viewsize.llm import html_text as H
from viewsize.llm.boosting import BoostedTrees

from .conftest import clashing

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def model():
    return H.train(None)


def article(page):
    """The blocks of the tables' own page layout, by hand."""
    inner = re.search(r"<article>(.*?)(</article>|$)", page, re.S)[1]
    inner = re.sub(r"</?b>", "", re.sub(r"<br>", " ", re.sub(r"</?(p|h1)>", "\n", inner)))
    return "\n\n".join(t for t in (" ".join(html.unescape(b).split()) for b in inner.split("\n")) if t)


def test_given_pages(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = {r["page_id"]: r for r in H.extract(pages, H.train(pages)).collect()}
    for r in pages.collect():
        assert got[r["page_id"]]["text"] == article(r["html"]) and got[r["page_id"]]["n_chars"] == len(got[r["page_id"]]["text"])


def test_unseen_generated_pages(model):
    r, right, exact, n = random.Random(1234), 0, 0, 0
    for _ in range(120):
        nodes = H.nodes_of(H.parse(H.generated_page(r)))
        kept, gold = H.decode(nodes, model.predict(H.features(nodes))), (H._gold(nodes) > 0).tolist()
        right += sum(a == b for a, b in zip(kept, gold))
        n += len(nodes)
        exact += H.render(nodes, kept) == H.render(nodes, gold)
    assert right / n > 0.94 and exact > 105


def test_hand_made_page(model):
    page = """<html><head><title>T</title></head><body class=home><div id=cookie-notice class="notice">We use cookies, ok? <button>Yes</button></div>
    <header class="site-header"><a href=/>Home</a><form class="search"><input name=q>Find</form></header>
    <nav class="menu"><ul><li><a href=1>One</a><li><a href=2>Two</a><li><a href=3>Three</a></ul></nav>
    <main><article class="post"><h1>A title &amp; more</h1><p>First paragraph,
    with   white&nbsp;space and an <a href=x>inline link</a>, long enough to be read as prose.<p>Second one &lt;here&gt;, it goes on for a while too.
    <script>if (a < b) document.write("<p>no</p>")</script><!-- <p>nor this</p> --><ul><li>An item of the list in the text, with words.<li>Another item of it, longer than a link.</ul></article>
    <section id="comments" class="comments"><h3>Comments</h3><div class="comment"><p>I liked it very much, thank you.</p></div></section></main>
    <aside class="sidebar"><h3>Related</h3><ul><li><a href=4>Four</a><li><a href=5>Five</a></ul></aside><footer>&copy; 2020 Someone, all rights</footer></body></html>"""
    assert H.extract_text(page, model) == (
        "A title & more\n\nFirst paragraph, with white space and an inline link, long enough to be read as prose.\n\nSecond one <here>, it goes on for a while too.\n\n"
        "An item of the list in the text, with words.\n\nAnother item of it, longer than a link."
    )


def test_nothing_is_kept_below_what_is_dropped(model):
    r = random.Random(5)
    for _ in range(30):
        nodes = H.nodes_of(H.parse(H.generated_page(r)))
        kept = H.decode(nodes, np.random.default_rng(1).normal(size=len(nodes)) * 3)
        at = {id(x): k for x, k in zip(nodes, kept)}
        assert all(not k or x.parent is None or at[id(x.parent)] for x, k in zip(nodes, kept))


def test_decoding_is_the_likeliest_labelling():
    import itertools

    nodes = H.nodes_of(H.parse("<body><div><p>a</p><p>b</p></div><div>c</div></body>"))
    at = {id(x): i for i, x in enumerate(nodes)}
    for seed in range(40):
        odds = np.random.default_rng(seed).normal(size=len(nodes)) * 2
        best = max(
            (c for c in itertools.product([False, True], repeat=len(nodes)) if c[0] and all(not c[i] or c[at[id(x.parent)]] for i, x in enumerate(nodes) if x.parent)),
            key=lambda c: sum(-np.logaddexp(0, -o if k else o) for o, k in zip(odds, c)),
        )
        assert tuple(H.decode(nodes, odds)) == best


@pytest.mark.parametrize("page", [None, "", "no tags at all", "<", "<p", "</p></p>", "<p>a<p>b</div>", "<!-- open", "<script>never closed", "<a href='x>y", "<table><td>1<td>2<tr><td>3", "a" * 50_000, "<div>" * 3000])
def test_anything_is_accepted(model, page):
    assert isinstance(H.extract_text(page, model), str)


@pytest.mark.parametrize("inner, want", [
    ('<svg viewBox="0 0 1 1" />', "before after"), ("<math/>", "before after"), ("<svg><title/><path d=x /></svg>", "before after"), ("<svg><title>t</title><script>s</script></svg>", "before after"),
    ("<math><mi>x</mi><mo>=</mo><mn>2</mn></math>", "before x=2 after"), ("<select name=s>", "before after"), ("<select><option>one</select>", "before one after"),
    ("<template>", "before after"), ("<noscript>", "before after"), ("<textarea>", "before after"), ("<iframe src=x>", "before after"), ("<title>", "before after"),
    ("<script>code()</script>", "before after"), ("<textarea>typed</textarea>", "before after"),
])
def test_no_text_is_lost_after_a_raw_element(inner, want):
    nodes = H.nodes_of(H.parse(f"<body><article><p>before {inner} after</p><p>last</p></article></body>"))
    assert H.render(nodes, [True] * len(nodes)).split() == [*want.split(), "last"]


def test_an_unclosed_select_ends_before_a_block_and_a_script_does_not():
    nodes = H.nodes_of(H.parse("<body><article><form><select><option>one<p>text</p></form><p>more</p></article></body>"))
    assert [x.parent.tag for x in nodes if x.tag == "p"] == ["form", "article"]
    nodes = H.nodes_of(H.parse("<body><p>text</p><script>if (a) { b = 1;"))
    assert H.render(nodes, [True] * len(nodes)) == "text"


def test_messy_pages(spark, model):
    rows = [(1, None, None), (None, "u", "<p>hello there, this is text</p>"), (2, "u", ""), (2, "u", ""), (3, "v", "<body>" + "<p>long text, here.</p>" * 20_000)]
    df = clashing(spark.createDataFrame(rows, "page_id long, url string, html string")).withColumnRenamed("text", "other")
    got = H.extract(df, H.train(df, generated=60)).collect()
    assert sorted((str(r["page_id"]), str(r["url"])) for r in got) == sorted((str(a), str(b)) for a, b, _ in rows)
    assert {r["n_chars"] for r in got if r["page_id"] in (1, 2)} == {0} and [r["n_chars"] for r in got if r["page_id"] == 3] == [20_000 * 18 - 2]
    assert H.extract(df.limit(0), model).collect() == []


@pytest.mark.parametrize("page", [
    '<p a="x"' * 150_000, "<a href='x" + "<b title=\"" + "<a '" * 200_000, "<b>" * 200_000 + "text", "<ul><li><ul>" + "<b>" * 20_000 + "<li></li>" * 20_000, "<div>" * 100_000 + "text",
    "<div>" * 400 + "<option></option>" * 60_000, "<" * 1_000_000, "<!--" * 200_000, "</p>" * 200_000, "<p>" + "<textarea>" * 100_000,
])
def test_bad_pages_of_megabytes_are_read_in_linear_time(page):
    began = time.process_time()
    nodes = H.nodes_of(H.parse(page))
    assert time.process_time() - began < 20
    assert H.render(nodes, [True] * len(nodes)).count("text") == page.count(">text")


def test_quotes_and_references():
    def whole(page):
        nodes = H.nodes_of(H.parse(page))
        return H.render(nodes, [True] * len(nodes))

    assert whole("<p class=\"a>b\">it's</p><p don't>one &amp; <i title='<p>'>two</i></p>AT&<b>amp;</b>") == "it's\n\none & two\n\nAT&amp;"
    assert whole("<p title=\"never closed>one</p><p>two</p>") == "one\n\ntwo"


def test_boosting_learns_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((2000, 5))
    y = ((x[:, 0] > 0.5) ^ (x[:, 3] > 0.3)).astype(float)
    m = BoostedTrees(trees=30, depth=3).fit(x, y)
    z = rng.random((500, 5))
    assert (((m.predict(z) > 0) == ((z[:, 0] > 0.5) ^ (z[:, 3] > 0.3))).mean()) > 0.96
