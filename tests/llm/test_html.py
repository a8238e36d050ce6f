"""Main text: the article's parts that must stay, what must go, hostile pages, exact marginals, odd inputs."""

import random
import time

import numpy as np
import pytest

from spark_curation.llm import html_tree


@pytest.fixture(scope="module")
def model():
    return html_tree.default_model()


FRAME = '<body><nav><ul><li><a href="/a">Home</a></li><li><a href="/b">News</a></li></ul></nav><article><h1>Head</h1>{}</article><footer>&copy; us</footer></body>'
PARTS = {
    "<p>See the list.</p><ul><li><a href=/x>First tool</a></li><li><a href=/y>Second tool</a></li></ul>": "See the list. First tool Second tool",
    "<p class=byline>By Jo Doe</p><p>Text here.</p>": "By Jo Doe Text here.",
    "<p>A <math><mi>x</mi></math> and <svg><text>label</text></svg>.</p>": "A x and label.",
    "<p>Seen.</p><p hidden>Not shown.</p><p style='display:none'>Nor this.</p>": "Seen. Not shown. Nor this.",
    "<p>One &amp; two.<p>Three\n  four.<script>no('</p>')</script><style>p{}</style><!-- no -->": "One & two. Three four.",
    "<table><tr><th>Size<td>4 cm<tr><th>Mass<td>2 kg</table>": "Size 4 cm Mass 2 kg",
    '<p>Good.</p><div class="ad-slot">Buy now!</div><form><label>Mail</label><input></form><p>End.</p>': "Good. End.",
    "<p>a < b and c > d</p>": "a < b and c > d",
    '<p>x <a href="/q>r</a> y</p><p>z</p>': "x r y z",
}


@pytest.mark.parametrize("part", PARTS)
def test_parts_of_an_article(model, part):
    assert model.extract([FRAME.format(part)]) == [f"Head {PARTS[part]}"]


def test_pages_without_an_article_element(model):
    pages = {
        "<nav><a href=x>Home</a></nav><p>Short text.</p><footer>&copy; x</footer>": "Short text.",
        "A page of plain text without any markup.": "A page of plain text without any markup.",
        "<body><p>One paragraph of words.</p><p>Another one.</p></body>": "One paragraph of words. Another one.",
        "<p>": "", "": "",
    }
    assert model.extract([*pages, None]) == [*pages.values(), ""]


def test_comments_and_notices_go(model):
    page = '<body><header>Site</header><div class="cookie-notice"><p>We use cookies.</p></div><article><h1>Head</h1><p>Words of it.</p></article><section id="comments"><h2>Replies</h2><p>Nice post, thanks.</p></section><aside><p>More.</p></aside></body>'
    assert model.extract([page]) == ["Head Words of it."]


def test_unseen_layouts(model):
    r = random.Random(99)
    wrong = total = 0
    for _ in range(300):
        t = html_tree.tree(html_tree.labelled_page(r))
        chance = model.content([t])[0]
        wrong += sum((chance[at] > 0.5) != t.label[at] for at, _ in t.runs)
        total += len(t.runs)
    assert wrong < 0.04 * total


@pytest.mark.parametrize("unit", ["<script ", "<div></p>", "<div>", "<svg>", "<b>", '<a x=">', "<i><b></i>", "<li><ul><div>", "<dd></dd><div>", "<!--", '<a "', "<p>x", "<a x='>", "<table><tr><td>", "<iframe>", "x<", "</div>"])
def test_hostile_pages_take_time_in_proportion(model, unit):
    took = []
    for size in (1 << 16, 1 << 18):
        began = time.process_time()
        model.extract([(unit * (size // len(unit) + 1))[:size]])
        took.append(time.process_time() - began)
    assert took[1] < 8 * max(took[0], 0.05)


def test_beliefs_are_exact_either_way():
    """Marginals on a small tree against the sum over all labellings, by levels and node by node."""
    t = html_tree.tree("<div><p>a.</p><ul><li>b</li></ul></div>")
    f = html_tree.Forest([t])
    rng = np.random.default_rng(0)
    node, edge = rng.normal(size=f.n), rng.normal(size=(2, 2))
    z, one = 0.0, np.zeros(f.n)
    for bits in range(1 << f.n):
        y = [bits >> i & 1 for i in range(f.n)]
        w = np.exp(sum(node[i] * y[i] for i in range(f.n)) + sum(edge[y[p], y[i]] for i, p in enumerate(f.parent) if p >= 0))
        z += w
        one += w * np.array(y)
    for f.narrow in (True, False):
        chance, pairs = f.beliefs(node, edge)
        assert np.allclose(chance, one / z) and np.allclose(pairs.sum(axis=0), 1)


def test_odd_tables(spark):
    rows = [(1, "u", None), (2, None, ""), (None, "u", FRAME.format("<p>Words.</p>")), (3, "u", FRAME.format("<p>Words.</p>")), (3, "u", FRAME.format("<p>Words.</p>")), (4, "u", FRAME.format("<p>" + "long text here. " * 20_000 + "</p>"))]
    df = spark.createDataFrame([(*r, "clash", 1) for r in rows], "page_id long, url string, html string, text string, n_chars int")
    got = html_tree.extract(df).collect()
    assert len(got) == 6 and {(r.page_id, r.text) for r in got if r.page_id != 4} == {(1, ""), (2, ""), (None, "Head Words."), (3, "Head Words.")}
    assert all(r.n_chars == len(r.text) for r in got) and max(r.n_chars for r in got) > 300_000
    assert html_tree.extract(df.where("false")).count() == 0
