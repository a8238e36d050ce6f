"""References without a semicolon: text to the parser as to the native recipe."""

from spark_curation.operators.render import parse_blocks, render_pages
from spark_curation.operators.scrapers import main_subtree

HTML = "<html><body><article><p>ver&amp</p><p>a &amp; b &copy; &copy c & d&</p></article></body></html>"
WANT = ["ver&amp", "a & b © &copy c & d&"]


def test_parser_reads_open_references_as_text(spark):
    assert [t for t, _ in parse_blocks(HTML)] == WANT
    native = render_pages(spark.createDataFrame([(1, "u", HTML)], "page_id long, url string, html string")).first()
    assert native["lines"] == WANT


def test_subtree_reads_open_references_as_text():
    assert main_subtree(HTML) == "\n".join(WANT)
