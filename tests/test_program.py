"""Programs, execution and alignment on worked examples and generated cases."""

import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from spark_curation.operators import align, execute, postfilter, program, render, teachers

LINES = ["Home", "About", "Rivers carry silt. [share]", "Read next"]


def run(spark, output, lines=LINES, **kw):
    df = spark.createDataFrame([(1, output)], "page_id long, output string").withColumn("lines", F.array(*map(F.lit, lines)))
    return execute.run(program.parse(df), **kw).first()


EDIT = '<edit>\n<extract>\nrm 1-2\n<edit>\nrm 4\nsub 3: " [share]"'


def test_worked_trace(spark):
    got = run(spark, EDIT)
    assert (got.text, got.provenance, got.words_stripped) == ("Rivers carry silt.", "refined", 2)
    assert run(spark, EDIT, disable=("edit",)).text == "Rivers carry silt. [share]\nRead next"
    assert run(spark, EDIT, disable=("extract",)).text == "Home\nAbout\nRivers carry silt."
    gone = run(spark, "<delete>\n<extract>\nrm 1-2\n<delete>")
    assert gone.text is None and gone.provenance == "deleted"
    new = run(spark, "<rewrite>\n<extract>\n<rewrite>\nSilt moves.\n\nIt settles.")
    assert new.text == "Silt moves.\n\nIt settles."
    assert run(spark, "<rewrite>\n<extract>\n<rewrite>\nx", disable=("rewrite",)).text is None
    assert run(spark, "<delete>\n<extract>\nrm 1\n<delete>", disable=("delete",)).text.startswith("About")


def test_cut_policies(spark):
    out = '<edit>\n<extract>\n<edit>\nsub 1: "ab"'
    assert run(spark, out, ["ab x ab"]).text == " x ab"
    assert run(spark, out, ["ab x ab"], cut_policy="all").text == " x "
    assert run(spark, out, ["ab"]).provenance == "empty"


@pytest.mark.parametrize("bad", ["", "keep", "<keep>", "<extract>\nrm 1"])
def test_malformed_output_never_falls_back_to_the_page(spark, bad):
    got = run(spark, bad)
    assert got.text is None and got.provenance == "malformed"


def test_kept_text_is_a_subsequence_of_the_page(spark):
    r = random.Random(5)
    rows = []
    for i in range(40):
        lines = [" ".join(r.choice(["a", "bc", "d.", "(x)"]) for _ in range(r.randrange(1, 6))) for _ in range(r.randrange(1, 8))]
        items = [f"rm {r.randrange(1, 9)}-{r.randrange(1, 9)}" for _ in range(r.randrange(3))] + [f'sub {r.randrange(1, 9)}: "{r.choice(["a", "(x)", "zz"])}"' for _ in range(r.randrange(3))]
        rows.append((i, lines, "<edit>\n<extract>\nrm 2\n<edit>\n" + "\n".join(items or ["rm 99"])))
    df = spark.createDataFrame(rows, "page_id long, lines array<string>, output string")
    for got in execute.run(program.parse(df)).collect():
        assert align.is_subsequence(got.text or "", "\n".join(got.lines))


def test_ranges_and_numbers(spark):
    df = spark.createDataFrame([([True, True, False, True],), ([False],), ([],)], "f array<boolean>")
    got = [[(x.a, x.b) for x in r[0]] for r in df.select(program.to_ranges(F.col("f"))).collect()]
    assert got == [[(1, 2), (4, 4)], [], []]
    one = spark.createDataFrame([(["x", "<lid:3> y"],)], "l array<string>")
    assert one.select(render.unnumber(render.number_lines(F.col("l")))).first()[0] == ["x", "<lid:3> y"]


def test_page_of_all_kinds_of_markup(spark):
    html = '<html><head><title>t</title></head><body><nav><a>Menu</a></nav><!-- <p>no</p> --><table><tr><td>Weight</td><td>12</td></tr></table><ul><li>Oak<li>Elm &amp; Ash</ul><script>var a="</p>";</script><p>Line<br>break</p><footer>&copy; x</footer></body></html>'
    df = spark.createDataFrame([(1, "u", html), (2, "u", None), (3, None, "")], "page_id long, url string, html string")
    for mode in ("native", "parser"):
        rows = {r.page_id: r.lines for r in render.render_pages(df, mode=mode).collect()}
        assert rows[1] == ["Menu", "Weight 12", "Oak", "Elm & Ash", "Line", "break", "© x"]
        assert rows[2] == rows[3] == []


def test_leaks(spark):
    df = spark.createDataFrame([("plain text",), ("a\nrm 3-4\nb",), ("<keep>",), ('sub 3: "x"',), ("rm -rf 3",)], "text string")
    assert [r.text for r in postfilter.reject_leaks(df).collect()] == ["plain text", "rm -rf 3"]


def test_rewrite_acceptance_bounds(spark):
    w = lambda n: " ".join(["w"] * n)
    rows = [(w(100), w(20), True), (w(100), w(19), False), (w(100), w(300), True), (w(100), w(301), False), (w(10), "", False), (w(10), "Sure, here it is " + w(5), False)]
    df = spark.createDataFrame(rows, "a string, b string, want boolean")
    assert all(r[0] == r[1] for r in df.select("want", teachers.accept_rewrite(F.col("a"), F.col("b"))).collect())


def test_refinement_marker_and_chunks(spark):
    m = teachers.DELETE_MARKER
    rows = [("", True), (m, True), ("x" * 100 + m, True), ("x" * 121 + m, False), ("fine", False), (None, True)]
    df = spark.createDataFrame(rows, "t string, want boolean")
    assert all(r[0] == r[1] for r in df.select("want", teachers.read_refinement(F.col("t"))).collect())
    parts = spark.createDataFrame([("a" * 7001,)], "t string").select(teachers.chunks(F.col("t"))).first()[0]
    assert [len(p) for p in parts] == [7000, 1]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text("ab c.", min_size=1, max_size=12).filter(str.strip), min_size=1, max_size=6), st.data())
def test_alignment_explains_deletions(lines, data):
    kept = [x for x in lines if data.draw(st.booleans())]
    drop, cuts, body = align.align(lines, "\n".join(kept))
    assert body is None
    left = [x for i, x in enumerate(lines) if i + 1 not in drop]
    for lid, frag in cuts:
        at = [i + 1 for i in range(len(lines)) if i + 1 not in drop].index(lid)
        left[at] = left[at].replace(frag, "", 1)
    assert left == kept


def test_alignment_of_fragments_and_changes():
    assert align.align(["a (x) b", "c"], "a b\nc") == ([], [(1, "(x) ")], None) or align.align(["a (x) b", "c"], "a b\nc")[2] is None
    assert align.align(["a b"], "changed text")[2] == "changed text"
