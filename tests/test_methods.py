"""Methods that SQL does not express, and invariants: packing, backends, student, owners, subtrees, tokens, archives, rulebook, ledger."""

import gzip
import random
from pathlib import Path
from urllib.parse import urlparse

import numpy as np
import pytest
from pyspark.sql import functions as F

from spark_curation import comparison, comparison_sql, surfaces, surfaces_sql, workloads
from spark_curation.functions import tokens
from spark_curation.io import checkpoint_dir, cut, remove, table, written
from spark_curation.operators import align, dedup, execute, metrics, program, proxy, render, rulebook, runlog, scrapers, student, targets
from spark_curation.plans import pipelines
from spark_curation.sources import archive
from tests.conftest import DATA


def test_packs_never_overflow(spark):
    r = random.Random(2)
    sizes = [100, 4090, 4000] + [r.choice([1, 50, 900, 4096, 5000]) for _ in range(300)]
    df = spark.createDataFrame([(i, n) for i, n in enumerate(sizes)], "page_id long, n_tokens long")
    rows = targets.pack(df, 4096, 3).collect()
    packs = {}
    for x in sorted(rows, key=lambda x: (x.shard, x.page_id)):
        packs.setdefault((x.shard, x.pack_id), []).append(x.n_tokens)
    assert len(rows) == len(sizes) and all(sum(p) <= 4096 or len(p) == 1 for p in packs.values())
    for (shard, k), p in packs.items():  # no target would have fitted into the sequence before
        assert k == 0 or sum(packs[shard, k - 1]) + p[0] > 4096
    assert {x.pack_id for x in targets.pack(df.limit(3).coalesce(1), 4096, 1).collect()} == {0, 1, 2}


def test_backends(spark):
    r = cut(pipelines.rendered_pages(table(spark, DATA, "pages")))
    made = pipelines.policy_outputs(r)
    again = pipelines.replay(r, made.where("page_id % 2 = 0")).collect()
    assert all((x.output is not None) == (x.page_id % 2 == 0) for x in again)
    asked = pipelines.endpoint(r, lambda prompts: [f"<keep>\n<extract>\n<keep>\n{len(p)}" for p in prompts], batch=3).collect()
    assert len(asked) == r.count() and all(x.output.startswith("<keep>") for x in asked)
    want = {x.page_id: x.text for x in execute.run(program.parse(made.drop("blocks"))).collect()}
    got = {x.page_id: x.text for x in execute.run(program.parse(pipelines.replay(r, made).drop("blocks"))).collect()}
    assert got == want


def test_whole_pass_over_a_pool(spark):
    got = pipelines.curate(table(spark, DATA, "pages")).collect()
    plain = {x.page_id: x for x in pipelines.curate(table(spark, DATA, "pages"), deduplicate=False).collect()}
    grams = lambda t: [tuple(t.split()[i : i + 13]) for i in range(len(t.split()) - 12)]
    owner = {}
    for i in sorted(plain):
        for g in grams(plain[i].text):
            owner.setdefault(g, i)
    want = {i for i, x in plain.items() if not grams(x.text) or sum(owner[g] < i for g in grams(x.text)) < 0.8 * len(grams(x.text))}
    assert {x.page_id for x in got} == want


def test_owners_that_stay(spark):
    r = random.Random(4)
    text = lambda n: " ".join(f"u{r.randrange(10**6)}" for _ in range(n))
    a, b, c = text(60), text(60), text(60)
    rows = [(1, a), (2, a + " " + b[: len(b) // 9]), (3, b + " " + b), (4, b), (5, c), (6, "few words"), (7, b + " " + c), (8, None)]
    rows += [(10 + i, " ".join(r.sample([a, b, c, text(20)], 2))) for i in range(20)]
    grams = lambda t: [tuple((t or "").split()[i : i + 13]) for i in range(len((t or "").split()) - 12)]
    owned, fell = set(), set()
    for i, t in rows:
        g = grams(t)
        if g and sum(x in owned for x in g) >= 0.8 * len(g):
            fell.add(i)
        else:
            owned |= set(g)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {x.id for x in dedup.survivors_only(df).collect()} == fell and fell
    assert fell <= {x.id for x in dedup.ngram(df).collect()}


def test_survivors_move_what_ids_share(spark):
    """Rounds read what ids share, not every gram; ids may be repeated, null and out of order, and a gram common to all."""
    r = random.Random(4)
    text = lambda n: [f"w{r.randrange(9_000)}" for _ in range(n)]
    common, rows = text(20), []
    for i in r.sample(range(-200, 70_000), 240):
        t = common + text(380)
        rows.append((i, " ".join(t)))
        if not len(rows) % 6:
            near = list(t)
            near[200] = "changed"
            rows += [(i + 100_000, " ".join(t)), (i + 9, " ".join(near + near[:60])), (i + 11, " ".join(near[90:]))]
    rows += [(rows[0][0], rows[7][1]), (None, rows[3][1]), (200_001, None), (200_002, " ".join(text(12))), (200_003, "a b " * 300), (200_004, "a b " * 9)]
    grams: dict[int, list] = {}
    for i, t in rows:
        ws = (t or "").split()
        grams.setdefault(i, []).extend(tuple(ws[k : k + 13]) for k in range(len(ws) - 12))
    owned, fell = set(), set()
    for i in sorted(i for i in grams if i is not None):
        if grams[i] and sum(g in owned for g in grams[i]) >= 0.8 * len(grams[i]):
            fell.add(i)
        else:
            owned |= set(grams[i])
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    held = lambda: sum(f.stat().st_size for f in Path(urlparse(checkpoint_dir(spark)).path).rglob("*") if f.is_file())
    before = held()
    assert {x.id for x in dedup.survivors_only(df).collect()} == fell and len(fell) > 60
    assert held() - before < sum(len(t or "") for _, t in rows) / 4
    assert dedup.shared_grams(df).count() < 0.1 * sum(map(len, grams.values()))
    assert dedup.survivors_only(df.limit(0)).count() == 0


def test_main_subtree():
    page = '<body><div id=side><p>Side words that are many and go on for long, longer than all else here, on and on.</p></div>{}</body>'
    assert scrapers.main_subtree(page.format("<article><h1>Head</h1><p>Body text.</p></article>")) == "Head\nBody text."
    assert scrapers.main_subtree(page.format('<div class="post-content"><p>Body <a href=x>link</a> text of some size.</p></div>')) == "Body link text of some size."
    assert scrapers.main_subtree("<body><a href=x>only links</a></body>") == "only links"
    assert scrapers.main_subtree("<div><p>one</p><div><p>a longer part of the page</p></div></div>") == "one\na longer part of the page"
    assert scrapers.main_subtree(None) == ""


def test_scraper_faults(spark):
    page = "<body><p>Intro text.</p><ul><li>Oak</li><li>Steel</li></ul><table><tr><td>a</td><td>b</td></tr></table><aside><p>A sidebar that is far longer than the page itself.</p></aside></body>"
    df = spark.createDataFrame([(1, page)], "page_id long, html string")
    text = lambda **kw: scrapers.tagdrop(df, **kw).first().text
    assert text().split("\n")[:4] == ["Intro text.", "Oak", "Steel", "a b"]
    assert "Oak" not in text(lost_lists=True) and "ab" in text(fused_cells=True)
    assert text(sidebar=True) == "A sidebar that is far longer than the page itself."


def test_density_follows_links_and_neighbours(spark):
    stops = "the be to of and that have with a in is it for on as are this was by at "
    long, linked = stops * 6 + "end.", "<a href=x>" + stops * 6 + "</a>"
    page = f"<body><p>Short lead</p><p>{long}</p><p>Tiny</p><p>{long}</p><p>{linked}</p><p>Last</p></body>"
    df = spark.createDataFrame([(1, page)], "page_id long, html string")
    assert scrapers.density(df).first().text == f"{long}\nTiny\n{long}"


def test_student_learns_and_edits(spark):
    p = cut(pipelines.programs(table(spark, DATA, "pages")))
    w, losses = student.fit(student.examples(p), student.examples(p), epochs=6, batches=2)
    assert losses[-1] < 0.7 * losses[0]
    got = program.parse(student.decode(p.select("page_id", "lines"), w)).join(p.select("page_id", F.col("strip").alias("want"), "lines"), "page_id").collect()
    ids = lambda rs: {i for r in rs for i in range(r.a, r.b + 1)}
    wrong = sum(len(ids(x.strip) ^ ids(x.want)) for x in got)
    assert wrong < 0.15 * sum(len(x.lines) for x in got) and all(x.status == "ok" for x in got)
    q = student.Weights()
    q.verdict[student.VERDICTS.index("edit"), 0] = 9.0
    q.line[1, 0], q.line[0, 0] = 9.0, -9.0
    out = {x.page_id: x.output for x in student.decode(p.select("page_id", "lines").limit(3), q).collect()}
    assert all(o.startswith("<edit>") and o.endswith(tuple("0123456789")) and "rm 1" in o.split("<edit>")[2] for o in out.values())


def test_drawing():
    p = np.array([0.5, 0.3, 0.15, 0.05])
    assert student.draw(p, 0.99, 0.0, 1.0) == 0
    assert [student.draw(p, u, 1.0, 1.0) for u in (0.0, 0.49, 0.6, 0.9, 0.97)] == [0, 0, 1, 2, 3]
    assert {student.draw(p, u / 100, 1.0, 0.8) for u in range(100)} == {0, 1} and {student.draw(p, u / 100, 1.0, 0.5) for u in range(100)} == {0}
    assert student.shortened("a b\nc d", 3) == "a b\nc" and student.shortened("a b", 3) == "a b"


def test_timeouts_are_named(spark):
    df = spark.createDataFrame([(1, "u", "<p>" + "word " * 60_000), (2, "u", "<p>Some text that is long enough.")], "page_id long, url string, html string")
    got = {x.page_id: x.skip_reason for x in render.admit(render.render_pages(df, mode="parser", timeout_s=0.0)).collect()}
    assert got[1] == "timeout"
    assert {x.page_id: x.skip_reason for x in render.admit(render.render_pages(df, mode="parser")).collect()} == {1: "long", 2: None}


def test_token_counts(spark):
    public = pytest.importorskip("public_tokenizers")
    path = public.path("byte_bpe_50k.tiktoken")
    texts = ["Some words, and 12 numbers.", "", None, "日本 𠀀 é", "a" * 500]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {x.doc_id: (x.w, x.b) for x in df.select("doc_id", tokens.count(F.col("text")).alias("w"), tokens.count(F.col("text"), "bpe", path).alias("b")).collect()}
    enc = tokens.encoder(path)
    assert got == {i: (len((t or "").split()), len(enc.encode_ordinary(t or ""))) for i, t in enumerate(texts)}


def test_archives_by_either_reader(spark, tmp_path):
    block = b"HTTP/1.1 200 OK\r\nA: b\r\n\r\n<p>gr\xc3\xbcn</p>"
    record = lambda i, kind: b"WARC/1.0\r\nWARC-Type: %s\r\nWARC-Record-ID: <%d>\r\nWARC-Target-URI: http://x/%d\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (kind, i, i, len(block), block)
    (tmp_path / "a.warc.gz").write_bytes(b"".join(gzip.compress(record(i, k)) for i, k in ((1, b"response"), (2, b"request"), (3, b"response"))))
    (tmp_path / "b.warc").write_bytes(record(4, b"response"))
    want = {(f"<{i}>", f"http://x/{i}", "<p>grün</p>") for i in (1, 3, 4)}
    assert {tuple(x) for x in archive.read_archive_files(spark, str(tmp_path)).collect()} == want
    assert {tuple(x) for x in archive.read_archives(spark, [str(tmp_path / "a.warc.gz"), str(tmp_path / "b.warc")]).collect()} == want


def test_rulebook_families(spark):
    lines = {
        "Share this story with friends": "social", "Add to cart": "shop", "© 2020 Some Company": "footer", "Privacy policy and more": "legal", "Home": "chrome", "Read more": "chrome",
        "Это строка": "foreign", "A &nbsp; B": "residue", "By Jane Roe, add to cart": None, "ISBN 12-3 all rights reserved": None, "A plain line of text.": None,
    }
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    assert {x.line: x.f for x in df.select("line", rulebook.noise(F.col("line")).alias("f")).collect()} == lines
    doc = "A story begins here. Share this now! It goes on.\nHome\n\nBy Jane Roe\nFollow us"
    got = rulebook.apply(spark.createDataFrame([(1, doc), (2, "Call us today. Book now!"), (3, None)], "doc_id long, text string")).collect()
    assert got[0].cleaned == "A story begins here. It goes on.\nBy Jane Roe" and (got[0].lines_gone, got[0].lines_changed) == (2, 1)
    assert got[1].family == "promotion" and got[1].cleaned is None and got[2].cleaned is None


def test_ledger(spark):
    book = runlog.Ledger()
    with book.step("once", "labels"):
        pass
    with pytest.raises(ValueError), book.step("once", "labels", workers=4):
        raise ValueError
    x = runlog.summary(book.table(spark)).collect()
    assert {(r.paid, r.step) for r in x} == {("once", "labels"), ("once", "all"), ("all", "all")} and len(book.rows) == 2


def test_edits_found_back():
    lines = ["One.", "Two words here.", "Three.", "Two words here."]
    assert align.align(lines, "One.\nTwo here.\nThree.") == ([4], [(2, "words ")], None)
    assert align.align(lines, "One.\nOther text.")[2] == "One.\nOther text."
    many = " ".join(f"a{i}@b.c x{i}" for i in range(12))
    drop, cuts, page = align.align([many], " ".join(f"x{i}" for i in range(12)))
    assert (drop, page) == ([], None) and len(cuts) >= 12


def test_proxy_prefers_the_corpus_it_has_read(spark):
    items = spark.createDataFrame([(i, " ".join(f"w{i}x{j}" for j in range(20))) for i in range(40)], "item_id long, text string")
    asked = cut(proxy.continuation_tasks(items).unionByName(proxy.order_tasks(items)))
    seen = {r.task: r for r in proxy.evaluate(proxy.train(items, asked), asked).collect()}
    assert seen["continue"].acc == 1.0 and seen["order"].acc == 1.0 and seen["order"].chance == 0.5
    none = proxy.evaluate(proxy.train(items.where("false"), asked), asked).collect()
    assert all(r.acc <= 0.25 for r in none)


def test_equal_tokens_by_group(spark):
    r = random.Random(3)
    rows = [(p, i, r.randrange(1, 50)) for p in "ab" for i in range(200)]
    df = spark.createDataFrame(rows, "pipeline string, doc_id long, n_tokens long")
    kept = metrics.equal_token_cut(df, 1000, ("pipeline",)).groupBy("pipeline").agg(F.sum("n_tokens").alias("t")).collect()
    assert all(1000 <= x.t < 1050 for x in kept)
    runs = sorted((x.pipeline, x.run, x.n_tokens) for x in metrics.token_run(df, ("pipeline",)).collect())
    for (p, a, n), (q, b, _) in zip(runs, runs[1:], strict=False):
        assert p != q or a + n == b


def test_written_stages_go(spark):
    df, at = written(spark.range(5), "stage")
    assert df.count() == 5
    remove(spark, at)
    with pytest.raises(Exception, match=r".*"):
        spark.read.parquet(at).count()


def test_soft_matching_bounds(spark):
    df = spark.createDataFrame([("same words here", "same words here"), ("one two", "xyz qrs"), ("", "a")], "source string, out string")
    got = [x.soft_f1 for x in metrics.soft_match_f1(df).collect()]
    assert got[0] == pytest.approx(1.0, abs=1e-5) and got[1] < 0.3 and got[2] == 0.0


def test_every_sql_has_its_query():
    assert set(comparison_sql.SQL) | set(surfaces_sql.SQL) <= set(workloads.QUERIES) and len(workloads.QUERIES) > 140
    assert not set(comparison_sql.SQL) & set(surfaces_sql.SQL) and comparison.query is surfaces.query
