"""Registered queries: every method, variant, baseline, measure and experiment on the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_curation import published
from spark_curation.functions import sql as sql_surface
from spark_curation.functions.text import count_words, ngrams, words
from spark_curation.io import cut, table
from spark_curation.operators import align, dedup, execute, judges, metrics, postfilter, program, refiners, relational, render, rules, scrapers, student, targets, teachers
from spark_curation.plans import pipelines
from spark_curation.streaming import pages as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def _pages(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "pages")


def _docs(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "documents")


def _programs(s: SparkSession, d: str) -> DataFrame:
    return pipelines.programs(_pages(s, d))


def _policy(s: SparkSession, d: str, **kw) -> DataFrame:
    return pipelines.policy(pipelines.rendered_pages(_pages(s, d)), **kw)


def _short(c: str) -> F.Column:
    """A short digest of a text column, for results that need not carry whole texts."""
    return F.substring(F.md5(F.coalesce(F.col(c), F.lit(""))), 1, 16)


def _range_text(c: str) -> F.Column:
    return F.array_join(F.transform(c, lambda r: F.concat_ws("-", r["a"].cast("string"), r["b"].cast("string"))), ",")


# ---- rendering ----


@query
def render_line_counts(s, d):
    return render.render_pages(_pages(s, d)).select("page_id", "n_lines", "n_chars", "n_tokens")


@query
def render_lines(s, d):
    r = render.render_pages(_pages(s, d), with_blocks=True)
    return r.select("page_id", F.posexplode("blocks").alias("pos", "b")).select("page_id", (F.col("pos") + 1).alias("lid"), F.col("b.text").alias("line"), F.col("b.zone").alias("zone"))


@query
def render_by_parser(s, d):
    r = render.render_pages(_pages(s, d), mode="parser", with_blocks=True)
    return r.select("page_id", F.posexplode("blocks").alias("pos", "b")).select("page_id", (F.col("pos") + 1).alias("lid"), F.col("b.text").alias("line"), F.col("b.zone").alias("zone"))


@query
def numbered_prompt(s, d):
    r = render.render_pages(_pages(s, d)).withColumn("prompt", render.number_lines(F.col("lines")))
    back = F.array_join(render.unnumber(F.col("prompt")), "\n") == F.array_join("lines", "\n")
    return r.select("page_id", F.md5("prompt").alias("prompt_md5"), back.alias("round_trip"))


@query
def admission(s, d):
    r = render.admit(render.render_pages(_pages(s, d)), min_chars=400)
    return r.groupBy(F.coalesce("skip_reason", F.lit("admitted")).alias("outcome")).agg(F.count("*").alias("n"))


# ---- programs ----


@query
def strip_policy_ranges(s, d):
    return teachers.extract(pipelines.rendered_pages(_pages(s, d))).select("page_id", _range_text("strip").alias("strip"), F.size("lines").alias("n_lines"))


@query
def policy_verdicts(s, d):
    p = _policy(s, d)
    return p.select("page_id", "verdict", "family", "edu", F.size("drop").alias("n_drop"), F.size("cuts").alias("n_cuts"), _range_text("drop").alias("drop_ranges"))


@query
def program_roundtrip(s, d):
    p = _policy(s, d)
    back = None
    for layout in ("decision_first", "extract_first"):
        again = program.parse(p.select("page_id", program.serialize(layout).alias("output"))).select("page_id", F.lit(layout).alias("layout"), F.struct("verdict", "strip", "drop", "cuts", "body").alias("got"))
        back = again if back is None else back.union(again)
    want = p.select("page_id", F.struct("verdict", "strip", "drop", "cuts", "body").alias("want"))
    return back.join(want, "page_id").select("page_id", "layout", F.to_json("got").eqNullSafe(F.to_json("want")).alias("same"))


#: Programs with the flaws that untrusted output shows, over a page of four lines.
FLAWED = [
    (1, "<keep>\n<extract>\nrm 1-2\n<keep>"), (2, "<extract>\nrm 4\n<edit>\nrm 1\nsub 3: \" [share]\""), (3, "<edit>\n<extract>\nrm 1-2; rm 4\n<edit>\nrm 3--3"),
    (4, "<keep>\n<extract>\nrm 3-9\n<delete>"), (5, "<edit>\n<extract>\n<edit>\nrm 4-2\nsub 1: \"absent\""), (6, "no program at all"), (7, ""),
    (8, "<rewrite>\n<extract>\nrm 1\n<rewrite>\nNew text.\nMore."), (9, "<edit>\n<extract>\n<edit>\nPlain page text."), (10, "<edit>\n<extract>\n<edit>\nsub 2: \"say \\\"hi\\\"\""),
]
FLAWED_LINES = ["Home", 'They say "hi" here', "Rivers carry silt. [share]", "Read next"]


def _flawed(s: SparkSession, d: str) -> DataFrame:
    """Every page with one of the flawed programs, over lines of which the first is the page's address."""
    made = F.element_at(F.array(*[F.lit(x) for _, x in FLAWED]), (F.pmod("page_id", F.lit(len(FLAWED))) + 1).cast("int"))
    lines = F.array(F.coalesce("url", F.lit("")), *map(F.lit, FLAWED_LINES[1:]))
    rows = _pages(s, d).select("page_id", made.alias("output"), lines.alias("lines"))
    return program.validate(program.parse(rows))


@query
def program_items(s, d):
    p = _flawed(s, d)
    cuts = F.array_join(F.transform("cuts", lambda c: F.concat_ws("=", c["lid"].cast("string"), c["frag"])), ";")
    return p.select("page_id", "verdict", "layout", "status", _range_text("strip").alias("strip"), _range_text("drop").alias("drop_ranges"), cuts.alias("cuts"), "body", "lenient")


@query
def program_problems(s, d):
    return _flawed(s, d).select("page_id", F.array_join("problems", ",").alias("problems"))


@query
def flawed_execution(s, d):
    return execute.run(_flawed(s, d)).select("page_id", "provenance", "text")


# ---- execution ----


def _executed(s, d, **kw) -> DataFrame:
    return execute.run(_programs(s, d), **kw)


def _by_verdict(name: str) -> None:
    def run(s, d):
        return _executed(s, d).where(F.col("verdict") == name).select("page_id", "provenance", "words_in", "words_stripped", "words_out", F.md5("text").alias("text_md5"))

    run.__name__ = f"execute_{name}"
    query(run)


for _v in ("keep", "edit", "delete", "rewrite"):
    _by_verdict(_v)


@query
def execute_relational(s, d):
    one = execute.run_relational(_programs(s, d).where("size(cuts) = 0"))
    return one.select("page_id", F.md5("text").alias("text_md5"))


@query
def verdict_counts(s, d):
    return _executed(s, d).groupBy("verdict").agg(F.count("*").alias("n_pages"), F.sum("words_in").alias("words_in"), F.coalesce(F.sum("words_out"), F.lit(0)).alias("words_out"))


@query
def provenance_counts(s, d):
    return _executed(s, d).groupBy("provenance").agg(F.count("*").alias("n"))


@query
def ablation_tokens(s, d):
    p = cut(_programs(s, d))
    out = None
    for name, off in {"full": (), "edit off": ("edit",), "rewrite off": ("rewrite",), "delete off": ("delete",), "extract off": ("extract",)}.items():
        one = execute.run(p, disable=off).agg(F.count_if(F.col("text").isNotNull()).alias("n_docs"), F.sum("words_out").alias("words")).select(F.lit(name).alias("variant"), "n_docs", "words")
        out = one if out is None else out.union(one)
    return out


@query
def cascaded_extract(s, d):
    gold = teachers.extract(render.render_pages(_pages(s, d), mode="parser", with_blocks=True)).select("page_id", F.col("strip").alias("other"))
    p = _programs(s, d).join(gold, "page_id").withColumn("strip", F.col("other"))
    return execute.run(p).agg(F.count_if(F.col("text").isNotNull()).alias("n_docs"), F.sum("words_out").alias("words"))


@query
def operation_profile(s, d):
    return metrics.operation_profile(_executed(s, d))


@query
def token_waterfall(s, d):
    return metrics.waterfall(cut(_programs(s, d)))


@query
def output_economy(s, d):
    return metrics.output_economy(_programs(s, d))


@query
def strip_stats(s, d):
    return metrics.strip_stats(_programs(s, d))


@query
def edit_stats(s, d):
    return metrics.edit_stats(_programs(s, d))


# ---- teachers and targets ----


def _targets(s, d) -> DataFrame:
    return targets.compose(_programs(s, d))


@query
def target_tokens(s, d):
    return _targets(s, d).select("page_id", "verdict", "n_tokens", F.md5("answer").alias("answer_md5"))


@query
def stage_mixture(s, d):
    t = cut(_targets(s, d))
    both = targets.mixture(t, 1, rewrite_share=0.01).unionByName(targets.mixture(t, 2))
    return both.groupBy("stage", "verdict").agg(F.count("*").alias("n"))


@query
def outcome_line(s, d):
    return targets.outcome_line(_targets(s, d))


@query
def fit_window(s, d):
    return targets.fit_window(_targets(s, d), 900).groupBy("verdict").agg(F.count("*").alias("n"), F.max("n_tokens").alias("longest"))


@query
def pack_sequences(s, d):
    return targets.pack(_targets(s, d), 4096, 4).groupBy("shard", "pack_id").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("n_tokens"))


@query
def target_invariant(s, d):
    """The program that a target spells executes to the teachers' own text."""
    p = _policy(s, d)
    ran = execute.run(p).select("page_id", F.col("text").alias("own"))
    again = execute.run(_programs(s, d)).select("page_id", "text")
    return ran.join(again, "page_id", "full_outer").agg(F.count("*").alias("n"), F.count_if(~F.col("own").eqNullSafe(F.col("text"))).alias("n_different"))


@query
def align_edit(s, d):
    """The edit policy's own text, aligned back to operations over the extracted lines."""
    p = _executed(s, d).where("verdict = 'edit'")
    kept = F.filter(F.transform("lines", lambda x, i: F.struct((i + 1).alias("lid"), x.alias("t"))), lambda q: ~F.exists("strip", lambda r: q["lid"].between(r["a"], r["b"])))
    got = align.to_edit(p.select("page_id", F.transform(kept, lambda q: q["t"]).alias("lines"), F.col("text").alias("cleaned")))
    return got.select("id", F.size("drop_ids").alias("n_drop"), F.size("cuts").alias("n_cuts"), F.col("body").isNotNull().alias("page_text"))


@query
def rewrite_accept(s, d):
    r = teachers.rewrite(F.col("text"))
    x = _docs(s, d).select("doc_id", "text", r.alias("out"))
    return x.select("doc_id", count_words(F.col("out")).alias("n_out"), teachers.accept_rewrite(F.col("text"), F.col("out")).alias("accepted"))


@query
def refinement_replies(s, d):
    """The output contract on refining replies: empty ones and early markers delete."""
    m = teachers.DELETE_MARKER
    replies = F.when(F.col("doc_id") % 4 == 0, F.lit("")).when(F.col("doc_id") % 4 == 1, F.concat(F.lit(m), F.col("text"))).when(F.col("doc_id") % 4 == 2, F.concat(F.substring(F.concat(F.col("text"), F.lit(" " * 130)), 1, 121), F.lit(m))).otherwise(F.col("text"))
    return _docs(s, d).select(F.pmod("doc_id", F.lit(4)).alias("kind"), teachers.read_refinement(replies).alias("delete")).groupBy("kind", "delete").agg(F.count("*").alias("n"))


@query
def edu_scores(s, d):
    return _docs(s, d).select("doc_id", teachers.edu_score(F.col("text")).alias("edu"))


@query
def valueless_families(s, d):
    return _docs(s, d).groupBy(F.coalesce(teachers.valueless(F.col("text")), F.lit("-")).alias("family")).agg(F.count("*").alias("n"))


@query
def rescue_threshold(s, d):
    scored = _docs(s, d).select("doc_id", teachers.valueless(F.col("text")).alias("family"), teachers.edu_score(F.col("text")).alias("edu")).where("family is not null")
    t = s.createDataFrame([(0.5,), (1.0,), (1.5,), (2.0,)], "threshold double")
    return scored.join(F.broadcast(t)).groupBy("threshold").agg(F.count("*").alias("n"), F.count_if(F.col("edu") >= F.col("threshold")).alias("rescued"))


@query
def rescue_variants(s, d):
    out = None
    for name, kw in {"edu 1.0": {}, "edu 1.5": {"threshold": 1.5}, "classifier": {"rescue": "classifier"}, "three_way": {"rescue": "three_way"}}.items():
        one = _policy(s, d, **kw).groupBy("verdict").agg(F.count("*").alias("n")).select(F.lit(name).alias("variant"), "verdict", "n")
        out = one if out is None else out.union(one)
    return out


# ---- filters and deduplication ----


@query
def postfilter_leaks(s, d):
    rows = _docs(s, d).select("doc_id", F.when(F.col("doc_id") % 50 == 7, F.concat(F.col("text"), F.lit("\nrm 3-4"))).when(F.col("doc_id") % 50 == 9, F.concat(F.lit("<keep>\n"), F.col("text"))).otherwise(F.col("text")).alias("text"))
    return postfilter.reject_leaks(rows).agg(F.count("*").alias("n_left"))


@query
def leak_rate(s, d):
    return metrics.leak_rate(_executed(s, d))


@query
def exact_dup_texts(s, d):
    return dedup.exact_copies(_docs(s, d))


@query
def ngram_dedup(s, d):
    return dedup.ngram(_docs(s, d)).select("id", "n_grams", "n_owned")


@query
def ngram_dedup_bloom(s, d):
    return dedup.ngram(_docs(s, d), mode="bloom").select("id")


@query
def unique_tokens(s, d):
    x = _docs(s, d).withColumn("n_tokens", count_words(F.col("text")))
    left = dedup.survivors(x, dedup.ngram(x))
    return metrics.unique_tokens(left.withColumn("pipeline", F.col("lang")))


@query
def equal_token_cut(s, d):
    x = _docs(s, d).select("doc_id", count_words(F.col("text")).alias("n_tokens"))
    return metrics.equal_token_cut(x, 100_000)


# ---- rules ----


@query
def page_statistics(s, d):
    x = rules.statistics(_docs(s, d))
    return x.select("doc_id", "n_words", "n_lines", *[F.round(c, 6).alias(c) for c in ("mean_word", "symbol_ratio", "alpha_share", "dup_line_share", "dup_line_chars", "dup_gram_share", "ended_share", "short_share")], "stop_words", "sentences")


def _stack(name: str) -> None:
    def run(s, d):
        return rules.apply(_docs(s, d), name).select("doc_id", F.md5("text").alias("text_md5"))

    run.__name__ = f"rules_{name}"
    query(run)


for _v in "abc":
    _stack(_v)


@query
def rules_a_spans(s, d):
    """Three-line spans that an earlier document has, by stack a's corpus rule."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")
    at = F.sequence(F.lit(1), F.size("l") - 2)
    spans = _docs(s, d).select("doc_id", lines.alias("l")).where(F.size("l") >= 3).select("doc_id", F.explode(F.transform(at, lambda i: F.md5(F.array_join(F.slice("l", i, F.lit(3)), "\n")))).alias("h"))
    own = spans.groupBy("h").agg(F.min("doc_id").alias("owner"))
    return spans.join(own, "h").where("owner < doc_id").groupBy("doc_id").agg(F.count("*").alias("n_spans"))


def _labels(s, d) -> DataFrame:
    return table(s, d, "labels").select(F.col("doc_id").alias("id"), (F.col("quality") == 1).alias("good"))


@query
def rule_decisions(s, d):
    return rules.decisions(_docs(s, d)).groupBy("stack", "rule").agg(F.count_if("dropped").alias("n_dropped"))


@query
def rule_false_drop(s, d):
    out = metrics.false_drop(rules.decisions(_docs(s, d)), _labels(s, d))
    return out.withColumn("false_drop", F.round("false_drop", 6))


@query
def keepdrop_accuracy(s, d):
    kept = rules.decisions(_docs(s, d)).groupBy("id", "stack").agg((~F.bool_or("dropped")).alias("keep"))
    out = metrics.keepdrop_accuracy(kept, _labels(s, d), ["stack"])
    return out.withColumn("accuracy", F.round("accuracy", 6))


# ---- scrapers, refiners, pipelines ----


def _scraper(name: str) -> None:
    def run(s, d):
        return scrapers.SCRAPERS[name](_pages(s, d)).select("page_id", F.md5("text").alias("text_md5"), count_words(F.col("text")).alias("n_tokens"))

    run.__name__ = f"scrape_{name}"
    query(run)


for _v in scrapers.SCRAPERS:
    _scraper(_v)


@query
def fused_cells(s, d):
    """Parts as tables of cells and lists, with and without a space between cells."""
    cell = lambda a, b: [F.lit(f"<tr><th>{a}</th><td>"), F.col(b).cast("string"), F.lit("</td></tr>")]
    html = F.concat(F.lit("<table>"), *cell("Brand", "p_brand"), *cell("Size", "p_size"), F.lit("</table><ul><li>"), "p_type", F.lit("</li><li>Steel</li></ul>"))
    x = table(s, d, "part").select(F.col("p_partkey").alias("page_id"), html.alias("html"))
    return scrapers.tagdrop(x).select("page_id", F.lit("spaced").alias("kind"), "text").union(scrapers.tagdrop(x, fused_cells=True).select("page_id", F.lit("fused").alias("kind"), "text"))


@query
def scraper_f1(s, d):
    gold = scrapers.teacher(_pages(s, d))
    out = None
    for name, f in scrapers.SCRAPERS.items():
        one = metrics.token_f1(f(_pages(s, d)), gold).agg(F.round(F.avg("precision"), 4).alias("precision"), F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("f1"), 4).alias("f1")).select(F.lit(name).alias("scraper"), "precision", "recall", "f1")
        out = one if out is None else out.union(one)
    return out


@query
def gold_documents(s, d):
    """Pages whose article is a document, by collapsed text: the link to labels."""
    main = F.transform(F.filter(render.native_blocks(F.col("html")), lambda b: b["zone"] == ""), lambda b: b["text"])
    p = _pages(s, d).select("page_id", main.alias("main")).select("page_id", F.array_join(F.slice("main", 2, F.size("main")), " ").alias("body"))
    docs = _docs(s, d).select("doc_id", F.trim(F.regexp_replace("text", r"\s+", " ")).alias("t"))
    hit = p.join(docs, F.md5("body") == F.md5("t"))
    return hit.groupBy("page_id").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("n_copies"))


@query
def refiner_chunkprog(s, d):
    return refiners.chunkprog(scrapers.tagdrop(_pages(s, d))).select("page_id", F.md5("text").alias("text_md5"), "words_in", "words_out")


@query
def chunk_programs(s, d):
    return refiners.chunk_programs(scrapers.tagdrop(_pages(s, d))).select("page_id", "output")


@query
def refiner_lineprog(s, d):
    return refiners.lineprog(scrapers.tagdrop(_pages(s, d))).select("page_id", F.md5("text").alias("text_md5"), "words_in", "words_out")


@query
def document_edit(s, d):
    return refiners.lineprog(_docs(s, d), "doc_id").select(F.col("page_id").alias("doc_id"), F.md5("text").alias("text_md5"), "words_in", "words_out")


@query
def conversation_edit(s, d):
    turns = table(s, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda t: F.regexp_replace(t["text"], r"\s+", " ")), "\n").alias("text"))
    return refiners.lineprog(turns, "conv_id").select(F.col("page_id").alias("conv_id"), "words_in", "words_out")


@query
def chunk_route(s, d):
    return refiners.orchestrated(_docs(s, d), id_col="doc_id").select(F.col("page_id").alias("doc_id"), "n_chunks", "n_dropped", "n_cleaned", "n_guided", count_words(F.col("text")).alias("words_out"))


@query
def teacher_pipeline(s, d):
    """The teachers in sequence without program text, as the reference for the student."""
    return execute.run(_policy(s, d)).groupBy("provenance").agg(F.count("*").alias("n"), F.coalesce(F.sum("words_out"), F.lit(0)).alias("words_out"))


# ---- published arithmetic ----


def _scores(s, d) -> DataFrame:
    """Mean length of documents as the score of their source, each language a scale."""
    return _docs(s, d).groupBy(F.col("source").alias("pipeline"), F.col("lang").alias("scale")).agg(F.avg("n_chars").alias("score"))


@query
def centered_accuracy(s, d):
    """A guess of quality by length (200 characters or more: good), one task for each language."""
    x = _docs(s, d).join(_labels(s, d), F.col("doc_id") == F.col("id")).groupBy(F.col("lang").alias("task")).agg(F.avg(((F.col("n_chars") >= 200) == F.col("good")).cast("double")).alias("acc"))
    return x.select("task", F.round("acc", 6).alias("acc"), F.round(metrics.centered(F.col("acc"), F.lit(0.5)), 6).alias("centered"))


@query
def suite_rollup(s, d):
    """The suite score from category means, by expanding each category to its tasks."""
    p = published.table(s)
    cats = F.array(*[F.struct(F.lit(c).alias("category"), F.col(c).alias("acc"), F.lit(n).alias("n")) for c, n in published.TASKS.items()])
    tasks = p.select("pipeline", "scale", F.explode(cats).alias("t")).select("pipeline", "scale", "t.*").select("pipeline", "scale", "category", "acc", F.lit(0.0).alias("chance"), F.explode(F.sequence(F.lit(1), F.col("n"))))
    return metrics.suite(tasks).select("pipeline", "scale", F.coalesce("category", F.lit("all")).alias("category"), F.round("score", 6).alias("score"), "n_tasks")


@query
def relative_gain(s, d):
    return metrics.relative(_scores(s, d), "src0")


@query
def scale_ranks(s, d):
    return metrics.rank(_scores(s, d)).where("place <= 2")


@query
def repetition_factor(s, d):
    """How often each source's characters are repeated at each budget, in millions."""
    budgets = F.array(*[F.struct(F.lit(k).alias("scale"), F.lit(v * 1e6).alias("budget")) for k, v in published.BUDGETS.items()])
    x = _docs(s, d).groupBy(F.col("source").alias("pipeline")).agg(F.sum("n_chars").alias("n")).select("pipeline", "n", F.inline(budgets))
    return x.select("pipeline", "scale", F.round(F.col("budget") / F.col("n"), 4).alias("repetition"))


@query
def welch(s, d):
    rows = [(m, sd, n) for m, sd, n in published.SEEDS.values()]
    x = s.createDataFrame([(*rows[0], *rows[1])], "m1 double, s1 double, n1 int, m2 double, s2 double, n2 int")
    return x.select(F.round(metrics.welch(*[F.col(c) for c in ("m1", "s1", "n1", "m2", "s2", "n2")]), 4).alias("t"))


# ---- quality, judges, lengths ----


def _judged(s, d) -> DataFrame:
    e = _executed(s, d)
    raw = F.array_join("lines", "\n")
    return e.select("page_id", "verdict", "provenance", judges.quality_score(raw).alias("q0"), judges.quality_score(F.col("text")).alias("q1"), teachers.edu_score(raw).alias("e0"), teachers.edu_score(F.col("text")).alias("e1"), judges.output_rating(F.col("text")).alias("rating"), F.col("text").isNotNull().alias("kept"))


@query
def before_after_by_verdict(s, d):
    return metrics.before_after(_judged(s, d).select("verdict", F.col("q0").alias("before"), F.when(F.col("kept"), F.col("q1")).alias("after")))


@query
def quality_by_group(s, d):
    j = _judged(s, d).where("kept")
    q = j.groupBy(metrics.quality_group(F.col("q0")).alias("grp")).agg(F.count("*").alias("n"), F.round(F.avg("q1"), 4).alias("after")).select(F.lit("quality").alias("scorer"), "grp", "n", "after")
    e = j.groupBy(metrics.edu_group(F.col("e0")).alias("grp")).agg(F.count("*").alias("n"), F.round(F.avg("e1"), 4).alias("after")).select(F.lit("edu").alias("scorer"), "grp", "n", "after")
    return q.union(e)


@query
def good_page_retention(s, d):
    return _judged(s, d).where("e0 >= 1.0").agg(F.count("*").alias("n_good"), F.round(F.avg(F.col("kept").cast("double")), 6).alias("kept"))


@query
def judge_by_group(s, d):
    j = _judged(s, d).where("kept")
    return j.groupBy(metrics.quality_group(F.col("q0")).alias("grp")).agg(F.count("*").alias("n"), F.round(F.avg("rating"), 4).alias("rating"), F.round(F.avg((F.col("rating") >= 2).cast("double")), 4).alias("keep_share"))


@query
def judge_replies(s, d):
    """A reply for each document: one with grades, one with a verdict, one that is no JSON, or none."""
    kind, n = F.pmod("doc_id", F.lit(4)), F.col("n_chars")
    grades = F.concat(F.lit('{"recall": '), (n % 3).cast("string"), F.lit(', "precision": 1, "integrity": 2}'))
    verdict = F.concat(F.lit('{"verdict": "keep", "value": '), (n % 4).cast("string"), F.lit("}"))
    x = _docs(s, d).select(F.col("doc_id").alias("id"), F.when(kind == 0, grades).when(kind == 1, verdict).when(kind == 2, F.concat(F.lit("keep "), "lang")).alias("reply"))
    return judges.read_replies(x).select("id", "judged.recall", "judged.verdict", "judged.value", "bad_reply")


@query
def paired_length(s, d):
    c = pipelines.corpora(_pages(s, d), ["raw", "unified"], deduplicate=False)
    return metrics.paired_length(c.where("pipeline = 'unified'"), c.where("pipeline = 'raw'"))


@query
def rewrite_faithfulness(s, d):
    kept = F.filter("lines", lambda x, i: ~F.exists("strip", lambda r: (i + 1).between(r["a"], r["b"])))
    p = _executed(s, d).where("verdict = 'rewrite'").select("page_id", F.array_join(kept, "\n").alias("source"), F.col("text").alias("out"))
    mode = F.mode(F.floor(F.col("soft_f1") * 20) / 20)  # the most frequent twentieth
    return metrics.soft_match_f1(p).agg(F.count("*").alias("n"), F.round(mode, 2).alias("mode_from"), F.round(F.avg("soft_f1"), 4).alias("mean_f1"), F.round(F.avg((F.col("soft_f1") > 0.8).cast("double")), 4).alias("over_08"))


@query
def embedding_soft_match(s, d):
    """Cosine of vectors to their label's mean: matching on given vectors in place of a model's."""
    v = table(s, d, "embeddings")
    means = v.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg("x").alias("m")).groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda t: t["m"]).alias("mean"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)
    e = F.transform("embedding", lambda x: x.cast("double"))
    sim = dot(e, F.col("mean")) / F.sqrt(dot(e, e) * dot(F.col("mean"), F.col("mean")))
    return v.join(F.broadcast(means), "label").groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg(sim), 4).alias("mean_cosine"))


# ---- student ----


#: The last student and what it was trained on: the queries about it share one training.
_TRAINED: dict[tuple[str, str], tuple] = {}


def _student(s, d):
    key = s.sparkContext.applicationId, d
    if key not in _TRAINED:
        _TRAINED.clear()
        p = cut(_programs(s, d))
        w, losses = student.fit(student.examples(targets.mixture(p, 1, rewrite_share=0.01)), student.examples(targets.mixture(p, 2)))
        _TRAINED[key] = p, w, losses
    return _TRAINED[key]


@query
def student_predictions(s, d):
    p, w, _ = _student(s, d)
    got = program.parse(student.decode(p, w))
    return got.groupBy("verdict").agg(F.count("*").alias("n"))


@query
def verdict_confusion(s, d):
    p, w, _ = _student(s, d)
    return metrics.confusion(program.parse(student.decode(p, w)), p)


@query
def token_f1_student(s, d):
    p, w, _ = _student(s, d)
    mine = execute.run(program.parse(student.decode(p, w)).join(p.select("page_id", "lines"), "page_id"))
    f1 = metrics.token_f1(mine.where("text is not null"), execute.run(p).where("text is not null"))
    return f1.agg(F.count("*").alias("n"), F.round(F.avg("f1"), 4).alias("f1"))


# ---- proxy suite ----


@query
def benchmark_hits(s, d):
    """Documents that share eight words in a row with a benchmark passage, by equi-join of 8-grams."""
    key = lambda df, i: df.select(F.col(i), F.explode(F.array_distinct(ngrams(words(F.col("text")), 8))).alias("g"))
    return key(_docs(s, d), "doc_id").join(key(table(s, d, "benchmark"), "item_id"), "g").groupBy("doc_id", "item_id").agg(F.count("*").alias("n_shared"))


@query
def decontaminated(s, d):
    return _docs(s, d).join(benchmark_hits(s, d).select("doc_id"), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n"))


# ---- streams ----


@query
def stream_verdicts(s, d):
    pages = streams.source(s, d, "pages", streams.PAGES)
    done = streams.drain(execute.run(pipelines.programs(pages)).select("page_id", "verdict", "provenance"))
    return done.groupBy("verdict").agg(F.count("*").alias("n"))


@query
def stream_dedup(s, d):
    x = streams.timed_pages(s, d).withColumn("url", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).select("url", "ts")
    return streams.drain(streams.first_urls(x, "60 days")).select("url").groupBy().agg(F.count("*").alias("n"))


@query
def event_tumbling(s, d):
    return streams.drain(streams.tumbling(streams.source(s, d, "events", streams.EVENTS)), "complete")


@query
def event_sliding(s, d):
    return streams.drain(streams.sliding(streams.source(s, d, "events", streams.EVENTS)), "complete")


@query
def event_sessions(s, d):
    x = streams.sessions(table(s, d, "events"))
    return x.groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.max("n").alias("longest"))


# ---- SQL surface and relational operators ----


@query
def page_lines_udtf(s, d):
    sql_surface.register(s)
    _pages(s, d).createOrReplaceTempView("curation_pages")
    return s.sql("SELECT page_id, count(*) AS n_lines, count_if(zone = '') AS n_content FROM curation_pages, LATERAL page_lines(html) GROUP BY page_id")


@query
def numbered_sql(s, d):
    sql_surface.register(s)
    render.render_pages(_pages(s, d)).createOrReplaceTempView("curation_rendered")
    return s.sql("SELECT page_id, md5(numbered(lines)) AS prompt_md5 FROM curation_rendered")


@query
def json_props(s, d):
    e = table(s, d, "events")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.get_json_object("props", "$").isNotNull()).alias("n_json"))


@query
def asof_event(s, d):
    e = table(s, d, "events")
    clicks = e.where("event_type = 'click'").select("user_id", "ts", "event_id")
    other = e.where("event_type <> 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("other_id"))
    return relational.asof(clicks, other, "user_id", "ts", "other_id").select("event_id", "last_other_id")


@query
def rollup_orders(s, d):
    o = table(s, d, "orders")
    return o.rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.grouping_id().cast("long").alias("g"))


@query
def cube_lineitem(s, d):
    x = table(s, d, "lineitem")
    return x.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query
def set_ops(s, d):
    a, b = rules.apply(_docs(s, d), "b").select("doc_id"), rules.apply(_docs(s, d), "c").select("doc_id")
    n = lambda x, k: x.agg(F.count("*").alias("n")).select(F.lit(k).alias("kind"), "n")
    return n(a.intersect(b), "both").union(n(a.subtract(b), "only b")).union(n(b.exceptAll(a), "only c")).union(n(a.union(b).distinct(), "either"))


@query
def semi_anti(s, d):
    c, o = table(s, d, "customer"), table(s, d, "orders")
    big = o.where("o_totalprice > 100000").select(F.col("o_custkey").alias("c_custkey"))
    semi = c.join(big, "c_custkey", "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("n_semi"))
    anti = c.join(big, "c_custkey", "left_anti").groupBy("c_mktsegment").agg(F.count("*").alias("n_anti"))
    return semi.join(anti, "c_mktsegment", "full_outer")


@query
def topk_per_group(s, d):
    o = table(s, d, "orders")
    return relational.top_k(o, "o_orderpriority", [F.col("o_totalprice").desc(), "o_orderkey"], 3).select("o_orderpriority", "o_orderkey", "place")


@query
def star_join(s, d):
    li, o, c, n, r = (table(s, d, t) for t in ("lineitem", "orders", "customer", "nation", "region"))
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query
def stream_host_lines(s, d):
    pages = streams.timed_pages(s, d)
    r = pages.select("url", "ts", F.transform(render.native_blocks(F.col("html")), lambda b: b["text"]).alias("lines"))
    return streams.drain(streams.host_lines(r), "complete").where("n >= 3").groupBy().agg(F.count("*").alias("n_lines"), F.max("n").alias("most"))


@query
def stream_interval_join(s, d):
    """Pages and their outputs, each output half an hour after its page: joined within two hours."""
    p = streams.timed_pages(s, d).select("page_id", "ts")
    late = F.when(F.col("page_id") % 5 == 0, F.expr("INTERVAL 3 HOURS")).otherwise(F.expr("INTERVAL 30 MINUTES"))
    o = streams.timed_pages(s, d).select("page_id", (F.col("ts") + late).alias("ts"), F.lit("<keep>").alias("output"))
    return streams.drain(streams.with_outputs(p, o).select("page_id")).groupBy().agg(F.count("*").alias("n"))
