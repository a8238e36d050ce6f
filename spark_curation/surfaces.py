"""Registered queries of the rulebook, corpus rules, the ledger, sources, SQL functions and further relational forms."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from spark_curation.functions import sql as sql_surface
from spark_curation.functions.text import count_words, words
from spark_curation.io import checkpoint_dir, cut, table
from spark_curation.operators import align, dedup, execute, judges, render, rulebook, rules, runlog, scrapers, teachers
from spark_curation.plans import pipelines
from spark_curation.sources import archive
from spark_curation.streaming import pages as streams
from spark_curation.workloads import query

# ---- rulebook and corpus rules ----


@query
def rulebook_lines(s, d):
    """Lines of documents by family of noise, and how many are protected."""
    x = table(s, d, "documents").select(F.explode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("line")).where("trim(line) <> ''")
    return x.groupBy(F.coalesce(rulebook.noise(F.col("line")), F.lit("-")).alias("family")).agg(F.count("*").alias("n"), F.count_if(rulebook.protected(F.col("line"))).alias("n_protected"))


@query
def rulebook_apply(s, d):
    x = rulebook.apply(table(s, d, "documents").select("doc_id", "text"))
    return x.select("doc_id", "family", F.md5("cleaned").alias("cleaned_md5"), "lines_gone", "lines_changed")


@query
def rulebook_families(s, d):
    return table(s, d, "documents").groupBy(F.coalesce(rulebook.worthless(F.col("text")), F.lit("-")).alias("family")).agg(F.count("*").alias("n"))


@query
def rules_a_removed(s, d):
    """Texts after stack a's corpus rule on repeated runs of lines."""
    return rules.a_spans(table(s, d, "documents")).select(F.col("id").alias("doc_id"), F.md5("text").alias("text_md5"), "n_gone")


@query
def rules_b_gate(s, d):
    pages = table(s, d, "pages").select("page_id", "url", F.lower(F.regexp_extract("html", r"(?i)<html[^>]*\blang=\"?([a-z]+)", 1)).alias("lang"))
    return rules.b_gate(pages).agg(F.count("*").alias("n_pages"), F.countDistinct("url").alias("n_urls"))


@query
def ngram_dedup_survivors(s, d):
    return dedup.survivors_only(table(s, d, "documents"))


# ---- teachers and alignment ----


@query
def lines_absent(s, d):
    """Lines that the default scraper's text lacks, found back on the rendered lines in order."""
    r = render.render_pages(table(s, d, "pages"))
    text = scrapers.tagdrop(table(s, d, "pages")).select("page_id", F.col("text").alias("extracted"))
    flags = align.lines_absent(F.col("lines"), F.col("extracted"))
    return r.join(text, "page_id").select("page_id", F.size(F.filter(flags, lambda x: x)).alias("n_absent"), "n_lines")


@query
def head_tail(s, d):
    x = table(s, d, "documents").select("doc_id", teachers.head_tail(F.col("text"), 100).alias("t"))
    return x.select("doc_id", F.size(words(F.col("t"))).cast("long").alias("n"), F.md5("t").alias("text_md5"))


@query
def refining_cap(s, d):
    """Replies of the refining stand-in against their output cap."""
    x = table(s, d, "documents").select(rulebook.capped(count_words(F.col("text")), count_words(teachers.rewrite(F.col("text")))).alias("ok"))
    return x.groupBy("ok").agg(F.count("*").alias("n"))


@query
def page_edit_audit(s, d):
    """Page-text edits: edited pages whose cleaned text is given as a whole, classed by what changed against the extracted lines."""
    p = execute.run(pipelines.programs(table(s, d, "pages"))).where("verdict = 'edit' and text is not null")
    kept = F.filter("lines", lambda x, i: ~F.exists("strip", lambda r: (i + 1).between(r["a"], r["b"])))
    pairs = p.select("page_id", F.array_join(kept, "\n").alias("source"), F.col("text").alias("body"))
    return align.classify_page_edit(pairs).agg(F.count("*").alias("n"), F.round(F.avg(F.col("pure_deletion").cast("double")), 6).alias("pure_deletion"), F.round(F.avg((F.col("changed_share") > 0).cast("double")), 6).alias("changed"))


@query
def rewrite_lengths(s, d):
    """Rewrites against their sources: ratio of words and how many stand."""
    x = table(s, d, "documents").select(F.col("text").alias("a"), teachers.rewrite(F.col("text")).alias("b"))
    ratio = F.try_divide(count_words(F.col("b")).cast("double"), count_words(F.col("a")).cast("double"))
    return x.agg(F.count("*").alias("n"), F.round(F.avg(ratio), 6).alias("mean_ratio"), F.count_if(teachers.accept_rewrite(F.col("a"), F.col("b"))).alias("n_accepted"))


# ---- ledger ----


def _ledger(s, d):
    """Orders as a ledger: their status says how a step is paid, their priority is the step, whole prices are hours."""
    paid = F.create_map(*map(F.lit, ("F", "once", "O", "per pool", "P", "per corpus")))
    return table(s, d, "orders").select(paid[F.col("o_orderstatus")].alias("paid"), F.col("o_orderpriority").alias("step"), F.floor("o_totalprice").cast("double").alias("hours"))


@query
def cost_ledger(s, d):
    return runlog.summary(_ledger(s, d))


@query
def cost_break_even(s, d):
    return runlog.break_even(_ledger(s, d), "1-URGENT", "5-LOW")


# ---- sources, SQL functions ----


@query
def csv_published(s, d):
    """Customers written as CSV and read back by a schema, each hundredth with a number that does not fit."""
    at = f"{checkpoint_dir(s)}/csv-{uuid.uuid4().hex}"
    hours = F.when(F.col("c_custkey") % 100 == 0, F.lit("many")).otherwise(F.floor("c_acctbal").cast("string"))
    table(s, d, "customer").select(F.col("c_mktsegment").alias("paid"), F.col("c_name").alias("step"), hours.alias("hours")).write.option("header", True).csv(at)
    x = archive.read_csv(s, at, "paid string, step string, hours double")
    return x.groupBy("paid").agg(F.count("*").alias("n"), F.sum("hours").alias("hours"), F.count("corrupt").alias("n_corrupt"))


@query
def run_program_sql(s, d):
    """Programs of the policy run by the SQL function, against the executor."""
    sql_surface.register(s)
    p = cut(pipelines.policy_outputs(pipelines.rendered_pages(table(s, d, "pages"))))
    p.createOrReplaceTempView("curation_outputs")
    got = s.sql("SELECT page_id, run_program(lines, output) AS text FROM curation_outputs WHERE output NOT LIKE '%\nsub %'")
    return got.select("page_id", F.md5("text").alias("text_md5"))


@query
def program_items_sql(s, d):
    """Items of the policy's programs as a relation."""
    sql_surface.register(s)
    pipelines.policy_outputs(pipelines.rendered_pages(table(s, d, "pages"))).createOrReplaceTempView("curation_programs")
    return s.sql("SELECT kind, count(*) AS n, cast(sum(b - a + 1) AS BIGINT) AS n_lines FROM curation_programs, LATERAL program_items(output) GROUP BY kind")


@query
def json_schema(s, d):
    """Event properties parsed by a schema, bad ones counted."""
    e = table(s, d, "events").select("event_type", F.from_json("props", "map<string,string>").alias("p"), "props")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("p").isNull() & F.col("props").isNotNull()).alias("n_bad"), F.sum(F.coalesce(F.size("p"), F.lit(0))).alias("n_keys"))


# ---- further relational forms ----


@query
def confusion_matrix(s, d):
    """Verdicts of two rescue thresholds as a matrix with margins."""
    r = cut(pipelines.rendered_pages(table(s, d, "pages")))
    a = pipelines.policy(r).select("page_id", F.col("verdict").alias("one"))
    b = pipelines.policy(r, threshold=1.5).select("page_id", F.col("verdict").alias("two"))
    return a.join(b.hint("shuffle_hash"), "page_id").groupBy("one").pivot("two", ["keep", "edit", "delete", "rewrite"]).agg(F.count(F.lit(1))).na.fill(0)


@query
def sketched_distinct(s, d):
    """Distinct words by a sketch that merges over languages, next to the exact number: within five parts in a hundred."""
    w = table(s, d, "documents").select("lang", F.explode(words(F.lower("text"))).alias("w"))
    per = w.groupBy("lang").agg(F.hll_sketch_agg("w", F.lit(14)).alias("sk"), F.countDistinct("w").alias("exact"))
    return per.select("lang", "exact", (F.abs(F.hll_sketch_estimate("sk") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close"))


@query
def approximate_quantiles(s, d):
    """Approximate against exact medians of document lengths: within five parts in a hundred."""
    x = table(s, d, "documents").select("lang", "n_chars")
    per = x.groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("exact"), F.percentile_approx("n_chars", 0.5, 10_000).alias("near"))
    return per.select("lang", "exact", (F.abs(F.col("near") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close"))


@query
def frequent_lines(s, d):
    """The ten lines that most documents have."""
    x = table(s, d, "documents").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("trim(line) <> ''")
    n = x.groupBy(F.md5("line").alias("line_md5")).agg(F.count("*").alias("n_docs"))
    return n.orderBy(F.col("n_docs").desc(), "line_md5").limit(10)


@query
def unpivoted_scores(s, d):
    """Scores of labelled documents in long form."""
    x = table(s, d, "documents").join(table(s, d, "labels"), "doc_id").select("quality", judges.quality_score(F.col("text")).cast("double").alias("quality_score"), teachers.edu_score(F.col("text")).alias("edu_score"))
    return x.unpivot(["quality"], ["quality_score", "edu_score"], "scorer", "value").groupBy("quality", "scorer").agg(F.count("*").alias("n"), F.round(F.avg("value"), 4).alias("mean"))


# ---- streams ----


@query
def stream_late_rows(s, d):
    """Rows that a one-hour watermark drops, against all: only that some are, and none is lost uncounted."""
    x = streams.late_rows(s, table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    return x.select("n_rows", (F.col("n_late") > 0).alias("some_late"))


@query
def stream_labels(s, d):
    """Arriving pages with a table of labels that does not change."""
    pages = streams.source(s, d, "pages", streams.PAGES).select("page_id")
    labels = table(s, d, "labels").select(F.col("doc_id").alias("page_id"), "quality")
    return streams.drain(streams.with_labels(pages, labels, "page_id")).groupBy("quality").agg(F.count("*").alias("n"))
