"""Registered queries that compare pipelines: the same pages through all of them, deduplicated, at equal budgets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words, portable_share, safe_ratio
from spark_curation.io import cut, fence, stored, table
from spark_curation.operators import execute, judges, metrics, proxy, render, scrapers, teachers
from spark_curation.plans import pipelines
from spark_curation.workloads import query

#: Budgets as multiples of what ``unified`` keeps.
SCALES = {"S": 1.0, "M": 4.0, "L": 7.5}
#: Seeds of the variance study and the share of each corpus that a seed takes.
SEEDS, SEED_SHARE = 5, 0.5


def corpora(s: SparkSession, d: str, names: list[str] | None = None, deduplicate: bool = True) -> DataFrame:
    """All pipelines' texts, written once, for everything that is measured on them."""
    return stored(pipelines.corpora(table(s, d, "pages"), names, deduplicate))


def tasks(s: SparkSession, d: str) -> DataFrame:
    return stored(proxy.suite_tasks(table(s, d, "benchmark"), table(s, d, "conversations"), table(s, d, "documents"), table(s, d, "labels")))


def scored(corpus: DataFrame, asked: DataFrame, by: tuple[str, ...], weight: F.Column | float = 1.0) -> DataFrame:
    """Proxy accuracies of every corpus of ``by``."""
    return proxy.compare(corpus, asked, by, weight)


def means(results: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """Mean centred accuracy by category, and over all tasks under ``suite``."""
    c = results.withColumn("category", proxy.category()).withColumn("c", metrics.centered(F.col("acc"), F.col("chance")))
    out = c.rollup(*by, "category").agg(F.avg("c").alias("score"), F.count("*").alias("n_tasks"), F.grouping_id().alias("g")).where("g in (0, 1)")
    return out.select(*by, F.coalesce("category", F.lit("suite")).alias("category"), F.round("score", 4).alias("score"), "n_tasks")


def at_scales(corpus: DataFrame) -> DataFrame:
    """Each corpus at each budget: cut to it where it has more, with ``rep`` saying how often it is repeated where it has less."""
    total = {r["pipeline"]: r["t"] for r in corpus.groupBy("pipeline").agg(F.sum("n_tokens").alias("t")).collect()}  # a row for each pipeline
    unit = float(total.get("unified") or 1)
    scales = F.array(*[F.struct(F.lit(k).alias("scale"), F.lit(f * unit).alias("budget")) for k, f in SCALES.items()])
    each = metrics.token_run(corpus, ("pipeline",), "page_id").select("pipeline", "page_id", "text", "n_tokens", "run", F.explode(scales).alias("x")).select("*", "x.*").where("run < budget")
    have = F.create_map(*[F.lit(x) for k, v in total.items() for x in (k, float(v))])[F.col("pipeline")] if total else F.lit(1.0)
    return each.select("pipeline", "scale", "page_id", "text", "n_tokens", F.greatest(F.lit(1.0), F.col("budget") / have).alias("rep"))


@query
def main_suite(s, d):
    """Eight pipelines, deduplicated, at three budgets, on all tasks."""
    each = at_scales(corpora(s, d))
    return means(scored(each, tasks(s, d), ("pipeline", "scale"), F.col("rep")), ("pipeline", "scale"))


@query
def main_unique_tokens(s, d):
    return metrics.unique_tokens(corpora(s, d))


@query
def main_repetition(s, d):
    """How often each corpus is repeated at each budget, and what is read of it."""
    return at_scales(corpora(s, d)).groupBy("pipeline", "scale").agg(F.sum("n_tokens").alias("n_read"), F.round(F.max("rep"), 4).alias("repetition"))


@query
def main_ranks(s, d):
    """Best and second-best pipeline of each budget, and the gain of the best over the stack of rules b."""
    m = main_suite(s, d).where("category = 'suite'").select("pipeline", "scale", "score")
    base = m.where("pipeline = 'rules_b'").select("scale", F.col("score").alias("base"))
    ranked = metrics.rank(m).where("place <= 2").join(F.broadcast(base), "scale")
    return ranked.select("scale", "place", "pipeline", "score", F.round(F.col("score") - F.col("base"), 4).alias("over_rules_b"))


@query
def proxy_suite(s, d):
    asked = tasks(s, d)
    known = table(s, d, "documents").where(~proxy.held_out(F.col("doc_id")))
    return proxy.evaluate(proxy.train(known, asked), asked)


@query
def proxy_bigrams(s, d):
    return proxy.train(table(s, d, "documents")).select("w1", "w2", F.col("c2").cast("long").alias("c2"), F.col("c1").cast("long").alias("c1"))


@query
def decontaminated_suite(s, d):
    """The passage tasks with and without the documents that share eight words in a row with a passage."""
    from spark_curation.workloads import benchmark_hits

    docs = table(s, d, "documents")
    clean = docs.join(benchmark_hits(s, d).select("doc_id"), "doc_id", "left_anti")
    both = docs.select(F.lit("all").alias("corpus"), "text").union(clean.select(F.lit("clean").alias("corpus"), "text"))
    asked = cut(proxy.continuation_tasks(table(s, d, "benchmark")))
    return scored(stored(both), asked, ("corpus",)).select("corpus", "n", "acc", "chance")


@query
def scraper_suite(s, d):
    """Four scrapers under rules b, and the model cascade, on all tasks."""
    pages = table(s, d, "pages")
    out = None
    for scraper, cleaner in [*((k, "b") for k in scrapers.SCRAPERS), ("teacher", "lineprog")]:
        one = pipelines.cascade(scrapers.SCRAPERS[scraper], cleaner)(pages).select(F.lit(f"{scraper} {cleaner}").alias("pipeline"), "page_id", "text")
        out = one if out is None else out.unionByName(one)
    return means(scored(stored(out), tasks(s, d), ("pipeline",)), ("pipeline",))


@query
def cascade_tokens(s, d):
    pages = table(s, d, "pages")
    out = None
    for scraper, cleaner in [(a, b) for a in scrapers.SCRAPERS for b in ("b", "lineprog")]:
        one = pipelines.cascade(scrapers.SCRAPERS[scraper], cleaner)(pages).select(F.lit(scraper).alias("scraper"), F.lit(cleaner).alias("cleaner"), count_words(F.col("text")).alias("w"))
        out = one if out is None else out.unionByName(one)
    return out.groupBy("scraper", "cleaner").agg(F.count("*").alias("n_docs"), F.sum("w").alias("words"))


@query
def ablation_suite(s, d):
    """The executor with single operations off, on all tasks."""
    p = stored(pipelines.programs(table(s, d, "pages")))
    return means(scored(stored(ablated(p)), tasks(s, d), ("variant",)), ("variant",))


def ablated(programs: DataFrame) -> DataFrame:
    """``(variant, page_id, text, words_out)``: every executor over the same programs, kept texts only."""
    out = None
    for name, off in {"full": (), "edit off": ("edit",), "rewrite off": ("rewrite",), "delete off": ("delete",), "extract off": ("extract",)}.items():
        one = execute.run(programs, disable=off).where("text is not null").select(F.lit(name).alias("variant"), "page_id", "text", "words_out")
        out = one if out is None else out.unionByName(one)
    return out


RESCUES = {"edu 1.0": {}, "edu 1.5": {"threshold": 1.5}, "classifier": {"rescue": "classifier"}, "three_way": {"rescue": "three_way"}}


def selection(s: SparkSession, d: str) -> DataFrame:
    """``(variant, share, page_id, verdict, text, words_out)``: rescue rules, and shares of rewrites that go into the corpus.

    What the rules decide on is worked out once for all of them, and a page is executed once for each verdict that it gets.
    """
    seen = fence(teachers.considered(teachers.extract(pipelines.rendered_pages(table(s, d, "pages")))))
    each = seen.withColumn("cases", F.array(*[F.struct(F.lit(name).alias("variant"), teachers.verdict(**kw).alias("verdict")) for name, kw in RESCUES.items()]))
    each = fence(each).select("*", F.explode(F.array_distinct(F.transform("cases", lambda c: c["verdict"]))).alias("verdict"))
    ran = execute.run(fence(teachers.decided(each))).where("text is not null")
    out = ran.select(F.explode(F.filter("cases", lambda c: c["verdict"] == F.col("verdict"))["variant"]).alias("variant"), "page_id", "verdict", "text", "words_out")
    shares = out.withColumn("share", F.explode(F.array(*map(F.lit, (0.1, 0.3, 1.0)))))
    draw = portable_share(F.lit("share"), F.col("page_id").cast("string"))
    return shares.where((F.col("verdict") != "rewrite") | (draw < F.col("share")))


@query
def selection_leaderboard(s, d):
    """Suite score of every rescue rule and share of rewrites, ranked."""
    x = stored(selection(s, d))
    n = x.groupBy("variant", "share").agg(F.count("*").alias("n_docs"), F.sum("words_out").alias("words"))
    m = means(scored(x, tasks(s, d), ("variant", "share")), ("variant", "share")).where("category = 'suite'").select("variant", "share", "score")
    return n.join(m, ["variant", "share"]).withColumn("place", F.dense_rank().over(Window.orderBy(F.col("score").desc())))  # a row for each variant


@query
def share_sweep(s, d):
    """Size and verdicts of the second stage's mixture at several shares of rewrites."""
    from spark_curation.operators import targets

    t = cut(targets.compose(pipelines.programs(table(s, d, "pages"))))
    out = None
    for share in (0.1, 0.2, 0.3, 0.5):
        one = targets.mixture(t, 2, rewrite_share=share).groupBy("verdict").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("n_tokens")).select(F.lit(share).alias("share"), "verdict", "n", "n_tokens")
        out = one if out is None else out.unionByName(one)
    return out


def seed_runs(s: SparkSession, d: str) -> DataFrame:
    """``(pipeline, seed, score)``: two pipelines, each trained on the half of its corpus that a seed draws."""
    c = corpora(s, d, ["unified", "refiner_lineprog"])
    each = c.withColumn("seed", F.explode(F.array(*map(F.lit, range(SEEDS))))).where(portable_share(F.concat(F.lit("seed"), F.col("seed").cast("string")), F.col("page_id").cast("string")) < SEED_SHARE)
    r = scored(each, tasks(s, d), ("pipeline", "seed"))
    return r.groupBy("pipeline", "seed").agg(F.round(F.avg(metrics.centered(F.col("acc"), F.col("chance"))), 6).alias("score"))


@query
def seed_variance(s, d):
    r = metrics.seed_summary(seed_runs(s, d))
    return r.select("pipeline", "n", F.round("mean", 4).alias("mean"), F.round("sd", 4).alias("sd"), F.round("least", 4).alias("least"), F.round("most", 4).alias("most"))


@query
def seed_welch(s, d):
    """Welch's t between the two pipelines of the seed study."""
    r = seed_runs(s, d).groupBy().agg(*[f(F.when(F.col("pipeline") == p, F.col("score"))).alias(f"{k}_{n}") for p, k in (("unified", "a"), ("refiner_lineprog", "b")) for n, f in (("m", F.avg), ("s", F.stddev_samp), ("n", F.count))])
    return r.select(F.round(metrics.welch(*[F.col(c) for c in ("a_m", "a_s", "a_n", "b_m", "b_s", "b_n")]), 2).alias("t"))


# ---- measures of every pipeline's texts ----


def judged(s: SparkSession, d: str) -> DataFrame:
    """Every page with every pipeline: scores of the page as rendered, and of what the pipeline kept of it (null if nothing)."""
    c = pipelines.corpora(table(s, d, "pages"), deduplicate=False).where("text <> ''").select("pipeline", F.col("page_id").alias("of"), "text", "n_tokens")
    r = pipelines.rendered_pages(table(s, d, "pages")).select("page_id", F.array_join("lines", "\n").alias("raw"))
    pages = cut(r.select("page_id", judges.quality_score(F.col("raw")).alias("q0"), teachers.edu_score(F.col("raw")).alias("e0"), count_words(F.col("raw")).alias("w0")))
    every = pages.withColumn("pipeline", F.explode(F.array(*[F.lit(p) for p in pipelines.PIPELINES])))
    scores = c.select("pipeline", "of", judges.quality_score(F.col("text")).alias("q1"), teachers.edu_score(F.col("text")).alias("e1"), judges.output_rating(F.col("text")).alias("rating"), "n_tokens")
    j = every.alias("p").join(scores.alias("c"), (F.col("p.pipeline") == F.col("c.pipeline")) & (F.col("page_id") == F.col("of")), "left")
    return cut(j.select("p.pipeline", "page_id", "q0", "e0", "w0", "q1", "e1", "rating", F.col("c.n_tokens").alias("w1")))


@query
def profile_by_pipeline(s, d):
    """Shares of pages dropped, and of kept ones by the share of words removed."""
    j = judged(s, d)
    gone = safe_ratio(F.col("w0") - F.col("w1"), F.col("w0"))
    n = j.select("pipeline", F.when(F.col("w1").isNull(), "dropped").otherwise(metrics.removal_bin(gone)).alias("bin")).groupBy("pipeline", "bin").agg(F.count("*").alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("pipeline")), 6))


@query
def groups_by_pipeline(s, d):
    """Mean score after cleaning and judge rating by score before, the group's share of pages and how many of them are kept."""
    j = judged(s, d)
    out = None
    for scorer, grp, after in (("quality", metrics.quality_group(F.col("q0")), "q1"), ("edu", metrics.edu_group(F.col("e0")), "e1")):
        g = j.groupBy("pipeline", grp.alias("grp")).agg(F.count("*").alias("n"), F.count("w1").alias("n_kept"), F.round(F.avg(after), 4).alias("after"), F.round(F.avg("rating"), 4).alias("rating"), F.round(F.avg((F.col("rating") >= 2).cast("double")), 4).alias("keep_share"))
        g = g.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("pipeline")), 6)).select("pipeline", F.lit(scorer).alias("scorer"), "grp", "n", "n_kept", "share", "after", "rating", "keep_share")
        out = g if out is None else out.unionByName(g)
    return out


@query
def retention_by_pipeline(s, d):
    """Share kept of the pages that score 1 or more, and the loss against rules b."""
    r = judged(s, d).where("e0 >= 1.0").groupBy("pipeline").agg(F.count("*").alias("n_good"), F.round(F.avg(F.col("w1").isNotNull().cast("double")), 6).alias("kept"))
    base = r.where("pipeline = 'rules_b'").select(F.col("kept").alias("base"))
    return r.crossJoin(F.broadcast(base)).select("pipeline", "n_good", "kept", F.round(F.col("kept") - F.col("base"), 6).alias("over_rules_b"))  # one row on the right


def _distinct(n: int) -> None:
    def run(s, d):
        c = corpora(s, d)
        least = min((r["t"] for r in c.groupBy("pipeline").agg(F.sum("n_tokens").alias("t")).collect()), default=0)
        return metrics.distinct_ngrams(metrics.equal_token_cut(c, least, ("pipeline",), "page_id"), n, by=("pipeline",))

    run.__name__ = f"distinct_{n}grams"
    run.__doc__ = "Distinct n-grams of every pipeline's corpus, cut to the tokens of the smallest."
    query(run)


for _n in (3, 5):
    _distinct(_n)


@query
def length_profile(s, d):
    return metrics.length_profile(corpora(s, d, deduplicate=False))


@query
def length_histogram(s, d):
    return metrics.length_histogram(corpora(s, d, deduplicate=False))


@query
def extraction_judge(s, d):
    """Grades of every scraper's text against the article's lines."""
    pages = table(s, d, "pages")
    gold = cut(scrapers.teacher(pages))
    out = None
    for name, f in scrapers.SCRAPERS.items():
        one = judges.extraction(f(pages), gold).select(F.lit(name).alias("scraper"), "recall", "precision", "integrity")
        out = one if out is None else out.unionByName(one)
    mean = lambda c: F.round(F.avg(c), 4).alias(c)
    return out.groupBy("scraper").agg(mean("recall"), mean("precision"), mean("integrity"), F.round(F.avg((F.col("recall") + F.col("precision") + F.col("integrity")) / 3), 4).alias("mean_grade"))


@query
def curated_pool(s, d):
    """The whole pass over a pool, deduplicated."""
    c = pipelines.curate(table(s, d, "pages"))
    return c.groupBy("provenance").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("n_tokens"))


@query
def rendered_once(s, d):
    """Pages and lines of the rendering that all pipelines share."""
    r = pipelines.rendered_pages(render.render_pages(table(s, d, "pages"), with_blocks=True))
    return r.agg(F.count("*").alias("n_pages"), F.sum("n_lines").cast("long").alias("n_lines"), F.sum("n_tokens").alias("n_tokens"))
