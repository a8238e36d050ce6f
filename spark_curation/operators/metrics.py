"""Cost and accuracy measures, each a DataFrame to a small DataFrame."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words, ngrams, safe_ratio, words


def centered(acc: Column, chance: Column) -> Column:
    """Accuracy with chance at 0 and all right at 1."""
    return (acc - chance) / (1 - chance)


def suite(tasks: DataFrame) -> DataFrame:
    """Mean centred accuracy of each category and of all tasks (category null), by pipeline and scale."""
    df = tasks.withColumn("c", centered(F.col("acc"), F.col("chance")))
    return df.rollup("pipeline", "scale", "category").agg(F.avg("c").alias("score"), F.count("*").alias("n_tasks"), F.grouping_id().alias("g")).where("g in (0, 1)").drop("g")


def relative(scores: DataFrame, base: str, value: str = "score") -> DataFrame:
    """Gain over a base pipeline at the same scale."""
    b = scores.where(F.col("pipeline") == base).select("scale", F.col(value).alias("base_score"))
    return scores.join(F.broadcast(b), "scale").select("pipeline", "scale", F.round(F.col(value) / F.col("base_score") - 1, 6).alias("gain"))


def rank(scores: DataFrame, value: str = "score") -> DataFrame:
    return scores.withColumn("place", F.dense_rank().over(Window.partitionBy("scale").orderBy(F.col(value).desc())))


def unique_tokens(corpus: DataFrame, by: str = "pipeline") -> DataFrame:
    return corpus.groupBy(by).agg(F.sum("n_tokens").alias("unique_tokens"), F.count("*").alias("n_docs"))


def repetition(totals: DataFrame, budget: float) -> DataFrame:
    return totals.withColumn("repetition", F.round(F.lit(float(budget)) / F.col("unique_tokens"), 6))


def keepdrop_accuracy(decided: DataFrame, labels: DataFrame, by: list[str]) -> DataFrame:
    """Share of equal decisions; ``decided`` has (id, keep), ``labels`` (id, good)."""
    return decided.join(labels, "id").groupBy(*by).agg(F.avg((F.col("keep") == F.col("good")).cast("double")).alias("accuracy"), F.count("*").alias("n"))


def false_drop(rule_decisions: DataFrame, labels: DataFrame) -> DataFrame:
    """For each rule, the share of its drops that the judge would keep."""
    dropped = rule_decisions.where("dropped").join(labels, "id")
    return dropped.groupBy("stack", "rule").agg(F.count("*").alias("n_dropped"), F.avg(F.col("good").cast("double")).alias("false_drop"))


def removal_bin(removed: Column) -> Column:
    """Edits by the share of words that they remove; up to 5 % counts as lightly trimmed."""
    return F.when(removed <= 0, "0").when(removed <= 0.05, "0-5").when(removed <= 0.20, "5-20").when(removed <= 0.50, "20-50").otherwise("50+")


def operation_profile(executed: DataFrame) -> DataFrame:
    """Share of pages by provenance and by words removed after extraction."""
    left = F.col("words_in") - F.col("words_stripped")
    gone = safe_ratio(left - F.coalesce("words_out", F.lit(0)), left)
    total = Window.partitionBy()
    binned = executed.select("provenance", F.when(F.col("provenance") == "refined", removal_bin(gone)).otherwise("-").alias("bin"))
    n = binned.groupBy("provenance", "bin").agg(F.count("*").alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(total), 6))


def before_after(scored: DataFrame, by: str = "verdict") -> DataFrame:
    return scored.groupBy(by).agg(F.count("*").alias("n"), F.round(F.avg("before"), 6).alias("before"), F.round(F.avg("after"), 6).alias("after"))


def quality_group(q: Column) -> Column:
    return F.when(q <= 2, "1-2").when(q <= 3, "3").otherwise("4-5")


def edu_group(e: Column) -> Column:
    return F.when(e < 0.5, "<0.5").when(e < 1.0, "0.5-1").otherwise(">=1")


def distinct_ngrams(docs: DataFrame, n: int, text_col: str = "text", by: tuple[str, ...] = ()) -> DataFrame:
    """Distinct over all n-grams; each distinct gram moves once for each map task that has it."""
    g = docs.select(*by, F.explode(F.transform(ngrams(words(F.col(text_col)), n), lambda x: F.xxhash64(x))).alias("h"))
    counted = g.groupBy(*by, "h").agg(F.count("*").alias("c"))
    out = counted.groupBy(*by).agg(F.count("*").alias("n_distinct"), F.sum("c").alias("n_total"))
    return out.withColumn("share", F.round(F.col("n_distinct") / F.col("n_total"), 6))


def token_run(docs: DataFrame, by: tuple[str, ...] = (), id_col: str = "doc_id", tokens: str = "n_tokens", buckets: int = 256) -> DataFrame:
    """Adds ``run``: the tokens before each document in a fixed pseudo-random order of its group, without a global sort.

    Totals of hash buckets are summed first; within a bucket a running sum goes on, so every window is a bucket.
    """
    from spark_curation.functions.text import portable_share

    rows = docs.withColumn("__pos", portable_share(F.col(id_col).cast("string"))).withColumn("__b", F.floor(F.col("__pos") * buckets).cast("int"))
    sums = rows.groupBy(*by, "__b").agg(F.sum(tokens).alias("t"))  # at most ``buckets`` rows for each group
    a, b = sums.alias("a"), sums.select(*[F.col(c).alias(f"o_{c}") for c in by], F.col("__b").alias("o__b"), F.col("t").alias("o_t"))
    same = F.col("o__b") < F.col("a.__b")
    for c in by:
        same = same & (F.col(f"o_{c}") == F.col(f"a.{c}"))
    before = a.join(F.broadcast(b), same, "left").groupBy(*[F.col(f"a.{c}").alias(c) for c in by], F.col("a.__b").alias("__b")).agg(F.coalesce(F.sum("o_t"), F.lit(0)).alias("__before"))
    w = Window.partitionBy(*by, "__b").orderBy("__pos", id_col).rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.join(F.broadcast(before), [*by, "__b"])
    return placed.select(*docs.columns, (F.col("__before") + F.coalesce(F.sum(tokens).over(w), F.lit(0))).alias("run"))


def equal_token_cut(docs: DataFrame, budget: int, by: tuple[str, ...] = (), id_col: str = "doc_id", tokens: str = "n_tokens", buckets: int = 256) -> DataFrame:
    """Documents of a fixed pseudo-random order until the budget of tokens is used."""
    return token_run(docs, by, id_col, tokens, buckets).where(F.col("run") < budget).select(*docs.columns)


def confusion(a: DataFrame, b: DataFrame, key: str = "page_id") -> DataFrame:
    """Counts of verdict pairs; pages that only one side has show as missing."""
    j = a.select(key, F.col("verdict").alias("one")).join(b.select(key, F.col("verdict").alias("two")), key, "full_outer")
    return j.groupBy(F.coalesce("one", F.lit("missing")).alias("one"), F.coalesce("two", F.lit("missing")).alias("two")).agg(F.count("*").alias("n"))


def token_f1(a: DataFrame, b: DataFrame, key: str = "page_id") -> DataFrame:
    """``(key, precision, recall, f1)`` of bags of words of ``a.text`` against ``b.text``."""
    bag = lambda d, c: d.select(key, F.explode(words(F.col("text"))).alias("w")).groupBy(key, "w").agg(F.count("*").alias(c))
    j = bag(a, "x").join(bag(b, "y"), [key, "w"], "full_outer")
    s = j.groupBy(key).agg(F.sum(F.least(F.coalesce("x", F.lit(0)), F.coalesce("y", F.lit(0)))).alias("both"), F.sum(F.coalesce("x", F.lit(0))).alias("nx"), F.sum(F.coalesce("y", F.lit(0))).alias("ny"))
    p, r = safe_ratio(F.col("both"), F.col("nx")), safe_ratio(F.col("both"), F.col("ny"))
    return s.select(key, p.alias("precision"), r.alias("recall"), safe_ratio(2 * F.col("both"), F.col("nx") + F.col("ny")).alias("f1"))


def waterfall(programs: DataFrame) -> DataFrame:
    """Words left after each operation in turn, over all pages, with the change to the step before."""
    from spark_curation.operators import execute

    off = {"input": ("extract", "delete", "edit", "rewrite"), "extract": ("delete", "edit", "rewrite"), "delete": ("edit", "rewrite"), "edit": ("rewrite",), "rewrite": ()}
    steps = None
    for k, (name, disable) in enumerate(off.items()):
        held = programs if "rewrite" not in disable else programs.withColumn("verdict", F.when(F.col("verdict") == "rewrite", "keep").otherwise(F.col("verdict"))).withColumn("body", F.when(F.col("verdict") == "edit", F.col("body")))
        one = execute.run(held, disable=disable).agg(F.coalesce(F.sum("words_out"), F.lit(0)).alias("words_left")).select(F.lit(k).alias("step"), F.lit(name).alias("operation"), "words_left")
        steps = one if steps is None else steps.union(one)
    w = Window.orderBy("step")
    return steps.withColumn("change", F.col("words_left") - F.lag("words_left").over(w))


def _quartiles(c: str) -> list[Column]:
    return [F.expr(f"percentile({c}, {p})").alias(f"{c}_{n}") for n, p in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))] + [F.round(F.avg(c), 6).alias(f"{c}_mean")]


def _thirds(at: Column, n: Column, name: str) -> list[Column]:
    """Shares of places (from 1 to n) in the first, middle and last third."""
    third = F.least(F.floor((at - 1) * 3 / n), F.lit(2))
    return [F.round(F.avg((third == k).cast("double")), 6).alias(f"{name}_{x}") for k, x in enumerate(("first", "middle", "last"))]


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0).cast("long"), lambda s, x: s + x)


def strip_stats(programs: DataFrame) -> DataFrame:
    """Extraction-operation statistics over all pages, one row: quartiles and means of operations and lines of a page, of lines and
    words of a span, where removed lines stand, pages that lose a leading or trailing block, and where the removed words were."""
    n = F.size("lines")
    sizes = F.transform("strip", lambda r: F.struct((r["b"] - r["a"] + 1).alias("lines"), _sum(F.transform(F.slice("lines", r["a"], r["b"] - r["a"] + 1), count_words)).alias("words"), r["a"].alias("a"), r["b"].alias("b")))
    per = programs.select(F.size("strip").alias("ops"), n.alias("n"), sizes.alias("spans")).withColumn("gone", _sum(F.transform("spans", lambda x: x["lines"].cast("long"))))
    words = lambda pick: _sum(F.transform(F.filter("spans", pick), lambda x: x["words"]))
    lead, trail = (lambda x: x["a"] == 1), (lambda x: (x["b"] == F.col("n")) & (x["a"] > 1))
    per = per.withColumns({"lead": words(lead), "trail": words(trail), "every": words(lambda x: F.lit(True)), "leads": F.exists("spans", lambda x: x["a"] == 1), "trails": F.exists("spans", lambda x: x["b"] == F.col("n"))})
    page = per.agg(
        F.count("*").alias("pages"), F.round(F.avg((F.col("ops") > 0).cast("double")), 6).alias("with_removal"), *_quartiles("ops"), *_quartiles("gone"),
        F.round(F.avg(F.col("leads").cast("double")), 6).alias("leading"), F.round(F.avg(F.col("trails").cast("double")), 6).alias("trailing"), F.sum("gone").alias("lines_gone"), F.sum("n").cast("long").alias("lines_in"),
        F.round(F.sum("lead") / F.sum("every"), 6).alias("words_leading"), F.round((F.sum("every") - F.sum("lead") - F.sum("trail")) / F.sum("every"), 6).alias("words_interior"), F.round(F.sum("trail") / F.sum("every"), 6).alias("words_trailing"),
    )
    span = per.select("n", F.explode("spans").alias("x")).select("n", F.col("x.lines").alias("span_lines"), F.col("x.words").alias("span_words"))
    span = span.agg(*_quartiles("span_lines"), *_quartiles("span_words"))
    at = per.select("n", F.explode(F.flatten(F.transform("spans", lambda x: F.sequence(x["a"], x["b"])))).alias("at")).agg(*_thirds(F.col("at"), F.col("n"), "lines"))
    return page.crossJoin(span).crossJoin(at)  # one row each


def edit_stats(programs: DataFrame) -> DataFrame:
    """Edit-operation statistics over edited pages, one row: operations of a page, kinds, spans, where edits stand among the extracted
    lines, and pages that touch the first or last of these."""
    e = programs.where("verdict = 'edit'")
    kept = F.filter(F.transform("lines", lambda x, i: i + 1), lambda i: ~F.exists("strip", lambda r: i.between(r["a"], r["b"])))
    e = e.select("lines", "drop", "cuts", "body", kept.alias("kept")).withColumn("n", F.size("kept"))
    spans = F.transform("drop", lambda r: F.struct((r["b"] - r["a"] + 1).alias("lines"), _sum(F.transform(F.slice("lines", r["a"], r["b"] - r["a"] + 1), count_words)).alias("words")))
    ids = F.concat(F.flatten(F.transform("drop", lambda r: F.sequence(r["a"], r["b"]))), F.transform("cuts", lambda c: c["lid"]))
    e = e.withColumns({"rm": F.size("drop"), "sub": F.size("cuts"), "spans": spans, "at": F.filter(F.transform(ids, lambda i: F.array_position("kept", i)), lambda p: p > 0)})
    share = lambda c: F.round(F.avg(c.cast("double")), 6)
    rm, sub, paged = F.col("rm") > 0, F.col("sub") > 0, F.col("body").isNotNull()
    page = e.agg(
        F.count("*").alias("pages"), F.count_if(~paged).alias("by_operations"), F.count_if(paged).alias("by_page_text"), *_quartiles("rm"), *_quartiles("sub"), share(rm & ~sub).alias("rm_only"), share(~rm & sub).alias("sub_only"), share(rm & sub).alias("both_kinds"),
        share(F.array_contains("at", F.lit(1).cast("long"))).alias("first_kept"), share(F.array_contains("at", F.col("n").cast("long"))).alias("last_kept"),
    )
    span = e.select(F.explode("spans").alias("x")).select(F.col("x.lines").alias("rm_lines"), F.col("x.words").alias("rm_words")).agg(*_quartiles("rm_lines"), *_quartiles("rm_words"))
    cut = e.select(F.explode("cuts").alias("x")).select(count_words(F.col("x.frag")).alias("sub_words")).agg(*_quartiles("sub_words"))
    at = e.select("n", F.explode("at").alias("p")).agg(*_thirds(F.col("p"), F.col("n"), "edits"))
    return page.crossJoin(span).crossJoin(cut).crossJoin(at)  # one row each


def length_profile(corpus: DataFrame, by: str = "pipeline") -> DataFrame:
    return corpus.groupBy(by).agg(F.count("*").alias("n"), F.expr("percentile(n_tokens, 0.5)").alias("median_tokens"), F.round(F.avg((F.col("n_tokens") < 100).cast("double")), 6).alias("under_100"))


def length_histogram(corpus: DataFrame, by: str = "pipeline") -> DataFrame:
    """Documents by powers of two of their tokens; those without any count under 0."""
    low = F.when(F.col("n_tokens") > 0, F.pow(F.lit(2.0), F.floor(F.log2("n_tokens"))).cast("long")).otherwise(F.lit(0).cast("long"))
    n = corpus.groupBy(by, low.alias("from_tokens")).agg(F.count("*").alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy(by)), 6))


def paired_length(a: DataFrame, b: DataFrame, key: str = "page_id") -> DataFrame:
    """Share of pages whose text in ``a`` is shorter than in ``b``, and the median ratio, where both keep one."""
    j = a.select(key, F.col("n_tokens").alias("x")).join(b.select(key, F.col("n_tokens").alias("y")), key).where("x > 0 and y > 0")
    return j.agg(F.count("*").alias("n"), F.round(F.avg((F.col("x") < F.col("y")).cast("double")), 6).alias("shorter"), F.round(F.expr("percentile(x / y, 0.5)"), 6).alias("median_ratio"))


def output_economy(programs: DataFrame) -> DataFrame:
    """Answer words against page words and against the removals, one row."""
    from spark_curation.operators.program import serialize

    per = programs.select(count_words(serialize()).alias("answer"), count_words(F.array_join("lines", "\n")).alias("page"), (F.size("strip") + F.size("drop") + F.size("cuts")).alias("ops"), "verdict").where("verdict <> 'rewrite'")
    return per.agg(F.count("*").alias("n"), F.round(F.sum("answer") / F.sum("page"), 6).alias("answer_share"), F.round(F.corr("answer", "ops"), 4).alias("with_ops"), F.round(F.corr("answer", "page"), 4).alias("with_page"))


def seed_summary(runs: DataFrame) -> DataFrame:
    return runs.groupBy("pipeline").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean"), F.round(F.stddev_samp("score"), 6).alias("sd"), F.min("score").alias("least"), F.max("score").alias("most"))


def welch(m1: Column, s1: Column, n1: Column, m2: Column, s2: Column, n2: Column) -> Column:
    """Welch's t of two samples given by mean, standard deviation and size."""
    return (m1 - m2) / F.sqrt(s1 * s1 / n1 + s2 * s2 / n2)


def leak_rate(executed: DataFrame) -> DataFrame:
    from spark_curation.operators.postfilter import leaked

    return executed.agg(F.count("*").alias("n"), F.round(F.avg(leaked().cast("double")), 6).alias("leaked"))


def soft_match_f1(pairs: DataFrame, a: str = "source", b: str = "out", dim: int = 256) -> DataFrame:
    """Adds ``soft_f1``: greedy matching of word vectors (hashed character trigrams stand in for a model's)."""
    from collections.abc import Iterator
    from zlib import crc32

    import numpy as np
    import pyarrow as pa

    def vectors(text: str) -> np.ndarray:
        ws = (text or "").split()
        m = np.zeros((len(ws), dim), np.float32)
        for i, w in enumerate(ws):
            w = f"<{w}>"
            for j in range(max(1, len(w) - 2)):
                m[i, crc32(w[j : j + 3].encode()) % dim] += 1
        return m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-9)

    def f1(x: str, y: str) -> float:
        p, q = vectors(x), vectors(y)
        if not len(p) or not len(q):
            return 0.0
        rows, cols = [], np.full(len(q), -1.0, np.float32)
        for at in range(0, len(p), 512):  # blocks bound the memory, not the text
            s = p[at : at + 512] @ q.T
            rows.append(s.max(1))
            cols = np.maximum(cols, s.max(0))
        r, c = float(np.concatenate(rows).mean()), float(cols.mean())
        return 2 * r * c / (r + c) if r + c else 0.0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            t = {a: batch.column(a).to_pylist(), b: batch.column(b).to_pylist()}
            yield batch.append_column("soft_f1", pa.array([f1(x, y) for x, y in zip(t[a], t[b], strict=True)], pa.float64()))

    return pairs.mapInArrow(run, ", ".join(f"`{n}` {k}" for n, k in pairs.dtypes) + ", soft_f1 double")
