"""Rule stacks: page and line rules of three published corpora, as one pass of page statistics and predicates on them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count, ngrams, safe_ratio, words
from spark_curation.io import fence

#: Word lists and thresholds of the stacks.
STOP_WORDS = ("the", "be", "to", "of", "and", "that", "have", "with")
ENDED = r"[.!?\"']$"
POLICY = r"(?i)javascript|terms of use|privacy policy|cookie policy|uses cookies"
FILLER = r"(?i)lorem ipsum"
BLOCKLIST = r"(?i)\b(?:worthless|pathetic|idiots?|disgusting)\b"
#: Hosts and paths that stack b does not take, and the languages it takes.
BLOCKED_URL = r"(?i)^[a-z]+://(?:[^/]*\.)?(?:adult|casino|torrent|warez)[^/]*|/(?:tag|search|login|cart)(?:/|\?|$)"
BAND = {
    "n_words": (50, 100_000), "mean_word": (3.0, 10.0), "symbol_ratio": (None, 0.1), "bullet_share": (None, 0.9), "ellipsis_share": (None, 0.3),
    "alpha_share": (0.8, None), "stop_words": (2, None), "dup_line_share": (None, 0.30), "dup_line_chars": (None, 0.20), "dup_gram_share": (None, 0.15),
}


def statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds the statistics that the stacks look at; null texts count as empty."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    df = docs.withColumns({"__w": words(text), "__l": F.filter(F.transform(F.split(text, "\n"), lambda x: F.trim(x)), lambda x: x != "")})
    w, lines = F.col("__w"), F.col("__l")
    n, m = F.size(w), F.size(lines)
    total = lambda a: F.aggregate(F.transform(a, lambda x: F.length(x)), F.lit(0), lambda s, x: s + x)
    share = lambda pred: safe_ratio(F.size(F.filter(lines, pred)), m)
    df = df.withColumn("__g", ngrams(w, 5))
    stats = {
        "n_words": n.cast("long"), "n_lines": m.cast("long"), "mean_word": safe_ratio(total(w), n),
        "symbol_ratio": safe_ratio(count(text, r"#|\.\.\.|…"), n),
        "bullet_share": share(lambda x: x.rlike(r"^[-*•]")), "ellipsis_share": share(lambda x: x.rlike(r"(?:\.\.\.|…)$")),
        "alpha_share": safe_ratio(count(text, r"\S*[A-Za-zÀ-ÿ]\S*"), n),
        "stop_words": F.size(F.array_intersect(F.transform(w, lambda x: F.lower(x)), F.array(*[F.lit(x) for x in STOP_WORDS]))).cast("long"),
        "dup_line_share": safe_ratio(m - F.size(F.array_distinct(lines)), m), "dup_line_chars": safe_ratio(total(lines) - total(F.array_distinct(lines)), total(lines)),
        "dup_gram_share": safe_ratio(F.size("__g") - F.size(F.array_distinct("__g")), F.size("__g")),
        "ended_share": share(lambda x: x.rlike(ENDED)), "short_share": share(lambda x: F.length(x) < 30),
        "sentences": count(F.concat(text, F.lit(" ")), r"[.!?]\s"), "upper_share": share(lambda x: x.rlike(r"^[^a-z]*[A-Z][^a-z]*$")),
    }
    return df.select(*docs.columns, *[c.alias(k) for k, c in stats.items()])


def band_rules() -> dict[str, Column]:
    """Rule name to whether it drops the page, for the common quality band."""
    out = {}
    for k, (lo, hi) in BAND.items():
        bad = F.lit(False)
        if lo is not None:
            bad = bad | (F.col(k) < lo)
        if hi is not None:
            bad = bad | (F.col(k) > hi)
        out[k] = bad
    return out


def page_rules() -> dict[str, dict[str, Column]]:
    """The page rules of each stack, cheapest first."""
    band = band_rules()
    text = F.coalesce("text", F.lit(""))
    a = {"filler": text.rlike(FILLER), "brace": F.contains(text, F.lit("{")), "sentences": F.col("sentences") < 3, "blocklist": text.rlike(BLOCKLIST)}
    c = {"ended_lines": F.col("ended_share") <= 0.12, "dup_chars": F.col("dup_line_chars") >= 0.1, "short_lines": F.col("short_share") >= 0.67}
    return {"a": a, "b": band, "c": band | {"c_" + k: v for k, v in c.items()} | {"a_filler": a["filler"], "a_brace": a["brace"]}}


def a_lines(text: Column, min_words: int = 5) -> Column:
    """Line rules of stack a: terminal punctuation, enough words, no scripts or policies."""
    ok = lambda x: x.rlike(ENDED) & (F.size(words(x)) >= min_words) & ~x.rlike(POLICY)
    return F.array_join(F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), ok), "\n")


def b_lines(text: Column) -> Column:
    """Line corrections of stack b: shouting, numbers only, counters, single words and short calls to action."""
    bad = lambda x: x.rlike(r"^[^a-z]*[A-Z][^a-z]*$") | x.rlike(r"^[0-9\s.,:;/-]+$") | x.rlike(r"(?i)^\s*[0-9.,]+ (?:likes?|views?|comments?|shares?)\s*$") | ~x.rlike(r"\S\s+\S") | x.rlike(r"(?i)^\s*(?:sign|log) ?in\b.{0,40}$|^\s*read more\b.{0,40}$")
    return F.array_join(F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: ~bad(x) | (F.trim(x) == "")), "\n")


def b_gate(pages: DataFrame, languages: tuple[str, ...] = ("en",), url_col: str = "url", lang_col: str = "lang") -> DataFrame:
    """The pages that stack b lets in, by URL and language; a page without a language goes."""
    return pages.where(~F.coalesce(F.col(url_col).rlike(BLOCKED_URL), F.lit(False)) & F.lower(F.col(lang_col)).isin(list(languages)))


def a_spans(docs: DataFrame, size: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, text, n_gone)``: lines that lie in a run of ``size`` lines which an earlier document has go, by stack a's corpus rule.

    Runs meet by their digest, with the least id of each counted before it moves; only
    the lines that go come back to their document.
    """
    lines = F.filter(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n"), lambda x: F.trim(x) != "")
    rows = docs.select(F.col(id_col).alias("id"), lines.alias("l"))
    at = F.sequence(F.lit(1), F.size("l") - (size - 1))
    spans = rows.where(F.size("l") >= size).select("id", F.posexplode(F.transform(at, lambda i: F.md5(F.array_join(F.slice("l", i, F.lit(size)), "\n")))).alias("i", "h"))
    own = spans.groupBy("h").agg(F.min("id").alias("owner"))
    gone = spans.join(own, "h").where("owner < id").groupBy("id").agg(F.collect_set("i").alias("starts"))
    left = F.filter(F.transform("l", lambda x, i: F.struct(i.alias("i"), x.alias("x"))), lambda p: ~F.exists("starts", lambda s: p["i"].between(s, s + (size - 1))))
    out = rows.join(gone, "id", "left").withColumn("starts", F.coalesce("starts", F.array().cast("array<int>"))).withColumn("left", left)
    return out.select("id", F.array_join(F.transform("left", lambda p: p["x"]), "\n").alias("text"), (F.size("l") - F.size("left")).alias("n_gone"))


def decisions(docs: DataFrame, stacks: tuple[str, ...] = ("a", "b", "c"), id_col: str = "doc_id") -> DataFrame:
    """``(id, stack, rule, dropped)`` in long form: a stack drops what any of its rules drops."""
    rules = [(s, r, c) for s in stacks for r, c in page_rules()[s].items()]
    every = F.array(*[F.struct(F.lit(s).alias("stack"), F.lit(r).alias("rule"), F.coalesce(c, F.lit(False)).alias("dropped")) for s, r, c in rules])
    return statistics(docs).select(F.col(id_col).alias("id"), F.explode(every).alias("d")).select("id", "d.*")


def apply(docs: DataFrame, stack: str) -> DataFrame:
    """The documents that a stack keeps, with its line rules applied; a line-filtered text that is empty falls."""
    if stack == "a":
        docs = docs.withColumn("text", a_lines(F.col("text")))
    if stack == "b":
        before = F.size(words(F.col("text")))
        docs = docs.withColumn("__new", b_lines(F.col("text"))).where(F.size(words(F.col("__new"))) >= 0.95 * before).withColumn("text", F.col("__new")).drop("__new")
    bad = F.lit(False)
    for c in page_rules()[stack].values():
        bad = bad | F.coalesce(c, F.lit(False))
    return fence(statistics(fence(docs))).where(~bad & (F.col("n_words") > 0)).select(*docs.columns)
