"""Program refiners over scraped text: chunk programs with line intervals from 0, and line programs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.operators import execute, teachers
from spark_curation.operators.program import CUTS, RANGES, to_ranges

CALL = r"remove_lines\(([0-9]+), ?([0-9]+)\)"


def _lines(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.trim(x) != "")


def noisy(lines: Column) -> Column:
    """Flags of lines that the stand-in policy removes: notices, short lines without an end, and copies of earlier ones."""
    bad = teachers.noisy_lines(lines)
    return F.zip_with(bad, lines, lambda b, x: b | ((F.length(x) < 20) & ~x.rlike(r"[.!?]$")))


def chunk_programs(docs: DataFrame, id_col: str = "page_id") -> DataFrame:
    """``(id, lines, output)``: a call for each interval of noisy lines, numbered from 0, or the call for no change."""
    df = docs.select(F.col(id_col).alias("page_id"), _lines(F.col("text")).alias("lines"))
    df = df.withColumn("r", to_ranges(noisy(F.col("lines"))))
    calls = F.transform("r", lambda r: F.concat(F.lit("remove_lines("), (r["a"] - 1).cast("string"), F.lit(", "), (r["b"] - 1).cast("string"), F.lit(")")))
    return df.select("page_id", "lines", F.when(F.size("r") > 0, F.array_join(calls, "\n")).otherwise("keep_all()").alias("output"))


def chunkprog(docs: DataFrame, id_col: str = "page_id") -> DataFrame:
    """``(page_id, text, ...)`` after running chunk programs; their numbers move up by one for the executor."""
    df = chunk_programs(docs, id_col)
    found = F.regexp_extract_all("output", F.lit(CALL), F.lit(0))
    drop = F.transform(found, lambda c: F.struct((F.regexp_extract(c, CALL, 1).cast("int") + 1).alias("a"), (F.regexp_extract(c, CALL, 2).cast("int") + 1).alias("b")))
    ready = df.withColumns({"strip": F.array().cast(RANGES), "drop": drop, "cuts": F.array().cast(CUTS), "body": F.lit(None).cast("string"), "verdict": F.lit("edit"), "status": F.lit("ok")})
    return execute.run(ready).select("page_id", "text", "words_in", "words_out")


def lineprog(docs: DataFrame, id_col: str = "page_id") -> DataFrame:
    """``(page_id, text, ...)`` after removing noisy lines and noise fragments from scraped text."""
    df = docs.select(F.col(id_col).alias("page_id"), _lines(F.col("text")).alias("lines")).withColumn("flags", noisy(F.col("lines")))
    left = F.filter(F.transform("lines", lambda x, i: F.struct((i + 1).alias("lid"), x.alias("t"))), lambda p: ~F.get("flags", p["lid"] - 1))
    cuts = F.flatten(F.transform(left, lambda p: F.transform(teachers.fragments(p["t"]), lambda f: F.struct(p["lid"].alias("lid"), f.alias("frag")))))
    ready = df.withColumns({"strip": F.array().cast(RANGES), "drop": to_ranges(F.col("flags")), "cuts": cuts, "body": F.lit(None).cast("string"), "verdict": F.lit("edit"), "status": F.lit("ok")})
    return execute.run(ready).select("page_id", "text", "words_in", "words_out")


def orchestrated(docs: DataFrame, size: int = 1500, id_col: str = "page_id") -> DataFrame:
    """``(page_id, text, n_chunks, n_dropped, n_cleaned, n_guided)``: chunks routed to drop, keep, line removal or guided rewriting.

    Chunks are whole lines gathered to about ``size`` characters; each goes one way by
    its own measures and all come together again in order.
    """
    df = docs.select(F.col(id_col).alias("page_id"), _lines(F.col("text")).alias("lines"))
    start = F.struct(F.array().cast("array<string>").alias("done"), F.lit("").alias("open"))

    def gather(acc: Column, line: Column) -> Column:
        grown = F.when(acc["open"] == "", line).otherwise(F.concat(acc["open"], F.lit("\n"), line))
        full = F.struct(F.concat(acc["done"], F.array(grown)).alias("done"), F.lit("").alias("open"))
        return F.when(F.length(grown) >= size, full).otherwise(F.struct(acc["done"].alias("done"), grown.alias("open")))

    done = lambda acc: F.when(acc["open"] == "", acc["done"]).otherwise(F.concat(acc["done"], F.array(acc["open"])))
    chunk = df.select("page_id", F.posexplode(F.aggregate("lines", start, gather, done)).alias("pos", "chunk"))
    family = teachers.valueless(F.col("chunk"))
    noisy_part = F.col("chunk").rlike(teachers.FRAGMENT) | F.col("chunk").rlike(teachers.NOTICE)
    routed = chunk.withColumn("route", F.when(family.isin("spam", "listing", "ui_only"), "drop").when(family == "gibberish", "guided").when(noisy_part, "clean").otherwise("keep"))
    cleaned = F.array_join(F.filter(F.transform(F.split("chunk", "\n"), lambda x: F.regexp_replace(x, teachers.FRAGMENT, "")), lambda x: ~x.rlike(teachers.NOTICE) & (F.trim(x) != "")), "\n")
    out = F.when(F.col("route") == "keep", F.col("chunk")).when(F.col("route") == "clean", cleaned).when(F.col("route") == "guided", teachers.rewrite(F.col("chunk")))
    routed = routed.withColumn("out", out)
    parts = F.array_sort(F.collect_list(F.when(F.col("out").isNotNull(), F.struct("pos", "out"))))
    n = lambda r: F.count_if(F.col("route") == r)
    return routed.groupBy("page_id").agg(
        F.nullif(F.array_join(F.transform(parts, lambda p: p["out"]), "\n"), F.lit("")).alias("text"), F.count("*").alias("n_chunks"), n("drop").alias("n_dropped"), n("clean").alias("n_cleaned"), n("guided").alias("n_guided")
    )
