"""The deterministic executor: lines and a program to the text of a page."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words
from spark_curation.io import fence


def _covered(ranges: Column, lid: Column) -> Column:
    return F.exists(ranges, lambda r: lid.between(r["a"], r["b"]))


def _cut(line: Column, cuts: Column, policy: str) -> Column:
    def one(acc: Column, c: Column) -> Column:
        at = F.instr(acc, c["frag"])
        if policy == "all":
            return F.replace(acc, c["frag"], F.lit(""))
        return F.when(at == 0, acc).otherwise(F.concat(F.substring(acc, F.lit(1), at - 1), F.substring(acc, at + F.length(c["frag"]), F.length(acc))))

    return F.aggregate(cuts, line, one)


def run(df: DataFrame, disable: tuple[str, ...] = (), cut_policy: str = "first") -> DataFrame:
    """Rows with ``lines`` and Program columns to Executed rows (text, provenance, word counts).

    Removals of the extraction block come first whatever the verdict; ``disable`` turns
    single operations off. Without extract, edits still address the input's lines.
    Fragments that are not found, or whose line is gone, change nothing; a line left
    blank goes. A page left without text gives no record and has provenance ``empty``.
    """
    none = F.array()
    strip = none.cast("array<struct<a:int,b:int>>") if "extract" in disable else F.col("strip")
    is_edit = (F.col("verdict") == "edit") & F.lit("edit" not in disable)
    pairs = F.transform("lines", lambda x, i: F.struct((i + 1).alias("lid"), x.alias("text")))
    df = df.withColumn("__kept", F.filter(pairs, lambda p: ~_covered(strip, p["lid"])))
    left = F.filter("__kept", lambda p: ~_covered(F.col("drop"), p["lid"]))
    cut = F.transform(left, lambda p: F.struct(p["lid"].alias("lid"), _cut(p["text"], F.filter("cuts", lambda c: c["lid"] == p["lid"]), cut_policy).alias("text")))
    df = df.withColumn("__edited", F.when(is_edit & F.col("body").isNull(), F.filter(cut, lambda p: F.trim(p["text"]) != "")).otherwise(F.col("__kept")))
    joined = lambda c: F.array_join(F.transform(c, lambda p: p["text"]), "\n")
    v = F.col("verdict")
    text = (
        F.when(F.col("status") != "ok", None)
        .when((v == "delete") & F.lit("delete" not in disable), None)
        .when(v == "rewrite", F.lit(None) if "rewrite" in disable else F.regexp_replace("body", r"^\s+|\s+$", ""))
        .when(is_edit & F.col("body").isNotNull(), F.col("body"))
        .otherwise(joined(F.col("__edited")))
    )
    df = df.withColumn("text", F.nullif(text, F.lit("")))
    tag = (
        F.when(F.col("status") != "ok", "malformed").when((v == "delete") & F.lit("delete" not in disable), "deleted").when(F.col("text").isNull(), "empty")
        .when(v == "rewrite", "rewritten").when(is_edit, "refined").otherwise("extracted")
    )
    raw, kept = F.array_join("lines", "\n"), joined(F.col("__kept"))
    stats = {"provenance": tag, "lines_in": F.size("lines"), "lines_kept": F.size("__kept"), "words_in": count_words(raw), "__left": count_words(kept), "words_out": count_words(F.col("text"))}
    return fence(df.withColumns(stats).withColumn("words_stripped", F.col("words_in") - F.col("__left")).drop("__kept", "__edited", "__left"))


def run_relational(df: DataFrame) -> DataFrame:
    """``(page_id, text)`` of keep and edit programs without cuts, as joins: lines less ranges, put together again."""
    lines = df.where("verdict in ('keep', 'edit') and status = 'ok' and body is null").select("page_id", F.posexplode("lines").alias("at", "line"), F.when(F.col("verdict") == "edit", F.concat("strip", "drop")).otherwise(F.col("strip")).alias("gone"))
    ranges = lines.where("at = 0").select(F.col("page_id").alias("of"), F.explode("gone").alias("r")).select("of", "r.a", "r.b")
    kept = lines.join(ranges, (F.col("page_id") == F.col("of")) & (F.col("at") + 1).between(F.col("a"), F.col("b")), "left_anti")
    ordered = F.array_sort(F.collect_list(F.struct("at", "line")))
    return kept.groupBy("page_id").agg(F.array_join(F.transform(ordered, lambda x: x["line"]), "\n").alias("text"))
