"""Judges: replies parsed by a fixed schema, and rule stand-ins that share no feature with the edu score."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import safe_ratio
from spark_curation.operators.teachers import with_junk

#: Characters a judge sees, and the keys of its replies.
INPUT = 24_000
REPLY = "recall int, precision int, integrity int, verdict string, value int"


def read_replies(df: DataFrame, col: str = "reply") -> DataFrame:
    """Adds ``judged``, null where a reply is not the JSON asked for, and ``bad_reply``."""
    parsed = F.from_json(F.col(col), REPLY, {"mode": "PERMISSIVE"})
    known = F.coalesce(parsed["verdict"], parsed["value"].cast("string"), parsed["recall"].cast("string")).isNotNull()
    return df.withColumns({"judged": F.when(known, parsed), "bad_reply": ~known})


def seen(text: Column) -> Column:
    return F.substring(text, 1, INPUT)


def quality_score(text: Column) -> Column:
    """1 to 5 by how much of a text is junk."""
    junk = lambda m: F.least(F.lit(1.0), m["symbols"] + m["shouts"] + m["runs"] + F.when(m["pipes"] >= 3, 0.5).otherwise(0.0))
    return with_junk(seen(text), lambda m: F.round(1 + 4 * (1 - junk(m))).cast("int"))


def output_rating(text: Column) -> Column:
    """0 to 3 for a kept text: no junk family, some length, sentences that end."""

    def grade(m: dict[str, Column]) -> Column:
        clean = F.when((m["symbols"] <= 0.1) & (m["shouts"] <= 0.1) & (m["runs"] <= 0.1), 1).otherwise(0)
        return clean + F.when(m["n_words"] >= 50, 1).otherwise(0) + F.when((m["ends"] * 40 >= m["n_words"]) & (m["ends"] > 0), 1).otherwise(0)

    return with_junk(seen(text), grade)


def extraction(found: DataFrame, gold: DataFrame, key: str = "page_id") -> DataFrame:
    """``(key, recall, precision, integrity)`` of 0 to 2 each, from the lines of an extracted text against gold lines."""
    lines = lambda c: F.filter(F.split(F.coalesce(c, F.lit("")), "\n"), lambda x: x != "")
    j = gold.select(key, lines(F.col("text")).alias("g")).join(found.select(key, lines(F.col("text")).alias("f")), key, "left")
    f = F.coalesce("f", F.array().cast("array<string>"))
    both = F.size(F.array_intersect(f, "g"))
    grade = lambda r: F.when(r >= 0.99, 2).when(r >= 0.5, 1).otherwise(0)
    order = F.filter("g", lambda x: F.array_contains(f, x)) == F.filter(f, lambda x: F.array_contains("g", x))
    return j.select(key, grade(safe_ratio(both, F.size(F.array_distinct("g")))).alias("recall"), grade(safe_ratio(both, F.size(F.array_distinct(f)))).alias("precision"), F.when(order, 2).when(both > 0, 1).otherwise(0).alias("integrity"))
