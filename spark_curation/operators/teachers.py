"""Stand-ins for the three teachers: extraction by zones, refining by a rulebook, rewriting by clean-up.

They keep the contracts of the models that they stand for (whole lines only; an empty
reply or an early marker means delete; seven-thousand-character chunks), not their judgement.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.io import fence
from spark_curation.functions.text import count, count_words, let, repeats, safe_ratio, words

#: The marker of the refining reply, the characters it is looked for in, rewriting chunk and acceptance.
DELETE_MARKER, HEAD, CHUNK, LO, HI = "[[DELETE]]", 120, 7000, 0.2, 3.0
#: Patterns of the rulebook.
SYMBOLED = r"[#%*$&]{3}[.,]?\s"
SHOUTED = r"[A-Z]{2,}[.,]*!!\s"
NOTICE = r"(?i)\b(?:licensed under|released under the) .*(?:license|cc )"
FRAGMENT = r" ?(?:[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+|\b[0-9]{1,3}(?:\.[0-9]{1,3}){3}\b|\b[0-9]{13,19}\b|(?:token|password) ?= ?\"?[0-9A-Za-z]{8,}\"?)"
PROTECTED = r"(?i)\b(?:isbn|doi|vol\.|by [A-Z][a-z]+ [A-Z][a-z]+)\b"
ARTIFACTS = r"(?i)^(?:here is|sure|as an ai|rewritten)"


def extract(rendered: DataFrame) -> DataFrame:
    """Adds ``strip``: ranges of the lines whose zone is a menu, footer, advert or the like."""
    from spark_curation.operators.program import to_ranges

    return rendered.withColumn("strip", to_ranges(F.transform("blocks", lambda b: b["zone"] != "")))


def with_junk(text: Column, body) -> Column:
    """``body`` of the measures of the valueless families, each worked out once: words, shares of symbol endings, shouts and runs, pipes, ends."""
    padded = F.concat(F.coalesce(text, F.lit("")), F.lit(" "))
    raw = F.struct(count_words(text).alias("n"), count(padded, SYMBOLED).alias("s"), count(padded, SHOUTED).alias("h"), repeats(words(text)).alias("r"), count(text, r"\|").alias("p"), count(text, r"[.!?]").alias("e"))
    return let(raw, lambda m: body({"n_words": m["n"], "symbols": safe_ratio(m["s"], m["n"]), "shouts": safe_ratio(m["h"], m["n"]), "runs": safe_ratio(m["r"], m["n"]), "pipes": m["p"], "ends": m["e"]}))


def valueless(text: Column) -> Column:
    """The family of a text without value, else null."""

    def family(m: dict[str, Column]) -> Column:
        return (
            F.when((m["symbols"] > 0.3) | (m["shouts"] > 0.3), "gibberish").when(m["runs"] > 0.3, "spam").when(m["pipes"] >= 3, "listing")
            .when((m["ends"] == 0) & (m["n_words"] < 10), "ui_only")
        )

    return with_junk(text, family)


def edu_score(text: Column) -> Column:
    """0 to 5: five times the root of the share of distinct words, the share of words with a letter and of punctuated lines."""
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: x != "")
    raw = F.struct(words(text).alias("w"), count(text, r"\S*[A-Za-zÀ-ÿ]\S*").alias("alpha"), F.transform(lines, lambda x: x.rlike(r"[.!?][\"')\]]*$")).alias("ended"))
    distinct = lambda m: safe_ratio(F.size(F.array_distinct(m["w"])), F.size(m["w"]))
    ended = lambda m: safe_ratio(F.size(F.filter(m["ended"], lambda x: x)), F.size(m["ended"]))
    return let(raw, lambda m: F.round(5 * F.sqrt(distinct(m)) * safe_ratio(m["alpha"], F.size(m["w"])) * ended(m), 4))


def noisy_lines(lines: Column) -> Column:
    """For each line whether it is a licence notice or stood before in the page; bibliographic lines and bylines are never noise, null lines neither."""
    again = lambda x, i: F.array_position(lines, x) <= i
    return F.transform(lines, lambda x, i: F.coalesce((again(x, i) | x.rlike(NOTICE)) & ~x.rlike(PROTECTED), F.lit(False)))


def fragments(line: Column) -> Column:
    return F.regexp_extract_all(line, F.lit(FRAGMENT), F.lit(0))


def considered(df: DataFrame) -> DataFrame:
    """Rows with ``lines`` and ``strip`` to all that ``refine`` decides on, which is the same for every rescue rule."""
    from spark_curation.operators.program import to_ranges

    df = df.withColumn("__main", F.transform("lines", lambda x, i: F.when(~F.exists(F.col("strip"), lambda r: (i + 1).between(r["a"], r["b"])), x)))
    df = df.withColumn("extracted", F.array_join("__main", "\n"))
    df = df.withColumn("family", valueless(F.col("extracted"))).withColumn("edu", edu_score(F.col("extracted")))
    df = df.withColumn("__bad", noisy_lines(F.col("__main"))).withColumn("drop", to_ranges(F.col("__bad")))
    clean = F.filter(F.transform("__main", lambda x, i: F.struct((i + 1).alias("lid"), x.alias("text"))), lambda p: p["text"].isNotNull() & ~F.get("__bad", p["lid"] - 1))
    df = df.withColumn("cuts", F.flatten(F.transform(clean, lambda p: F.transform(fragments(p["text"]), lambda f: F.struct(p["lid"].alias("lid"), f.alias("frag"))))))
    df = fence(df).withColumn("rewritten", rewrite(F.col("extracted")))
    return df.withColumn("accepted", accept_rewrite(F.col("extracted"), F.col("rewritten"))).drop("__main", "__bad")


def verdict(rescue: str = "edu", threshold: float = 1.0, hi: float = 2.0) -> Column:
    """The verdict on a row of ``considered`` under a rescue rule, see ``refine``."""
    bad = F.col("family").isNotNull()
    worth = {
        "edu": F.col("edu") >= threshold,
        "three_way": F.col("edu").between(threshold, hi),
        "classifier": count_words(F.col("rewritten")) * 2 >= count_words(F.col("extracted")),
    }[rescue]
    as_is = (F.col("edu") > hi) if rescue == "three_way" else F.lit(False)
    touched = (F.size("drop") > 0) | (F.size("cuts") > 0)
    return F.when(bad & as_is, "keep").when(bad & worth & F.col("accepted"), "rewrite").when(bad, "delete").when(touched, "edit").otherwise("keep")


def decided(df: DataFrame) -> DataFrame:
    """Rows of ``considered`` with their ``verdict`` to programs."""
    from spark_curation.operators.program import CUTS, RANGES

    is_edit, none = F.col("verdict") == "edit", F.array()
    return df.withColumns(
        {
            "verdict_echo": F.col("verdict"),
            "drop": F.when(is_edit, F.col("drop")).otherwise(none.cast(RANGES)),
            "cuts": F.when(is_edit, F.col("cuts")).otherwise(none.cast(CUTS)),
            "body": F.when(F.col("verdict") == "rewrite", F.col("rewritten")),
            "status": F.lit("ok"),
        }
    ).drop("rewritten", "accepted")


def refine(df: DataFrame, rescue: str = "edu", threshold: float = 1.0, hi: float = 2.0) -> DataFrame:
    """Rows with ``lines`` and ``strip`` to policy programs (verdict, drop, cuts, body) on the same line ids.

    Valueless texts are deleted, or rewritten where the rescue rule finds them worth it:
    ``edu`` takes scores from ``threshold``; ``classifier`` takes texts that keep half of
    their words after clean-up; ``three_way`` keeps scores from ``hi`` as they are.
    """
    return decided(considered(df).withColumn("verdict", verdict(rescue, threshold, hi)))


def read_refinement(cleaned: Column, marker: str = DELETE_MARKER, head: int = HEAD) -> Column:
    """Whether a refining reply means delete: empty, or the marker within its first characters."""
    text = F.coalesce(cleaned, F.lit(""))
    return (F.trim(text) == "") | (F.instr(F.substring(text, 1, head), marker) > 0)


def chunks(text: Column, size: int = CHUNK) -> Column:
    """Consecutive pieces of ``size`` characters."""
    n = F.greatest(F.ceil(F.length(text) / size).cast("int"), F.lit(1))
    return F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.substring(text, i * size + 1, F.lit(size)))


def rewrite(text: Column, size: int = CHUNK) -> Column:
    """A paraphrase stand-in, chunk by chunk: symbol endings, shouting and repeated marks go, shouted words in lower case."""

    def one(c: Column) -> Column:
        c = F.regexp_replace(F.regexp_replace(c, r"[#%*$&]{3}", ""), r"!{2,}", "")
        return F.trim(F.regexp_replace(F.regexp_replace(c, r" ?\| ?", ", "), r"[ \t]+", " "))

    return F.array_join(F.transform(chunks(F.coalesce(text, F.lit("")), size), one), " ")


def head_tail(text: Column, budget: int = 4096) -> Column:
    """The first and last words of a chunk over the budget, half each."""
    ws = words(text)
    half = budget // 2
    short = F.array_join(F.concat(F.slice(ws, 1, half), F.slice(ws, -half, half)), " ")
    return F.when(F.size(ws) > budget, short).otherwise(text)


def accept_rewrite(source: Column, out: Column, lo: float = LO, hi: float = HI) -> Column:
    """A rewrite stands if it is not empty, opens without a lead-in and has 0.2 to 3 times the words."""
    fits = let(F.struct(count_words(out).alias("n"), count_words(source).alias("of")), lambda c: safe_ratio(c["n"], c["of"]).between(lo, hi))
    return (F.trim(F.coalesce(out, F.lit(""))) != "") & ~out.rlike(ARTIFACTS) & fits
