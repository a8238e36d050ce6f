"""The refining rulebook: families of valueless texts, signal that is never touched, noise, and how lines are cleaned.

A line goes as a whole where it is noise. Of a longer line only whole sentences of noise
go: a sentence is kept or dropped, never mended. What is protected stays in any case,
and the order and structure of what is left does not change.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count, count_words
from spark_curation.operators.teachers import valueless

#: What is never noise.
PROTECTED = {
    "bibliographic": r"(?i)\b(?:isbn|issn|doi|arxiv)\b|\bvol\. ?[0-9]|\bpp\. ?[0-9]",
    "byline": r"(?:^|\s)[Bb]y [A-Z][a-z]+ [A-Z][a-z]+",
    "quotation": r"^[\"“«].*[\"”»][.,]?$",
    "description": r"(?i)\b(?:hardcover|paperback|[0-9]+ pages|published by|dimensions|weight:)",
    "prose": r"^[^|]{120,}[.!?][\"')]*$",
}
#: Families of noise, each for a whole line or a whole sentence.
NOISE = {
    "chrome": r"(?i)^(?:home|menu|search|skip to (?:main )?content|read (?:more|next)|next|previous|back to top|log ?in|sign ?(?:in|up)|[0-9]+ (?:comments?|views?|likes?))[.!]?$",
    "social": r"(?i)\b(?:share (?:this|on)|follow us|like us|tweet this|subscribe to|join our newsletter)\b",
    "footer": r"(?i)©|\ball rights reserved\b|\bpowered by\b",
    "legal": r"(?i)\b(?:privacy policy|terms of (?:use|service)|cookie policy|contact us|licen[sc]ed under|released under the)\b",
    "shop": r"(?i)\b(?:add to (?:cart|basket)|in stock|out of stock|free shipping|buy now|checkout)\b",
    "foreign": r"^[^A-Za-zÀ-ÿ]*[\x{400}-\x{4FF}\x{4E00}-\x{9FFF}\x{3040}-\x{30FF}][^A-Za-zÀ-ÿ]*$",
    "residue": r"&(?:nbsp|amp|lt|gt|quot);|</?[a-z]+>|\{\{|\}\}|Ã.|â€",
}
#: Calls of a text that sells one service, and how many make it worthless in how few words.
CALLS, MOST_WORDS, LEAST_CALLS = r"(?i)\b(?:call us|call now|book now|order now|our services|free quote|get in touch|visit our)\b", 120, 2
SENTENCE = r"[^.!?]+[.!?]+[\"')]*\s*|[^.!?]+$"


def protected(line: Column) -> Column:
    """Whether a line is signal of one of the families."""
    out = F.lit(False)
    for p in PROTECTED.values():
        out = out | line.rlike(p)
    return out


def noise(line: Column) -> Column:
    """The family of a line or sentence of noise; null where it is none or is protected."""
    out = F.when(protected(line), F.lit(None).cast("string"))
    for name, p in NOISE.items():
        out = out.when(line.rlike(p), name)
    return out


def worthless(text: Column) -> Column:
    """The family of a text without value: those of the teacher, and promotion of a single service."""
    promotion = (count(text, CALLS) >= LEAST_CALLS) & (count_words(text) <= MOST_WORDS)
    return F.coalesce(valueless(text), F.when(promotion, "promotion"))


def clean_line(line: Column) -> Column:
    """A line without its sentences of noise; null where the whole line is noise or nothing is left."""
    sentences = F.regexp_extract_all(line, F.lit(SENTENCE), F.lit(0))
    left = F.trim(F.array_join(F.filter(sentences, lambda s: noise(F.trim(s)).isNull()), ""))
    return F.when(protected(line), line).when(F.size(sentences) > 1, F.nullif(left, F.lit(""))).when(noise(line).isNull(), line)


def apply(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with ``family`` (null for texts of value), ``cleaned`` (null for the others) and how many lines changed or went."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = docs.withColumn("family", worthless(text)).withColumn("__lines", F.filter(F.split(text, "\n"), lambda x: F.trim(x) != ""))
    out = out.withColumn("__clean", F.transform("__lines", clean_line))
    gone = F.size(F.filter("__clean", lambda x: x.isNull()))
    changed = F.size(F.filter(F.zip_with("__clean", "__lines", lambda a, b: a.isNotNull() & (a != b)), lambda x: x))
    cleaned = F.when(F.col("family").isNull(), F.nullif(F.array_join("__clean", "\n"), F.lit("")))
    return out.withColumns({"cleaned": cleaned, "lines_gone": gone, "lines_changed": changed}).drop("__lines", "__clean")


def capped(tokens_in: Column, tokens_out: Column, slack: int = 256) -> Column:
    """Whether a refining reply keeps its cap: the input's tokens and a fixed number more."""
    return tokens_out <= tokens_in + slack
