"""Column functions on text, all evaluated in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Character references decoded by the native renderer, the ampersand last.
REFERENCES = (("&copy;", "©"), ("&middot;", "·"), ("&quot;", '"'), ("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&#39;", "'"), ("&amp;", "&"))


def decode_references(c: Column) -> Column:
    for name, char in REFERENCES:
        c = F.replace(c, F.lit(name), F.lit(char))
    return c


def squeeze(c: Column) -> Column:
    """White space runs to one space, ends trimmed."""
    return F.trim(F.regexp_replace(c, r"\s+", " "))


def words(c: Column) -> Column:
    """Maximal runs without white space."""
    return F.regexp_extract_all(F.coalesce(c, F.lit("")), F.lit(r"\S+"), F.lit(0))


def count_words(c: Column) -> Column:
    return F.regexp_count(F.coalesce(c, F.lit("")), F.lit(r"\S+")).cast("long")


def count(c: Column, pattern: str) -> Column:
    return F.regexp_count(F.coalesce(c, F.lit("")), F.lit(pattern)).cast("long")


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` worked out once, though body uses it inside lambdas."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def ngrams(ws: Column, n: int) -> Column:
    """Array of the n-word strings of an array of words, in order; empty if there are fewer words."""

    def of(w: Column) -> Column:
        at = F.sequence(F.lit(1), F.size(w) - (n - 1))
        return F.when(F.size(w) >= n, F.transform(at, lambda i: F.array_join(F.slice(w, i, F.lit(n)), " "))).otherwise(F.array().cast("array<string>"))

    return let(ws, of)


def repeats(ws: Column) -> Column:
    """How many words equal the word before them."""
    return let(ws, lambda w: F.size(F.filter(w, lambda x, i: (i > 0) & (x == F.get(w, i - 1)))).cast("long"))


def portable_share(*parts: Column) -> Column:
    """A number in [0, 1) from md5 of the parts, the same in any engine: for samples that all plans agree on."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def safe_ratio(a: Column, b: Column) -> Column:
    """a / b as a double, 0 where b is 0."""
    return F.when(b == 0, F.lit(0.0)).otherwise(a.cast("double") / b.cast("double"))
