"""Page programs: text to a fixed struct and back, with checks of what untrusted output may hold."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import let

RANGES, CUTS = "array<struct<a:int,b:int>>", "array<struct<lid:int,frag:string>>"
#: The tags of the two layouts and the items of payloads.
VERDICT = r"<(keep|delete|edit|rewrite)>"
DECISION_FIRST = r"(?s)^\s*" + VERDICT + r"\s*<extract>(.*?)" + VERDICT + r"(.*)$"
EXTRACT_FIRST = r"(?s)^\s*<extract>(.*?)" + VERDICT + r"(.*)$"
LINE_ITEM = r"(?m)^[ \t]*rm[ \t]+([0-9]{1,6})(?:-([0-9]{1,6}))?[ \t]*$"
CUT_ITEM = r'(?m)^[ \t]*sub[ \t]+([0-9]{1,6}):[ \t]*("(?:[^"\\]|\\.)*")[ \t]*$'
LENIENT = r";|--|–|—"


def _normal(block: Column, strict: bool) -> Column:
    if strict:
        return block
    return F.regexp_replace(F.regexp_replace(block, r"[ \t]*;[ \t]*", "\n"), r"--|–|—", "-")


def parse_ranges(block: Column) -> Column:
    """Line and range removals of a block, in order."""
    found = F.regexp_extract_all(block, F.lit(LINE_ITEM), F.lit(0))
    a = lambda x: F.regexp_extract(x, LINE_ITEM, 1).cast("int")
    b = lambda x: F.coalesce(F.nullif(F.regexp_extract(x, LINE_ITEM, 2), F.lit("")).cast("int"), a(x))
    return F.transform(found, lambda x: F.struct(a(x).alias("a"), b(x).alias("b")))


def parse_cuts(block: Column) -> Column:
    """Fragment removals of a block, in order; fragments are quoted as in JSON."""
    found = F.regexp_extract_all(block, F.lit(CUT_ITEM), F.lit(0))
    frag = lambda x: F.get_json_object(F.concat(F.lit('{"s":'), F.regexp_extract(x, CUT_ITEM, 2), F.lit("}")), "$.s")
    return F.transform(found, lambda x: F.struct(F.regexp_extract(x, CUT_ITEM, 1).cast("int").alias("lid"), frag(x).alias("frag")))


def parse(df: DataFrame, col: str = "output", strict: bool = False) -> DataFrame:
    """Adds the Program columns for the text in ``col``, in whichever layout it is.

    Output that fits neither layout has status ``malformed`` and null parts; it never
    falls back to raw text. An edit payload without any item is the page text itself; the
    body of a rewrite is all that follows its line, white space at its ends included.
    """
    out = F.coalesce(F.col(col), F.lit(""))
    first = out.rlike(DECISION_FIRST)
    ok = first | out.rlike(EXTRACT_FIRST)
    part = lambda d, e: F.when(first, F.regexp_extract(out, DECISION_FIRST, d)).when(ok, F.regexp_extract(out, EXTRACT_FIRST, e))
    df = df.withColumns(
        {
            "layout": F.when(first, "decision_first").when(ok, "extract_first"),
            "verdict": part(1, 2),
            "verdict_echo": part(3, 2),
            "__strip": part(2, 1),
            "__payload": F.regexp_replace(part(4, 3), r"^\s+|\s+$", ""),
            "__whole": F.regexp_replace(part(4, 3), r"^[ \t\r]*\n", ""),
            "lenient": F.coalesce(part(2, 1).rlike(LENIENT), F.lit(False)) & F.lit(not strict),
        }
    )
    edit = F.col("verdict") == "edit"
    items = F.when(edit, _normal(F.col("__payload"), strict))
    df = df.withColumns({"strip": parse_ranges(_normal(F.col("__strip"), strict)), "drop": F.when(edit, parse_ranges(items)), "cuts": F.when(edit, parse_cuts(items))})
    paged = edit & (F.size("drop") == 0) & (F.size("cuts") == 0) & (F.col("__payload") != "")
    none = lambda kind: F.array().cast(kind)
    body = F.when((F.col("verdict") == "rewrite") & (F.col("__payload") != ""), F.col("__whole")).when((F.col("verdict") == "rewrite") | paged, F.col("__payload"))
    status = F.when(F.col("layout").isNull(), "malformed").otherwise("ok")
    df = df.withColumn("payload", F.coalesce("__payload", F.lit("")))
    return df.withColumns({"body": body, "strip": F.coalesce("strip", none(RANGES)), "drop": F.coalesce("drop", none(RANGES)), "cuts": F.coalesce("cuts", none(CUTS)), "status": status}).drop("__strip", "__payload", "__whole")


def validate(programs: DataFrame, lines: str = "lines") -> DataFrame:
    """Adds ``problems``: echo, out-of-range or inverted ids, fragments that are not there, payloads that must be empty."""
    n = F.size(lines)
    ranges = F.concat("strip", "drop")
    text = lambda c: F.get(F.col(lines), c["lid"] - 1)
    flags = [
        F.when(F.col("status") == "malformed", "malformed"),
        F.when(F.col("verdict") != F.col("verdict_echo"), "echo"),
        F.when(F.exists(ranges, lambda r: r["a"] > r["b"]), "inverted"),
        F.when(F.exists(ranges, lambda r: (r["a"] < 1) | (r["b"] > n)), "range"),
        F.when(F.exists("cuts", lambda c: F.coalesce(F.instr(text(c), c["frag"]) == 0, F.lit(True))), "fragment"),
        F.when((F.col("verdict") == "rewrite") & (F.col("body") == ""), "no_body"),
        F.when(F.col("verdict").isin("keep", "delete") & (F.col("payload") != ""), "payload"),
    ]
    return programs.withColumn("problems", F.array_compact(F.array(*flags)))


def to_ranges(flags: Column) -> Column:
    """Array of booleans, one for each line, to maximal inclusive ranges of the true ones."""

    def of(held: Column) -> Column:
        at = lambda i: F.coalesce(F.get(held, i), F.lit(False))
        ids = F.sequence(F.lit(0), F.greatest(F.size(held) - 1, F.lit(0)))
        starts = F.filter(ids, lambda i: at(i) & ~F.when(i > 0, at(F.greatest(i - 1, F.lit(0)))).otherwise(False))
        ends = F.filter(ids, lambda i: at(i) & ~at(i + 1))
        return F.zip_with(starts, ends, lambda a, b: F.struct((a + 1).alias("a"), (b + 1).alias("b")))

    return let(flags, of)


def _items(ranges: Column) -> Column:
    one = lambda r: F.when(r["a"] == r["b"], F.concat(F.lit("rm "), r["a"].cast("string"))).otherwise(F.concat(F.lit("rm "), r["a"].cast("string"), F.lit("-"), r["b"].cast("string")))
    return F.transform(ranges, one)


def _quoted(frag: Column) -> Column:
    inner = F.replace(F.replace(frag, F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"'))
    return F.concat(F.lit('"'), F.replace(F.replace(inner, F.lit("\n"), F.lit("\\n")), F.lit("\t"), F.lit("\\t")), F.lit('"'))


def serialize(layout: str = "decision_first") -> Column:
    """Column with the text of the program in columns verdict, strip, drop, cuts and body."""
    tag = F.concat(F.lit("<"), F.col("verdict"), F.lit(">"))
    cuts = F.transform("cuts", lambda c: F.concat(F.lit("sub "), c["lid"].cast("string"), F.lit(": "), _quoted(c["frag"])))
    payload = F.when((F.col("verdict") == "edit") & F.col("body").isNull(), F.concat(_items(F.col("drop")), cuts)).when(F.col("body").isNotNull(), F.array("body")).otherwise(F.array().cast("array<string>"))
    strip = F.concat(F.array(F.lit("<extract>")), _items(F.col("strip")))
    parts = F.concat(strip, F.array(tag), payload)
    return F.array_join(F.concat(F.array(tag), parts) if layout == "decision_first" else parts, "\n")
