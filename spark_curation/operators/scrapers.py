"""Scrapers: text of a page by rules of thumb, one column each, with the faults the comparison needs."""

from __future__ import annotations

import re
from html.parser import HTMLParser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import safe_ratio, words
from spark_curation.operators.render import _Reader, closed_references, native_blocks

#: Bounds of block classification by length, stop words and links.
SHORT, LONG, STOP_LOW, STOP_HIGH, LINKED = 70, 200, 0.30, 0.32, 0.2
#: Characters that stand for the ends of a link while blocks are cut.
OPEN, CLOSE = "\x02", "\x03"
STOPS = "the be to of and that have with a in is it for on as are this was by at from or an der die und von zu das mit den ist ein de la le les et des en que un une el los del se por con".split()


def _join(blocks: Column) -> Column:
    return F.array_join(F.transform(blocks, lambda b: b["text"]), "\n")


def _blocks(pages: DataFrame) -> Column:
    """The blocks of rendered pages as they are, else of their markup."""
    return F.col("blocks") if "blocks" in pages.columns else native_blocks(F.col("html"))


def tagdrop(pages: DataFrame, fused_cells: bool = False, lost_lists: bool = False, sidebar: bool = False) -> DataFrame:
    """Default scraper: text outside menus, footers and headers; adverts in plain blocks stay.

    Three faults of such scrapers can be turned on: table cells joined without a space,
    lists left out, and a sidebar taken for the page where it is longer than the rest.
    """
    if not (fused_cells or lost_lists):
        blocks = _blocks(pages)
    else:
        html = F.regexp_replace("html", r"(?i)</?t[dh]\b[^>]*>", "") if fused_cells else F.col("html")
        blocks = native_blocks(F.regexp_replace(html, r"(?is)<(ul|ol)\b.*?</\1>", " ") if lost_lists else html)
    size = lambda c: F.length(_join(c))
    df = pages.select("page_id", blocks.alias("blocks")).select("page_id", F.filter("blocks", lambda b: ~b["zone"].isin("nav", "footer", "header")).alias("kept"))
    if sidebar:
        aside, rest = (F.filter("kept", lambda b: (b["zone"] == "aside") == x) for x in (True, False))
        df = df.select("page_id", F.when(size(aside) > size(rest), aside).otherwise(F.col("kept")).alias("kept"))
    return df.select("page_id", _join(F.col("kept")).alias("text"))


class _Subtrees(HTMLParser):
    """For each element that may hold the main content, what stands in it."""

    HOLDERS = frozenset("article main section div td body".split())
    NAMED = re.compile(r"\b(?:article|content|post|entry|main|story)\b", re.I)

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.reader = _Reader()
        #: (marked as content, depth, first line, last line, text characters less three times those in links)
        self.found: list[list] = []
        self.open: list[tuple[str, int]] = []
        self.link = 0

    def handle_starttag(self, tag: str, attrs: list) -> None:
        self.reader.handle_starttag(tag, attrs)
        self.link += tag == "a"
        if tag in self.HOLDERS:
            named = tag in ("article", "main") or bool(self.NAMED.search(" ".join(v or "" for k, v in attrs if k in ("class", "id", "role"))))
            self.open.append((tag, len(self.found)))
            self.found.append([named, len(self.open), len(self.reader.blocks), None, 0])

    def handle_endtag(self, tag: str) -> None:
        self.reader.handle_endtag(tag)
        self.link -= tag == "a" and self.link > 0
        at = next((i for i in range(len(self.open) - 1, -1, -1) if self.open[i][0] == tag), None)
        if at is not None:
            for _, k in self.open[at:]:
                self.found[k][3] = len(self.reader.blocks)
            del self.open[at:]

    def handle_data(self, data: str) -> None:
        self.reader.handle_data(data)
        if not self.reader.skip:
            n = len(data.strip()) * (-3 if self.link else 1)
            for _, k in self.open:
                self.found[k][4] += n


def main_subtree(html: str | None) -> str:
    """Text of the element with the most text outside links: one marked as content if there is any, the deepest of equal ones; all lines as a fall-back."""
    p = _Subtrees()
    p.feed(closed_references(html))
    p.close()
    p.reader.flush()
    blocks = p.reader.blocks
    good = [f for f in p.found if f[4] > 0 and f[2] < (f[3] if f[3] is not None else len(blocks))]
    if not good:
        return "\n".join(t for t, _ in blocks)
    best = max(good, key=lambda f: (f[0], f[4], f[1]))
    return "\n".join(t for t, _ in blocks[best[2] : best[3]])


def maintree(pages: DataFrame) -> DataFrame:
    """Best subtree: the text of the element that ``main_subtree`` chooses; needs the markup."""
    from collections.abc import Iterator

    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([main_subtree(h.as_py()) for h in b.column(1)], pa.string())], ["page_id", "text"])

    return pages.select("page_id", "html").mapInArrow(run, "page_id long, text string")


def density(pages: DataFrame) -> DataFrame:
    """Block classes by links, length and stop words, undecided blocks settled by the nearest decided ones on both sides; needs the markup."""
    marked = F.regexp_replace(F.regexp_replace("html", r"(?i)<a\b[^>]*>", OPEN), r"(?i)</a>", CLOSE)
    stop = lambda t: safe_ratio(F.size(F.filter(words(F.lower(t)), lambda w: w.isin(STOPS))), F.size(words(t)))

    def plain(b: Column) -> Column:
        linked = F.length(F.array_join(F.regexp_extract_all(b["text"], F.lit(f"{OPEN}[^{CLOSE}]*"), F.lit(0)), "")) - F.length(F.regexp_replace(b["text"], f"[^{OPEN}]", ""))
        text = F.translate(b["text"], OPEN + CLOSE, "")
        return F.struct(F.trim(text).alias("text"), b["zone"].alias("zone"), safe_ratio(linked, F.length(text)).alias("links"))

    def grade(b: Column) -> Column:
        n, s = F.length(b["text"]), stop(b["text"])
        long = F.when((s >= STOP_HIGH) & (n > LONG), "good").when(s >= STOP_LOW, "near").otherwise("bad")
        return F.when((b["zone"] != "") | (b["links"] > LINKED), "bad").when(n < SHORT, "short").otherwise(long)

    df = pages.select("page_id", F.filter(F.transform(native_blocks(marked), plain), lambda b: b["text"] != "").alias("blocks")).withColumn("c", F.transform("blocks", grade))
    none = F.array().cast("array<string>")
    # what stands before each block: one sweep forward over the classes, and the same over their reverse
    step = lambda acc, x: F.concat(acc, F.array(F.when(x.isin("good", "bad"), x).otherwise(F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit("bad")))))
    df = df.withColumns({"ahead": F.aggregate("c", none, step), "back": F.reverse(F.aggregate(F.reverse("c"), none, step))})
    left = lambda i: F.coalesce(F.get("ahead", i - 1), F.lit("bad")) == "good"
    right = lambda i: F.coalesce(F.get("back", i + 1), F.lit("bad")) == "good"
    keep = F.transform("c", lambda x, i: (x == "good") | ((x == "near") & (F.when(i > 0, left(i)).otherwise(False) | right(i))) | ((x == "short") & F.when(i > 0, left(i)).otherwise(False) & right(i)))
    df = df.withColumn("keep", keep)
    kept = F.filter("blocks", lambda b, i: F.get("keep", i))
    return df.select("page_id", _join(kept).alias("text"))


def teacher(pages: DataFrame) -> DataFrame:
    """The extraction teacher as a scraper: lines without a zone."""
    return pages.select("page_id", _join(F.filter(_blocks(pages), lambda b: b["zone"] == "")).alias("text"))


SCRAPERS = {"tagdrop": tagdrop, "maintree": maintree, "density": density, "teacher": teacher}

