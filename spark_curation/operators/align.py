"""Edited text back to operations: lines first, then characters within a line, else the page text as a whole."""

from __future__ import annotations

from collections.abc import Iterator
from difflib import SequenceMatcher

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import let


def is_subsequence(out: str, src: str) -> bool:
    """Whether ``out`` comes from ``src`` by deletions alone."""
    it = iter(src)
    return all(c in it for c in out)


def _cuts(line: str, new: str) -> list[str] | None:
    """Fragments whose first occurrences, removed in turn, make ``new`` of ``line``; none if that can't be."""
    found, rest = [], line
    while rest != new:
        head = next((i for i, (a, b) in enumerate(zip(rest, new, strict=False)) if a != b), min(len(rest), len(new)))
        best = None
        for size in range(1, len(rest) - len(new) + 1):
            for start in range(head, max(-1, head - size), -1):
                frag = rest[start : start + size]
                left = rest[:start] + rest[start + size :]
                if left[: head + 1] == new[: head + 1] and rest.find(frag) == start and is_subsequence(new, left):
                    best = frag, left
                    break
            if best:
                break
        if not best:
            return None
        found.append(best[0])
        rest = best[1]
    return found


def align(lines: list[str], cleaned: str) -> tuple[list[int], list[tuple[int, str]], str | None]:
    """(dropped line ids, fragment removals, page text): the page text only where no deletions explain ``cleaned``."""
    new = [x for x in cleaned.split("\n") if x.strip()]
    drop: list[int] = []
    cuts: list[tuple[int, str]] = []
    i = 0
    for want in new:
        while i < len(lines):
            line = lines[i]
            if line == want:
                break
            later = want in lines[i + 1 :]
            if not later and len(want) < len(line) and is_subsequence(want, line):
                got = _cuts(line, want)
                if got is not None:
                    cuts += [(i + 1, f) for f in got]
                    break
            drop.append(i + 1)
            i += 1
        else:
            return [], [], cleaned
        i += 1
    drop += range(i + 1, len(lines) + 1)
    return drop, cuts, None


def to_edit(df: DataFrame, lines: str = "lines", cleaned: str = "cleaned", id_col: str = "page_id") -> DataFrame:
    """``(id, drop_ids, cuts, body)`` for each row; a null cleaned text drops every line."""
    cut = pa.list_(pa.struct([("lid", pa.int32()), ("frag", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [align(x.as_py() or [], y.as_py() or "") for x, y in zip(b.column(1), b.column(2), strict=True)]
            columns = [b.column(0), pa.array([g[0] for g in got], pa.list_(pa.int32())), pa.array([[{"lid": i, "frag": f} for i, f in g[1]] for g in got], cut), pa.array([g[2] for g in got], pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["id", "drop_ids", "cuts", "body"])

    rows = df.select(F.col(id_col).cast("long"), lines, cleaned)
    return rows.mapInArrow(run, "id long, drop_ids array<int>, cuts array<struct<lid:int,frag:string>>, body string")


def lines_absent(lines: Column, extracted: Column) -> Column:
    """Flags of the lines that an extractor's text does not have, by whole lines."""
    have = F.transform(F.split(F.coalesce(extracted, F.lit("")), "\n"), lambda x: F.trim(x))
    return let(have, lambda h: F.transform(lines, lambda x: ~F.array_contains(h, x)))


def classify_page_edit(df: DataFrame, src: str = "source", out: str = "body") -> DataFrame:
    """Adds ``pure_deletion`` and ``changed_share`` (of words) to rows with a page-text edit."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t = b.to_pydict()
            pure = [is_subsequence(o or "", s or "") for s, o in zip(t[src], t[out], strict=True)]
            share = []
            for s, o in zip(t[src], t[out], strict=True):
                a, c = (s or "").split(), (o or "").split()
                same = sum(m.size for m in SequenceMatcher(None, a, c, autojunk=False).get_matching_blocks())
                share.append(1 - 2 * same / (len(a) + len(c)) if a or c else 0.0)
            yield b.append_column("pure_deletion", pa.array(pure)).append_column("changed_share", pa.array(share, pa.float64()))

    schema = ", ".join(f"`{n}` {t}" for n, t in df.dtypes) + ", pure_deletion boolean, changed_share double"
    return df.mapInArrow(run, schema)
