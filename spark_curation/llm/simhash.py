"""Near duplicates by SimHash, found through deletion variants of fingerprint segments.

A fingerprint of 64 bits is cut into fewer segments than bits may differ, so that
two fingerprints within the distance have a segment that differs in one bit at the
most. Each segment is indexed once for each of its bits with that bit wildcarded:
two segments that differ in one bit or none share a variant. An equality join on
the variants finds the candidates, and the distance is verified inside the join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_digest

from spark_curation.io import cut, shuffled
from spark_curation.llm.graph import components, join_small

BITS, SEED = 64, 42


def fingerprint(text: str | None, width: int = 4, piece: int = 100_000) -> int:
    """SimHash of one text as a signed 64-bit integer; zero for a text without words.

    Every shingle counts, repeats included, in pieces of bounded memory.
    """
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts = ends - sizes
    n = max(1, len(words) - width + 1)
    last = ends[min(width, len(words)) - 1 :]
    sums = np.zeros(BITS, np.int64)
    for at in range(0, n, piece):
        spans = zip(starts[at : min(n, at + piece)].tolist(), last[at : at + piece].tolist(), strict=False)
        raw = b"".join([xxh64_digest(joined[a:b], SEED) for a, b in spans])
        sums += np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * sums > n).tobytes(), "big", signed=True)


def with_fingerprints(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp)`` for every row; a narrow pass that hashes whole texts in Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = pa.array([fingerprint(t, width) for t in b.column(1).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), fps], ["doc_id", "fp"])

    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, fp long")


def segments(distance: int) -> list[tuple[int, int]]:
    """(offset, width) of the fewest segments of which one differs by at most one bit."""
    k = max(2, distance // 2 + 1)
    edges = [BITS * i // k for i in range(k + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:], strict=False)]


def _variants(fp: F.Column, distance: int) -> F.Column:
    """Array of the keys of all one-wildcard variants: segment, bit and what is left."""
    keys = []
    for off, width in segments(distance):
        part = F.shiftrightunsigned(fp, off).bitwiseAND(F.lit((1 << width) - 1))
        for i in range(width):
            left = part.bitwiseAND(F.lit(((1 << width) - 1) ^ (1 << i)))
            keys.append(left.bitwiseOR(F.lit((off + i) << 48)))
    return F.array(*keys)


def links(fps: DataFrame, distance: int = 4) -> DataFrame:
    """Pairs ``(u, v)`` of different fingerprints that differ in at most ``distance`` bits, once each.

    ``fps`` holds distinct fingerprints in ``fp``. The pair is taken only at its
    first shared variant, so that the join makes each link once and nothing else.
    """
    v = fps.select("fp", F.explode(_variants(F.col("fp"), distance)).alias("key"))
    a, b = v.select(F.col("key").alias("at"), F.col("fp").alias("u")), v.select("key", F.col("fp").alias("v"))
    x = F.col("u").bitwiseXOR(F.col("v"))
    first = F.lit(-1)
    for off, width in reversed(segments(distance)):
        part = F.shiftrightunsigned(x, off).bitwiseAND(F.lit((1 << width) - 1))
        slot = F.when(part == 0, F.lit(off)).otherwise(F.lit(off) + F.bit_count(part - 1))
        first = F.when(F.bit_count(part) <= 1, slot).otherwise(first)
    near = (F.bit_count(x) <= distance) & (F.shiftrightunsigned(F.col("key"), 48).cast("int") == first)
    return a.join(shuffled(b), (F.col("at") == F.col("key")) & (F.col("u") > F.col("v")) & near).select("u", "v")


def near_duplicates(docs: DataFrame, distance: int = 4, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` for each row of ``docs``.

    component_id is the smallest id reachable over links between fingerprints; texts
    without words share the fingerprint zero and link like any other. Rows with a
    null id keep their fingerprint and get the component of its other rows, if any.
    Repeated rows stay; an empty table gives none; other columns are ignored.
    """
    found = _grouped(docs, distance, width, id_col, text_col)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


#: Stands for no id; larger than any id that a group could take its name from.
_NONE = (1 << 63) - 1


def _grouped(docs: DataFrame, distance: int, width: int, id_col: str, text_col: str) -> DataFrame:
    """``(doc_id, fp, part, component_id)``: ``part`` tells components apart that share their smallest id.

    The nodes of the graph are (smallest id, fingerprint), so the smallest node reachable
    has the smallest id reachable, and no group ever meets under one key.
    """
    fps = cut(with_fingerprints(docs, width, id_col, text_col))
    nodes = fps.groupBy("fp").agg(F.coalesce(F.min("doc_id"), F.lit(_NONE)).alias("least"), F.count("*").alias("n"))
    near = links(nodes.select("fp"), distance)
    name = lambda side: nodes.select(F.col("fp").alias(side), F.struct("least", "fp").alias(f"{side}_node"))
    edges = near.join(shuffled(name("u")), "u").join(shuffled(name("v")), "v").select(F.col("u_node").alias("u"), F.col("v_node").alias("v"))
    comp = components(edges).select(F.col("node.fp").alias("linked"), F.col("component").alias("root"))
    root = F.coalesce("root", F.struct("least", "fp"))
    named = nodes.join(shuffled(comp), nodes["fp"] == comp["linked"], "left").select("fp", "n", root.alias("root"))
    by_fp = named.select("fp", "n", F.col("root.fp").alias("part"), F.nullif(F.col("root.least"), F.lit(_NONE)).alias("component_id"))
    return join_small(fps, by_fp, "fp").select("doc_id", "fp", "part", "component_id")


def _unused(docs: DataFrame, *names: str) -> list[str]:
    """The names, made longer where ``docs`` has such a column."""
    taken = {c.lower() for c in docs.columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n += "_"
        out.append(n)
    return out


def keep_one(docs: DataFrame, distance: int = 4, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stand for their group: those whose id is the smallest of the component.

    Of rows of one component that share that id one stays, one with the smallest
    fingerprint; unrelated texts that share an id all stay. Rows with a null id stay
    only where no row of their group has an id, and then all do. An empty table stays empty.
    """
    found = cut(_grouped(docs, distance, width, id_col, text_col))
    stay = found.where(F.col("doc_id").eqNullSafe(F.col("component_id")))
    stays, print_, of = _unused(docs, "stays", "print", "of_print")
    key = F.col(f"`{id_col}`").cast("long")
    if found.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null").isEmpty():
        return docs.join(shuffled(stay.select(F.col("doc_id").alias(stays))), key == F.col(stays), "left_semi")
    named = stay.where("doc_id is not null").groupBy("part", "doc_id").agg(F.min("fp").alias(of)).select(F.col("doc_id").alias(stays), of)
    free = stay.where("doc_id is null").select(F.col("fp").alias(of)).distinct()
    rows = docs.withColumn(print_, F.udf(lambda t: fingerprint(t, width), "long")(F.col(f"`{text_col}`").cast("string")))
    one = rows.where(key.isNotNull()).join(shuffled(named), (key == F.col(stays)) & (F.col(print_) == F.col(of)), "left_semi").dropDuplicates([id_col, print_])
    return one.unionByName(rows.where(key.isNull()).join(shuffled(free), F.col(print_) == F.col(of), "left_semi")).drop(print_)
