"""Benchmark decontamination: short test items inside long documents, by MinHash signatures in partitions of item sizes.

The signature of an item is its smallest shingle hashes (a bottom MinHash), as deep as
its size needs: a document that contains at least the threshold of an item's shingles
misses at most the rest, so of one hash more than that rest one must be the
document's own. Items are parted by size in classes that double; each class has a
bound, the largest hash that the signature of any of its items reaches. A document's
signature for a class is what it has below the class's bound, so a long document is
signed as finely as items of that size need and no finer. Documents whose signature
meets an item's are verified by exact shingle containment.

Nothing is missed: depths and bounds make the search exact, not a matter of recall.
A benchmark of a proven size travels to every worker as an index; a larger one is a
table that document signatures are joined to.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.io import cut
from spark_curation.llm.shingling import shingle_hashes, shingles, word_hashes, words

#: Words in a shingle, share of an item's shingles that makes a hit, most characters of items that travel to every worker.
WIDTH, THRESHOLD, HELD = 5, 0.8, 16_000_000
#: Sizes of classes are powers of two below this one.
_CLASSES = 64


def size_class(n: int) -> int:
    """Which of the doubling classes ``n`` shingles fall into."""
    return n.bit_length()


def depth(n: int, threshold: float) -> int:
    """How many smallest hashes of ``n`` a document with the threshold of them cannot miss all of."""
    return int((1 - threshold) * n + 1e-9) + 1


def signature(ws: list[bytes], width: int, threshold: float) -> tuple[int, int, np.ndarray]:
    """(shingle width, size class, smallest hashes in order) of an item; one shorter than a shingle is a shingle of its own."""
    w = min(width, len(ws))
    h = np.unique(shingle_hashes(word_hashes(ws), w) >> np.uint64(1))
    return w, size_class(len(h)), h[: depth(len(h), threshold)]


class Partition:
    """Signatures of the items of one shingle width and size class."""

    def __init__(self, signed: dict[int, list[int]]):
        self.signed = signed
        self.keys = np.array(sorted(signed), np.uint64)
        self.bound = self.keys[-1]
        self.bits = np.zeros(1 << 18, bool)
        self.bits[(self.keys >> np.uint64(45)).astype(np.int64)] = True

    def meet(self, h: np.ndarray) -> set[int]:
        """Items whose signature meets that of a document with the hashes ``h``."""
        some = h[self.bits[(h >> np.uint64(45)).astype(np.int64)]]
        some = some[some <= self.bound]
        if not len(some):
            return set()
        at = np.searchsorted(self.keys, some)
        return {key for x in set(some[self.keys[at] == some].tolist()) for key in self.signed[x]}


class Index:
    """Items and their signatures by width and class, ready to probe with documents."""

    def __init__(self, items: list[tuple[int | None, str]], width: int = WIDTH, threshold: float = THRESHOLD):
        self.threshold = threshold
        self.ids = [key for key, _ in items]
        #: By place of an item, its shingles.
        self.items: dict[int, frozenset[bytes]] = {}
        signed: dict[tuple[int, int], dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
        for key, (_, text) in enumerate(items):
            if ws := words(text):
                w, of, few = signature(ws, width, threshold)
                self.items[key] = frozenset(shingles(ws, w))
                for h in few.tolist():
                    signed[w, of][h].append(key)
        self.parts: dict[int, list[Partition]] = defaultdict(list)
        for (w, _), s in sorted(signed.items()):
            self.parts[w].append(Partition(dict(s)))

    def hits(self, text: str | None) -> list[tuple[int | None, int, int]]:
        """(item, its shingles, how many of them the text has) for the items that the text contains."""
        out = []
        ws = words(text)
        hashed = word_hashes(ws)
        for w, parts in self.parts.items():
            h = shingle_hashes(hashed, w) >> np.uint64(1)
            wanted = set().union(*(p.meet(h) for p in parts)) if len(h) else set()
            if wanted:
                have = set(shingles(ws, w))
                out += [(self.ids[k], len(self.items[k]), n) for k in sorted(wanted) if (n := len(self.items[k] & have)) >= self.threshold * len(self.items[k]) - 1e-9]
        return out


def _items(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    return benchmark.select(F.col(f"`{id_col}`").cast("long").alias("item_id"), F.col(f"`{text_col}`").cast("string").alias("text")).where("text is not null").distinct()


def _held(items: DataFrame, held: int):
    """The items as a broadcast list where they are no longer than ``held`` together (and 64 characters each), else None."""
    if (items.agg(F.sum(F.length("text") + 64)).first()[0] or 0) > held:
        return None
    rows = sorted(((r["item_id"], r["text"]) for r in items.collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1]))
    return items.sparkSession.sparkContext.broadcast(rows)


def _joined(rows: DataFrame, items: DataFrame, width: int, threshold: float) -> DataFrame:
    """Hits of ``(key, text)`` rows as ``(key, item_id, n_item, n_shared)`` by joins of signatures, for any number of items.

    Equal keys are taken to have equal texts; each has its hits once.
    """
    spark = rows.sparkSession
    named = cut(items.withColumn("item", F.md5(F.concat(F.coalesce(F.col("item_id").cast("string"), F.lit("")), F.lit("|"), F.col("text")))))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for item, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if ws := words(text):
                    w, of, few = signature(ws, width, threshold)
                    out += [(item, w * _CLASSES + of, h) for h in few.tolist()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*out, strict=True)) or [[]] * 3, (pa.string(), pa.int32(), pa.int64()), strict=True)], ["item", "part", "h"])

    signed = cut(named.select("item", "text").mapInArrow(sign, "item string, part int, h long"))
    bounds = {r["part"]: r["bound"] for r in signed.groupBy("part").agg(F.max("h").alias("bound")).collect()}  # a row for each width and class

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for key, text in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                hashed = word_hashes(words(text))
                by_width = {w: np.unique(shingle_hashes(hashed, w) >> np.uint64(1)).astype(np.int64) for w in {p // _CLASSES for p in bounds}}
                few = [(p, h[: np.searchsorted(h, bound, "right")]) for p, bound in bounds.items() for h in [by_width[p // _CLASSES]]]
                if n := sum(len(h) for _, h in few):
                    parts = np.concatenate([np.full(len(h), p, np.int32) for p, h in few])
                    yield pa.RecordBatch.from_arrays([pa.repeat(key, n), pa.array(parts), pa.array(np.concatenate([h for _, h in few]))], ["key", "part", "h"])

    texts = rows.groupBy("key").agg(F.min("text").alias("text"))
    pairs = cut(texts.mapInArrow(probe, "key string, part int, h long").join(signed, ["part", "h"]).select("key", "item").distinct())

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, ws, have = None, [], {}
        for b in batches:
            out = []
            for key, item, item_id, text in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if item is None:
                    at, ws, have = key, words(text), {}
                    continue
                mine = words(text)
                w = min(width, len(mine))
                if at == key and w not in have:
                    have[w] = set(shingles(ws, w))
                wanted = set(shingles(mine, w))
                n = len(wanted & have[w])
                if n >= threshold * len(wanted) - 1e-9:
                    out.append((key, item_id, len(wanted), n))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*out, strict=True)) or [[]] * 4, (pa.string(), pa.int64(), pa.int64(), pa.int64()), strict=True)], ["key", "item_id", "n_item", "n_shared"])

    none = F.lit(None)
    own = texts.join(pairs.select("key").distinct(), "key").select("key", none.cast("string").alias("item"), none.cast("long").alias("item_id"), "text")
    theirs = pairs.join(named, "item").select("key", "item", "item_id", "text")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    both = own.union(theirs).repartition(n, "key").sortWithinPartitions("key", F.col("item").asc_nulls_first())
    return both.mapInArrow(verify, "key string, item_id long, n_item long, n_shared long")


def search(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", held: int = HELD, width: int = WIDTH, threshold: float = THRESHOLD) -> DataFrame:
    """``(doc_id, item_id, n_item, n_shared, containment)``: each row of ``docs`` with each item that it contains.

    Items without words match nothing; one shorter than a shingle must stand whole.
    Null texts contain nothing. Rows that repeat in ``docs`` give repeated hits;
    items that share an id are each searched, equal rows of the benchmark once. Items
    with a null id are left out here, as no row can name them; ``keep_clean`` has them.
    Empty tables give no hits.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    items = _items(benchmark).where("item_id is not null")
    if (known := _held(items, held)) is not None:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = Index(known.value, width, threshold)
            for b in batches:
                found = [(k.as_py(), *h) for k, t in zip(*b.columns, strict=True) for h in index.hits(t.as_py())]
                columns = list(zip(*found, strict=True)) or [[]] * 4
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["doc_id", "item_id", "n_item", "n_shared"])

        out = rows.mapInArrow(run, "doc_id long, item_id long, n_item long, n_shared long")
    else:
        keyed = rows.where("text is not null").withColumn("key", F.md5("text"))
        out = keyed.select("doc_id", "key").join(_joined(keyed, items, width, threshold), "key").select("doc_id", "item_id", "n_item", "n_shared")
    return out.withColumn("containment", F.col("n_shared") / F.col("n_item"))


def keep_clean(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", held: int = HELD, width: int = WIDTH, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that contain no benchmark item, with an id or without; all columns as they were.

    Rows with a null text and repeated rows stay; an empty table stays empty, and an empty benchmark keeps all.
    """
    items = _items(benchmark)
    if (known := _held(items, held)) is not None:
        at = docs.columns.index(text_col)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = Index(known.value, width, threshold)
            for b in batches:
                yield b.filter(pa.array([not index.hits(t.as_py()) for t in b.column(at)], pa.bool_()))

        return docs.mapInArrow(run, docs.schema)
    key = F.md5(F.col(f"`{text_col}`").cast("string"))
    rows = docs.select(key.alias("key"), F.col(f"`{text_col}`").cast("string").alias("text")).where("text is not null")
    dirty = _joined(rows, items, width, threshold).select(F.col("key").alias("dirty_key")).distinct()
    return docs.join(dirty, key == dirty["dirty_key"], "left_anti")


#: The same search by exact containment alone, for DuckDB (items of five words and more).
ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
s AS (SELECT DISTINCT item_id, array_to_string(w[i:i+4], ' ') AS s FROM (SELECT item_id, w, unnest(range(1, len(w) - 3)) AS i FROM b)),
n AS (SELECT item_id, count(*) AS n_item FROM s GROUP BY 1),
d AS (SELECT DISTINCT doc_id, array_to_string(w[i:i+4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w)),
h AS (SELECT doc_id, item_id, count(*) AS n_shared FROM d JOIN s USING (s) GROUP BY 1, 2)
SELECT doc_id, item_id, CAST(n_item AS BIGINT) AS n_item, CAST(n_shared AS BIGINT) AS n_shared, n_shared / n_item AS containment
FROM h JOIN n USING (item_id) WHERE n_shared >= 0.8 * n_item"""
