"""Corpus deduplication by the share of n-grams that an earlier document owns."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words, ngrams, words
from spark_curation.io import cut, remove, shuffled, written

#: Words in a gram, and the share of owned grams that drops a document.
N, THRESHOLD = 13, 0.8
#: Words, or ids of lists, that a task holds as arrays at a time.
PIECE = 1 << 20


def exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, owner)`` for documents whose text an earlier one has."""
    key = F.sha2(F.coalesce(text_col, F.lit("")), 256)
    rows = docs.select(F.col(id_col).alias("id"), key.alias("key"))
    first = rows.groupBy("key").agg(F.min("id").alias("owner"))
    return rows.join(first, "key").where("id <> owner").select("id", "owner")


def grams(docs: DataFrame, n: int, id_col: str, text_col: str, by: list[str]) -> DataFrame:
    at = F.explode(F.transform(ngrams(words(F.col(text_col)), n), lambda g: F.xxhash64(g)))
    return docs.select(*by, F.col(id_col).alias("id"), at.alias("h"))


def ngram(docs: DataFrame, n: int = N, threshold: float = THRESHOLD, mode: str = "exact", id_col: str = "doc_id", text_col: str = "text", by: tuple[str, ...] = (), bits: int = 24) -> DataFrame:
    """``(by..., id, n_grams, n_owned, share)`` of documents that fall: at least ``threshold`` of their grams belong to an earlier id.

    A gram's owner is the smallest id that has it, of all documents. Documents with
    fewer words than a gram have no row. ``exact`` sends (gram, id, count), combined
    within each document first, to the gram and back; ``bloom`` probes a filter of
    ``bits`` bits for each (gram's bucket) of what smaller ids hold, see ``bloom``.
    """
    keys = [*by, "h"]
    own = grams(docs, n, id_col, text_col, list(by)).groupBy(*keys, "id").agg(F.count("*").alias("c"))
    if mode == "bloom":
        return bloom(own, list(by), threshold, bits)
    first = own.groupBy(*keys).agg(F.min("id").alias("owner"))
    scored = own.join(first, keys)
    out = scored.groupBy(*by, "id").agg(F.sum("c").alias("n_grams"), F.sum(F.when(F.col("owner") < F.col("id"), F.col("c")).otherwise(0)).alias("n_owned"))
    return out.withColumn("share", F.col("n_owned") / F.col("n_grams")).where(F.col("share") >= threshold)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def _blobs(n: int, bits: int):
    """Grams of ``(id, hashes of words)`` rows by the first ``bits`` of their hash: its other seven bytes, and steps from id to id."""

    def piece(ids: np.ndarray, sizes: np.ndarray, ws: np.ndarray) -> pa.RecordBatch | None:
        of = np.maximum(sizes - (n - 1), 0)
        if not of.any():
            return None
        total = len(ws) - (n - 1)
        h = np.zeros(total, np.uint64)
        for j in range(n):
            h = _mix(h ^ ws[j : j + total])
        h = h[np.arange(n, total + n) <= np.repeat(np.cumsum(sizes), sizes)[:total]]
        doc = np.repeat(ids, of)
        bucket = (h >> np.uint64(64 - bits)).astype(np.uint16 if bits <= 16 else np.int64)
        order = np.argsort(bucket, kind="stable") if (ids[1:] >= ids[:-1]).all() else np.lexsort((doc, bucket))
        bucket, h, doc = bucket[order], h[order], doc[order]
        at = np.append(np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])), len(h))
        low = np.ascontiguousarray(h.view(np.uint8).reshape(-1, 8)[:, :7])
        step = np.append(0, doc[1:] - doc[:-1])
        step[at[:-1]] = 0
        steps = []
        for i, j in zip(at[:-1], at[1:], strict=True):
            s = step[i:j].view(np.uint64)
            steps.append(s.astype(np.min_scalar_type(s.max())).tobytes())
        rests = [low[i:j].tobytes() for i, j in zip(at[:-1], at[1:], strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(bucket[at[:-1]].astype(np.int64)), pa.array(doc[at[:-1]]), pa.array(rests, pa.binary()), pa.array(steps, pa.binary())], ["bucket", "id", "rest", "steps"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, off, ws = b.column(0).to_numpy(), b.column(1).offsets.to_numpy().astype(np.int64), b.column(1).values.to_numpy().view(np.uint64)
            i = 0
            while i < len(ids):
                j = max(i + 1, int(np.searchsorted(off, off[i] + PIECE, "right")) - 1)
                if (out := piece(ids[i:j], np.diff(off[i : j + 1]), ws[off[i] : off[j]])) is not None:
                    yield out
                i = j

    return run


def _combined(ids: np.ndarray, counts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, ...]:
    """``(keys, ids, counts, sizes)``: equal lists of ids (one after the other, ``sizes`` long) as one, their counts added up."""
    begin = np.cumsum(sizes) - sizes
    place = np.arange(len(ids)) - np.repeat(begin, sizes)
    keys = np.add.reduceat(_mix(_mix(ids.view(np.uint64)) + _mix(place.astype(np.uint64) + np.uint64(1))), begin) if len(ids) else np.empty(0, np.uint64)
    some, first, which = np.unique(keys, return_index=True, return_inverse=True)
    size = sizes[first]
    start = np.cumsum(size) - size
    take = np.repeat(begin[first] - start, size) + np.arange(size.sum())
    if (sizes != size[which]).any() or (ids[take][(to := np.repeat(start[which], sizes) + place)] != ids).any():
        return keys, ids, counts, sizes  # two lists of one key: each stays as it is
    total = np.zeros(len(take), np.int64)
    np.add.at(total, to, counts)
    return some, ids[take], total, size


class _Lists:
    """Lists of ids with counts, combined whenever ``PIECE`` ids have come; what is given back may hold a list more than once."""

    def __init__(self):
        self.held, self.size = [], 0

    def add(self, ids: np.ndarray, counts: np.ndarray, sizes: np.ndarray) -> None:
        self.held.append((ids, counts, sizes))
        self.size += len(ids)

    def full(self) -> bool:
        return self.size >= PIECE

    def take(self) -> tuple[np.ndarray, ...]:
        out = _combined(*(np.concatenate(c) for c in zip(*self.held, strict=True)))
        self.held, self.size = [], 0
        return out


def _sharers(h: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, ...]:
    """``(ids, counts, sizes)``: for each gram that more ids than one have, these in order and how often each has it."""
    order = np.argsort(h)
    same = h[order][1:] == h[order][:-1]
    order = order[np.append(same, False) | np.append(False, same)]
    h, ids = h[order], ids[order]
    order = np.lexsort((ids, h))
    h, ids = h[order], ids[order]
    at = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (ids[1:] != ids[:-1]))[: len(h)])
    counts = np.diff(np.append(at, len(h)))
    h, ids = h[at], ids[at]
    sizes = np.diff(np.append(np.flatnonzero(np.append(True, h[1:] != h[:-1])[: len(h)]), len(h)))
    several = np.repeat(sizes > 1, sizes)
    return ids[several], counts[several], sizes[sizes > 1]


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``(key, ids, counts)``: the ids that share grams, from blobs sorted by bucket."""
    lists, held, at = _Lists(), [], None

    def rows() -> pa.RecordBatch:
        keys, ids, counts, sizes = lists.take()
        off = pa.array(np.append(0, np.cumsum(sizes)), pa.int32())
        return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.ListArray.from_arrays(off, pa.array(ids)), pa.ListArray.from_arrays(off, pa.array(counts))], ["key", "ids", "counts"])

    for b in batches:
        for bucket, first, rest, steps in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if bucket != at and held:
                lists.add(*_sharers(*(np.concatenate(c) for c in zip(*held, strict=True))))
                held = []
                if lists.full():
                    yield rows()
            at = bucket
            h = np.zeros((len(rest) // 7, 8), np.uint8)
            h[:, :7] = np.frombuffer(rest, np.uint8).reshape(-1, 7)
            step = np.frombuffer(steps, f"u{len(steps) // len(h)}").astype(np.uint64).view(np.int64)
            held.append((h.view(np.uint64)[:, 0], first + np.cumsum(step)))
    if held:
        lists.add(*_sharers(*(np.concatenate(c) for c in zip(*held, strict=True))))
    if lists.held:
        yield rows()


def _members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``(h, id, c)``: a row for each id of each list, lists that came from several tasks combined."""
    lists, n = _Lists(), TaskContext.get().partitionId() << 40

    def rows() -> pa.RecordBatch:
        nonlocal n
        _, ids, counts, sizes = lists.take()
        of = np.repeat(np.arange(n, n + len(sizes)), sizes)
        n += len(sizes)
        return pa.RecordBatch.from_arrays([pa.array(of), pa.array(ids), pa.array(counts)], ["h", "id", "c"])

    for b in batches:
        off = b.column(1).offsets.to_numpy().astype(np.int64)
        lists.add(*(b.column(i).flatten().to_numpy() for i in (1, 2)), np.diff(off))
        if lists.full():
            yield rows()
    if lists.held:
        yield rows()


def shared_grams(docs: DataFrame, n: int = N, id_col: str = "doc_id", text_col: str = "text", by: tuple[str, ...] = ()) -> DataFrame:
    """``(h, id, c)``: what ids share, from all grams: ``c`` places of ``id`` have grams that exactly the ids under ``h`` have.

    Grams that one id alone has are left out, and grams with the same ids are one ``h``, so
    this is small beside the text. Each gram moves once, as seven bytes of its hash under
    the bits that deal it out, and a step from the id before. All of a gram's ids meet in
    one task, some tens of bytes for each. Ids are whole numbers; rows with a null id are left out.
    Rows of different values of ``by`` share nothing; their ids must differ.
    """
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bits = max(8, (8 * parts - 1).bit_length())
    rows = docs.where(F.col(f"`{id_col}`").isNotNull()).select(F.col(f"`{id_col}`").cast("long").alias("id"), F.transform(words(F.col(f"`{text_col}`")), lambda w: F.xxhash64(w, *by)).alias("ws"))
    blobs = rows.mapInArrow(_blobs(n, bits), "bucket long, id long, rest binary, steps binary")
    lists = blobs.repartitionById(parts, F.shiftright(F.col("bucket") * parts, bits).cast("int")).sortWithinPartitions("bucket").mapInArrow(_shared, "key long, ids array<long>, counts array<long>")
    return lists.repartition(parts, "key").mapInArrow(_members, "h long, id long, c long")


def fallen(docs: DataFrame, groups: list[str], by: str, n: int = N, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(by, id)`` of what ``ngram`` drops within each of ``groups``, the values of ``by``: each gram moves once, see ``shared_grams``.

    An id goes with its group as one number; where ids leave no room for that, ``ngram`` itself is run.
    """
    k = len(groups)
    ends = docs.agg(F.min(id_col), F.max(id_col)).first()
    if any(x is not None and abs(x) >= (1 << 62) // k for x in ends):
        return ngram(docs, n, threshold, id_col=id_col, text_col=text_col, by=(by,)).select(by, "id")
    at = F.element_at(F.create_map(*[F.lit(x) for i, g in enumerate(groups) for x in (g, i)]), F.col(by))
    rows = docs.select((F.col(id_col).cast("long") * k + at).alias("id"), F.col(text_col).alias("text"), at.alias("g")).where("id is not null")
    own = written(shared_grams(rows, n, "id", "text", ("g",)), "shared")[0]
    first = own.groupBy("h").agg(F.min("id").alias("owner"))
    owned = own.join(shuffled(first), "h").where("owner < id").groupBy("id").agg(F.sum("c").alias("owned"))
    size = rows.select("id", F.greatest(count_words(F.col("text")) - (n - 1), F.lit(0)).alias("n")).groupBy("id").agg(F.sum("n").alias("n"))
    fell = owned.join(shuffled(size), "id").where(F.col("owned") / F.col("n") >= threshold)
    of = F.element_at(F.array(*map(F.lit, groups)), (F.pmod("id", F.lit(k)) + 1).cast("int"))
    return fell.select(of.alias(by), F.expr(f"(id - pmod(id, {k})) div {k}").alias("id"))


def survivors_only(docs: DataFrame, n: int = N, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text", most: int = 50) -> DataFrame:
    """``(id)`` of documents that fall when only documents that stay own grams, as if ids came one by one.

    Whether a document falls depends on earlier ids alone, so two bounds close in on the
    one answer: with all possible owners too many fall, with the sure ones too few. Each
    round counts what ids share, see ``shared_grams``; the grams themselves move once.
    """
    own, at = written(shared_grams(docs, n, id_col, text_col), "shared")
    many = F.greatest(count_words(F.col(f"`{text_col}`")) - (n - 1), F.lit(0))
    size = cut(docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), many.alias("n")).where("id is not null").groupBy("id").agg(F.sum("n").alias("n")))

    def falls(owners: DataFrame) -> DataFrame:
        first = owners.groupBy("h").agg(F.min("id").alias("owner"))
        owned = own.join(shuffled(first), "h").where("owner < id").groupBy("id").agg(F.sum("c").alias("owned"))
        return cut(owned.join(shuffled(size), "id").where(F.col("owned") >= F.col("n") * threshold).select("id"))

    try:
        most_fall = falls(own)
        for _ in range(most):
            least_fall = falls(own.join(shuffled(most_fall), "id", "left_anti"))
            if least_fall.count() == most_fall.count():
                return least_fall
            most_fall = falls(own.join(shuffled(least_fall), "id", "left_anti"))
            if least_fall.count() == most_fall.count():
                return least_fall
    finally:
        remove(docs.sparkSession, at)
    raise RuntimeError("owners did not settle")


def bloom(own: DataFrame, by: list[str], threshold: float, bits: int, waves: int = 4) -> DataFrame:
    """The same with Bloom bitmaps: ids come in waves, each probes the bitmaps of the waves before it.

    Bitmaps are cut into buckets of 32,768 bits and joined by bucket, so none is ever
    whole in one place. False positives can only raise a share. Owners within a wave
    are found exactly.
    """
    per = 1 << 15
    slot = F.pmod(F.xxhash64("h", *by), F.lit(1 << bits))
    edges = own.agg(F.percentile_approx("id", [i / waves for i in range(1, waves)])).first()[0] or []
    wave = F.lit(0)
    for e in edges:
        wave = wave + F.when(F.col("id") > e, 1).otherwise(0)
    rows = own.withColumns({"slot": slot, "wave": wave}).withColumns({"bucket": F.floor(F.col("slot") / per), "bit": (F.col("slot") % per).cast("long")})
    maps = rows.groupBy("bucket", "wave").agg(F.bitmap_construct_agg("bit").alias("map"))
    later = maps.select("bucket", "map", F.explode(F.sequence(F.col("wave") + 1, F.lit(waves))).alias("wave")).where(F.col("wave") < waves)
    merged = later.groupBy("bucket", "wave").agg(F.bitmap_or_agg("map").alias("map"))
    byte = F.conv(F.hex(F.substring("map", (F.floor(F.col("bit") / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    hit = F.coalesce(F.getbit(byte, (F.col("bit") % 8).cast("int")) == 1, F.lit(False))
    probed = rows.join(merged, ["bucket", "wave"], "left").withColumn("before", hit).drop("map")
    first = rows.groupBy(*by, "h", "wave").agg(F.min("id").alias("owner"))
    scored = probed.join(first, [*by, "h", "wave"])
    mine = F.when(F.col("before") | (F.col("owner") < F.col("id")), F.col("c")).otherwise(0)
    out = scored.groupBy(*by, "id").agg(F.sum("c").alias("n_grams"), F.sum(mine).alias("n_owned"))
    return out.withColumn("share", F.col("n_owned") / F.col("n_grams")).where(F.col("share") >= threshold)


def survivors(docs: DataFrame, dropped: DataFrame, id_col: str = "doc_id") -> DataFrame:
    return docs.join(dropped.select(F.col("id").alias(id_col)), id_col, "left_anti")
