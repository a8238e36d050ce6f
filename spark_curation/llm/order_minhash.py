"""Order MinHash fingerprints, in DataFrame expressions only.

K-mers are runs of words numbered by occurrence, so a word run that comes three times
is three elements. One hash deals the elements to bins and ranks them there (one
permutation split into bins in place of a permutation for each entry, which makes one
sort do for all entries); each bin keeps its smallest elements, puts them back into
text order and hashes that tuple. Two texts agree on a bin when the same elements were
smallest and stand in the same order, so moved passages count as edits, unlike in a
set sketch.

Elements travel as packed 63-bit integers, whose arrays Spark sorts as primitives.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Words in a k-mer, elements in a tuple, bits of the bin number (64 bins).
K, TUPLE, BIN_BITS = 3, 2, 6
#: Bits of a position (more words than a string can have) and of a rank within a bin.
POS, RANK = 31, 26
#: Scripts written without spaces; each of their characters is a word.
UNSPACED = "[\\u3040-\\u30ff\\u3400-\\u9fff\\uac00-\\ud7af]"

_mask = lambda bits: F.lit((1 << bits) - 1)


def _same(a: Column, i: Column, shift: int, value: Column) -> Column:
    return F.shiftright(F.get(a, i), shift) == value


def _elements(words: Column) -> Column:
    """Sorted packed (k-mer hash, position) of all k-mers; the whole sequence if there are fewer words."""
    n = F.size(words)
    at = lambda i, j: F.get(words, (i + j).cast("int"))
    whole = F.array(F.xxhash64(F.array_join(words, " ")).bitwiseAND(_mask(63 - POS)) * F.lit(1 << POS))
    pack = lambda i: (F.xxhash64(*[at(i, j) for j in range(K)]).bitwiseAND(_mask(63 - POS)) * F.lit(1 << POS)).bitwiseOR(i.cast("long"))
    runs = F.transform(F.sequence(F.lit(0), F.greatest(n - K, F.lit(0))), pack)
    return F.sort_array(F.when(n == 0, F.array().cast("array<bigint>")).when(n < K, whole).otherwise(runs))


def _occurrence(a: Column, v: Column, i: Column) -> Column:
    """How many equal k-mers stand before place ``i`` of the sorted array: the start of the run by binary steps back."""
    h = F.shiftright(v, POS)

    def step(acc: Column, b: Column) -> Column:
        return F.when((acc >= b) & _same(a, acc - b, POS, h), acc - b).otherwise(acc)

    start = F.aggregate(F.lit([1 << b for b in range(POS - 1, -1, -1)]).cast("array<int>"), i, step)
    return F.when((i > 0) & _same(a, i - 1, POS, h), i - start).otherwise(F.lit(0))


def _ranked(a: Column) -> Column:
    """Sorted packed (bin, rank, position) of the occurrence-numbered k-mers."""

    def one(v: Column, i: Column) -> Column:
        g = F.xxhash64(F.shiftright(v, POS), _occurrence(a, v, i))
        return g.bitwiseAND(F.lit(((1 << (BIN_BITS + RANK)) - 1) << POS)).bitwiseOR(v.bitwiseAND(_mask(POS)))

    return F.sort_array(F.transform(a, one))


def _smallest(a: Column) -> Column:
    """Sorted packed (bin, position, rank) of the smallest elements of each bin."""
    top = POS + RANK
    few = F.filter(a, lambda w, i: (i < TUPLE) | ~_same(a, i - TUPLE, top, F.shiftright(w, top)))
    rank = lambda w: F.shiftright(w, POS).bitwiseAND(_mask(RANK))
    swap = lambda w: (F.shiftright(w, top) * F.lit(1 << top)).bitwiseOR(w.bitwiseAND(_mask(POS)) * F.lit(1 << RANK)).bitwiseOR(rank(w))
    return F.sort_array(F.transform(few, swap))


def _tuples(a: Column) -> Column:
    """For each bin that has elements: its number above 32 bits of the hash of its ranks in text order."""
    top = POS + RANK

    def one(w: Column, i: Column) -> Column:
        of = F.shiftright(w, top)
        ranks = [F.when(_same(a, i + j, top, of), F.get(a, i + j).bitwiseAND(_mask(RANK))) for j in range(TUPLE)]
        first = (i == 0) | ~_same(a, i - 1, top, of)
        return F.when(first, (of * F.lit(1 << 32)).bitwiseOR(F.xxhash64(*ranks).bitwiseAND(_mask(32))))

    return F.filter(F.transform(a, one), lambda t: t.isNotNull())


def add_signature(df: DataFrame, text_col: str, into: str) -> DataFrame:
    """Adds the signature of ``text_col``: one long for each bin that has elements; none for a text without words.

    The steps are stacked projections over named columns, so that no step is
    worked out twice.
    """
    step = f"__{into}"
    split = F.split(F.col(text_col), f"\\s+|(?<={UNSPACED})|(?={UNSPACED})")
    keep = [c for c in df.columns if c != into]
    df = df.withColumn(step, F.array_remove(F.coalesce(split, F.array().cast("array<string>")), ""))
    for f in (_elements, _ranked, _smallest, _tuples):
        df = df.select(*keep, f(F.col(step)).alias(step))
    return df.withColumnRenamed(step, into)


def printed(sig: Column) -> Column:
    """A signature as text: two hex digits of the bin and four of its hash, for each bin that has elements."""
    short = lambda s: F.lpad(F.hex((F.shiftright(s, 32) * F.lit(1 << 16)).bitwiseOR(s.bitwiseAND(_mask(16)))), 6, "0")
    return F.lower(F.array_join(F.transform(sig, short), ""))


def likeness(a: Column, b: Column) -> Column:
    """0 to 1: the share of agreeing bins, brought from tuples back to single elements by the root."""
    bins = lambda s: F.transform(s, lambda x: F.shiftright(x, 32))
    every = F.size(F.array_union(bins(a), bins(b)))
    return F.when(every == 0, F.lit(1.0)).otherwise(F.pow(F.size(F.array_intersect(a, b)) / every, F.lit(1.0 / TUPLE)))


def _bounds(docs: DataFrame, per_bucket: int, most: int) -> list[int]:
    """Ids at which consecutive buckets of documents start; at most ``most`` numbers reach the driver."""
    n = docs.count()
    if n == 0:
        return []
    buckets = max(1, min(most, n // per_bucket))
    at = [i / buckets for i in range(buckets)]
    got = docs.agg(F.min("key"), F.percentile_approx("key", at, max(10_000, 10 * buckets))).first()
    return sorted({got[0], *got[1]})


def with_next(docs: DataFrame, carry: list[str], per_bucket: int = 1500, most: int = 100_000) -> DataFrame:
    """Adds ``next_<c>`` for each column of ``carry``, from the following row by id; the last row gets the first one's.

    Rows are dealt to buckets of consecutive ids, and the row that opens a bucket goes
    to the bucket before as well, so the order needs one shuffle and no global sort.
    Null ids come first; equal ids are ordered by the carried columns.
    """
    docs = docs.withColumn("key", F.coalesce("doc_id", F.lit(-(1 << 63))))
    bounds = _bounds(docs, per_bucket, most)
    if not bounds:
        return docs.select("doc_id", *carry, *[F.col(c).alias(f"next_{c}") for c in carry])
    last = len(bounds)
    edges = F.lit(bounds).cast("array<bigint>")
    steps = F.lit([1 << b for b in range(last.bit_length() - 1, -1, -1)]).cast("array<int>")
    find = lambda acc, s: F.when((acc + s < last) & (F.get(edges, acc + s) <= F.col("key")), acc + s).otherwise(acc)
    docs = docs.withColumn("bucket", F.aggregate(steps, F.lit(0), find))
    own = F.struct(F.col("bucket").alias("b"), F.lit(0).alias("late"))
    before = F.struct(F.pmod(F.col("bucket") - 1, F.lit(last)).alias("b"), F.lit(1).alias("late"))
    opens = F.get(edges, F.col("bucket")) == F.col("key")
    dealt = docs.select("doc_id", "key", *carry, F.explode(F.when(opens, F.array(own, before)).otherwise(F.array(own))).alias("to"))
    w = Window.partitionBy("to.b").orderBy("to.late", "key", *carry)
    led = dealt.select("doc_id", "to", *carry, *[F.lead(c).over(w).alias(f"next_{c}") for c in carry])
    return led.where("to.late = 0").select("doc_id", *carry, *[f"next_{c}" for c in carry])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprint of each text and of its edited text, and how like they are.

    The edited text has the last half (rounded down) of the code points replaced by
    the first as many of the next document's. A null text counts as empty; a text
    without words has the empty fingerprint and is wholly like another such text.
    Repeated rows and null ids stay; an empty table gives none.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    led = with_next(add_signature(rows, "text", "sig"), ["text", "sig"])
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = led.select("*", n.cast("long").alias("n_chars"), F.concat(F.left("text", n - half), F.left("next_text", half)).alias("edited"))
    both = add_signature(edited.drop("text", "next_text"), "edited", "edited_sig")
    return both.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        printed(F.col("sig")).alias("fingerprint"),
        printed(F.col("edited_sig")).alias("edited_fingerprint"),
        likeness(F.col("sig"), F.col("edited_sig")).alias("near_edited"),
        likeness(F.col("sig"), F.col("next_sig")).alias("near_next"),
    )
