"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or nothing on each text. Votes are counted by
pattern over all documents (a table bounded by the labellers, not by the data);
expectation-maximisation over the counts estimates how accurate each labeller is and
gives every pattern a posterior. A linear scorer over hashed word endings and votes
is then trained on the posteriors and scores every document. It learns from a bounded
number of different texts of each pattern, those of the smallest text hashes, weighed
by how many rows the pattern has; so no pattern goes unseen, and neither other columns
nor the layout of the table change what is drawn.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh3_64_intdigest

from spark_curation.io import cut

#: Buckets of the hashed scorer, and texts of each vote pattern that it is trained on at most.
BUCKETS, SAMPLE = 4096, 64
#: The least score that keeps a document; below one half, since dropping a good text costs more than keeping a bad one.
KEEP = 0.35
LABELLERS = ("symbols", "shouting", "pipes", "runs", "variety", "sentences", "letters", "wordsize")
#: The first labellers are alarms: on a good text they go off with this chance at the most. Without such a
#: bound the model takes a lone alarm, which all others outvote, for noise.
ALARMS, FALSE_ALARM = 5, 5e-4
_SYMBOLS = re.compile(r"[^\w\s.,;:!?)\]}\"'»”’…-]{2,}(?=\s|$)|[!?]{2,}(?=\s|$)")
_ENDED = re.compile(r"[.!?…。！？][\"'»”’)]*(?=\s|$)")
_RUN = re.compile(r"(?<!\S)(\S+)(?=\s+\1(?!\S))")


def _vote(bad: bool, good: bool) -> str:
    return "0" if bad else "1" if good else "-"


def votes(text: str | None) -> str:
    """One character for each labeller: 1 good, 0 bad, - for no vote."""
    text = text or ""
    words = text.split()
    n = len(words)
    if not n:
        return "0" + "-" * (len(LABELLERS) - 1)
    marked = len(_SYMBOLS.findall(text)) / n
    shouted = sum(map(str.isupper, words)) / n
    pipes = text.count(" | ")
    runs = sum(map(str.__eq__, words, words[1:])) / n
    variety = len(set(words)) / n
    ended = len(_ENDED.findall(text))
    letters = sum(len(w) for w in words if w[0].isalpha() or w[-1].isalpha()) / sum(map(len, words))
    size = len(text) / n
    return "".join(
        (
            _vote(marked > 0.3, marked < 0.05),
            _vote(shouted > 0.3 and n >= 3, shouted < 0.1),
            _vote(pipes >= 3 and pipes > 0.05 * n, pipes == 0),
            _vote(runs > 0.3, runs < 0.05),
            _vote(n >= 40 and variety < 0.15, n >= 10 and variety > 0.3 or n >= 500 and variety > 0.2),
            _vote(n >= 40 and ended == 0, ended > n / 60),
            _vote(letters < 0.5, letters > 0.8),
            _vote(size < 2.5 or size > 25, 3.5 < size < 12),
        )
    )


def fit_labellers(counts: dict[str, int], rounds: int = 60) -> tuple[dict[str, float], np.ndarray]:
    """Posterior chance of good quality for each vote pattern, and each labeller's chance of a
    yes vote on good and on bad texts, by expectation-maximisation from the votes' majority."""
    patterns = sorted(counts)
    if not patterns:
        return {}, np.full((len(LABELLERS), 2), 0.5)
    n = np.array([counts[p] for p in patterns], float)
    yes, no = (np.array([[c == v for c in p] for p in patterns], float) for v in "10")
    post = np.where(no.sum(1) > 0, 0.1, 0.9)  # a bad vote is meant as an alarm
    for _ in range(rounds):
        good, bad = n * post, n * (1 - post)
        rate = [(1 + yes.T @ w * 1.0) / (2 + (yes + no).T @ w) for w in (good, bad)]
        rate = [np.clip(r, 5e-4, 1 - 5e-4) for r in rate]
        rate[0][:ALARMS] = np.maximum(rate[0][:ALARMS], 1 - FALSE_ALARM)
        rate[1] = np.minimum(rate[1], rate[0])  # no labeller is taken to mean the opposite
        prior = np.clip((8 + good.sum()) / (10 + n.sum()), 0.05, 0.95)
        side = [np.log(p) + yes @ np.log(r) + no @ np.log(1 - r) for p, r in ((prior, rate[0]), (1 - prior, rate[1]))]
        post = 1 / (1 + np.exp(np.clip(side[1] - side[0], -50, 50)))
    return dict(zip(patterns, post.tolist(), strict=True)), np.array(rate).T


def features(text: str | None, pattern: str) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and values: shares of hashed word endings, and the votes."""
    raw = (text or "").encode("utf-8", "surrogatepass").split()
    ends = Counter([w[-3:] for w in raw])
    idx = [zlib.crc32(k) % BUCKETS for k in ends]
    val = [v / len(raw) for v in ends.values()]
    shown = [zlib.crc32(f"{name}={c}".encode()) % BUCKETS for name, c in zip(LABELLERS, pattern, strict=True)]
    return np.array(idx + shown, np.int64), np.array(val + [0.5] * len(shown))


def fit_scorer(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, n: np.ndarray, epochs: int = 60, rate: float = 1.0, ridge: float = 1e-4) -> np.ndarray:
    """Weights of the hashed scorer (the last is the bias): logistic regression of features on posteriors ``y`` of rows that stand for ``n`` each, classes weighed alike."""
    w = np.zeros(BUCKETS + 1)
    if not rows:
        return w
    n = n / n.sum()
    share = np.clip([(n * (1 - y)).sum(), (n * y).sum()], 0.02, 1)
    weight = n * (y / share[1] + (1 - y) / share[0])
    size = np.array([len(i) for i, _ in rows])
    at, idx, val = np.repeat(np.arange(len(rows)), size), np.concatenate([i for i, _ in rows]), np.concatenate([v for _, v in rows])
    seen = np.zeros(BUCKETS + 1)
    for _ in range(epochs):
        z = np.bincount(at, w[idx] * val, len(rows)) + w[-1]
        err = weight * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y)
        grad = np.append(np.bincount(idx, err[at] * val, BUCKETS), err.sum()) + ridge * w
        seen += grad**2
        w -= rate * grad / np.sqrt(seen + 1e-12)
    return w


def score(text: str | None, pattern: str, w: np.ndarray) -> float:
    idx, val = features(text, pattern)
    return float(1 / (1 + np.exp(-np.clip((w[idx] * val).sum() + w[-1], -30, 30))))


def _survey(sample: int):
    """For a partition: how many rows each pattern has, and the features of its texts of the smallest hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n: Counter[str] = Counter()
        drawn: dict[str, dict[int, tuple[np.ndarray, np.ndarray]]] = {}
        bound: dict[str, int] = {}
        for b in batches:
            for t in b.column(0):
                text = t.as_py()
                p = votes(text)
                n[p] += 1
                h = xxh3_64_intdigest((text or "").encode("utf-8", "surrogatepass")) >> 1
                few = drawn.setdefault(p, {})
                if h in few or h > bound.get(p, 1 << 63):
                    continue
                few[h] = features(text, p)
                if len(few) >= 2 * sample:
                    bound[p] = sorted(few)[sample - 1]
                    drawn[p] = {k: v for k, v in few.items() if k <= bound[p]}
        rows = [(p, k, None, None, None) for p, k in n.items()]
        rows += [(p, None, h, *few[h]) for p, few in drawn.items() for h in sorted(few)[:sample]]
        columns = list(zip(*rows, strict=True)) or [[]] * 5
        kinds = (pa.string(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.float64()))
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["votes", "n", "h", "idx", "val"])

    return run


def train(docs: DataFrame, sample: int = SAMPLE, text_col: str = "text") -> tuple[dict[str, float], np.ndarray, np.ndarray]:
    """(posterior by vote pattern, labeller rates, scorer weights) for the texts of ``docs``.

    Votes are counted over every row. Of each pattern, the ``sample`` different texts
    of the smallest hashes train the scorer, as features of bounded size; that is the
    only bounded part. They depend on the set of texts alone.
    """
    surveyed = docs.select(F.col(f"`{text_col}`").cast("string").alias("text")).mapInArrow(_survey(sample), "votes string, n long, h long, idx array<long>, val array<double>")
    surveyed = cut(surveyed)
    counts = {r["votes"]: r["n"] for r in surveyed.where("n is not null").groupBy("votes").agg(F.sum("n").alias("n")).collect()}
    post, rates = fit_labellers(counts)
    first = lambda df, *by: df.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("h"))).where(F.col("r") <= sample).drop("r")
    texts = surveyed.where("h is not null").groupBy("votes", "h").agg(F.first("idx").alias("idx"), F.first("val").alias("val")).withColumn("part", F.pmod("h", F.lit(64)))
    drawn = sorted(first(first(texts, "votes", "part"), "votes").select("votes", "h", "idx", "val").collect())
    of = Counter(r["votes"] for r in drawn)
    rows = [(np.array(r["idx"], np.int64), np.array(r["val"])) for r in drawn]
    y, n = (np.array([f(r["votes"]) for r in drawn]) for f in (post.get, lambda p: counts[p] / of[p]))
    return post, rates, fit_scorer(rows, y, n)


def classify(docs: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, votes, posterior, score, keep)`` for every row.

    ``keep`` is a score of ``KEEP`` or more. A null or empty text has one bad vote and
    is scored like any other; equal texts get equal scores, whatever else the table
    holds in its columns. Repeated rows and null ids stay, an empty table gives none.
    """
    post, _, w = train(docs, sample, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t.as_py() for t in b.column(1)]
            cast = [votes(t) for t in texts]
            scores = [score(t, p, w) for t, p in zip(texts, cast, strict=True)]
            columns = [b.column(0), pa.array(cast, pa.string()), pa.array([post.get(p) for p in cast], pa.float64()), pa.array(scores, pa.float64()), pa.array([s >= KEEP for s in scores], pa.bool_())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "votes", "posterior", "score", "keep"])

    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, votes string, posterior double, score double, keep boolean")


def keep_good(docs: DataFrame, sample: int = SAMPLE, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the classifier keeps, all columns as they were.

    Null and empty texts are judged like others; repeated rows stay or go together; an empty table stays empty.
    """
    _, _, w = train(docs, sample, text_col)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t.as_py() for t in b.column(at)]
            yield b.filter(pa.array([score(t, votes(t), w) >= KEEP for t in texts], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
