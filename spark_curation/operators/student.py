"""The student: verdicts and line removals from lines alone, trained on composed targets in two stages.

A softmax over page features gives the verdict, two logistics over line features what
extraction and what an edit removes; line features include the verdict's probabilities,
so that weighing decisions five times shifts all. One summed loss is minimised; each
step takes a batch of the rows by their hash, sums gradients of the partitions and moves
weights of fixed size.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import islice
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.io import cut
from spark_curation.operators.render import MAX_ANSWER

VERDICTS = ("keep", "delete", "edit", "rewrite")
PAGE, LINE, HASH = 12, 14, 64
_TOP = PAGE + 1


def line_features(lines: list[str]) -> np.ndarray:
    """Shape, place and hashed words of each line; no markup."""
    n = len(lines)
    x = np.zeros((n, LINE + HASH))
    seen: set[str] = set()
    for i, t in enumerate(lines):
        ws = t.split()
        x[i, :LINE] = (
            1, i < 1, i < 4, i < 8, n - i <= 1, n - i <= 3, len(ws) < 4, 4 <= len(ws) < 12, len(ws) >= 30, t[-1:] in ".!?",
            "©" in t or "·" in t, t in seen, sum(c.isdigit() for c in t) > 0.2 * len(t), t.isupper(),
        )
        seen.add(t)
        for w in ws:
            x[i, LINE + crc32(w.lower().encode()) % HASH] += min(0.5, 4 / len(ws))
    return x


def page_features(lines: list[str]) -> np.ndarray:
    text = "\n".join(lines)
    ws = text.split()
    n = max(1, len(ws))
    marks = sum(text.count(c) for c in "#%*$&|!")
    return np.array([1, np.log1p(n) / 5, len(lines) / 50, marks / n, sum(w.isupper() for w in ws) / n, len(set(ws)) / n, sum(a == b for a, b in zip(ws, ws[1:], strict=False)) / n, text.count(" | ") / n, sum(x[-1:] in ".!?" for x in lines) / max(1, len(lines)), len(set(lines)) / max(1, len(lines)), any("@" in x or "licensed" in x.lower() for x in lines), sum(c.isdigit() for c in text) / max(1, len(text))], float)


@dataclass
class Weights:
    verdict: np.ndarray = field(default_factory=lambda: np.zeros((len(VERDICTS), PAGE)))
    #: One row for what extraction removes, one for what an edit removes.
    line: np.ndarray = field(default_factory=lambda: np.zeros((2, LINE + HASH + len(VERDICTS))))

    def probabilities(self, lines: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        z = self.verdict @ page_features(lines)
        p = np.exp(z - z.max())
        p /= p.sum()
        x = np.hstack([line_features(lines), np.tile(p, (len(lines), 1))]) if lines else np.zeros((0, self.line.shape[1]))
        return p, 1 / (1 + np.exp(-np.clip(x @ self.line.T, -30, 30))), x


def _gradients(weights: Weights, decision: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gv, gl, loss, n = np.zeros_like(weights.verdict), np.zeros_like(weights.line), 0.0, 0
        for b in batches:
            for row in b.to_pylist():
                p, q, x = weights.probabilities(row["lines"])
                y = VERDICTS.index(row["verdict"])
                t = np.stack([np.array(row[k] or [], float) for k in ("strip", "drop")], 1)
                gv += decision * np.outer(p - np.eye(len(VERDICTS))[y], page_features(row["lines"]))
                m = max(1, len(t))
                gl += ((q - t).T @ x) / m
                loss += -decision * np.log(p[y] + 1e-12) - float(np.sum(t * np.log(q + 1e-12) + (1 - t) * np.log(1 - q + 1e-12))) / m
                n += 1
        flat = np.concatenate([gv.ravel(), gl.ravel(), [loss, n]])
        yield pa.RecordBatch.from_arrays([pa.array(range(len(flat)), pa.int32()), pa.array(flat)], ["i", "g"])

    return run


def examples(programs: DataFrame) -> DataFrame:
    """Target programs with ``lines`` to training rows; what the teachers saw of the markup stays behind."""
    flags = lambda c: F.transform("lines", lambda x, i: F.exists(c, lambda r: (i + 1).between(r["a"], r["b"])).cast("int"))
    return programs.select("lines", "verdict", flags("strip").alias("strip"), flags("drop").alias("drop"))


def fit(first: DataFrame, second: DataFrame | None = None, decision_weight: float = 5.0, epochs: int = 3, batches: int = 4, peak: float = 0.8, warmup: int = 3) -> tuple[Weights, list[float]]:
    """Weights after stage 1 and, going on from them, stage 2; and the mean loss of every step.

    An epoch goes through the rows once in ``batches`` steps, a row's batch being its hash.
    """
    w, losses = Weights(), []
    steps = epochs * batches
    for stage in (first, second):
        if stage is None:
            continue
        stage = cut(stage)  # read by every step
        seen = np.zeros(w.verdict.size + w.line.size)
        for step in range(steps):
            part = stage.where(F.pmod(F.xxhash64("lines", "verdict"), F.lit(batches)) == step % batches)
            summed = part.mapInArrow(_gradients(w, decision_weight), "i int, g double").groupBy("i").agg(F.sum("g").alias("g")).collect()
            flat = np.zeros(len(seen) + 2)
            for r in summed:
                flat[r["i"]] = r["g"]
            if not flat[-1]:
                continue
            n = flat[-1]
            losses.append(float(flat[-2] / n))
            g = flat[:-2] / n
            seen += g * g
            rate = peak * min(1.0, (step + 1) / warmup) * (0.5 + 0.5 * np.cos(np.pi * step / steps))
            move = rate * g / np.sqrt(seen + 1e-9) * 0.5
            w = Weights(w.verdict - move[: w.verdict.size].reshape(w.verdict.shape), w.line - move[w.verdict.size :].reshape(w.line.shape))
    return w, losses


def draw(p: np.ndarray, u: float, temperature: float, top_p: float) -> int:
    """The choice that the number ``u`` in [0, 1) draws from the likeliest choices that make up ``top_p`` together; the likeliest at temperature 0."""
    if temperature <= 0:
        return int(p.argmax())
    p = p ** (1 / temperature)
    p = p / p.sum()
    order = np.argsort(-p, kind="stable")
    few = order[: 1 + int(np.searchsorted(np.cumsum(p[order]), top_p - 1e-12))]
    kept = np.zeros_like(p)
    kept[few] = p[few]
    return int(np.searchsorted(np.cumsum(kept / kept.sum()), u, "right").clip(0, len(p) - 1))


def shortened(text: str, most: int) -> str:
    """The text up to the end of its ``most``-th word."""
    last = next(islice(re.finditer(r"\S+", text), most - 1, None), None)
    return text if last is None else text[: last.end()]


def decode(rendered: DataFrame, weights: Weights, temperature: float = 0.0, top_p: float = 1.0, seed: int = 0, most: int = MAX_ANSWER) -> DataFrame:
    """``(page_id, output)``: one program for each page, in the decision-first layout.

    Temperature 0 takes the likeliest verdict; above it the verdict is drawn by a hash
    of page and seed, so that runs agree. An edit without a line to remove is a keep.
    Output ends after ``most`` words, as a model's does, in the middle of what it writes.
    """

    def ranges(flags: list[bool]) -> list[str]:
        out, i = [], 0
        while i < len(flags):
            j = i
            while j < len(flags) and flags[j]:
                j += 1
            if j > i:
                out.append(f"rm {i + 1}" if j == i + 1 else f"rm {i + 1}-{j}")
            i = max(j, i + 1)
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            outs = []
            for page, lines in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                p, q, _ = weights.probabilities(lines or [])
                v = VERDICTS[draw(p, crc32(f"{seed}|{page}".encode()) / 2**32, temperature, top_p)]
                strip = q[:, 0] > 0.5
                drop = ranges(((q[:, 1] > 0.5) & ~strip).tolist()) if v == "edit" else []
                if v == "edit" and not drop:
                    v = "keep"
                left = [x for x, s in zip(lines or [], strip.tolist(), strict=True) if not s]
                tail = ["\n".join(left)] if v == "rewrite" else drop
                outs.append(shortened("\n".join([f"<{v}>", "<extract>", *ranges(strip.tolist()), f"<{v}>", *tail]), most))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(outs, pa.string())], ["page_id", "output"])

    return rendered.select("page_id", "lines").mapInArrow(run, "page_id long, output string")
