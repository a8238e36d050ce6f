"""Training targets: composing teacher outputs, mixtures of the two stages, window gate and packing."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.functions.text import count_words, portable_share
from spark_curation.operators.program import serialize
from spark_curation.operators.render import WINDOW, number_lines

#: Shares of the two stages.
REWRITE_STAGE_1, REWRITE_STAGE_2 = 0.001, 0.30


def compose(programs: DataFrame, layout: str = "decision_first") -> DataFrame:
    """Rows with lines and a program to ``(page_id, verdict, prompt, answer, n_tokens)``."""
    rows = programs.select("page_id", "verdict", number_lines(F.col("lines")).alias("prompt"), serialize(layout).alias("answer"))
    return rows.withColumn("n_tokens", count_words(F.col("prompt")) + count_words(F.col("answer")))


def mixture(targets: DataFrame, stage: int, rewrite_share: float | None = None, seed: int = 0) -> DataFrame:
    """A stage's mixture, drawn by a hash of the page so that every plan draws the same.

    Stage 1 takes nearly all of the other verdicts and few rewrites; stage 2 takes every
    rewrite and as many others as bring rewrites to their share. Only the counts of
    verdicts reach the driver.
    """
    n = {r["verdict"]: r["n"] for r in targets.groupBy("verdict").agg(F.count("*").alias("n")).collect()}
    rewrites, others = n.get("rewrite", 0), sum(v for k, v in n.items() if k != "rewrite")
    if stage == 1:
        share = REWRITE_STAGE_1 if rewrite_share is None else rewrite_share
        keep_r, keep_o = (min(1.0, share * others / ((1 - share) * rewrites)) if rewrites else 0.0), 1.0
    else:
        share = REWRITE_STAGE_2 if rewrite_share is None else rewrite_share
        keep_r, keep_o = 1.0, (min(1.0, rewrites * (1 - share) / (share * others)) if others else 0.0)
    draw = portable_share(F.lit(str(seed)), F.col("page_id").cast("string"))
    return targets.where(draw < F.when(F.col("verdict") == "rewrite", keep_r).otherwise(keep_o)).withColumn("stage", F.lit(stage))


def fit_window(targets: DataFrame, size: int = WINDOW) -> DataFrame:
    return targets.where(F.col("n_tokens") <= size)


def outcome_line(targets: DataFrame) -> DataFrame:
    """The line of the prompt that tells how often each verdict comes, as one row."""
    n = targets.groupBy("verdict").agg(F.count("*").alias("n"))
    total = n.agg(F.sum("n").alias("total"))
    share = n.crossJoin(F.broadcast(total)).select("verdict", F.round(100 * F.col("n") / F.col("total"), 1).alias("share"))
    parts = F.transform(F.array_sort(F.collect_list(F.struct("verdict", "share"))), lambda x: F.concat(x["verdict"], F.lit(" "), x["share"].cast("string"), F.lit("%")))
    return share.agg(F.array_join(parts, ", ").alias("line"))


def pack(targets: DataFrame, size: int = WINDOW, shards: int = 64) -> DataFrame:
    """``(page_id, n_tokens, shard, pack_id)``: within each shard of pages, in page order, a sequence takes targets while they fit.

    No sequence is longer than ``size``, unless a single target is. The total is carried
    along a sorted stream, so a shard of any length takes no memory; shards are the
    parallelism, and there should be as many as make good tasks.
    """
    shard = F.floor(portable_share(F.col("page_id").cast("string")) * shards).cast("int")
    rows = targets.select(F.col("page_id").cast("long").alias("page_id"), F.col("n_tokens").cast("long").alias("n_tokens"), shard.alias("shard"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, pack_id, fill = None, 0, 0
        for b in batches:
            packs = []
            for n, s in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                if s != at:
                    at, pack_id, fill = s, 0, 0
                elif fill + n > size:
                    pack_id, fill = pack_id + 1, 0
                fill += n
                packs.append(pack_id)
            yield b.append_column("pack_id", pa.array(packs, pa.int64()))

    return rows.repartition("shard").sortWithinPartitions("shard", "page_id").mapInArrow(run, "page_id long, n_tokens long, shard int, pack_id long")
