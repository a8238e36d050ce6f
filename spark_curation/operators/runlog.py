"""The ledger of a run: what each step cost, and whether it is paid once, for each pool or for each corpus."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Published hours of GPUs by step, and the total printed with them.
PUBLISHED = (
    ("once", "extraction labels", 150.0), ("once", "refining labels", 204.0), ("once", "rewrites", 7.0), ("once", "fine-tuning, stage 1", 244.0), ("once", "fine-tuning, stage 2", 37.0),
    ("per pool", "refiner_chunkprog", 147.0), ("per pool", "refiner_lineprog", 180.0), ("per pool", "unified", 494.0), ("per pool", "extraction teacher", 1366.0), ("per pool", "orchestrated", 1652.0),
    ("per corpus", "pretraining S", 26.0), ("per corpus", "pretraining M", 240.0), ("per corpus", "pretraining L", 740.0),
)
TOTAL = 14_643.0


class Ledger:
    """Rows ``(paid, step, hours)`` of steps as they end; a step that is tried again adds to its cost."""

    def __init__(self) -> None:
        self.rows: list[tuple[str, str, float]] = []

    @contextmanager
    def step(self, paid: str, name: str, workers: int = 1) -> Iterator[None]:
        began = time.monotonic()
        try:
            yield
        finally:
            self.rows.append((paid, name, (time.monotonic() - began) * workers / 3600))

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "paid string, step string, hours double")


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(PUBLISHED), "paid string, step string, hours double")


def summary(ledger: DataFrame) -> DataFrame:
    """Hours of each step, of each kind of payment and of all, with their shares."""
    sums = ledger.rollup("paid", "step").agg(F.sum("hours").alias("hours"))
    total = ledger.agg(F.sum("hours").alias("all_hours"))
    return sums.crossJoin(F.broadcast(total)).select(F.coalesce("paid", F.lit("all")).alias("paid"), F.coalesce("step", F.lit("all")).alias("step"), F.round("hours", 6).alias("hours"), F.round(F.col("hours") / F.col("all_hours"), 6).alias("share"))  # one row on the right


def break_even(ledger: DataFrame, one: str = "unified", other: str = "orchestrated") -> DataFrame:
    """Pools after which the steps paid once for ``one`` cost less than what ``other`` takes more for each pool."""
    at = lambda s: F.sum(F.when((F.col("paid") == "per pool") & (F.col("step") == s), F.col("hours")))
    once = F.sum(F.when(F.col("paid") == "once", F.col("hours")))
    return ledger.agg(once.alias("once"), (at(other) - at(one)).alias("saved_per_pool")).withColumn("pools", F.round(F.col("once") / F.col("saved_per_pool"), 4))
