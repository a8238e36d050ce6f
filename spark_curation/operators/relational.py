"""Generic relational operators on the tables without text."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """For each left row the last right value at or before its time, within the key: one union and one window, no pairs."""
    a = left.select(by, on, F.lit(None).cast(dict(right.dtypes)[value]).alias("v"), F.lit(1).alias("side"), F.struct(*left.columns).alias("row"))
    b = right.select(by, on, F.col(value).alias("v"), F.lit(0).alias("side"), F.lit(None).cast(a.schema["row"].dataType).alias("row"))
    w = Window.partitionBy(by).orderBy(on, "side").rowsBetween(Window.unboundedPreceding, 0)
    return a.union(b).withColumn("found", F.last("v", ignorenulls=True).over(w)).where("side = 1").select("row.*", F.col("found").alias(f"last_{value}"))


def top_k(df: DataFrame, by: str, order: list, k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(by).orderBy(*order))).where(F.col("place") <= k)
