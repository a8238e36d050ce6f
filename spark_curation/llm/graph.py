"""Connected components of an edge table, for graphs with hubs.

Alternates two rewirings: every node hands its larger neighbours to the smallest
node it knows, then its smaller ones. Each round is grouped minima with map-side
combining and equi-joins, so a hub is an ordinary skewed join key and no list of
neighbours is ever gathered. Rounds grow with the logarithm of the longest path.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.io import cut, shuffled


def _large(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return both.where("v > u").join(shuffled(low), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = down.groupBy("u").agg(F.min("v").alias("m"))
    handed = down.join(shuffled(low), "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return handed.union(low.select("u", F.col("m").alias("v"))).where("u <> v")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(u, v)`` links to ``(node, component)``, where component is the smallest node reachable.

    Nodes are of any type that has an order. Nodes without a link do not appear. Self links, repeated links and nulls on
    either side are ignored; an empty table gives an empty result.
    """
    edges = edges.select("u", "v").where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    edges = cut(edges)
    mark = _mark(edges)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        edges = cut(_small(_large(edges).distinct()).distinct())
        now = _mark(edges)
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)


def join_small(rows: DataFrame, named: DataFrame, key: str, share: int = 1000) -> DataFrame:
    """``rows`` with the columns of ``named``, which has each key once and in ``n`` how many rows have it.

    Keys that more than one in ``share`` rows have, fewer than ``share`` of them, travel
    to every task; the rest is an ordinary join without hot keys.
    """
    total = named.agg(F.sum("n")).first()[0] or 0
    named = cut(named)
    hot = F.broadcast(named.where(F.col("n") * share > total).drop("n"))
    cold = rows.join(hot.select(key), key, "left_anti").join(shuffled(named.where(F.col("n") * share <= total).drop("n")), key)
    return cold.unionByName(rows.join(hot, key))


def _mark(edges: DataFrame) -> tuple:
    """Count and order-free digest: equal when a round changed nothing."""
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())
