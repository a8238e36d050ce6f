"""Sides that grow with the corpus are never broadcast, however small Spark takes them for."""

from pyspark.sql import functions as F

from spark_curation.llm import graph, simhash


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_links_and_groups_are_joined_without_broadcast(spark):
    fps = spark.range(5).toDF("fp")
    assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold").startswith("10485760")
    found = plan(simhash.links(fps))
    assert "SortMergeJoin" in found and "Broadcast" not in found
    edges = spark.range(5).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    for step in (graph._large, graph._small):
        assert "Broadcast" not in plan(step(edges))
    named = fps.select("fp", F.lit(1).alias("n"))
    assert "SortMergeJoin" in plan(graph.join_small(fps, named, "fp"))


def test_one_of_each_is_kept_without_broadcast(spark):
    docs = spark.range(9).select(F.col("id").alias("doc_id"), F.concat(F.lit("text of words "), F.col("id") % 3).alias("text"))
    kept = simhash.keep_one(docs)
    rows = [r["doc_id"] for r in kept.collect()]
    assert len(rows) >= 1 and 0 in rows
    assert "SortMergeJoin" in plan(kept) and "Broadcast" not in plan(kept)
