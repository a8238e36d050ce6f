"""What several corpora have in common is worked out once, with the results of each by itself."""

from pyspark.sql import functions as F

from spark_curation import comparison
from spark_curation.io import cut, table
from spark_curation.operators import dedup, execute, proxy
from spark_curation.plans import pipelines
from tests.conftest import DATA


def rows_of(node, kind):
    """Rows that the nodes of a kind made in a plan that has run."""
    if node.nodeName() == "AdaptiveSparkPlan":
        return rows_of(node.executedPlan(), kind)
    if "QueryStage" in node.nodeName():
        return rows_of(node.plan(), kind)
    own = node.metrics().apply("numOutputRows").value() if node.nodeName() == kind else 0
    return own + sum(rows_of(node.children().apply(i), kind) for i in range(node.children().size()))


def test_a_text_of_many_corpora_is_cut_into_words_once(spark):
    items = spark.createDataFrame([(i, " ".join(f"w{i * j % 50}" for j in range(20))) for i in range(40)], "item_id long, text string")
    asked = cut(proxy.continuation_tasks(items))
    corpus = cut(items.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(5)))).where("item_id % 7 <> part"))
    weight = 1.0 + F.col("part") / 4
    one = proxy.evaluate(proxy.train(corpus, asked, ("part",), weight), asked, ("part",))
    got = comparison.scored(corpus, asked, ("part",), weight)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, one.collect()))
    assert 0 < rows_of(got._jdf.queryExecution().executedPlan(), "Generate") <= 2 * 40 * 19 + 6


def test_grams_of_groups_move_once_and_fall_as_before(spark):
    docs = table(spark, DATA, "documents").select(F.expr("case when doc_id % 23 = 0 then null when doc_id % 5 = 0 then doc_id div 2 else doc_id - 30 end").alias("doc_id"), "text")
    x = cut(docs.select(F.lit("a").alias("g"), "*").union(docs.where("doc_id % 3 > 0").select(F.lit("b"), "*")).union(docs.where("doc_id < 0").select(F.lit("b"), "*")))
    want = sorted((r.g, r.id) for r in dedup.ngram(x, by=("g",)).collect())
    assert want and sorted(map(tuple, dedup.fallen(x, ["a", "b"], "g").collect())) == want
    far = x.withColumn("doc_id", F.col("doc_id") + (1 << 62))
    assert sorted(map(tuple, dedup.fallen(far, ["a", "b"], "g").collect())) == [(g, i + (1 << 62)) for g, i in want]
    none = x.where("false")
    assert dedup.fallen(none, ["a", "b"], "g").collect() == []


def test_rescue_rules_share_their_work(spark):
    got = comparison.selection(spark, DATA).where("share = 1.0")
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Scan parquet") <= 2 and "Union" not in plan
    rendered = cut(pipelines.rendered_pages(table(spark, DATA, "pages")))
    rows = got.select("variant", "page_id", "verdict", "text").collect()
    for name, kw in comparison.RESCUES.items():
        want = execute.run(pipelines.policy(rendered, **kw)).where("text is not null").select("page_id", "verdict", "text").collect()
        assert sorted(tuple(r)[1:] for r in rows if r.variant == name) == sorted(map(tuple, want))
