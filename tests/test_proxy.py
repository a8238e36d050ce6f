"""Questions move once, however many corpora they are put to."""

from pyspark.sql import functions as F

from spark_curation.io import cut
from spark_curation.operators import proxy


def test_texts_are_spelled_once_and_groups_do_not_multiply_questions(spark):
    items = spark.createDataFrame([(i, " ".join(f"w{i}x{j}" for j in range(20))) for i in range(40)], "item_id long, text string")
    asked = cut(proxy.continuation_tasks(items))
    assert asked.count() == 40 * 9 + 40 * 4  # nine pairs in each second half, four candidates of each question
    corpus = cut(items.withColumn("half", F.explode(F.array(F.lit(0), F.lit(1)))).where("half = 0 or item_id < 20"))
    groups = spark.createDataFrame([(0,), (1,), (2,)], "half int")
    got = proxy.evaluate(proxy.train(corpus, asked, ("half",)), asked, ("half",), groups)
    assert "NestedLoop" not in got._jdf.queryExecution().executedPlan().toString()
    acc = {r.half: (r.n, r.acc) for r in got.collect()}
    assert acc[0] == (40, 1.0) and acc[2][1] <= 0.25 and acc[2][1] < acc[1][1] < 1.0
