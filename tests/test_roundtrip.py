"""A rewrite whose text ends in white space is read back as it was spelled."""

from pyspark.sql import functions as F

from spark_curation.operators import execute, program


def test_rewrite_keeps_the_ends_of_its_body(spark):
    bodies = ["New text. ", " \n more", "a\n\nb \n"]
    rows = spark.createDataFrame([(i, "rewrite", [], [], [], b, ["One line."]) for i, b in enumerate(bodies)], f"page_id long, verdict string, strip {program.RANGES}, drop {program.RANGES}, cuts {program.CUTS}, body string, lines array<string>")
    for layout in ("decision_first", "extract_first"):
        read = program.parse(rows.select("page_id", "lines", F.col("body").alias("want"), program.serialize(layout).alias("output")))
        assert [(r.want, r.body) for r in read.orderBy("page_id").collect()] == [(b, b) for b in bodies]
    assert [r.text for r in execute.run(read).orderBy("page_id").collect()] == [b.strip() for b in bodies]
