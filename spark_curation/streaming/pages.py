"""Structured Streaming forms: the per-page chain is stateless, so it is the batch code; state is only in windows and dedup."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_curation.io import checkpoint_dir

PAGES = "page_id long, url string, html string"
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, sf_dir: str, name: str, schema: str) -> DataFrame:
    """A stream over the files of one table, read as they come; the glob takes a table of one file and of many."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 64).parquet(f"{sf_dir.rstrip('/')}/{name}.parque[t]")


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and gives what it wrote.

    Each micro-batch overwrites its own folder, so a batch that is tried again after a
    failure leaves no copies.
    """
    spark = stream.sparkSession
    at = f"{checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")

    put(spark.createDataFrame([], stream.schema), -1)  # so that a stream without rows has a result too
    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.schema(stream.schema).option("recursiveFileLookup", "true").parquet(f"{at}/out")


def timed_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages with an arrival time: page k arrives with event k."""
    events = spark.read.parquet(f"{sf_dir.rstrip('/')}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    return source(spark, sf_dir, "pages", PAGES).join(events, F.col("page_id") == F.col("event_id")).drop("event_id")


def first_urls(stream: DataFrame, late: str = "30 days") -> DataFrame:
    """Each URL once within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["url"])


def tumbling(events: DataFrame, size: str = "1 hour", late: str = "60 days") -> DataFrame:
    w = F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "1 hour", step: str = "30 minutes", late: str = "60 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "1 hour", late: str = "60 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def late_rows(spark: SparkSession, events: DataFrame, late: str = "1 hour", batches: int = 4) -> DataFrame:
    """``(n_rows, n_late)``: how many rows a watermark of ``late`` lets a windowed count drop when events come in ``batches`` files by id.

    The engine's own measure, summed over the progress of all micro-batches.
    """
    at = f"{checkpoint_dir(spark)}/late-{uuid.uuid4().hex}"
    parts = events.withColumn("part", F.pmod("event_id", F.lit(batches)).cast("int"))
    for i in range(batches):  # one file for each micro-batch
        parts.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(f"{at}/in")
    rows = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{at}/in")
    counted = rows.withWatermark("ts", late).groupBy(F.window("ts", "1 hour")).count()
    run = counted.writeStream.outputMode("append").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(lambda b, _: b.count()).start()
    run.awaitTermination()
    done = run.recentProgress
    dropped = sum(int(op["numRowsDroppedByWatermark"]) for p in done for op in p["stateOperators"])
    return spark.createDataFrame([(sum(int(p["numInputRows"]) for p in done), dropped)], "n_rows long, n_late long")


def with_labels(stream: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    """A stream with a table that does not change: the table is read anew for each micro-batch."""
    return stream.join(labels, key, "left")


def with_outputs(pages: DataFrame, outputs: DataFrame, within: str = "2 hours", late: str = "60 days") -> DataFrame:
    """Arrived pages with the model outputs that come within a time bound: both sides ``(page_id, ts, ...)``, state bounded by watermarks as wide as the disorder of the files."""
    a = pages.withWatermark("ts", late)
    b = outputs.select(F.col("page_id").alias("of"), F.col("ts").alias("done"), "output").withWatermark("done", late)
    return a.join(b, F.expr(f"page_id = of AND done >= ts AND done <= ts + INTERVAL {within}")).drop("of")


def host_lines(stream: DataFrame, keep: str = "30 days", late: str = "60 days"):
    """``(start, host, line, n)``: counts of a host's lines, the boilerplate signal of a crawl, by periods of ``keep``.

    Lines are kept as digests of 64 bits with their counts; a period's state goes once
    the watermark has passed its end, so the state is bounded by what arrives in a period.
    """
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    rows = stream.withWatermark("ts", late).select("ts", host.alias("host"), F.explode(F.transform("lines", lambda x: F.xxhash64(x))).alias("line"))
    return rows.groupBy(F.window("ts", keep), "host", "line").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "host", "line", "n")
