"""Readers and writers: a data source for archives of crawled pages, text forms, and a resumable sharded sink."""

from __future__ import annotations

import gzip
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from spark_curation.functions.text import portable_share


class _Member(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class _Reader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [_Member(p) for p in self.paths]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        path = partition.value
        opener = gzip.open if path.endswith(".gz") else open
        with opener(path, "rb") as f:
            yield from records(f)


def records(f) -> Iterator[tuple]:
    """``(record id, target, page)`` of the response records of an open archive."""
    while line := f.readline():
        if not line.startswith(b"WARC/"):
            continue
        fields = {}
        while line := f.readline().strip():
            k, _, v = line.decode("utf-8", "replace").partition(":")
            fields[k.strip().lower()] = v.strip()
        block = f.read(int(fields.get("content-length", 0)))
        if fields.get("warc-type") == "response":
            head, gap, body = block.partition(b"\r\n\r\n")
            yield fields.get("warc-record-id"), fields.get("warc-target-uri"), (body if gap else head).decode("utf-8", "replace")


class ArchiveSource(DataSource):
    """``spark.read.format("page_archive").option("paths", "a,b").load()``: response records, one partition for each archive file."""

    @classmethod
    def name(cls) -> str:
        return "page_archive"

    def schema(self) -> str:
        return "record_id string, url string, html string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader([p for p in self.options.get("paths", "").split(",") if p])


def read_archives(spark: SparkSession, paths: list[str]) -> DataFrame:
    spark.dataSource.register(ArchiveSource)
    return spark.read.format("page_archive").option("paths", ",".join(paths)).load()


def read_archive_files(spark: SparkSession, path: str) -> DataFrame:
    """``(record_id, url, html)`` of the response records of archives, through Spark's own reader, for stores that only it can open.

    A file is one task's work and held in memory as it is stored, so archives should be of the usual size of a gigabyte at the most.
    """
    import io

    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                raw = content.as_py()
                f = gzip.open(io.BytesIO(raw)) if raw[:2] == b"\x1f\x8b" else io.BytesIO(raw)
                held: list[tuple] = []
                for row in records(f):
                    held.append(row)
                    if len(held) == 500:
                        yield _rows(held)
                        held = []
                yield _rows(held)

    def _rows(held: list[tuple]) -> pa.RecordBatch:
        columns = list(zip(*held, strict=True)) or [[]] * 3
        return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in columns], ["record_id", "url", "html"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, "record_id string, url string, html string")


def read_html_files(spark: SparkSession, path: str, charset: str = "UTF-8") -> DataFrame:
    """One page in a file: path as URL, decoded content."""
    return spark.read.format("binaryFile").load(path).select(F.col("path").alias("url"), F.decode("content", charset).alias("html"))


def read_text_pages(spark: SparkSession, path: str) -> DataFrame:
    """One plain page in a file."""
    return spark.read.text(path, wholetext=True).withColumnRenamed("value", "text")


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Published numbers or other small tables as CSV with a header; lines that do not fit the schema keep their text in ``corrupt``."""
    return spark.read.schema(f"{schema}, corrupt string").option("header", True).option("columnNameOfCorruptRecord", "corrupt").csv(path)


def read_outputs(spark: SparkSession, path: str) -> DataFrame:
    """Model outputs as JSON lines; lines that are none keep their text in ``corrupt``."""
    return spark.read.schema("page_id long, output string, corrupt string").option("columnNameOfCorruptRecord", "corrupt").json(path)


def write_targets(targets: DataFrame, path: str) -> None:
    """Training targets as JSON lines of messages."""
    turn = lambda role, c: F.struct(F.lit(role).alias("role"), F.col(c).alias("content"))
    targets.select("page_id", F.array(turn("user", "prompt"), turn("assistant", "answer")).alias("messages")).write.mode("overwrite").json(path)


def write_corpus(corpus: DataFrame, path: str, shards: int = 64, id_col: str = "page_id") -> None:
    """Parquet by pipeline and shard; a rerun replaces only the partitions it makes again."""
    shard = F.floor(portable_share(F.col(id_col).cast("string")) * shards).cast("int")
    (corpus.withColumn("shard", shard).repartition("pipeline", "shard").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("pipeline", "shard").parquet(path))


def remaining(todo: DataFrame, done: DataFrame, id_col: str = "page_id") -> DataFrame:
    """What an earlier run has not written yet."""
    return todo.join(done.select(id_col).distinct(), id_col, "left_anti")
