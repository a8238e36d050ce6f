"""Scans with explicit paths and a place for durable intermediate results."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region nation customer supplier part orders lineitem events documents "
    "embeddings pages benchmark labels conversations"
).split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; the path goes to Spark's reader untouched, whatever its file system."""
    if name not in TABLES:
        raise KeyError(name)
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder for intermediate results, which the session names.

    A temporary folder is set only where there is none and everything runs on one
    machine, as in tests; on a cluster a missing setting is an error.
    """
    sc = spark.sparkContext
    if (at := sc.getCheckpointDir()) is not None:
        return at
    at = spark.conf.get("spark.checkpoint.dir", None)
    if at is None:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        at = tempfile.mkdtemp(prefix="spark-curation-")
    sc.setCheckpointDir(at)
    return at


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and go on from the files.

    Used where a result is read more than once and costs more to make than to read.
    """
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """``df`` written to the shared folder as compressed columns and read back, and where it is, for ``remove``."""
    spark = df.sparkSession
    at = f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(at)
    return spark.read.schema(df.schema).parquet(at), at


def stored(df: DataFrame) -> DataFrame:
    """As ``cut``, in compressed columns: for tables of whole texts."""
    return written(df, "stored")[0]


def remove(spark: SparkSession, at: str) -> None:
    """Deletes what ``written`` wrote, on whatever file system it is."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(at)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def shuffled(df: DataFrame) -> DataFrame:
    """``df`` as a side of a join that sorts and merges, whatever size Spark takes it for.

    A side that grows with the corpus may be under the session's broadcast threshold
    and still be more than a small driver can build a table of, several at once above all.
    """
    return df.hint("merge")


def fence(df: DataFrame) -> DataFrame:
    """The same rows behind a generator that predicates and projections do not pass.

    Catalyst writes the definition of every column into a predicate that it pushes
    below a projection. Over a long chain of derived columns that text grows with every
    step; a fence after the step keeps it short. Rows do not move.
    """
    return df.select(F.inline(F.array(F.struct(*[F.col(f"`{c}`") for c in df.columns]))))
