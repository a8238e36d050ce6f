"""A corpus from raw documents: good texts, one of each near copy, no test items, no personal data, as token ids.

Each stage takes what the one before kept. All but the last return the columns of
``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spark_curation.io import remove, table, written
from spark_curation.llm import decontamination, pieces, pii, quality, simhash


def good_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier keeps.

    Null and empty texts are judged like others; repeated rows stay or go together. Extra columns are carried or ignored; an empty table stays empty.
    """
    return quality.keep_good(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group of near duplicates.

    Of repeated rows one stays; rows with a null id stay where no row of their group has an id. Extra columns are carried or ignored; an empty table stays empty.
    """
    return simhash.keep_one(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain no benchmark item.

    Null texts and repeated rows stay; an empty benchmark keeps all. Extra columns are carried or ignored; an empty table stays empty.
    """
    return decontamination.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def without_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data replaced by its kind.

    Null texts stay null, repeated rows stay. Extra columns are carried or ignored; an empty table stays empty.
    """
    return pii.redact_documents(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every document, with digests of ids, decoded text and source spans.

    A null text counts as empty; repeated rows and null ids stay. Extra columns are carried or ignored; an empty table stays empty.
    """
    encoded = pieces.encode_documents(docs, pieces.tokenizer_path())
    return pieces.digests(encoded, "ids")


STAGES = [
    ("quality", good_texts),
    ("near_duplicates", one_of_each),
    ("decontamination", without_benchmark),
    ("pii", without_personal_data),
    ("tokens", token_ids),
]

#: SQL cannot express the trained stages; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage keeps is written once, and removed when the next one is done."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs, at = written(stage(spark, docs, sf_dir), name)
        if before:
            remove(spark, before)
        before = at
    return STAGES[-1][1](spark, docs, sf_dir)
