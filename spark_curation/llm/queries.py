"""Registered queries of the training-data operators and their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline

from spark_curation.io import table
from spark_curation.llm import decontamination, html_tree, licences, order_minhash, passages, pieces, pii, quality, simhash, warc_derivatives


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Votes, posterior, score and decision of every document. Odd rows: see the operator; an empty table gives no rows."""
    return quality.classify(table(spark, sf_dir, "documents"))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with each benchmark item that it contains. Odd rows: see the operator; an empty table gives no rows."""
    return decontamination.search(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids, decoded text and source spans of every document. Odd rows: see the operator; an empty table gives no rows."""
    return pieces.digests(pieces.encode_documents(table(spark, sf_dir, "documents"), pieces.tokenizer_path()))


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Metadata and conversion records of every page, with digests in place of blocks. Odd rows: see the operator; an empty table gives no rows."""
    return warc_derivatives.digests(warc_derivatives.derivatives(warc_derivatives.responses(table(spark, sf_dir, "pages"))))


def op5_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places and labels of licence phrases in every document. Odd rows: see the operator; an empty table gives no rows."""
    return licences.scan(table(spark, sf_dir, "documents"))


def op6_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page. Odd rows: see the operator; an empty table gives no rows."""
    return html_tree.extract(table(spark, sf_dir, "pages"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and group of every document. Odd rows: see the operator; an empty table gives no rows."""
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts, digest and spans of personal data in every document. Odd rows: see the operator; an empty table gives no rows."""
    return pii.digests(pii.find(table(spark, sf_dir, "documents")))


def op9_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of every document and of its edited text, and how like they are. Odd rows: see the operator; an empty table gives no rows."""
    return order_minhash.fingerprints(table(spark, sf_dir, "documents"))


def op10_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class and repeated word ranges of every document. Odd rows: see the operator; an empty table gives no rows."""
    return passages.repeated(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality": op1_quality,
    "op2_sentencepiece": op2_sentencepiece,
    "op3_decontamination": op3_decontamination,
    "op4_warc": op4_warc,
    "op5_licences": op5_licences,
    "op6_html": op6_html,
    "op7_simhash": op7_simhash,
    "op8_pii": op8_pii,
    "op9_order_minhash": op9_order_minhash,
    "op10_passages": op10_passages,
    "pipeline": corpus_pipeline.run,
}

ORACLES: dict[str, str] = {
    "op3_decontamination": decontamination.ORACLE,
    "op5_licences": licences.oracle_sql(),
}
