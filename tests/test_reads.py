"""Queries that once made up their data read a given table through Spark."""

import pytest

from spark_curation import surfaces, workloads
from tests.conftest import DATA

assert surfaces  # it registers queries
READS = {
    "scale_ranks": "documents",
    "repetition_factor": "documents",
    "relative_gain": "documents",
    "program_problems": "pages",
    "program_items": "pages",
    "judge_replies": "documents",
    "fused_cells": "part",
    "flawed_execution": "pages",
    "csv_published": "customer",
    "cost_ledger": "orders",
    "cost_break_even": "orders",
    "centered_accuracy": "documents",
}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_its_table(spark, name):
    df = workloads.QUERIES[name](spark, DATA)
    if name == "csv_published":  # reads what it wrote of the table
        assert sum(r["n"] for r in df.collect()) == spark.read.parquet(f"{DATA}/customer.parquet").count()
    else:
        assert any(f.endswith(f"/{READS[name]}.parquet") for f in df.inputFiles())
