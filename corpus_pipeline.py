"""The corpus pipeline: five stages over ``documents``, each written and read again.

The stages and what they give for nulls, empty texts, ties, repeated rows, empty tables
and further columns are in ``gridlake.llm.stages``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gridlake.llm.common import Scratch, handed, release
from gridlake.llm.stages import STAGES

#: SQL can't express byte-pair encoding or the local search; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage; what a stage left behind goes once the next is written."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    with Scratch(spark, "pipeline") as s:
        last = len(STAGES) - 1
        for k, (_, stage) in enumerate(STAGES):
            mark = handed()
            rows = stage(spark, docs, sf_dir)
            docs = s.save(rows, f"stage-{k}") if k < last else s.keep(rows, f"stage-{k}")
            release(spark, mark) if k < last else None
            s.drop(f"stage-{k - 1}")
    return docs
