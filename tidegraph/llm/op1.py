"""Query op1_personal_data."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tidegraph.llm.common import table
from tidegraph.llm.personal_data import find, trained


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(table(spark, sf_dir, "documents").select("doc_id", "text"), trained())
