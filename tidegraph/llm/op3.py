"""Query op3_lm_scoring."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.llm.common import crc_mod, table
from tidegraph.llm.lm_scoring import score


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = score(table(spark, sf_dir, "documents").select("doc_id", "text"), crc_mod("doc_id", 7) != 2)
    return found.withColumn("held_out", F.coalesce(crc_mod("doc_id", 7) == 2, F.lit(False)))
