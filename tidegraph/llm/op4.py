"""Query op4_document_fingerprints."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tidegraph.llm.common import table
from tidegraph.llm.imatch import Lexicon, with_next


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    partitions = max(docs.rdd.getNumPartitions(), int(spark.conf.get("spark.sql.shuffle.partitions")))
    return with_next(docs, Lexicon.build(docs), partitions)
