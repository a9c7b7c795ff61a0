"""Query op9_pieces."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession

from tidegraph.llm.common import table
from tidegraph.llm.pieces import encode, load

#: A SentencePiece model file on the driver; the environment may name another.
MODEL_PATH = os.environ.get("PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")


def query(spark: SparkSession, sf_dir: str, path: str = MODEL_PATH) -> DataFrame:
    return encode(table(spark, sf_dir, "documents").select("doc_id", "text"), load(path), digest=True)
