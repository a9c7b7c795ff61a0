"""A corpus pipeline of five stages, each over all that the one before it kept.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read
again as the next one's docs. All but the last return the columns of docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.llm import language_id, mixing, near_duplicates, op9, personal_data, pieces
from tidegraph.plans.scratch import Scratch


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents whose language cannot be told: null texts and texts without a letter. The lang of the
    others becomes the predicted one where it was null."""
    model = language_id.fit(docs.select("doc_id", "text", "lang"), F.lit(True))
    found = language_id.identify(docs, model).where(F.col("lang_pred") != language_id.UNDETERMINED)
    return found.withColumn("lang", F.coalesce("lang", "lang_pred")).select(docs.columns)


def near_duplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group: the row of the smallest id. Documents without an id all stay, since
    nothing tells them apart in a group; of rows with one id, the first text in order stays."""
    found = near_duplicates.near_duplicates(docs)
    kept = found.where("id = component_id").groupBy("id").agg(F.count(F.lit(1)).alias("rows"))
    rows = docs.join(kept.withColumnRenamed("id", "doc_id"), "doc_id", "left")
    single = rows.where("doc_id is null or rows = 1").select(docs.columns)
    several = rows.where("rows > 1").groupBy("doc_id").agg(F.min(F.struct("text", *[c for c in docs.columns if c not in ("doc_id", "text")])).alias("r"))
    return single.unionByName(several.select("doc_id", "r.*").select(docs.columns))


def personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Redacts personal data and secrets in the texts."""
    return personal_data.find(docs, personal_data.trained(), output="text")


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mixes sources; a document stands in the result as often as its source's weight asks."""
    mixed = mixing.mix(docs, payload=docs.columns)
    return mixed.select("row.*")


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids in place of the texts."""
    return pieces.encode(docs, pieces.load(op9.MODEL_PATH))


STAGES = [
    ("language_id", language),
    ("near_duplicates", near_duplicate),
    ("personal_data", personal),
    ("mixing", mixture),
    ("pieces", tokenize),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    scratch = Scratch(spark, "pipeline")
    for name, stage in STAGES:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return docs


#: Trained models and boosted trees are not SQL; tests hold the stages against brute force.
ORACLE_SQL = None
