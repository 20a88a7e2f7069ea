"""The corpus pipeline: five stages over ``documents``, each on all that the
one before it kept.

quality    documents that the attention classifier scores under 0.5 go
near_copies  one document of each group stays (five-word shingles, J >= 0.8)
decontaminate  documents that contain a benchmark item go
secrets    secrets are replaced in the texts; all documents stay
pack       what is left becomes sequences of at most 2048 tokens

Every stage but the last returns the columns of ``documents``; ``n_chars``
follows the text where a stage changes it. Empty tables pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from querymend.llm import common, decontam, jaccard_join, packing, quality, secrets

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.keep_good(docs.select(*COLUMNS), model)


def keep_one_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_first(docs.select(*COLUMNS), jaccard_join.Plan(width=5, num=80, den=100))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.keep_clean(docs.select(*COLUMNS), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def remove_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs = docs.select(*COLUMNS)
    found = secrets.scan(docs, secrets.new_ledger(spark), secrets.RuleSet("r1"))
    return secrets.redact(docs, found).withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packing_query(docs)


STAGES = [
    ("quality", keep_quality),
    ("near_copies", keep_one_copy),
    ("decontaminate", drop_contaminated),
    ("secrets", remove_secrets),
    ("pack", pack_sequences),
]
#: SQL cannot express a trained model and the tokens; see tests/llm/.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each is written to the shared folder and read again."""
    folder = common.workspace(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = common.materialize(stage(spark, docs, sf_dir), folder, name)
    return docs
