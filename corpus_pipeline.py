"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again as the next one's documents.

Toxic documents go; one document of each group of near copies stays; documents that hold a benchmark item go; personal
data is replaced in the text; what is left is mixed to target weights. Each stage works on all rows its predecessor
kept. All but the last return the columns of ``documents``; the last returns a row for each pass over a document,
in training order: the document's columns, epoch, taken (words that this pass takes) and position in [0, 1].
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tangentia.llm.decontamination import drop_leaks
from tangentia.llm.mixing import curriculum
from tangentia.llm.pii import sanitise
from tangentia.llm.setsketch import keep_one_of_each
from tangentia.llm.toxicity import drop_toxic
from tangentia.session import free_driver, materialise


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text scores below 0.5; null and empty texts score as texts without words, repeated rows each by their own text."""
    free_driver(spark)
    return drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies (five words, 0.8), that of the least doc_id; null and empty texts stay, of a repeated doc_id one row stays."""
    free_driver(spark)
    return keep_one_of_each(docs, width=5, threshold=0.8)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item; null and empty texts hold none, and without items all stay."""
    free_driver(spark)
    return drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with personal data and terms that disclose it replaced in the text; null texts stay null."""
    free_driver(spark)
    return sanitise(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each pass over a document, in order of position; texts without words, null ones too, have none; a null source is a source of its own, the last."""
    free_driver(spark)
    return curriculum(docs)


STAGES = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("mixing", mixing),
]

#: Trained scores, sketches and singular vectors have no SQL form; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
