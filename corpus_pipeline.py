"""The corpus pipeline: quality, shared lines, near duplicates, secrets, packing.

Each stage reads what its predecessor wrote as Parquet and calls one operator; all but the last return the columns of
`documents`. Stages work on an empty table, on null and very long texts, on repeated rows and with further columns as their operators
say; `n_chars` always counts the code points of the text that is returned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textquarry.llm import jaccard, linededup, packing, quality, secrets
from textquarry.llm._tables import Workspace
from textquarry.shared import spread


def _like(docs: DataFrame, new: DataFrame) -> DataFrame:
    """The columns of docs, with the length of the new text."""
    if "n_chars" in docs.columns:
        new = new.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return new.select(*docs.columns)


def reject_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; it learns from `labels.quality` outside the held-out fold."""
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_shared_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Long lines that at least five documents hold stay in the largest id only."""
    return _like(docs, linededup.drop_shared_lines(docs, counts=None))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class stays (five-word shingles, similarity 0.8): the least id."""
    return jaccard.keep_one(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Live-looking credentials are replaced; widely copied examples stay."""
    return _like(docs, secrets.redact_live(docs))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece of a document and its place in a training sequence."""
    return packing.pack(docs)


STAGES = [
    ("quality", reject_low_quality),
    ("line_dedup", drop_shared_lines),
    ("near_duplicates", drop_near_duplicates),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]

#: The classifier's scores and the verified links are not SQL; tests compare each stage with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    space = Workspace(spark, "pipeline")
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    for name, stage in STAGES[:-1]:
        docs = space.write(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
