"""Measures over corpora: token cubes, comparison, lengths, attrition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..config import CORPUS_A_UPTO, UNVERIFIED_UPTO, VERIFIED_UPTO


def source_number(source: Column) -> Column:
    return F.regexp_extract(source, r"(\d+)", 1).cast("int")


def with_split(docs: DataFrame) -> DataFrame:
    """Adds split, corpus and modality."""
    n = source_number(F.col("source"))
    return docs.withColumns({
        "split": F.when(n <= VERIFIED_UPTO, "verified").when(n <= UNVERIFIED_UPTO, "unverified").otherwise("synthetic"),
        "corpus": F.when(n <= VERIFIED_UPTO, "own").when(n <= CORPUS_A_UPTO, "A").when(n <= UNVERIFIED_UPTO, "B").otherwise("own"),
        "modality": F.element_at(F.array(F.lit("web"), F.lit("pdf"), F.lit("speech")), (F.col("doc_id") % 3 + 1).cast("int")),
    })


def token_cube(docs: DataFrame, tokens: Column) -> DataFrame:
    out = docs.withColumn("t", tokens).cube("lang", "split").agg(F.sum("t").cast("long").alias("tokens"), F.count(F.lit(1)).alias("docs"))
    return out.select(F.coalesce("lang", F.lit("all")).alias("lang"), F.coalesce("split", F.lit("all")).alias("split"), "tokens", "docs")


def attrition(died: DataFrame, stages: list[str], by: str = "lang", moved: tuple[str, int] | None = None) -> DataFrame:
    """Alive documents and words after each stage from one pass.

    *died* has `died_at` (index of the stage that removed the document, null if none) and words_<i> per stage index. *moved* names a column that
    takes the place of *by* from a stage on, as for documents that change their language there.
    """
    group = lambda i: F.col(moved[0]) if moved and i >= moved[1] else F.col(by)
    alive = lambda i: F.when(F.col("died_at").isNull() | (F.col("died_at") > i), F.col(f"words_{i}"))
    rows = F.explode(F.array(*(F.struct(group(i).alias(by), F.lit(i).alias("stage_no"), F.lit(s).alias("stage"), alive(i).alias("w")) for i, s in enumerate(stages))))
    out = died.select(rows.alias("r")).select("r.*").groupBy(by, "stage_no", "stage").agg(F.count("w").alias("docs"), F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("words"))
    # One row per group and stage.
    w = Window.partitionBy(by).orderBy("stage_no")
    drop = lambda c: F.when(F.lag(c).over(w) > 0, 1 - F.col(c) / F.lag(c).over(w)).otherwise(F.lit(0.0))
    return out.withColumns({"docs_drop": drop("docs"), "words_drop": drop("words")})


def stage_metrics(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """The same rows; when they are computed, the observation holds how many rows and bytes of text passed, without a further pass."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("bytes")), seen
