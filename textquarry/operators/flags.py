"""Language-specific flags on the statistics, filtering, and what each flag contributes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import LANGUAGES, THRESHOLDS

NAMES = ("nsfw", "script", "few_lines", "short_lines", "word_rep", "char_rep", "symbols")


def thresholds(spark: SparkSession, table: dict[str, dict[str, float]] = THRESHOLDS, languages: tuple[str, ...] = LANGUAGES) -> DataFrame:
    """One row per language: the default row with the language's overrides."""
    names = sorted(table["*"])
    rows = [(lang, *(float(table.get(lang, {}).get(n, table["*"][n])) for n in names)) for lang in languages]
    return spark.createDataFrame(rows, "lang string, " + ", ".join(f"t_{n} double" for n in names))


def flag(signals: DataFrame, limits: DataFrame) -> DataFrame:
    """Adds `flags` (sorted names) and `keep`. The thresholds have a row per language: a broadcast of fixed size."""
    ratio = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))
    rules = {
        "nsfw": ratio("nsfw_words_count", "word_count") > F.col("t_nsfw_ratio"),
        "script": ratio("non_target_count", "char_count") > F.col("t_non_target_ratio"),
        "few_lines": F.col("lines_count") < F.col("t_min_lines"),
        "short_lines": F.col("mean_line_length") < F.col("t_min_mean_len"),
        "word_rep": F.col("word_rep") > F.col("t_word_rep"),
        "char_rep": F.col("char_rep") > F.col("t_char_rep"),
        "symbols": F.col("symbol_ratio") > F.col("t_symbol_ratio"),
    }
    out = signals.join(F.broadcast(limits), "lang")
    out = out.withColumn("flags", F.array_sort(F.array_compact(F.array(*(F.when(rule, F.lit(name)) for name, rule in rules.items())))))
    return out.withColumn("keep", F.size("flags") == 0).drop(*(c for c in out.columns if c.startswith("t_")))


def flag_matrix(flagged: DataFrame) -> DataFrame:
    """Documents per set of flags: what each filter removes alone and together."""
    return flagged.groupBy(F.array_join("flags", "+").alias("flag_set")).agg(F.count(F.lit(1)).alias("n"))


def calibrate(signals: DataFrame, metric: str, q: float, exact: bool = True) -> DataFrame:
    """Per-language quantile of a statistic; exact needs a language's values, approximate does not."""
    f = F.percentile(metric, F.lit(q)) if exact else F.percentile_approx(metric, F.lit(q), F.lit(10_000))
    return signals.groupBy("lang").agg(f.alias("threshold"))


def build_word_list(docs: DataFrame, labels: DataFrame, min_docs: int = 3, min_lift: float = 5.0, parity: int = 0) -> DataFrame:
    """Candidate words by how much more often toxic documents of half of the labels hold them."""
    from ..functions import text as T

    half = labels.filter(F.col("doc_id") % 2 == parity).select("doc_id", "toxic")
    held = docs.join(half, "doc_id").select("lang", "toxic", F.explode(F.array_distinct(T.folded_words(F.col("text")))).alias("word"))
    per_word = held.groupBy("lang", "word").agg(F.sum("toxic").cast("long").alias("pos"), F.sum(1 - F.col("toxic")).cast("long").alias("neg"))
    totals = docs.join(half, "doc_id").groupBy("lang").agg(F.sum("toxic").cast("long").alias("n_pos"), F.sum(1 - F.col("toxic")).cast("long").alias("n_neg"))
    lift = ((F.col("pos") + 0.5) / (F.col("n_pos") + 1.0)) / ((F.col("neg") + 0.5) / (F.col("n_neg") + 1.0))
    return per_word.filter(F.col("pos") >= min_docs).join(F.broadcast(totals), "lang").withColumn("lift", lift).filter(F.col("lift") >= min_lift).select("lang", "word", "pos", "neg", "lift")
