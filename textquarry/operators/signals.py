"""Document statistics, beside the text."""

from __future__ import annotations

import math
import re
from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import NSFW
from ..functions import text as T
from .clean import symbol_ratio

_SPACES = re.compile(r"[ \t\n\x0b\f\r]+")
#: Everything but letters of scripts other than the target one.
TARGET = r"[\p{IsLatin}\p{N}\p{P}\p{S}\p{Z}\p{M}\s]"


def nsfw_count(lang: Column, text: Column, lists: dict[str, tuple[str, ...]] = NSFW) -> Column:
    """Listed words of the language in the text, as whole words in any case."""
    out = F.lit(0)
    for name, banned in lists.items():
        if banned:
            word = r"(?<![\p{L}\p{N}_])(?:" + "|".join(banned) + r")(?![\p{L}\p{N}_])"
            out = F.when(lang == name, F.regexp_count(F.lower(text), F.lit(word))).otherwise(out)
    return out


def non_target_count(text: Column) -> Column:
    return F.length(F.regexp_replace(text, TARGET, ""))


def char_repetition(text: Column, n: int = 10, least: int = 2) -> Column:
    return T.repeated_share(F.transform(T.char_grams(text, n), lambda g: F.xxhash64(g)), least)


def word_repetition(text: Column, n: int = 5, least: int = 2) -> Column:
    return T.repeated_share(F.transform(T.ngrams(T.words(text), n), lambda g: F.xxhash64(g)), least)


def _hashed_windows(x: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(max(0, len(x) - n + 1), np.uint64)
    for k in range(n):
        out = (out ^ x[k : k + len(out)]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return out


def top_gram_share(text: pd.Series) -> pd.Series:
    """Share of the floor(sqrt(distinct)) commonest character 10-grams, inside the row; null for texts without any."""

    def share(t: str | None) -> float | None:
        h = np.sort(_hashed_windows(np.frombuffer((t or "").encode("utf-32-le"), np.uint32).astype(np.uint64), 10))
        if not len(h):
            return None
        counts = np.sort(np.diff(np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1], [True]]))))
        return float(counts[len(counts) - math.isqrt(len(counts)) :].sum() / len(h))

    return pd.Series([share(t) for t in text], dtype="float64")


def repetition_scores(text: pd.Series) -> pd.DataFrame:
    """Both n-gram scores by sorted hashes: the production form of the two column expressions above."""

    def share(h: np.ndarray) -> float:
        if not len(h):
            return 0.0
        h = np.sort(h)
        same = h[1:] == h[:-1]
        first = np.concatenate([[True], ~same])
        last = np.concatenate([~same, [True]])
        return float((~(first & last)).sum() / len(h))

    chars, words = [], []
    for t in text:
        points = np.frombuffer((t or "").encode("utf-32-le"), np.uint32).astype(np.uint64)
        chars.append(share(_hashed_windows(points, 10)))
        known: defaultdict = defaultdict()
        known.default_factory = known.__len__
        parts = [x for x in _SPACES.split(t or "") if x]
        words.append(share(_hashed_windows(np.fromiter(map(known.__getitem__, parts), np.uint64, len(parts)), 5)) if len(parts) >= 5 else 0.0)
    return pd.DataFrame({"char_rep": chars, "word_rep": words})


def signals(df: DataFrame, repetition: bool = True) -> DataFrame:
    """doc_id, lang and the statistics; arrays are made once in a projection of their own."""
    keep = [c for c in ("doc_id", "lang", "source") if c in df.columns]
    text = F.coalesce(F.col("text"), F.lit(""))
    # The arrays stand in an own projection; the optimiser does not copy expensive expressions into each use.
    count = lambda x: F.regexp_count(x, F.lit(r"\S+"))
    base = df.select(*keep, text.alias("text"), F.transform(T.sentences(text), count).alias("_s"))
    n = F.size("_s")
    columns = [
        F.octet_length("text").cast("long").alias("bytes"),
        count(F.col("text")).cast("long").alias("word_count"),
        F.length("text").cast("long").alias("char_count"),
        n.cast("long").alias("lines_count"),
        F.when(n > 0, F.aggregate("_s", F.lit(0), lambda a, x: a + x) / n).otherwise(F.lit(0.0)).alias("mean_line_length"),
        F.coalesce(F.array_min("_s"), F.lit(0)).cast("long").alias("min_line_length"),
        F.coalesce(F.array_max("_s"), F.lit(0)).cast("long").alias("max_line_length"),
        nsfw_count(F.col("lang"), F.col("text")).cast("long").alias("nsfw_words_count"),
        non_target_count(F.col("text")).cast("long").alias("non_target_count"),
    ]
    if repetition:
        base = base.withColumn("_r", F.pandas_udf(repetition_scores, "char_rep double, word_rep double")("text"))
        columns += [F.col("_r.char_rep").alias("char_rep"), F.col("_r.word_rep").alias("word_rep")]
    return base.select(*keep, *columns, symbol_ratio(F.col("text")).alias("symbol_ratio"))
