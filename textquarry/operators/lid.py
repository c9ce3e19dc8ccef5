"""Language identification: three models, the ensemble that prefers the first, and reports.

Models are tables of a fixed size made from counts that each task adds up for its own texts (distinct n-grams, never a row per
character). One pass over the texts gives the votes of all three models.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..functions.arrays import mix

#: Frequent function words.
FUNCTION_WORDS = {
    "en": ("the", "of", "and", "to", "is", "was", "that", "for", "with", "as"),
    "fr": ("le", "la", "les", "des", "et", "est", "une", "dans", "pour", "qui"),
    "de": ("der", "die", "das", "und", "ist", "nicht", "ein", "eine", "mit", "von"),
    "es": ("el", "los", "las", "del", "y", "es", "por", "con", "una", "que"),
}
#: Longest n-gram of the first model and its size; n-grams of a rank profile; confidence over which two models overrule the first.
LONGEST, MOST, RANKS, TAU = 4, 20_000, 300, 0.1


def predict_words(docs: DataFrame) -> DataFrame:
    """doc_id, lang, conf by the share of function words; ties go to the later name."""
    best = docs.select("doc_id", *_words_vote(F.col("text")))
    return best.select("doc_id", F.col("l2").alias("lang"), F.col("c2").alias("conf"))


def _words_vote(text: Column) -> tuple[Column, Column]:
    folded = T.folded_words(text)
    scores = lambda f: F.array(*(F.struct(F.size(F.filter(f, _within(ws))).alias("n"), F.lit(lang).alias("l")) for lang, ws in FUNCTION_WORDS.items()))
    best = T.let(folded, lambda f: F.struct(F.size(f).alias("t"), F.array_max(scores(f)).alias("b")))
    return best["b"]["l"].alias("l2"), (best["b"]["n"] / F.greatest(best["t"], F.lit(1))).alias("c2")


def _within(ws: tuple[str, ...]):
    return lambda w: w.isin(*ws)


def ensemble(p1: Column, p2: Column, p3: Column, conf2: Column, conf3: Column, tau: float = TAU) -> Column:
    """The preferred model, unless both others agree on another language with confidence over tau."""
    return F.when((p2 == p3) & (p2 != p1) & (F.least(conf2, conf3) > tau), p2).otherwise(F.coalesce(p1, p2))


def majority(p1: Column, p2: Column, p3: Column) -> Column:
    """Plain vote; the first model where all differ."""
    return F.when(p2 == p3, p2).otherwise(F.coalesce(p1, p2))


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)


def _windows(points: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of n characters."""
    out = np.full(max(0, len(points) - n + 1), n, np.uint64)
    for k in range(n):
        out = mix(out + points[k : k + len(out)])
    return out


def gram_counts(docs: DataFrame, longest: int = LONGEST) -> DataFrame:
    """(lang, g, c): counts of the character n-grams of the lower-case texts of each language."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, Counter] = {}

        def emit() -> Iterator[pa.RecordBatch]:
            for lang, counts in seen.items():
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(counts), pa.string()), pa.array(list(counts), pa.string()), pa.array(list(counts.values()), pa.int64())], ["lang", "g", "c"])
            seen.clear()

        for batch in batches:
            for text, lang in zip(batch.column("text").to_pylist(), batch.column("lang").to_pylist(), strict=True):
                counts, points = seen.setdefault(lang, Counter()), _points(text or "")
                for n in range(1, longest + 1):
                    _, first, times = np.unique(_windows(points, n), return_index=True, return_counts=True)
                    for i, c in zip(first.tolist(), times.tolist(), strict=True):
                        counts[text[i : i + n]] += c
            if sum(map(len, seen.values())) > 500_000:
                yield from emit()
        yield from emit()

    held = docs.filter("lang is not null").select("lang", F.lower("text").alias("text")).mapInArrow(run, "lang string, g string, c long")
    return held.groupBy("lang", "g").agg(F.sum("c").alias("c"))


@dataclass
class Models:
    langs: list[str]
    keys: np.ndarray
    logs: np.ndarray
    ranks: list[dict[int, int]]
    longest: int
    k: int


def train(docs: DataFrame, longest: int = LONGEST, most: int = MOST, k: int = RANKS) -> Models:
    """The first model's smoothed log-probabilities of the *most* commonest n-grams, and the third one's *k* commonest trigrams per language."""
    from ..shared import Workspace

    counts = Workspace(docs.sparkSession, "lid").write(gram_counts(docs, longest))
    total = {r["lang"]: r["t"] for r in counts.groupBy("lang").agg(F.sum("c").alias("t")).collect()}
    top = counts.groupBy("g").agg(F.sum("c").alias("n")).orderBy(F.col("n").desc(), "g").limit(most).select("g")
    rows = counts.join(F.broadcast(top), "g").toArrow().to_pylist()
    langs = sorted(total)
    place = {g: i for i, g in enumerate(sorted({r["g"] for r in rows}))}
    table = np.zeros((len(place), len(langs)))
    for r in rows:
        table[place[r["g"]], langs.index(r["lang"])] = r["c"]
    logs = np.log((table + 1) / (np.array([total[x] for x in langs], float) + most)) if langs else table
    keys = np.array([_windows(_points(g), len(g))[0] for g in place], np.uint64)
    order = np.argsort(keys)
    best = Window.partitionBy("lang").orderBy(F.col("c").desc(), "g")
    profile = counts.filter(F.length("g") == 3).withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k).collect()
    ranks: list[dict[int, int]] = [{} for _ in langs]
    for r in profile:
        ranks[langs.index(r["lang"])][int(_windows(_points(r["g"]), 3)[0])] = r["r"]
    return Models(langs, keys[order], logs[order], ranks, longest, k)


_VOTES = "l1 string, c1 double, l2 string, c2 double, l3 string, c3 double"


def votes(docs: DataFrame, models: Models) -> DataFrame:
    """doc_id, the language and the confidence of each model; null where a model sees nothing. Columns of docs other than the text are kept."""
    keep = [c for c in docs.columns if c != "text"]
    rows = docs.select(*keep, F.lower("text").alias("text"), *_words_vote(F.col("text")))
    seen = F.col("text").rlike(r"[\p{L}\p{N}_]")
    rows = rows.withColumn("l2", F.when(seen, F.col("l2"))).withColumn("c2", F.when(seen, F.col("c2")))
    schema = docs.select(*keep).schema
    profiles = [(np.array(sorted(p), np.uint64), np.array([p[h] for h in sorted(p)], np.int64)) for p in models.ranks]

    def first(windows: list[np.ndarray]) -> tuple[str | None, float | None]:
        h = np.concatenate(windows)
        if not len(models.keys) or not len(h):
            return None, None
        at = np.minimum(np.searchsorted(models.keys, h), len(models.keys) - 1)
        at = at[models.keys[at] == h]
        if not len(at):
            return None, None
        s = models.logs[at].mean(0)
        e = np.exp(s)
        best = max(range(len(s)), key=lambda i: (s[i], models.langs[i]))
        return models.langs[best], float(e[best] / e.sum())

    def third(text: str, h: np.ndarray) -> tuple[str | None, float | None]:
        if not len(h) or not models.langs:
            return None, None
        keys, at, times = np.unique(h, return_index=True, return_counts=True)
        # Ties of counts go by the text of the n-gram.
        own = sorted(range(len(keys)), key=lambda i: (-times[i], text[at[i] : at[i] + 3]))[: models.k] if len(keys) <= models.k else _first(keys, at, times, text, models.k)
        keys, rank = keys[own], np.arange(1, len(own) + 1)
        gains = []
        for hashes, ranks in profiles:
            i = np.minimum(np.searchsorted(hashes, keys), len(hashes) - 1) if len(hashes) else np.zeros(0, int)
            hit = hashes[i] == keys if len(hashes) else np.zeros(len(keys), bool)
            gains.append(int((models.k - np.abs(rank[hit] - ranks[i[hit]])).sum()) if hit.any() else 0)
        best = max(range(len(gains)), key=lambda i: (gains[i], models.langs[i]))
        return (models.langs[best], gains[best] / (models.k * len(own))) if gains[best] else (None, None)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ones, threes = [], []
            for text in batch.column("text").to_pylist():
                points = _points(text or "")
                windows = [_windows(points, n) for n in range(1, models.longest + 1)]
                ones.append(first(windows))
                threes.append(third(text or "", _windows(points, 3)))
            extra = [pa.array([v[i] for v in votes], t) for votes in (ones, threes) for i, t in ((0, pa.string()), (1, pa.float64()))]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), extra[0], extra[1], batch.column("l2"), batch.column("c2"), extra[2], extra[3]], [*keep, "l1", "c1", "l2", "c2", "l3", "c3"])

    from pyspark.sql.types import StructType, _parse_datatype_string

    return rows.mapInArrow(run, StructType([*schema.fields, *_parse_datatype_string(_VOTES).fields]))


def _first(keys: np.ndarray, at: np.ndarray, times: np.ndarray, text: str, k: int) -> list[int]:
    """The k commonest, ties by text: only the ties of the last count are compared as texts besides the ones above it."""
    cut = np.partition(times, -k)[-k]
    pool = np.flatnonzero(times >= cut).tolist()
    return sorted(pool, key=lambda i: (-times[i], text[at[i] : at[i] + 3]))[:k]


def report(labelled: DataFrame, truth: str, columns: dict[str, str]) -> DataFrame:
    """model, lang, precision, recall, accuracy: for each column of predictions and each language of the truth."""
    rows = F.explode(F.array(*(F.struct(F.lit(name).alias("model"), F.col(column).alias("said")) for name, column in columns.items()))).alias("v")
    v = labelled.select(F.col(truth).alias("truth"), rows).select("truth", "v.model", "v.said")
    n = v.groupBy("model", "truth", "said").agg(F.count(F.lit(1)).alias("n"))
    right = F.when(F.col("truth") == F.col("said"), F.col("n")).otherwise(0)
    overall = n.groupBy("model").agg((F.sum(right) / F.sum("n")).alias("accuracy"))
    recall = n.groupBy("model", F.col("truth").alias("lang")).agg((F.sum(right) / F.sum("n")).alias("recall"))
    precision = n.groupBy("model", F.col("said").alias("lang")).agg((F.sum(right) / F.sum("n")).alias("precision"))
    # Tables of one row per model and language.
    return recall.join(precision, ["model", "lang"], "left").join(overall, "model").select("model", "lang", F.coalesce("precision", F.lit(0.0)).alias("precision"), "recall", "accuracy")
