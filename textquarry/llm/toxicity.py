"""Toxicity classifier whose scores are held still under swaps of identity terms.

Features are hashed words and word beginnings (so that compounds and endings of a stem are learned
together). A bounded sample of labelled documents gives document counts per feature, added up by
Spark; the `KEPT` features that separate the labels most are kept. Logistic regression on those is solved by
Newton steps on the driver, with a penalty on the change of the score under swaps:

    loss + ridge * |w|^2 + SWAP * sum over swaps of share * (w . (x - x'))^2

A swap is made in a labelled text: every occurrence of an identity term is replaced by another term of its group, the
changed text is read again as any text, and x - x' is what differs. So a feature that the text holds otherwise, too, does not change, and nor does
one of a text that holds both terms. A text's swaps share one unit of weight per term. Each pair of terms of a group is swapped once more as a text of the
term alone, so that terms that were rare in the sample are tied as well. Equal differences are added up by Spark.

`swap_report` measures what that does: changes of score and of decision under swaps of labelled texts.

Sizes: the sample has at most `MAX_TRAIN` rows (least hashes), so the broadcast ids, the features
sent to the driver and the weights are bounded whatever the corpus. Scoring is one map pass over whole texts.

Defined cases: null text is empty; an empty text scores as its intercept; a null id is held out and never learned
from; repeated label rows count once (the greatest label); without both labels the score is the share of label 1;
repeated documents are scored each; empty tables give empty results; other columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace
from ._text import buffers, mix, steps, token_hashes, tokens
from .quality import fold

MAX_TRAIN, KEPT, BUCKETS, RIDGE, SWAP = 40_000, 1024, 1 << 22, 0.5, 4.0
STEMS = (4, 5, 6, 7)

# Identity terms that may stand for each other, by group.
IDENTITY = (
    ("women", "men", "girls", "boys"), ("woman", "man", "girl", "boy"), ("female", "male"), ("mother", "father"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"), ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino", "african", "european"), ("gay", "straight", "lesbian", "bisexual", "queer", "transgender"),
    ("immigrants", "refugees", "foreigners", "natives", "locals"), ("old", "young", "elderly"), ("disabled", "blind", "deaf", "autistic"),
    ("femmes", "hommes"), ("musulmans", "chrétiens", "juifs", "athées"), ("noirs", "blancs", "asiatiques", "arabes"), ("immigrés", "réfugiés", "étrangers"),
    ("frauen", "männer"), ("muslime", "christen", "juden", "atheisten"), ("schwarze", "weiße", "asiaten"), ("migranten", "flüchtlinge", "ausländer"),
    ("mujeres", "hombres"), ("musulmanes", "cristianos", "judíos", "ateos"), ("negros", "blancos", "asiáticos", "árabes"), ("inmigrantes", "refugiados", "extranjeros"),
)


def word_features(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(buckets, rows, word hashes, word rows): a bucket per word and per beginning of `STEMS` bytes."""
    s, e, first = tokens(raw, offsets)
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    words = token_hashes(raw, s, e)
    parts, rows = [words], [row]
    for k in STEMS:
        long = np.flatnonzero(e - s > k)
        parts.append(mix(token_hashes(raw, s[long], s[long] + k) + np.uint64(k)))
        rows.append(row[long])
    return (np.concatenate(parts) % np.uint64(BUCKETS)).astype(np.int64), np.concatenate(rows), words, row


_GROUP = {t: g for g in IDENTITY for t in g}
_TERM = re.compile(r"(?<!\w)(" + "|".join(sorted(map(re.escape, _GROUP), key=len, reverse=True)) + r")(?!\w)", re.IGNORECASE)


def swaps(text: str) -> Iterator[tuple[str, float]]:
    """(text with a term replaced by another of its group, weight); a term's swaps share a weight of 1."""
    for term in sorted({m.lower() for m in _TERM.findall(text)} & _GROUP.keys()):
        others = [t for t in _GROUP[term] if t != term]
        for other in others:
            yield _TERM.sub(lambda m, a=term, b=other: b if m.group(0).lower() == a else m.group(0), text), 1 / len(others)


def _distinct(bucket: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    key = np.unique(row.astype(np.int64) * BUCKETS + bucket)
    return key % BUCKETS, key // BUCKETS


def labelled(docs: DataFrame, labels: DataFrame, parts: int, held_out: int, most: int = MAX_TRAIN) -> DataFrame:
    """Texts of a bounded sample of labelled documents outside the held-out fold."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "y").filter("doc_id is not null and y is not null")
    known = known.groupBy("doc_id").agg(F.max("y").alias("y")).filter(fold(F.col("doc_id"), parts) != held_out)
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    return docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").select("text", "y")


def feature_counts(sample: DataFrame) -> DataFrame:
    """(bucket, pos, neg): documents of either label that hold the feature, per feature seen with label 1."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros((2, BUCKETS), np.int32)
        for part in steps(batches, "text"):
            y = part.column("y").to_numpy(zero_copy_only=False).astype(int)
            bucket, row, _, _ = word_features(*buffers(part.column("text")))
            bucket, row = _distinct(bucket, row)
            for label in (0, 1):
                seen[label] += np.bincount(bucket[y[row] == label], minlength=BUCKETS).astype(np.int32)
        at = np.flatnonzero(seen[0] + seen[1])
        for k in range(0, len(at), 100_000):
            i = at[k : k + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(seen[1][i]), pa.array(seen[0][i])], ["bucket", "pos", "neg"])

    # A feature without any document of label 1 can't be picked, but its share in another partition may have one.
    return sample.mapInArrow(count, "bucket int, pos int, neg int").groupBy("bucket").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg")).filter("pos > 0")


class Model:
    def __init__(self, intercept: float) -> None:
        self.buckets, self.weights, self.intercept = np.zeros(0, np.int64), np.zeros(0), intercept


def _places(model: Model) -> np.ndarray:
    place = np.full(BUCKETS, -1, np.int16)
    place[model.buckets] = np.arange(len(model.buckets))
    return place


def _held(texts: pa.Array, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(kept features, first feature of each text): the distinct kept features of each text, ascending."""
    bucket, row, _, _ = word_features(*buffers(texts))
    hit = place[bucket] >= 0
    bucket, row = _distinct(bucket[hit], row[hit])
    return place[bucket].astype(np.int32), np.searchsorted(row, np.arange(len(texts) + 1))


def _swap_rows(texts: list[str]) -> tuple[list[int], list[str], list[float]]:
    at, changed, weight = [], [], []
    for i, text in enumerate(texts):
        for new, w in swaps(text):
            at.append(i)
            changed.append(new)
            weight.append(w)
    return at, changed, weight


def swap_differences(sample: DataFrame, model: Model) -> DataFrame:
    """(gone, new, weight): kept features that swaps in the texts take away and bring, and the weight of all swaps that do so."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = _places(model)
        for part in steps(batches, "text"):
            texts = [t or "" for t in part.column("text").to_pylist()]
            at, changed, weight = _swap_rows(texts)
            if not at:
                continue
            x, first = _held(part.column("text"), place)
            for low in range(0, len(at), 1000):
                y, second = _held(pa.array(changed[low : low + 1000], pa.large_string()), place)
                gone, new, shares = [], [], []
                for k, i in enumerate(at[low : low + 1000]):
                    a, b = x[first[i] : first[i + 1]], y[second[k] : second[k + 1]]
                    minus, plus = np.setdiff1d(a, b), np.setdiff1d(b, a)
                    if len(minus) or len(plus):
                        gone.append(minus.tolist())
                        new.append(plus.tolist())
                        shares.append(weight[low + k])
                yield pa.RecordBatch.from_arrays([pa.array(gone, pa.list_(pa.int32())), pa.array(new, pa.list_(pa.int32())), pa.array(shares, pa.float64())], ["gone", "new", "weight"])

    if not len(model.buckets):
        return sample.sparkSession.createDataFrame([], "gone array<int>, new array<int>, weight double")
    found = sample.select("text").mapInArrow(run, "gone array<int>, new array<int>, weight double")
    return found.groupBy("gone", "new").agg(F.sum("weight").alias("weight"))


def fit(sample: DataFrame, kept: int = KEPT, swap_weight: float = SWAP) -> Model:
    totals = {r["y"]: r["n"] for r in sample.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    pos, neg = totals.get(1, 0), totals.get(0, 0)
    if not pos or not neg:
        share = pos / (pos + neg) if pos + neg else 0.5
        return Model(float(np.log((share + 1e-3) / (1 - share + 1e-3))))
    # Signed root of the likelihood-ratio statistic would need logs of zero; the chi-square form does not.
    counts = feature_counts(sample)
    gap = F.col("pos") * F.lit(float(neg)) - F.col("neg") * F.lit(float(pos))
    seen = F.col("pos") + F.col("neg")
    chi = gap * gap / (seen * (F.lit(float(pos + neg)) - seen + 1.0))
    best = counts.filter("pos + neg >= 3").withColumn("chi", chi).orderBy(F.col("chi").desc(), "bucket").limit(kept).select("bucket").collect()
    model = Model(0.0)
    model.buckets = np.sort(np.array([r["bucket"] for r in best], np.int64))
    size = len(model.buckets)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = _places(model)
        for part in steps(batches, "text"):
            x, first = _held(part.column("text"), place)
            yield pa.RecordBatch.from_arrays([part.column("y"), pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(x))], ["y", "x"])

    rows = sample.select("text", F.col("y").cast("int").alias("y")).mapInArrow(encode, "y int, x array<int>").toArrow()
    y = rows.column("y").to_numpy().astype(np.float64)
    lists = rows.column("x").combine_chunks()
    ends, x = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False)

    # Swap differences, as a quadratic form in the weights.
    swap = np.zeros((size + 1, size + 1))

    def tie(minus: list[int], plus: list[int], weight: float) -> None:
        at, d = np.array([*minus, *plus], int), np.array([1.0] * len(minus) + [-1.0] * len(plus))
        swap[np.ix_(at, at)] += weight * np.outer(d, d)

    if swap_weight:
        for r in swap_differences(sample, model).toArrow().to_pylist():
            tie(r["gone"], r["new"], r["weight"])
        place = _places(model)
        for group in IDENTITY:
            alone, first = _held(pa.array(group, pa.string()), place)
            held = [set(alone[first[i] : first[i + 1]].tolist()) for i in range(len(group))]
            for i, a in enumerate(held):
                for b in held[i + 1 :]:
                    if a != b:
                        tie(sorted(a - b), sorted(b - a), len(y) / 1000)

    w = np.zeros(size + 1)
    w[size] = np.log(pos / neg)
    ridge = np.full(size + 1, RIDGE)
    ridge[size] = 1e-6

    def blocks() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Rows as dense blocks of bounded size, and their labels."""
        for low in range(0, len(y), 4096):
            high = min(low + 4096, len(y))
            dense = np.zeros((high - low, size + 1), np.float32)
            dense[np.repeat(np.arange(high - low), np.diff(ends[low : high + 1])), x[ends[low] : ends[high]]] = 1
            dense[:, size] = 1
            yield dense, y[low:high]

    for _ in range(12):
        grad, hess = ridge * w + 2 * swap_weight * (swap @ w), np.diag(ridge) + 2 * swap_weight * swap
        for dense, label in blocks():
            p = 1 / (1 + np.exp(-np.clip(dense @ w.astype(np.float32), -30, 30).astype(np.float64)))
            grad += (dense.T @ (p - label).astype(np.float32)).astype(np.float64)
            hess += ((dense * np.maximum(p * (1 - p), 1e-6).astype(np.float32)[:, None]).T @ dense).astype(np.float64)
        move = np.linalg.solve(hess, grad)
        w -= move
        if np.abs(move).max() < 1e-4:
            break
    model.weights, model.intercept = w[:size], float(w[size])
    return model


def train(docs: DataFrame, labels: DataFrame, parts: int = 5, held_out: int = 0, swap_weight: float = SWAP) -> Model:
    space = Workspace(docs.sparkSession, "toxicity")
    return fit(space.write(labelled(docs, labels.withColumnRenamed("toxic", "y"), parts, held_out).repartition(12)), swap_weight=swap_weight)


def _score(texts: pa.Array, model: Model, place: np.ndarray) -> np.ndarray:
    x, first = _held(texts, place)
    row = np.repeat(np.arange(len(texts)), np.diff(first))
    total = model.intercept + np.bincount(row, weights=model.weights.astype(np.float64)[x] if len(model.buckets) else None, minlength=len(texts))
    return 1 / (1 + np.exp(-np.clip(total, -40, 40)))


def scores(docs: DataFrame, model: Model) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = _places(model)
        for part in steps(batches, "text"):
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(_score(part.column("text"), model, place))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")


def swap_report(texts: DataFrame, model: Model) -> DataFrame:
    """(toxic, swaps, mean_change, flips, called_toxic) per label of (text, toxic): swaps of identity terms in these texts, the mean change of the score,
    changes of the decision, and texts with a term that are called toxic (of label 0: false positives on neutral mentions)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = _places(model)
        for part in steps(batches, "text"):
            at, changed, weight = _swap_rows([t or "" for t in part.column("text").to_pylist()])
            if not at:
                continue
            base = _score(part.column("text"), model, place)
            new = _score(pa.array(changed, pa.large_string()), model, place)
            y, at, first = part.column("toxic").to_numpy(zero_copy_only=False), np.array(at), np.diff(np.array(at), prepend=-1) != 0
            yield pa.RecordBatch.from_arrays(
                [pa.array(y[at].astype(np.int32)), pa.array(np.abs(new - base[at])), pa.array((new >= 0.5) != (base[at] >= 0.5)), pa.array(first & (base[at] >= 0.5))], ["toxic", "change", "flip", "called"]
            )

    rows = texts.select("text", F.col("toxic").cast("int").alias("toxic")).filter("toxic is not null").mapInArrow(run, "toxic int, change double, flip boolean, called boolean")
    return rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("swaps"), F.avg("change").alias("mean_change"), F.count_if("flip").alias("flips"), F.count_if("called").alias("called_toxic"))


def toxicity_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    out = scores(docs, train(docs, labels))
    return out.select("doc_id", F.coalesce(fold(F.col("doc_id"), 5) == 0, F.lit(True)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
