"""Quality classifier: random Fourier features of document statistics, ridge by summed normal equations,
isotonic calibration.

Statistics of each whole text come from one map pass over the bytes. Labelled rows (at most
`MAX_TRAIN`, least hashes first) are joined to the narrow statistics, never to texts. Each partition of that bounded sample
sums its share of the normal equations; the shares are added and solved on the driver (a matrix whose size is fixed by
`FEATURES`). A fold of the sample that the solver has not seen is counted in fixed score bins and
made monotone by pooling adjacent violators.

Defined cases: null text is empty and gets the score of its statistics; a null id is held out and never learned from; repeated label
rows count once (the least label); without labels of both kinds all scores are the share of label 1, or 0.5 without any;
repeated documents are scored each; empty tables give empty results; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace
from ._text import _IS_SPACE, buffers, distinct_per_row, grams, segment_sum, steps, token_hashes, tokens

#: Bound of the labelled sample, random features, ridge weight, calibration bins.
MAX_TRAIN, FEATURES, RIDGE, BINS, PARTS = 60_000, 256, 1.0, 2048, 16

_B = np.arange(256)
_UPPER = (_B >= 65) & (_B <= 90)
_LETTER = _UPPER | ((_B >= 97) & (_B <= 122)) | (_B >= 128)
_DIGIT = (_B >= 48) & (_B <= 57)
_MARK = (_B > 32) & (_B < 127) & ~_LETTER & ~_DIGIT
_SYMBOL = np.isin(_B, [ord(c) for c in "#$%&*|@^~<>{}[]=+/_\\`"])
_CLASSES = [_UPPER, _LETTER, _DIGIT, _MARK, _SYMBOL, _IS_SPACE, _B == 10, _B >= 192, _B == ord("!"), _B == ord("."), _B == ord("|"), _B == ord(",")]
STATISTICS = 26


def statistics(column: pa.Array) -> np.ndarray:
    """One row of `STATISTICS` numbers per text."""
    raw, offsets = buffers(column)
    size = np.diff(offsets).astype(np.float64)
    per = np.maximum(size, 1)
    counts = [segment_sum(c[raw], offsets) for c in _CLASSES]
    upper, letters, digits, marks, symbols, space, lines, wide, shout, stop, pipe, comma = counts
    s, e, first = tokens(raw, offsets)
    words = token_hashes(raw, s, e)
    n = np.diff(first).astype(np.float64)
    per_n = np.maximum(n, 1)
    length = (e - s).astype(np.float64)
    same = np.zeros(len(words), bool)
    same[1:] = words[1:] == words[:-1]
    same[first[:-1][first[:-1] < len(words)]] = False
    kinds, begin = distinct_per_row(words, first)
    three, at3 = grams(words, first, 3)
    kinds3, begin3 = distinct_per_row(three, at3)
    # Counts of equal words: the sorted words of a row are runs.
    row = np.repeat(np.arange(len(n)), np.diff(first))
    order = np.lexsort((words, row))
    w, r = words[order], row[order]
    new = np.ones(len(w), bool)
    new[1:] = (w[1:] != w[:-1]) | (r[1:] != r[:-1])
    at = np.flatnonzero(new)
    run = np.diff(np.append(at, len(w))).astype(np.float64)
    top = np.zeros(len(n))
    full = np.flatnonzero(np.diff(begin) > 0)
    if len(full):
        top[full] = np.maximum.reduceat(run, begin[:-1][full])
    share = run / per_n[r[at]] if len(at) else run
    entropy = segment_sum(-share * np.log(np.maximum(share, 1e-12)), begin)
    mean_len = segment_sum(length, first) / per_n
    var_len = np.maximum(0, segment_sum(length**2, first) / per_n - mean_len**2)
    out = np.stack([
        np.log1p(size), np.log1p(n), mean_len, np.sqrt(var_len), upper / np.maximum(letters, 1), letters / per, digits / per, marks / per,
        symbols / per, space / per, np.log1p(lines), np.log1p(lines / per_n * 100), wide / per, shout / per_n, stop / per_n, pipe / per_n,
        comma / per_n, np.diff(begin) / per_n, segment_sum(same, first) / per_n, np.diff(begin3) / np.maximum(np.diff(at3), 1), top / per_n,
        entropy / np.log(np.maximum(n, 2)), segment_sum(length > 20, first) / per_n, segment_sum(length <= 2, first) / per_n, (size == 0).astype(float), (n < 5).astype(float),
    ], axis=1)
    return out.astype(np.float32)


def statistics_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text"):
            x = statistics(part.column("text"))
            at = np.arange(0, x.size + 1, STATISTICS, dtype=np.int32)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(pa.array(at), pa.array(x.reshape(-1)))], ["doc_id", "x"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(make, "doc_id long, x array<float>")


def fold(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo parts."""
    return F.crc32(doc_id.cast("string")) % parts


class Model:
    """Scaling, random projection, ridge weights and the monotone map to probabilities."""

    def __init__(self, base: float = 0.5) -> None:
        rng = np.random.default_rng(20240501)
        self.w = rng.normal(0, 1 / np.sqrt(STATISTICS), (STATISTICS, FEATURES))
        self.b = rng.uniform(0, 2 * np.pi, FEATURES)
        self.mean, self.scale = np.zeros(STATISTICS), np.ones(STATISTICS)
        self.weights: np.ndarray | None = None
        self.at, self.value = np.array([0.0]), np.array([base])

    def lift(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        # The constant and the plain statistics stand beside the random features.
        return np.concatenate([np.ones((len(z), 1)), z, np.sqrt(2 / FEATURES) * np.cos(z @ self.w + self.b) * 4], axis=1)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.zeros(len(x)) if self.weights is None else self.lift(x) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.raw(x), self.at, self.value)


def _matrix(part: pa.RecordBatch) -> np.ndarray:
    column = part.column("x")
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, STATISTICS)


def _summed(sample: DataFrame, share) -> list[np.ndarray]:
    """Add up `share(x, y)` (a tuple of arrays) over the partitions of the bounded sample."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for part in batches:
            if part.num_rows:
                new = share(_matrix(part), part.column("y").to_numpy(zero_copy_only=False).astype(np.float64))
                total = new if total is None else [a + b for a, b in zip(total, new, strict=True)]
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([a.astype(np.float64).tobytes() for a in total]), pa.array(range(len(total)), pa.int32())], ["v", "i"])

    out: dict[int, np.ndarray] = {}
    for v, i in sample.select("x", "y").mapInArrow(run, "v binary, i int").collect():
        new = np.frombuffer(v, np.float64)
        out[i] = out[i] + new if i in out else new
    return [out[i] for i in sorted(out)]


def pool_adjacent(value: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Least-squares non-decreasing fit."""
    blocks: list[list[float]] = []
    for v, w in zip(value, weight, strict=True):
        blocks.append([v, w, 1])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            v2, w2, n2 = blocks.pop()
            v1, w1, n1 = blocks.pop()
            blocks.append([(v1 * w1 + v2 * w2) / (w1 + w2), w1 + w2, n1 + n2])
    return np.concatenate([np.full(int(n), v) for v, _, n in blocks]) if blocks else np.zeros(0)


def fit(sample: DataFrame) -> Model:
    """`sample`: x array<float>, y int, calibrate boolean; bounded by the caller."""
    train, check = sample.filter("not calibrate"), sample.filter("calibrate")
    sums = _summed(train, lambda x, y: [np.array([len(y), y.sum()]), x.sum(0), (x**2).sum(0)])
    if not sums:
        return Model()
    n, positive = sums[0]
    model = Model(positive / n)
    if positive in (0, n):
        return model
    model.mean = sums[1] / n
    model.scale = np.sqrt(np.maximum(sums[2] / n - model.mean**2, 1e-8))
    heavy = np.array([n / (2 * (n - positive)), n / (2 * positive)])

    def share(x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
        z, w = model.lift(x), heavy[y.astype(int)]
        return [((z * w[:, None]).T @ z).reshape(-1), (z * (w * (2 * y - 1))[:, None]).sum(0)]

    gram, right = _summed(train, share)
    size = len(right)
    penalty = np.eye(size) * RIDGE
    penalty[0, 0] = 1e-6
    model.weights = np.linalg.solve(gram.reshape(size, size) + penalty, right)

    def binned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            if part.num_rows:
                k = np.clip(np.floor((model.raw(_matrix(part)) + 2) / 4 * BINS), 0, BINS - 1)
                yield pa.RecordBatch.from_arrays([pa.array(k.astype(np.int32)), part.column("y")], ["k", "y"])

    rows = check.select("x", F.col("y").cast("int").alias("y")).mapInArrow(binned, "k int, y int").groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.sum("y").alias("p")).orderBy("k").collect()
    if rows:
        k, count, ones = (np.array([r[c] for r in rows], float) for c in ("k", "n", "p"))
        fitted = pool_adjacent(ones / count, count)
        # One knot per pooled block, at its mean score, so that the map rises strictly between blocks.
        change = np.flatnonzero(np.diff(fitted)) + 1
        cuts = np.concatenate([[0], change, [len(fitted)]])
        centre = (k + 0.5) / BINS * 4 - 2
        model.at = np.array([np.average(centre[a:b], weights=count[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)])
        # A block's value leans to the base rate by one row, so that small blocks aren't certain.
        held = [(ones[a:b].sum(), count[a:b].sum()) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        model.value = np.maximum.accumulate(np.array([(p + positive / n) / (m + 1) for p, m in held]))
        if len(model.at) == 1:
            model.at, model.value = np.array([-2.0, 2.0]), np.array([max(0.0, fitted[0] - 1e-3), min(1.0, fitted[0] + 1e-3)])
    else:
        model.at, model.value = np.array([-1.0, 1.0]), np.array([0.0, 1.0])
    return model


def sample_of(stats: DataFrame, labels: DataFrame, parts: int, held_out: int, most: int = MAX_TRAIN) -> DataFrame:
    """Statistics of labelled documents outside the held-out fold, at most *most* rows."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "y").filter("doc_id is not null and y is not null")
    known = known.groupBy("doc_id").agg(F.min("y").alias("y")).filter(fold(F.col("doc_id"), parts) != held_out)
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = stats.join(F.broadcast(known), "doc_id")
    return rows.select("x", "y", (F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(4)) == 0).alias("calibrate")).repartition(PARTS)


def train(stats: DataFrame, labels: DataFrame, space: Workspace, parts: int = 3, held_out: int = 1) -> Model:
    return fit(space.write(sample_of(stats, labels.withColumnRenamed("quality", "y"), parts, held_out)))


def scores(stats: DataFrame, model: Model) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            for at in range(0, part.num_rows, 4096):
                some = part.slice(at, 4096)
                yield pa.RecordBatch.from_arrays([some.column("doc_id"), pa.array(np.clip(model.score(_matrix(some)), 0.0, 1.0))], ["doc_id", "score"])

    return stats.select("doc_id", "x").mapInArrow(run, "doc_id long, score double")


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    space = Workspace(docs.sparkSession, "quality")
    stats = space.write(statistics_table(docs))
    out = scores(stats, train(stats, labels, space))
    return out.select("doc_id", F.coalesce(fold(F.col("doc_id"), 3) == 1, F.lit(True)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """The documents that the classifier accepts; all columns stay as they are.

    The statistics are made again in the pass that filters, so texts are not shuffled.
    """
    space = Workspace(docs.sparkSession, "quality")
    model = train(space.write(statistics_table(docs)), labels, space)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text"):
            yield part.filter(pa.array(model.score(statistics(part.column("text")).astype(np.float64)) >= threshold))

    return docs.mapInArrow(run, docs.schema)
