"""Exact top-k by inner product with a pivot table.

Vectors are turned into integers, floor(64 x). One more coordinate makes all stored vectors equally long,
so that a larger inner product is a smaller distance: d(q, x)^2 = |q|^2 + M - 2 q.x with M the greatest squared length.
Distances of every vector to `PIVOTS` pivots are the table, written beside the vectors. For a query, the greatest difference of its own pivot
distances and a vector's is a lower bound of their distance, hence an upper bound of their score. Runs of rows whose bound reaches the
threshold of a query are evaluated in the order of their bounds, until the next bound is under its k-th score so far. The first
threshold of a query comes from a bounded sample, whose exact scores are real candidates.

Rows are dealt by nearest pivot (a range partition with the distance and the id as further keys, so that a vector that a
third of the rows repeat spreads) into blocks of about `HELD` rows. A task holds one block, cut into runs of `RUN` rows at most, rings
around one pivot, with intervals of pivot distances, which eliminate whole runs, and the queries stream past it, `TOGETHER` at a time, neighbours first: one matrix product for all queries
that a run is open to. Only long vectors (`WIDE`) are bounded row by row within a run: for others 128 differences cost far more than the product
that they may save. Nothing passes through the driver, and memory is bounded by the block.
Each block answers with k rows per query at most, and a last aggregation keeps k per query.

How much is eliminated depends on the vectors: `evaluated` reports it. Vectors without clusters (independent components, 64 of them) lie at nearly
equal distances from all pivots, and most pairs must be evaluated then; results are exact either way.

Defined cases: vectors that are null, hold null or non-finite components, or differ in length from the pivots take no part, neither
as query nor as candidate; equal scores go to the smaller id; rows that repeat an id are one row (the least vector); null ids
take no part; fewer than k candidates give all; empty tables give an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._tables import Workspace

PIVOTS, SAMPLE, HELD, RUN, STEP = 128, 4096, 65_536, 256, 1024
#: Queries that are searched together, and answers after which their thresholds are raised.
TOGETHER, FRESH = 256, 32_768
#: Vectors so many times longer than the list of pivots cost more to multiply than to bound one by one.
WIDE = 16
#: Rounding of distances and bounds; scores are whole numbers.
SLACK = 0.25
SCALE = 64


def to_integers(vector: Column, scale: int = SCALE) -> Column:
    """floor(scale * x) per component, or null where the vector takes no part."""
    wide = F.transform(vector, lambda x: x.cast("double"))
    bad = F.exists(wide, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    whole = F.transform(wide, lambda x: F.floor(x * F.lit(float(scale))).cast("long"))
    return F.when(vector.isNotNull() & ~F.coalesce(bad, F.lit(True)) & (F.size(vector) > 0), whole)


def _rows(column: pa.Array, dim: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def choose_pivots(sample: np.ndarray, count: int) -> np.ndarray:
    """Farthest-first choice from the sample."""
    picked = [int(np.argmax((sample**2).sum(1)))]
    far = ((sample - sample[picked[0]]) ** 2).sum(1)
    while len(picked) < min(count, len(sample)) and far.max() > 0:
        picked.append(int(np.argmax(far)))
        far = np.minimum(far, ((sample - sample[picked[-1]]) ** 2).sum(1))
    return sample[picked]


def _distances(x: np.ndarray, last: np.ndarray, pivots: np.ndarray, pivot_last: np.ndarray) -> np.ndarray:
    square = (x**2).sum(1)[:, None] + (pivots**2).sum(1)[None, :] - 2 * (x @ pivots.T) + (last[:, None] - pivot_last[None, :]) ** 2
    return np.sqrt(np.maximum(square, 0))


class _Block:
    """Rows of one block and their pivot distances; *x* is of a type in which all products are exact."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, d: np.ndarray, top: float) -> None:
        # Runs are rings of one cell: the shuffle that brings the rows need not keep their order.
        cell = d.argmin(1)
        turn = np.lexsort((d[np.arange(len(d)), cell], cell))
        self.ids, self.x, self.d, self.top = ids[turn], x[turn], np.ascontiguousarray(d[turn].T, np.float32), top
        cell = cell[turn]
        at = np.flatnonzero((np.arange(len(cell)) - np.searchsorted(cell, cell)) % RUN == 0)
        self.at = np.append(at, len(ids))
        self.low, self.high = np.minimum.reduceat(self.d, at, axis=1), np.maximum.reduceat(self.d, at, axis=1)

    def _bound(self, square: np.ndarray, far: np.ndarray) -> np.ndarray:
        """Upper bound of the score from a lower bound of the distance, with room for the rounding of distances."""
        return (square + self.top - far.astype(np.float64) ** 2) / 2 + SLACK + (square + self.top) * 2.0**-21

    def _runs(self, square: np.ndarray, q_d: np.ndarray) -> np.ndarray:
        """Bounds of all queries and runs by the intervals of pivot distances."""
        far = np.zeros((len(q_d), self.low.shape[1]), np.float32)
        gap = np.empty_like(far)
        for p in range(len(self.low)):
            own = q_d[:, p, None]
            np.maximum(far, np.subtract(self.low[p], own, out=gap), out=far)
            np.maximum(far, np.subtract(own, self.high[p], out=gap), out=far)
        return self._bound(square[:, None], far)

    def _rows(self, square: np.ndarray, q_d: np.ndarray, rows: slice) -> np.ndarray:
        """Bounds of all queries and the rows of a run by the table itself."""
        d = self.d[:, rows]
        far = np.zeros((len(q_d), d.shape[1]), np.float32)
        gap = np.empty_like(far)
        for p in range(len(d)):
            np.maximum(far, np.abs(np.subtract(d[p], q_d[:, p, None], out=gap), out=gap), out=far)
        return self._bound(square[:, None], far)

    def search(self, q_ids: np.ndarray, q: np.ndarray, q_d: np.ndarray, floor: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """For queries together: places of queries, ids and scores of the k best of the block that reach the floor; how many rows each query evaluated."""
        square, least, done = (q.astype(np.float64) ** 2).sum(1), floor.astype(np.float64), np.zeros(len(q), np.int64)
        q, q_d = q.astype(self.x.dtype), q_d.astype(np.float32)
        bound = self._runs(square, q_d)
        who, ids, scores, fresh = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)], 0

        def best() -> None:
            """The k best so far; the k-th is the next threshold."""
            nonlocal fresh
            w, i, s = np.concatenate(who), np.concatenate(ids), np.concatenate(scores)
            turn = np.lexsort((i, -s, w))
            w, i, s = w[turn], i[turn], s[turn]
            rank = np.arange(len(w)) - np.searchsorted(w, w)
            full = rank == k - 1
            least[w[full]] = s[full]
            who[:], ids[:], scores[:], fresh = [w[rank < k]], [i[rank < k]], [s[rank < k]], 0

        for run in np.argsort(-bound.max(0), kind="stable"):
            at = np.flatnonzero(bound[:, run] >= least)
            if not len(at):
                continue
            rows = slice(self.at[run], self.at[run + 1])
            x, own = self.x[rows], self.ids[rows]
            if x.shape[1] >= WIDE * len(self.d):
                some = (self._rows(square[at], q_d[at], rows) >= least[at, None]).any(0)
                x, own = x[some], own[some]
            score = (q if len(at) == len(q) else q[at]) @ x.T
            done[at] += len(own)
            hit = np.flatnonzero(score >= least[at, None].astype(score.dtype))
            if len(hit):
                row, column = np.divmod(hit, len(own))
                found = own[column]
                other = found != q_ids[at[row]]
                who.append(at[row[other]])
                ids.append(found[other])
                scores.append(score.reshape(-1)[hit[other]].astype(np.float64))
                fresh += len(ids[-1])
                if fresh >= FRESH:
                    best()
        best()
        return who[0], ids[0], scores[0], done


def _answers(vectors: DataFrame, queries: DataFrame, k: int, id_col: str, vector_col: str, held: int) -> tuple[Workspace, DataFrame] | None:
    """(query_id, vec_id, score, block, evaluated, rows): per query and block the k best; a block without any has a row with null id and score."""
    spark = vectors.sparkSession
    space = Workspace(spark, "topk")
    clean = lambda df: df.select(F.col(id_col).cast("long").alias("id"), to_integers(F.col(vector_col)).alias("v")).filter("id is not null and v is not null").groupBy("id").agg(F.min("v").alias("v"))
    rows = space.write(clean(vectors))
    asked = space.write(clean(queries))
    sample = rows.orderBy(F.xxhash64("id"), "id").limit(SAMPLE).toArrow()
    if not sample.num_rows:
        return None
    dim = int(np.bincount([len(v) for v in sample.column("v").to_pylist()]).argmax())
    fits = F.size("v") == dim
    rows, asked = rows.filter(fits), asked.filter(fits)
    sample = sample.filter(pa.compute.equal(pa.compute.list_value_length(sample.column("v")), dim)).combine_chunks()
    sample_x, sample_ids = _rows(sample.column("v"), dim), sample.column("id").to_numpy()
    square = F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x * x)
    count, top = rows.agg(F.count(F.lit(1)), F.max(square)).first()
    top = float(top)
    # Whole numbers, and all their partial sums, are exact below 2^24 in short floats.
    kind = np.float32 if top * (asked.agg(F.max(square)).first()[0] or 0) < 2.0**48 else np.float64
    pivots = choose_pivots(sample_x, PIVOTS)
    pivot_last = np.sqrt(np.maximum(top - (pivots**2).sum(1), 0))

    def tabulate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            if part.num_rows:
                x = _rows(part.column("v"), dim)
                d = _distances(x, np.sqrt(np.maximum(top - (x**2).sum(1), 0)), pivots, pivot_last).astype(np.float32)
                at = pa.array(np.arange(0, d.size + 1, d.shape[1], dtype=np.int32))
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), part.column("v"), pa.ListArray.from_arrays(at, pa.array(d.reshape(-1))), pa.array(d.argmin(1).astype(np.int32)), pa.array(d.min(1).astype(np.float64))],
                    ["id", "v", "d", "cell", "near"],
                )

    table = rows.mapInArrow(tabulate, "id long, v array<long>, d array<float>, cell int, near double")
    # At least a block per core, while blocks have some rows, and as many for each core.
    cores = spark.sparkContext.defaultParallelism
    blocks = max(1, -(-count // held), min(cores, count // STEP))
    blocks = -(-blocks // cores) * cores if blocks > cores else blocks
    table = table.repartitionByRange(blocks, "cell", "near", "id").sortWithinPartitions("cell", "near", "id")
    table = space.write(table.select(F.pmod(F.spark_partition_id(), F.lit(blocks)).alias("p"), "id", "v", "d"))

    def first_threshold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                q, own = _rows(part.column("v"), dim), part.column("id").to_numpy()
                score = np.rint(q @ sample_x.T)
                score[own[:, None] == sample_ids[None, :]] = -np.inf
                floor = np.partition(score, -k, axis=1)[:, -k] if score.shape[1] > k else np.full(len(q), -np.inf)
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("v"), pa.array(floor)], ["id", "v", "floor"])

    # Each block makes the pivot distances of the queries again: they are longer than the queries, of which every block has a copy.
    asked = asked.mapInArrow(first_threshold, "id long, v array<long>, floor double")
    asked = space.write(asked).select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("p"), "id", "v", F.lit(None).cast("array<float>").alias("d"), "floor")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, parts, block = None, [], None
        for batch in batches:
            p, is_query = batch.column("p").to_numpy(), ~np.asarray(batch.column("floor").is_null())
            cuts = np.flatnonzero((np.diff(p) != 0) | (is_query[1:] != is_query[:-1])) + 1
            for low, high in zip([0, *cuts.tolist()], [*cuts.tolist(), len(p)], strict=True):
                if low == high:
                    continue
                part = batch.slice(low, high - low)
                x, ids = _rows(part.column("v"), dim), part.column("id").to_numpy()
                if p[low] != key:
                    key, parts, block = p[low], [], None
                if not is_query[low]:
                    parts.append((ids, x.astype(kind), _rows(part.column("d"), len(pivots)).astype(np.float32)))
                    continue
                if not parts:
                    continue
                if block is None:
                    block, parts = _Block(*(np.concatenate([part[i] for part in parts]) for i in range(3)), top), [()]
                d, floor = _distances(x, np.zeros(len(x)), pivots, pivot_last), part.column("floor").to_numpy()
                # Neighbours ask for the same runs.
                turn = np.argsort(d.argmin(1), kind="stable")
                for begin in range(0, len(turn), TOGETHER):
                    own = turn[begin : begin + TOGETHER]
                    who, found, score, done = block.search(ids[own], x[own], d[own], floor[own], k)
                    none = np.setdiff1d(np.arange(len(own)), who)
                    at, empty = np.concatenate([who, none]), pa.nulls(len(none), pa.int64())
                    same = lambda value: pa.array(np.full(len(at), value, np.int64))  # noqa: B023, E731
                    columns = [pa.array(ids[own][at]), pa.concat_arrays([pa.array(found), empty]), pa.concat_arrays([pa.array(score.astype(np.int64)), empty]), same(key), pa.array(done[at]), same(len(block.ids))]
                    yield pa.RecordBatch.from_arrays(columns, ["query_id", "vec_id", "score", "block", "evaluated", "rows"])

    both = table.withColumn("floor", F.lit(None).cast("double")).unionByName(asked)
    dealt = both.repartitionById(blocks, "p").sortWithinPartitions("p", F.col("floor").isNotNull())
    return space, dealt.select("p", "id", "v", "d", "floor").mapInArrow(search, "query_id long, vec_id long, score long, block long, evaluated long, rows long")


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", held: int = HELD) -> DataFrame:
    """query_id, rank, vec_id, score: the k greatest inner products of each query among all other rows."""
    answers = _answers(vectors, queries, k, id_col, vector_col, held)
    if answers is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    found = answers[0].write(answers[1].filter("vec_id is not null").select("query_id", "vec_id", "score"))
    by_query = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(by_query)).filter(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def evaluated(vectors: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", held: int = HELD) -> DataFrame:
    """query_id, evaluated, rows: how many rows each query evaluated, of how many."""
    answers = _answers(vectors, queries, k, id_col, vector_col, held)
    if answers is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, evaluated long, rows long")
    per_block = answers[1].select("query_id", "block", "evaluated", "rows").distinct()
    return per_block.groupBy("query_id").agg(F.sum("evaluated").alias("evaluated"), F.sum("rows").alias("rows"))


ORACLE = r"""
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS DOUBLE)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 20
"""
