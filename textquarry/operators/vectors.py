"""Cosine neighbours of a stated set of query vectors among all vectors, block by block."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Vectors that one task holds while the queries pass by.
BLOCK = 65_536


def _matrix(batch: pa.RecordBatch) -> np.ndarray:
    lists = batch.column("v")
    return lists.flatten().to_numpy(zero_copy_only=False).reshape(len(lists), -1)


def vector_pairs(vectors: DataFrame, queries: DataFrame, threshold: float, block: int = BLOCK) -> DataFrame:
    """(src, dst, cosine) at or over the threshold, for each query and all other vectors.

    Vectors are dealt into blocks of about *block* rows by a hash of their id; each block is held once and the queries stream past it,
    so memory is bounded by the block. Vectors that are null, empty or zero take no part; all others have one length.
    """
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
    clean = lambda df: df.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v")).withColumn("l", norm(F.col("v"))).filter("id is not null and l > 0").select("id", F.transform("v", lambda x: x / F.col("l")).alias("v"))
    blocks = max(1, -(-vectors.count() // block))
    here = clean(vectors).select(F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("p"), F.lit(0).alias("asked"), "id", "v")
    asked = clean(queries).select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("p"), F.lit(1).alias("asked"), "id", "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, held, matrix = None, [], [], None
        for batch in batches:
            p, a = batch.column("p").to_numpy(), batch.column("asked").to_numpy()
            cuts = np.flatnonzero((np.diff(p) != 0) | (np.diff(a) != 0)) + 1
            for low, high in zip([0, *cuts.tolist()], [*cuts.tolist(), len(p)], strict=True):
                if low == high:
                    continue
                part = batch.slice(low, high - low)
                if p[low] != key:
                    key, ids, held, matrix = p[low], [], [], None
                if not a[low]:
                    ids.append(part.column("id").to_numpy())
                    held.append(_matrix(part))
                elif ids:
                    if matrix is None:
                        matrix, names = np.concatenate(held), np.concatenate(ids)
                    own = part.column("id").to_numpy()
                    cosine = _matrix(part) @ matrix.T
                    i, j = np.nonzero((cosine >= threshold) & (own[:, None] != names[None, :]))
                    yield pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(names[j]), pa.array(cosine[i, j])], ["src", "dst", "cosine"])

    dealt = here.unionByName(asked).repartition(blocks, "p").sortWithinPartitions("p", "asked")
    return dealt.mapInArrow(run, "src long, dst long, cosine double")
