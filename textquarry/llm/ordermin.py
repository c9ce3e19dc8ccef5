"""Order MinHash fingerprints, which follow edit distance rather than set overlap.

Tokens are words and single marks (`_text`). Every k-mer of tokens carries the number of its earlier occurrences in the
text, so that repeated k-mers differ. For each of `SKETCHES` hash functions the `TUPLE` k-mers of least hash are chosen,
put back into text order, and hashed as a tuple; the tuples are the fingerprint. Two fingerprints' likeness is the share of
equal tuples. A moved passage changes tuples although the set of k-mers stays.

`fingerprint_edits` gives each document's fingerprint, that of its edited text (last half replaced by the start of the next document,
in descending id), and likenesses. The next document is found without a global sort in one task: a sorted pass over ids and
lengths cuts the ids into ranges of about `RANGE_BYTES` of text, each range is one partition that also gets the first document of the
range after it, and a sorted stream does the rest. Texts are shuffled once. The driver holds one number per range, at most
`MOST_RANGES`; beyond that many times `RANGE_BYTES` ranges hold more bytes, which costs parallelism but no memory, as they are streamed.

Defined cases: null text is empty; all texts without tokens share one fingerprint; fewer tokens than k make one k-mer, fewer
k-mers than TUPLE make a tuple of those; equal ids follow each other by text, in descending order; a null id comes last; the only
document is its own successor; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._text import buffers, grams, mix, token_hashes, tokens

K, SKETCHES, TUPLE = 3, 32, 2
#: Bytes of text (document and edited text) per vectorised step, bytes of a range, and most ranges.
_STEP, RANGE_BYTES, MOST_RANGES = 1 << 20, 8 << 20, 1 << 18


def _occurrences(values: np.ndarray, row: np.ndarray) -> np.ndarray:
    """How many equal values stand before each value in its row."""
    key = mix(values ^ mix(row.astype(np.uint64) + np.uint64(1)))
    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    first = np.ones(len(key), bool)
    first[1:] = sorted_key[1:] != sorted_key[:-1]
    start = np.flatnonzero(first)
    run = np.arange(len(key)) - np.repeat(start, np.diff(np.append(start, len(key))))
    out = np.empty(len(key), np.int64)
    out[order] = run
    return out


def fingerprints(texts: pa.Array, k: int = K, sketches: int = SKETCHES, size: int = TUPLE) -> np.ndarray:
    """uint64 array, a row of tuple hashes per text."""
    raw, offsets = buffers(texts)
    s, e, first = tokens(raw, offsets, marks=True)
    values, begin = grams(token_hashes(raw, s, e, fold=False), first, k)
    n = len(texts)
    out = np.zeros((n, sketches), np.uint64)
    if not len(values):
        return out
    count = np.diff(begin)
    row = np.repeat(np.arange(n), count)
    values = mix(values ^ mix(_occurrences(values, row).astype(np.uint64) * np.uint64(0x9E3779B1)))
    place = np.arange(len(values)) - begin[:-1][row]
    bits = max(1, int(count.max() - 1).bit_length())
    low = np.uint64((1 << bits) - 1)
    full = np.flatnonzero(count > 0)
    at = begin[:-1][full]
    factor = mix(np.arange(7001, 7001 + sketches, dtype=np.uint64)) | np.uint64(1)
    slot = place.astype(np.uint64)
    done = np.uint64(2**64 - 1)
    for j in range(sketches):
        # High bits order the k-mers, low bits remember the place: one minimum gives both.
        h = (mix_fast(values * factor[j]) & ~low) | slot
        chosen = np.full((len(full), size), -1, np.int64)
        for t in range(min(size, int(count.max()))):
            least = np.minimum.reduceat(h, at)
            where = (least & low).astype(np.int64)
            ok = (count[full] > t)
            chosen[ok, t] = where[ok]
            h[at[ok] + where[ok]] = done
        chosen.sort(axis=1)
        total = np.zeros(len(full), np.uint64)
        for t in range(size):
            has = chosen[:, t] >= 0
            part = np.zeros(len(full), np.uint64)
            part[has] = values[at[has] + chosen[has, t]]
            total = mix(total * np.uint64(31) + part + np.uint64(t + 1))
        out[full, j] = total
    return out


def mix_fast(x: np.ndarray) -> np.ndarray:
    """High bits of a product are good enough once the values are mixed."""
    return x ^ (x >> np.uint64(32))


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a == b).mean(axis=1)


def to_hex(prints: np.ndarray) -> list[str]:
    return [r.tobytes().hex() for r in prints.astype(">u8")]


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint: map-only."""
    from ._text import steps

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text", _STEP):
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(to_hex(fingerprints(part.column("text"))))], ["doc_id", "fingerprint"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, fingerprint string")


_SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _emit(ids: list, texts: list[str]) -> pa.RecordBatch:
    """texts holds one more than ids: the last one's successor."""
    n = len(ids)
    edited = []
    for t, u in zip(texts[:-1], texts[1:], strict=True):
        half = len(t) // 2
        edited.append(t[: len(t) - half] + u[:half])
    own = fingerprints(pa.array(texts, pa.large_string()))
    new = fingerprints(pa.array(edited, pa.large_string()))
    return pa.RecordBatch.from_arrays(
        [
            pa.array(ids, pa.int64()), pa.array([len(t) for t in texts[:-1]], pa.int64()), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited], pa.string()),
            pa.array(to_hex(own[:n]), pa.string()), pa.array(to_hex(new), pa.string()), pa.array(likeness(own[:n], new)), pa.array(likeness(own[:n], own[1:])),
        ],
        ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
    )


def _stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted: ranges in order, each in descending id, then its lookahead row."""
    ids: list = []
    texts: list[str] = []
    size = 0
    for batch in batches:
        for k in range(0, batch.num_rows, 256):
            part = batch.slice(k, 256)
            for doc, text, ahead in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), part.column("ahead").to_pylist(), strict=True):
                texts.append(text or "")
                size += len(texts[-1])
                if ahead:
                    if ids:
                        yield _emit(ids, texts)
                    ids, texts, size = [], [], 0
                    continue
                if size > _STEP and ids:
                    yield _emit(ids, texts)
                    texts = texts[-1:]
                    ids, size = [], len(texts[0])
                ids.append(doc)


def _cuts(keys: DataFrame, range_bytes: int) -> list[int]:
    """Least ids of the ranges, greatest first: a pass in order of ids closes a range after so many bytes."""

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = 0
        for batch in batches:
            ids, size = batch.column("doc_id").to_numpy(), batch.column("size").to_numpy()
            done = total + np.cumsum(size)
            total = int(done[-1]) if len(done) else total
            full = done // range_bytes > (done - size) // range_bytes
            if full.any():
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(ids[full]))], ["cut"])

    held = keys.filter("doc_id is not null").repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    return sorted({r["cut"] for r in held.mapInArrow(close, "cut long").collect()}, reverse=True)


def _range_of(doc_id: Column, cuts: list[int]) -> Column:
    """How many cuts are greater than the id, by binary search; a null id stands under all cuts."""
    steps = [1 << k for k in reversed(range(len(cuts).bit_length()))]
    cut_array = F.from_json(F.lit(json.dumps(cuts)), "array<bigint>")
    further = lambda at, step: F.when(F.coalesce(F.get(cut_array, at + step - 1) > doc_id, F.lit(False)), at + step).otherwise(at)
    found = F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), further) if cuts else F.lit(0)
    return F.when(doc_id.isNull(), F.lit(len(cuts))).otherwise(found).cast("int")


def fingerprint_edits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", range_bytes: int = RANGE_BYTES) -> DataFrame:
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    keys = rows.select("doc_id", (F.octet_length("text") + 1).cast("long").alias("size"))
    total = keys.agg(F.sum("size")).first()[0]
    if not total:
        return spark.createDataFrame([], _SCHEMA)
    cuts = _cuts(keys, max(range_bytes, -(-total // MOST_RANGES)))
    # Range 0 has the greatest ids.
    part = _range_of(F.col("doc_id"), cuts)
    heads = keys.withColumn("r", part).groupBy("r").agg(F.max(F.struct(F.col("doc_id").isNotNull(), "doc_id")).alias("m")).orderBy("r").select("r", "m.doc_id").collect()
    order = [h["r"] for h in heads]
    # A range that is not empty hands its first document to the one before it; the first range's goes to the last.
    before = {r: order[i - 1] for i, r in enumerate(order)}
    head = spark.createDataFrame([(h["r"], h["doc_id"], before[h["r"]]) for h in heads], "r int, head long, target int")
    tagged = rows.withColumn("r", part).join(F.broadcast(head), "r")
    # A head goes to its own range and ahead to the one before. Of rows that share a head's id, all go there and the first of them counts.
    stay = F.struct(F.col("r").alias("r"), F.lit(False).alias("ahead"))
    go = F.struct(F.col("target").alias("r"), F.lit(True).alias("ahead"))
    places = F.when(F.col("doc_id").eqNullSafe(F.col("head")), F.array(stay, go)).otherwise(F.array(stay))
    both = tagged.select("doc_id", "text", F.explode(places).alias("p")).select("doc_id", "text", "p.r", "p.ahead")
    dealt = both.repartitionById(len(cuts) + 1, "r").sortWithinPartitions("r", "ahead", F.col("doc_id").desc_nulls_last(), F.col("text").desc())
    return dealt.select("doc_id", "text", "ahead").mapInArrow(_stream, _SCHEMA)
