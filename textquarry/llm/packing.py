"""Best-fit packing of documents into training sequences of several permitted lengths.

Lengths are summed per document; documents longer than the greatest length are cut into pieces of it and a rest. Pieces
are dealt by hash into groups of about `GROUP` pieces, and each group is packed on its own, longest piece first:

* a piece goes to the open bin with the least room that still holds it;
* if none does, a bin is opened. Which sizes may be opened is chosen for the group as a whole: every suffix of the
  permitted lengths is tried on the group's histogram, a new bin being the one of least cost per token among them, and the
  plan of least total cost wins;
* at last each bin shrinks to the smallest permitted length that holds its contents.

The cost of a bin is its length plus `OVERHEAD`. Only ids and lengths are shuffled. Groups are fixed by hashes, so a rerun gives
the same bins; a group's size does not grow with the corpus.

Defined cases: null or empty text has length 0 and takes no place (a row with null bin); ties go to the smaller id and piece; rows that repeat
an id are packed each; a null id packs like any other; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CAPACITIES = (256, 512, 1024, 2048, 4096)
OVERHEAD, GROUP = 8, 100_000


def word_count(text: Column) -> Column:
    """Tokens by white space; null counts as 0."""
    return F.coalesce(F.regexp_count(text, F.lit(r"\S+")), F.lit(0))


def cost(capacity: int, overhead: int = OVERHEAD) -> int:
    return capacity + overhead


def best_fit(lengths: list[int], openable: tuple[int, ...], capacities: tuple[int, ...] = CAPACITIES) -> tuple[list[int], list[int]]:
    """(bin of each item, final capacity of each bin) for items in the order given.

    Open bins are held by room: a sorted list of rooms, and the bins of each room.
    """
    rooms: list[int] = []
    of_room: dict[int, list[int]] = {}
    filled: list[int] = []
    size: list[int] = []
    place: list[int] = []
    for need in lengths:
        k = bisect.bisect_left(rooms, need)
        if k < len(rooms):
            room = rooms[k]
            bins = of_room[room]
            b = bins.pop()
            if not bins:
                del of_room[room]
                rooms.pop(k)
        else:
            fitting = [c for c in openable if c >= need] or [capacities[-1]]
            # Least cost per token when the rest of the bin fills up as well as bins did so far.
            held = sum(filled) / max(1, sum(size)) if len(size) > 32 else 0.95
            c = min(fitting, key=lambda c: (cost(c) / max(need, held * c), c))
            b, room = len(size), c
            size.append(c)
            filled.append(0)
        filled[b] += need
        place.append(b)
        room -= need
        if room:
            if room not in of_room:
                bisect.insort(rooms, room)
                of_room[room] = []
            of_room[room].append(b)
    final = [capacities[bisect.bisect_left(capacities, f)] for f in filled]
    return place, final


def pack_group(lengths: list[int], capacities: tuple[int, ...] = CAPACITIES) -> tuple[list[int], list[int]]:
    """The cheapest of the joint choices of sizes to open."""
    plans = [best_fit(lengths, capacities[k:], capacities) for k in range(len(capacities))]
    return min(plans, key=lambda p: sum(map(cost, p[1])))


def pack(docs: DataFrame, capacities: tuple[int, ...] = CAPACITIES, id_col: str = "doc_id", text_col: str = "text", length: Column | None = None, group: int = GROUP) -> DataFrame:
    """One row per piece: doc_id, piece, start and length in tokens, bin_id, capacity, offset in the bin."""
    most = capacities[-1]
    sized = docs.select(F.col(id_col).cast("long").alias("doc_id"), (word_count(F.col(text_col)) if length is None else length).cast("long").alias("n"))
    total = sized.agg(F.sum(F.greatest(F.lit(1), F.ceil(F.col("n") / most)))).first()[0] or 0
    groups = max(1, -(-int(total) // group))
    starts = F.when(F.col("n") > 0, F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.lit(most).cast("long"))).otherwise(F.array(F.lit(0).cast("long")))
    pieces = sized.select("doc_id", "n", F.posexplode(starts).alias("piece", "start")).select("doc_id", "piece", "start", F.least(F.col("n") - F.col("start"), F.lit(most)).alias("length"))
    pieces = pieces.withColumn("g", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)).cast("int"))

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(batches).sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending")])
        n = t.column("length").to_pylist()
        filled = [x for x in n if x > 0]
        place, final = pack_group(filled, capacities)
        empty = [None] * (len(n) - len(filled))
        at, offset = [0] * len(final), []
        for b, x in zip(place, filled, strict=True):
            offset.append(at[b])
            at[b] += x
        base = key[0].as_py() << 32
        yield pa.RecordBatch.from_arrays(
            [*(t.column(c).combine_chunks() for c in ("doc_id", "piece", "start", "length")), pa.array([base + b for b in place] + empty, pa.int64()), pa.array([final[b] for b in place] + empty, pa.int32()), pa.array(offset + empty, pa.int32())],
            ["doc_id", "piece", "start", "length", "bin_id", "capacity", "offset"],
        )

    return pieces.groupBy("g").applyInArrow(run, "doc_id long, piece int, start long, length long, bin_id long, capacity int, offset int")


def packing_report(packed: DataFrame) -> DataFrame:
    """Per capacity: bins, tokens, fill."""
    bins = packed.filter("bin_id is not null").groupBy("bin_id").agg(F.first("capacity").alias("capacity"), F.sum("length").alias("tokens"))
    return bins.groupBy("capacity").agg(F.count(F.lit(1)).alias("bins"), F.sum("tokens").alias("tokens"), (F.sum("tokens") / F.sum("capacity")).alias("fill"))
