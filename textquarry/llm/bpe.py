"""Byte-level BPE encoding and decoding by ranks.

Every distinct word of the corpus is merged once. The `COMMON` words that a sample of about `SAMPLE` documents holds most often are encoded first and
broadcast. Units of up to `UNIT_BYTES` of text are split by the pattern into words, and written
as lists of the unit's other distinct words, dealt into buckets by a hash, and, per document, packed indexes into both. The lists of a bucket meet
in one shuffle; each distinct word of a bucket is encoded. Encoding is a fold of Spark higher-order functions over its byte array: each step joins the adjacent pair of least
rank, the leftmost of equal ones. Ranks come from a literal in the plan: all pairs of codes that make a piece, in an array whose places a
displacement hash gives, so that a look-up costs the same for any vocabulary. The codes go back to the units that hold the word, are
spread over the indexes there, and decoding concatenates the binary pieces of the codes.

Shuffled are a unit's distinct words that are not common, and their codes with the packed indexes; texts never are. What is broadcast has
a fixed size (ranks, common words), and memory is bounded by the unit. The sample decides only what is shuffled, not the result; a frequent word that
it missed is encoded once for every `TOGETHER` tasks that split texts, so that the list of units that hold a word is bounded.

Words of more than `LONG` bytes are merged by a heap in the unit's task instead (same ranks, same result): a fold copies its state at
each step, so its cost grows with the square of the word.

Defined cases: null text is empty; an empty text has no codes (digests of nothing); repeated rows and ids are encoded each; an empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import json
import zlib
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace

UNIT_BYTES, LONG, COMMON, SAMPLE, TOGETHER = 32 << 20, 256, 3 << 17, 20_000, 1 << 10


def read_ranks(path: str) -> dict[bytes, int]:
    """A rank file: one base64 piece and its rank per line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def _let(value: Column, use) -> Column:
    """Bind a value to a variable inside an expression."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _prime(least: int) -> int:
    n = max(least, 3) | 1
    while any(n % k == 0 for k in range(3, int(n**0.5) + 1, 2)):
        n += 2
    return n


def displacements(keys: np.ndarray) -> tuple[np.ndarray, int]:
    """(factors, places): key * factors[key mod len(factors)] mod places is different for all keys.

    Crowded buckets choose their factor first; a bucket takes the least factor that leads all its keys to free places.
    """
    places = _prime(len(keys) * 8 // 5 + 7)
    buckets = _prime(max(len(keys) // 3, int(keys.max(initial=1)) // places) + 1)
    factors, taken = np.ones(buckets, np.int64), np.zeros(places, bool)
    order = np.argsort(keys % buckets, kind="stable")
    own, begin, count = np.unique(keys[order] % buckets, return_index=True, return_counts=True)
    for k in np.argsort(-count, kind="stable").tolist():
        mine = keys[order[begin[k] : begin[k] + count[k]]].tolist()
        factor = 1
        while len(at := {key * factor % places for key in mine}) < len(mine) or any(taken[p] for p in at):
            factor += 1
        factors[own[k]] = factor
        taken[list(at)] = True
    return factors, places


class RankTable:
    """The ranks as literals: codes of the bytes, and the code that each pair of adjacent codes makes."""

    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.bits = (max(ranks.values()) + 1).bit_length()
        self.none, self.edge = 1 << self.bits, (1 << self.bits) - 1
        pairs = {(ranks[p[:k]] << self.bits) | ranks[p[k:]]: r for p, r in ranks.items() for k in range(1, len(p)) if p[:k] in ranks and p[k:] in ranks}
        keys, made = np.array(list(pairs), np.int64), np.array(list(pairs.values()), np.int64)
        factors, self.places = displacements(keys)
        self.buckets = len(factors)
        slots = np.zeros(self.places, np.int64)  # 0: no key
        slots[keys * factors[keys % self.buckets] % self.places] = ((keys + 1) << (self.bits + 1)) | made
        # Strings that become arrays when the plan is optimised.
        literal = lambda values: F.from_json(F.lit(json.dumps(values)), "array<bigint>")
        self.factors, self.slots, self.bytes = literal(factors.tolist()), literal(slots.tolist()), literal([ranks.get(bytes([b]), self.edge) for b in range(256)])
        # Pieces that merging their bytes does not give; such a word has the code of the piece.
        odd = {p.decode(): r for p, r in ranks.items() if merge_by_heap(p, ranks, whole=False) != [r] and p.decode("utf-8", "ignore").encode() == p}
        self.odd = F.from_json(F.lit(json.dumps(odd)), "map<string,int>") if odd else None

    def get(self, slots: Column, factors: Column, a: Column, b: Column) -> Column:
        """The code that two adjacent codes make, or `none`."""
        key = F.shiftleft(a, self.bits).bitwiseOR(b)
        slot = F.get(slots, key * F.get(factors, key % self.buckets) % self.places)
        return F.least(slot.bitwiseXOR(F.shiftleft(key + 1, self.bits + 1)), F.lit(self.none).cast("long"))


def encode_word(word: Column, table: RankTable) -> Column:
    """Codes of one word (a string) as array<int>.

    The state is one array of longs, an element per piece, between two edges that join nothing:
    code of the piece that it makes with its successor | place of its first byte | own code. So the least element names the leftmost pair of least
    rank, and its upper part is the code of the new piece.
    """
    # The literals stand in the plan once, bound to variables.
    codes = _let(table.slots, lambda slots: _let(table.factors, lambda factors: _encode_word(word, table, slots, factors)))
    return codes if table.odd is None else _let(F.try_element_at(table.odd, word), lambda c: F.when(c.isNotNull(), F.array(c)).otherwise(codes))


def _encode_word(word: Column, table: RankTable, slots: Column, factors: Column) -> Column:
    bits, two = table.bits, 2 * table.bits
    long = lambda x: F.lit(x).cast("long")
    own, low = long((1 << bits) - 1), long((1 << two) - 1)
    joined = lambda a, b: F.shiftleft(table.get(slots, factors, a, b), two)
    stop = long(table.none << two)

    def step(state: Column, _: Column) -> Column:
        def join(least: Column) -> Column:
            def at(p: Column) -> Column:
                new, left, right = F.shiftright(least, two), F.get(state, p - 2), F.get(state, p + 1)
                before = joined(left.bitwiseAND(own), new).bitwiseOR(left.bitwiseAND(low))
                here = joined(new, right.bitwiseAND(own)).bitwiseOR(least.bitwiseAND(long(((1 << bits) - 1) << bits))).bitwiseOR(new)
                return F.concat(F.slice(state, F.lit(1), p - 2), F.array(before, here), F.slice(state, p + 2, F.size(state)))

            return F.when(least >= stop, state).otherwise(_let(F.array_position(state, least).cast("int"), at))

        return _let(F.array_min(state), join)

    def fold(codes: Column) -> Column:
        element = lambda a, i: joined(a, F.coalesce(F.get(codes, i + 1), long(table.edge))).bitwiseOR(F.shiftleft((i + 1).cast("long"), bits)).bitwiseOR(a)
        edge = F.array(long((table.none << two) | table.edge))
        start = F.concat(edge, F.transform(codes, element), edge)
        return F.aggregate(codes, start, step, lambda s: F.transform(F.slice(s, F.lit(2), F.size(s) - 2), lambda x: x.bitwiseAND(own).cast("int")))

    # One character per byte of the UTF-8 form.
    raw = F.split(F.decode(F.encode(word, "UTF-8"), "ISO-8859-1"), "")
    return _let(F.transform(raw, lambda c: F.get(table.bytes, F.ascii(c))), fold)


def merge_by_heap(piece: bytes, ranks: dict[bytes, int], whole: bool = True) -> list[int]:
    """The same merges in n log n steps, for long words."""
    if whole and piece in ranks:
        return [ranks[piece]]
    n = len(piece)
    end, prev, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
    heap: list[tuple[int, int, int]] = []

    def offer(i: int) -> None:
        j = end[i]
        if j < n and (r := ranks.get(piece[i : end[j]])) is not None:
            heapq.heappush(heap, (r, i, end[j]))

    for i in range(n):
        offer(i)
    while heap:
        _, i, stop = heapq.heappop(heap)
        if not alive[i] or end[i] >= n or end[end[i]] != stop or end[i] == stop:
            continue
        j = end[i]
        alive[j] = False
        end[i] = stop
        if stop < n:
            prev[stop] = i
        if prev[i] >= 0:
            offer(prev[i])
        offer(i)
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = end[i]
    return out


def _pack(a: np.ndarray) -> bytes:
    """int32 by byte planes, compressed."""
    return pa.compress(a.astype(np.int32).view(np.uint8).reshape(-1, 4).T.tobytes(), codec="zstd", asbytes=True)


def _unpack(blob: bytes, size: int) -> np.ndarray:
    if not size:
        return np.zeros(0, np.int32)
    raw = np.frombuffer(pa.decompress(blob, size * 4, codec="zstd", asbytes=True), np.uint8)
    return np.ascontiguousarray(raw.reshape(4, -1).T).view(np.int32).reshape(-1)


_UNIT = "unit long, docs array<long>, counts array<int>, n long, at binary, bucket array<int>, words array<array<string>>, first array<int>, long array<string>"


def _split_texts(batches: Iterator[pa.RecordBatch], pattern: str) -> Iterator[tuple[int | None, list[str], int]]:
    """(doc_id, words, length of the text) of each document."""
    import regex

    find = regex.compile(pattern).findall
    for batch in batches:
        for k in range(0, batch.num_rows, 256):
            part = batch.slice(k, 256)
            for doc, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), strict=True):
                yield doc, find(text or ""), len(text or "")


def common_words(texts: DataFrame, pattern: str, table: RankTable, most: int = COMMON, sample: int = SAMPLE) -> pa.Table:
    """(word, codes): the words that a sample of (doc_id, text) holds most often, those of at least two occurrences."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for _, words, _ in _split_texts(batches, pattern):
            seen.update(words)
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])

    share = sample / max(texts.count(), 1)
    some = texts.sample(share, seed=1) if share < 1 else texts
    counts = some.mapInArrow(count, "word string, n long").filter(F.octet_length("word") <= LONG).groupBy("word").agg(F.sum("n").alias("n"))
    # The most frequent words get the least indexes, which pack best.
    best = counts.filter("n >= 2").orderBy(F.col("n").desc(), "word").limit(most).select("word").toArrow()
    # Dealt anew, since the optimiser would encode a table of the driver's on the driver.
    rows = texts.sparkSession.createDataFrame(best.append_column("i", pa.array(np.arange(best.num_rows)))).repartition(16)
    return rows.select("word", encode_word(F.col("word"), table).alias("codes"), "i").toArrow().sort_by("i")


def units(texts: DataFrame, pattern: str, buckets: int, common=None) -> DataFrame:
    """Units of (doc_id, text): distinct words outside the broadcast list *common* by bucket (those of more than `LONG` bytes apart), and indexes of each
    document's words. Indexes count the common words first."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shared = {w: i for i, w in enumerate(common.value)} if common else {}
        unit = TaskContext.get().partitionId() << 32

        def emit() -> pa.RecordBatch:
            flat = np.concatenate(at) if at else np.zeros(0, np.int32)
            new = list(known)[len(shared) :]
            words = pa.array(new, pa.string())
            bare = pa.compute.greater(pa.compute.binary_length(words), LONG).to_numpy(zero_copy_only=False)
            of = np.where(bare, buckets, np.fromiter((zlib.crc32(w.encode()) % buckets for w in new), np.int64, len(new)))
            # New words are numbered by bucket, long ones last, so that a list of words needs only the index of its first.
            order = np.argsort(of, kind="stable").astype(np.int32)
            number = np.concatenate([np.arange(len(shared)), len(shared) + np.argsort(order)]).astype(np.int32)
            flat = number[flat]
            words, short = words.take(pa.array(order)), len(new) - int(bare.sum())
            held, first = np.unique(of[order[:short]], return_index=True)
            lists = pa.ListArray.from_arrays(pa.array([*first.tolist(), short], pa.int32()), words.slice(0, short))
            one = lambda a: pa.ListArray.from_arrays(pa.array([0, len(a)], pa.int32()), a)
            row = [pa.array([unit]), pa.array([ids], pa.list_(pa.int64())), one(pa.array([len(a) for a in at], pa.int32())), pa.array([len(flat)]), pa.array([_pack(flat)], pa.binary())]
            row += [one(pa.array(held.astype(np.int32))), one(lists), one(pa.array(first.astype(np.int32))), one(words.slice(short))]
            return pa.RecordBatch.from_arrays(row, ["unit", "docs", "counts", "n", "at", "bucket", "words", "first", "long"])

        def fresh() -> defaultdict:
            known: defaultdict = defaultdict(None, shared)
            known.default_factory = known.__len__  # a new word gets the next index
            return known

        ids, at, known, size = [], [], fresh(), 0
        for doc, words, length in _split_texts(batches, pattern):
            ids.append(doc)
            at.append(np.fromiter(map(known.__getitem__, words), np.int32, len(words)))
            size += length
            if size >= UNIT_BYTES:
                yield emit()
                unit += 1
                ids, at, known, size = [], [], fresh(), 0
        if ids:
            yield emit()

    return texts.mapInArrow(split, _UNIT)


def pack_codes(coded: DataFrame) -> DataFrame:
    """(unit, i, codes) of words to (unit, i, size, flat): one row per run of a unit's words, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        unit = None

        def emit() -> pa.RecordBatch:
            i, count, flat = (np.concatenate([h[k] for h in held]) for k in range(3))
            row = [[unit], [_pack(np.diff(i, prepend=0))], [_pack(count)], [len(i)], [_pack(flat)], [len(flat)]]
            return pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(row, types, strict=True)], ["unit", "i", "size", "words", "flat", "codes"])

        types = [pa.int64(), pa.binary(), pa.binary(), pa.int32(), pa.binary(), pa.int32()]
        for batch in batches:
            u = batch.column("unit").to_numpy()
            cuts = np.flatnonzero(np.diff(u)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(u)], strict=True):
                if a == b:
                    continue
                if held and u[a] != unit:
                    yield emit()
                    held = []
                unit = int(u[a])
                lists = batch.column("codes").slice(a, b - a)
                held.append((batch.column("i").slice(a, b - a).to_numpy().astype(np.int32), np.diff(lists.offsets.to_numpy()).astype(np.int32), lists.flatten().to_numpy(zero_copy_only=False).astype(np.int32)))
        if held:
            yield emit()

    dealt = coded.select("unit", "i", "codes").sortWithinPartitions("unit", "i")
    return dealt.mapInArrow(run, "unit long, i binary, size binary, words int, flat binary, codes int")


def _gather(flat: np.ndarray, start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Concatenate flat[start : start + count] of all rows."""
    ends = np.cumsum(count)
    return flat[np.repeat(start - (ends - count), count) + np.arange(ends[-1] if len(ends) else 0)]


def encode_documents(docs: DataFrame, ranks: dict[bytes, int], pattern: str, finish, schema: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`finish(doc_id, codes, decode)` makes a row of *schema* per document; decode gives the bytes of codes."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    table = RankTable(ranks)
    first = common_words(texts, pattern, table)
    common = docs.sparkSession.sparkContext.broadcast(first.column("word").to_pylist())
    lists = first.column("codes").combine_chunks()
    common_codes = docs.sparkSession.sparkContext.broadcast((np.diff(lists.offsets.to_numpy()).astype(np.int64), lists.flatten().to_numpy().astype(np.int32)))
    buckets = 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    split = Workspace(docs.sparkSession, "bpe").write(units(texts, pattern, buckets, common))
    lists = split.select("unit", F.explode(F.arrays_zip("bucket", "words", "first")).alias("l")).select("unit", "l.*").repartition("bucket")
    held = lists.select("unit", "bucket", "first", F.posexplode("words").alias("k", "word")).select("unit", "bucket", "word", (F.col("first") + F.col("k")).alias("i"))
    # Grouped inside the buckets, without another shuffle.
    distinct = held.groupBy("bucket", "word", F.shiftright("unit", 32 + TOGETHER.bit_length() - 1).alias("tasks")).agg(F.collect_list(F.struct("unit", "i")).alias("places"))
    coded = distinct.select(encode_word(F.col("word"), table).alias("codes"), "places").select("codes", F.explode("places").alias("p"))
    coded = pack_codes(coded.select("p.unit", "p.i", "codes"))
    heads = split.select("unit", F.struct("docs", "counts", "n", "at", "long").alias("head"))
    both = heads.unionByName(coded, allowMissingColumns=True)
    dealt = both.repartition("unit").sortWithinPartitions("unit", F.col("head").isNull())
    pieces = [b""] * (max(ranks.values()) + 1)
    for piece, rank in ranks.items():
        pieces[rank] = piece

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decode = lambda codes: b"".join(map(pieces.__getitem__, codes.tolist()))

        def rows_of(head: dict, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            at = _unpack(head["at"], head["n"])
            shared_count, shared_flat = common_codes.value
            short = np.concatenate([np.zeros(0, np.int64), *(np.cumsum(_unpack(p["i"], p["words"])) for p in parts)]).astype(np.int64)
            index = np.concatenate([np.arange(len(shared_count)), np.concatenate([short, len(short) + np.arange(len(head["long"]))]) + len(shared_count)])
            long = [merge_by_heap(w.encode(), ranks) for w in head["long"]]
            count_in = np.concatenate([shared_count, *(_unpack(p["size"], p["words"]) for p in parts), np.array([len(c) for c in long], np.int64)]).astype(np.int64)
            flat = np.concatenate([shared_flat, *(_unpack(p["flat"], p["codes"]) for p in parts), *(np.array(c, np.int32) for c in long)])
            start, count = np.zeros(len(index), np.int64), np.zeros(len(index), np.int64)
            start[index], count[index] = np.cumsum(count_in) - count_in, count_in
            done, rows = 0, []
            for doc, m in zip(head["docs"], head["counts"], strict=True):
                mine = at[done : done + m]
                done += m
                rows.append(finish(doc, _gather(flat, start[mine], count[mine]), decode))
                if len(rows) >= 2000:
                    yield pa.RecordBatch.from_pylist(rows, out)
                    rows = []
            if rows:
                yield pa.RecordBatch.from_pylist(rows, out)

        # A unit begins with its head; the packed codes of its words follow.
        head, parts = None, []
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                if row["head"] is None:
                    parts.append(row)
                    continue
                if head is not None:
                    yield from rows_of(head, parts)
                head, parts = row["head"], []
        if head is not None:
            yield from rows_of(head, parts)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    out = to_arrow_schema(_parse_datatype_string(schema))
    return dealt.mapInArrow(spread, schema)


def _digest(doc: int | None, codes: np.ndarray, decode) -> dict:
    return {"doc_id": doc, "n_tokens": len(codes), "ids_sha256": hashlib.sha256(codes.astype("<u4").tobytes()).hexdigest(), "decoded_sha256": hashlib.sha256(decode(codes)).hexdigest()}


def _codes(doc: int | None, codes: np.ndarray, decode) -> dict:
    return {"doc_id": doc, "codes": codes.tolist(), "decoded": decode(codes)}


def encode(docs: DataFrame, ranks: dict[bytes, int], pattern: str) -> DataFrame:
    """doc_id, codes array<int>, decoded binary."""
    return encode_documents(docs, ranks, pattern, _codes, "doc_id long, codes array<int>, decoded binary")


def code_digest(docs: DataFrame, ranks: dict[bytes, int], pattern: str) -> DataFrame:
    return encode_documents(docs, ranks, pattern, _digest, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
