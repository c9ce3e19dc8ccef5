"""Kneser-Ney perplexities without a model table: each bucket of contexts makes its part of the model and scores its positions.

A position is its last *order* words. Positions are dealt by language and the word before the last one, so that a bucket holds all that its n-grams need:
their counts, the distinct words on their left, the sums of their contexts. Only two things come from all buckets: the counts of counts (a few numbers per
language) and the words with their numbers of left neighbours. Words travel as 64-bit hashes in a dictionary of each packet, positions as packed codes. Nothing
is sampled or capped; results equal those of `lm.perplexity`.
"""

from __future__ import annotations

import ctypes
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import config
from ..functions.arrays import mix
from ..shared import Workspace
from . import lm
from .lm import FALLBACK, _find, _hashes, _more

#: Positions that a map task packs at a time, and characters of training text per bucket.
STEP, CHARS = 3 << 19, 8 << 20
#: Distinct words up to which the words of all languages are broadcast (16 bytes each); a model of more words is scored by joins.
WORDS = 10_000_000
PACKETS = "lang string, bucket int, kind int, data binary"
TABLE, STATS, LOWEST, SCORED = range(4)


def bucket_count(docs: DataFrame, text: str = "text") -> int:
    """Buckets per language, in proportion to the training text."""
    chars = docs.agg(F.sum(F.length(text))).first()[0] or 0
    return max(4, math.ceil(chars / CHARS))


def _free() -> None:
    """Gives memory of finished packets back: workers are kept for later tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def _put(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed string; the bytes of equal weight stand together."""
    raw = []
    for a in arrays:
        a = np.ascontiguousarray(a)
        planes = a.view(np.uint8).reshape(-1, a.itemsize).T.tobytes() if len(a) else b""
        raw.append(np.array([ord(a.dtype.kind), a.itemsize, len(a)], np.int64).tobytes() + planes)
    data = b"".join(raw)
    return np.int64(len(data)).tobytes() + pa.Codec("zstd", 3).compress(data, asbytes=True)


def _get(data: bytes) -> list[np.ndarray]:
    size = int(np.frombuffer(data, np.int64, 1)[0])
    raw = pa.Codec("zstd").decompress(data[8:], size, asbytes=True)
    out, at = [], 0
    while at < len(raw):
        kind, width, n = (int(x) for x in np.frombuffer(raw, np.int64, 3, at))
        at += 24
        planes = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n)
        out.append(np.ascontiguousarray(planes.T).reshape(-1).view(f"{chr(kind)}{width}"))
        at += n * width
    return out


def _narrow(codes: np.ndarray, most: int) -> np.ndarray:
    return codes.astype(np.uint8 if most <= 1 << 8 else np.uint16 if most <= 1 << 16 else np.uint32)


def _coded(codes: np.ndarray, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes of a packet (any shape) numbered by frequency, and the dictionary of that packet."""
    times = np.bincount(codes.reshape(-1), minlength=len(words))
    used = np.flatnonzero(times)
    used = used[np.argsort(-times[used], kind="stable")]
    to = np.zeros(len(words), np.uint32)
    to[used] = np.arange(len(used), dtype=np.uint32)
    return _narrow(to[codes], len(used)), words[used]


class _Words:
    """Sentences as arrays of words, each word by its hash."""

    def read(self, batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        """Sizes of the sentences and the words of all."""
        lists = batch.column("s")
        return np.diff(lists.offsets.to_numpy()).astype(np.int64), _hashes(lists.flatten())

    def coded(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of the distinct words, after 0 for none, and the place of each word among them."""
        known, codes = np.unique(np.concatenate([np.zeros(1, np.uint64), words]), return_inverse=True)
        return known, codes[1:].astype(np.uint32)


class _Cut:
    """Sentences that are cut into pieces here, each piece by its number."""

    def __init__(self, model_file: str) -> None:
        self.pieces = lm.Pieces(model_file)

    def read(self, batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        return self.pieces.cut(batch.column("x"))

    def coded(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        used = np.flatnonzero(np.bincount(words, minlength=len(self.pieces.hashes)))
        to = np.zeros(len(self.pieces.hashes), np.uint32)
        to[used] = np.arange(1, len(used) + 1, dtype=np.uint32)
        return np.concatenate([np.zeros(1, np.uint64), self.pieces.hashes[used]]), to[words]


def _listed(seqs: DataFrame | lm.Subwords) -> DataFrame:
    return seqs.sequences() if isinstance(seqs, lm.Subwords) else seqs


def _packets(seqs: DataFrame | lm.Subwords, order: int, buckets: int, docs: bool) -> DataFrame:
    """Packets of positions: dictionary, then the words of each position from the last one to the left (0 before a sentence), and with *docs* their documents."""
    kind = SCORED if docs else TABLE
    file = seqs.model_file if isinstance(seqs, lm.Subwords) else None

    def pack(words: np.ndarray, place: np.ndarray, doc: np.ndarray, lang: str, source: _Words | _Cut) -> Iterator[tuple]:
        known, codes = source.coded(words)
        last = np.flatnonzero(place > 1)
        shifted = [codes[last]]
        for k in range(1, order):
            shifted.append(np.where(place[last] > k, codes[np.maximum(last - k, 0)], np.uint32(0)))
        bucket = (mix(known) % np.uint64(buckets)).astype(np.int64)
        rank = np.empty(len(known), np.int64)
        rank[np.argsort(bucket, kind="stable")] = np.arange(len(known))
        third = shifted[2] if order > 2 else np.zeros(len(last), np.uint32)
        if len(known) < 1 << 21:
            turn = np.argsort((rank[shifted[1]] << 42) | (shifted[0].astype(np.int64) << 21) | third)
        else:
            turn = np.lexsort((third, shifted[0], rank[shifted[1]]))
        at = bucket[shifted[1][turn]]
        ends = np.flatnonzero(np.concatenate([at[1:] != at[:-1], [True]])) + 1 if len(at) else np.zeros(0, np.int64)
        begin = 0
        for end in ends:
            mine = turn[begin:end]
            cut, dictionary = _coded(np.stack([s[mine] for s in shifted]), known)
            arrays = [dictionary, *cut]
            if docs:
                ids, which = np.unique(doc[last[mine]], return_inverse=True)
                arrays += [np.diff(ids, prepend=0), _narrow(which, len(ids))]
            yield lang, int(at[begin]), kind, _put(*arrays)
            begin = end

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        source = _Cut(file) if file else _Words()
        held: dict[str, list[tuple]] = {}
        total: dict[str, int] = {}

        def flush(lang: str) -> pa.RecordBatch:
            rows = list(pack(*(np.concatenate(x) for x in zip(*held.pop(lang), strict=True)), lang, source))
            total.pop(lang)
            _free()
            return pa.RecordBatch.from_pydict(dict(zip(("lang", "bucket", "kind", "data"), map(list, zip(*rows, strict=True)), strict=True)), pa.schema([("lang", pa.string()), ("bucket", pa.int32()), ("kind", pa.int32()), ("data", pa.binary())]))

        for batch in batches:
            if not batch.num_rows:
                continue
            size, words = source.read(batch)
            ends = np.cumsum(size)
            place = (np.arange(len(words)) - np.repeat(ends - size, size) + 1).astype(np.int32)
            ids = np.repeat(batch.column("doc_id").to_numpy(zero_copy_only=False), size) if docs else place
            coded = batch.column("lang").dictionary_encode()
            which = np.repeat(coded.indices.to_numpy(zero_copy_only=False), size)
            for i, lang in enumerate(coded.dictionary.to_pylist()):
                mine = which == i
                held.setdefault(lang, []).append((words[mine], place[mine], ids[mine]))
                total[lang] = total.get(lang, 0) + int(mine.sum())
                if total[lang] >= STEP:
                    yield flush(lang)
        for lang in list(held):
            yield flush(lang)

    rows = seqs.sentences() if file else seqs.select("doc_id", "lang", "s")
    return rows.filter("lang is not null").mapInArrow(run, PACKETS)


def _key(words: np.ndarray, codes: list[np.ndarray], rows: np.ndarray | slice = slice(None)) -> np.ndarray:
    """Hashes of the words that stand in all of *codes*, the last word first."""
    key = np.zeros(len(codes[0][rows]), np.uint64)
    for c in codes:
        key = _more(key, words[c[rows]])
    return key


def _grouped(key: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A place of each distinct key, in their order, and the sum of its weights."""
    turn = np.argsort(key)
    if not len(turn):
        return turn, weight
    key = key[turn]
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return turn[first], np.add.reduceat(weight[turn], first)


def _distinct(words: np.ndarray, parts: list[list[np.ndarray]], times: list[np.ndarray]) -> tuple[list[np.ndarray], np.ndarray]:
    codes = [np.concatenate(x) for x in zip(*parts, strict=True)]
    parts.clear()
    first, total = _grouped(_key(words, codes), np.concatenate(times))
    return [c[first] for c in codes], total


class _Keys:
    """Sorted distinct hashes, found from the place where their leading bits begin: hashes are even, so that a look-up reads one or two of them."""

    def __init__(self, keys: np.ndarray) -> None:
        self.n, bits = len(keys), max(1, len(keys).bit_length() - 1)
        self.keys, self.shift = np.append(keys, ~np.uint64(0)), np.uint64(64 - bits)
        self.first = np.zeros((1 << bits) + 1, np.int32 if self.n < 1 << 31 else np.int64)
        np.cumsum(np.bincount((keys >> self.shift).view(np.int64), minlength=1 << bits), out=self.first[1:])

    def find(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A place for each wanted hash, and whether it is there."""
        at = self.first[(wanted >> self.shift).view(np.int64)].astype(np.int64)
        found = self.keys[at]
        todo = np.flatnonzero(found < wanted)
        while len(todo):
            at[todo] += 1
            found[todo] = self.keys[at[todo]]
            todo = todo[found[todo] < wanted[todo]]
        return np.minimum(at, max(self.n - 1, 0)), (found == wanted) & (at < self.n)


def _ranked(key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys in their order, a place of each, and for every place the number of its key."""
    turn = np.argsort(key)
    key = key[turn]
    new = np.concatenate([[True], key[1:] != key[:-1]]) if len(key) else np.zeros(0, bool)
    which = np.empty(len(key), np.int32 if len(key) < 1 << 31 else np.int64)
    which[turn] = np.cumsum(new) - 1
    return key[new], turn[new], which


def _tables(words: np.ndarray, codes: list[np.ndarray], times: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Per order from 2: a row of *codes* for each n-gram, by its hash; its count (raw on top and where a sentence begins, else distinct left words);
    its hash; and the place in the order below of what it has without its first word (order 2: none)."""
    order = len(codes)
    length, keys = np.zeros(len(times), np.int8), [np.zeros(len(times), np.uint64)]
    for c in codes:
        length += words[c] != 0
        keys.append(_more(keys[-1], words[c]))
    rows = np.flatnonzero(length == order).astype(np.int32)
    rows = rows[np.argsort(keys[order][rows])]
    out = [(rows, times[rows], keys[order][rows], np.zeros(0, np.int32))]
    for k in range(order - 1, 1, -1):
        above = out[-1]
        starts = np.flatnonzero(length == k).astype(np.int32)
        rows = np.concatenate([above[0], starts])
        key, first, which = _ranked(keys[k][rows])
        total = np.bincount(which[: len(above[0])], minlength=len(key)) + np.bincount(which[len(above[0]) :], weights=times[starts], minlength=len(key)).astype(np.int64)
        out[-1] = (*above[:3], which[: len(above[0])])
        out.append((rows[first], total, key, np.zeros(0, np.int32)))
    return out[::-1]


def _made(packets: DataFrame, order: int) -> DataFrame:
    """Per bucket: its distinct positions, the counts of counts of orders 2 and more, and its words with their numbers of left neighbours."""

    def make(key: tuple, table: pa.Table) -> pa.Table:
        lang, bucket = key[0].as_py(), key[1].as_py()
        held = [_get(data.as_py()) for data in table.column("data")]
        words = np.unique(np.concatenate([x[0] for x in held]))
        parts, times, fresh = [], [], 0
        for dictionary, *codes in held:
            to = np.searchsorted(words, dictionary).astype(np.uint32)
            codes, total = _distinct(words, [[to[c] for c in codes]], [np.ones(len(codes[0]), np.int64)])
            parts.append(codes)
            times.append(total)
            fresh += len(total)
            if fresh > STEP // 2:
                codes, total = _distinct(words, parts, times)
                parts, times, fresh = [codes], [total], 0
        held.clear()
        codes, times = _distinct(words, parts, times)
        third = codes[min(2, order - 1)]
        turn = np.argsort((codes[1].astype(np.int64) << 42) | (codes[0].astype(np.int64) << 21) | third) if len(words) < 1 << 21 else np.lexsort((third, codes[0], codes[1]))
        codes, times = [c[turn] for c in codes], times[turn]
        tables = _tables(words, codes, times)
        seen = np.array([np.count_nonzero(c == i) for _, c, *_ in tables for i in range(1, 5)], np.int64)
        left = np.bincount(codes[0][tables[0][0]], minlength=len(words))
        cut, dictionary = _coded(np.stack(codes), words)
        del tables
        data = [_put(dictionary, *cut, _narrow(times, int(times.max()) + 1)), seen.tobytes(), _put(words[left > 0], left[left > 0].astype(np.int64))]
        del codes, cut
        _free()
        return pa.table({"lang": [lang] * 3, "bucket": pa.array([bucket] * 3, pa.int32()), "kind": pa.array([TABLE, STATS, LOWEST], pa.int32()), "data": pa.array(data, pa.binary())})

    return packets.groupBy("lang", "bucket").applyInArrow(make, PACKETS)


def _discounts(n: np.ndarray, modified: bool) -> np.ndarray:
    """As `lm.discounts`, from the four counts of counts."""
    n1, n2, n3, n4 = (float(x) for x in n)
    if not modified:
        return np.repeat(n1 / (n1 + 2 * n2) if n1 > 0 and n2 > 0 else 0.75, 3)
    if min(n1, n2, n3, n4) > 0:
        y = n1 / (n1 + 2 * n2)
        d = np.array([1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3])
        if (d >= 0).all():
            return d
    return np.array(FALLBACK)


def _taken(counts: np.ndarray, d: np.ndarray) -> np.ndarray:
    return d[np.minimum(counts, 3) - 1]


class Bucketed:
    """A model in buckets: `perplexity` of any sentences."""

    def __init__(self, train: DataFrame | lm.Subwords, buckets: int, order: int = config.LM_ORDER, modified: bool = True, most: int = WORDS) -> None:
        """*train*: doc_id, lang, s as `lm.sequences` makes them, or sentences to be cut into pieces."""
        if order < 2:
            raise ValueError("buckets are of the word before the last one: order 2 or more")
        self.spark, self.order, self.buckets = (train.docs if isinstance(train, lm.Subwords) else train).sparkSession, order, buckets
        self.space = Workspace(self.spark, "buckets")
        self.made = self.space.write(_made(_packets(train, order, buckets, docs=False), order), free=True)
        seen: dict[str, np.ndarray] = {}
        for row in self.made.filter(F.col("kind") == STATS).select("lang", "data").toLocalIterator():
            seen[row.lang] = seen.get(row.lang, 0) + np.frombuffer(row.data, np.int64).reshape(-1, 4)

        def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lang, data in zip(batch.column("lang").to_pylist(), batch.column("data").to_pylist(), strict=True):
                    words, left = _get(data)
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(words), pa.string()), pa.array(words.view(np.int64)), pa.array(left)], ["lang", "w", "c"])

        words = self.made.filter(F.col("kind") == LOWEST).select("lang", "data").mapInArrow(spell, "lang string, w long, c long")
        words = self.space.write(words.groupBy("lang", "w").agg(F.sum("c").alias("c")), free=True)
        self.joined = lm.kneser_ney(_listed(train), order, modified) if words.count() > most else None
        if self.joined:
            return
        rows = words.toArrow().combine_chunks()
        coded = rows.column("lang").combine_chunks().dictionary_encode() if rows.num_rows else None
        self.words, self.cuts = {}, {}
        for i, lang in enumerate(coded.dictionary.to_pylist() if rows.num_rows else []):
            mine = np.flatnonzero(coded.indices.to_numpy() == i)
            w, c = rows.column("w").to_numpy()[mine].view(np.uint64), rows.column("c").to_numpy()[mine]
            d = _discounts([np.count_nonzero(c == j) for j in range(1, 5)], modified)
            unknown = _taken(c, d).sum() / c.sum() / (len(c) + 1)
            turn = np.argsort(w)
            self.words[lang] = w[turn], ((c - _taken(c, d)) / c.sum() + unknown)[turn], unknown
            self.cuts[lang] = [_discounts(n, modified) for n in seen[lang]]

    def perplexity(self, seqs: DataFrame | lm.Subwords) -> DataFrame:
        """doc_id, lang, tokens, ppl of the documents whose language the model has."""
        if self.joined:
            return lm.perplexity(_listed(seqs), self.joined, "join")
        order, cuts, sent = self.order, self.cuts, self.spark.sparkContext.broadcast(self.words)

        def model(data: bytes, lang: str) -> list[tuple]:
            """Per order from 2: hashes of n-grams, their probabilities, hashes of contexts, their back-off weights."""
            dictionary, *codes, times = _get(data)
            (words, probs, _), out = sent.value[lang], []
            at, hit = _find(words, dictionary)
            lowest, back = np.where(hit, probs[at], 0.0), np.zeros(len(times), np.uint64)
            for k, (rows, counts, grams, below) in enumerate(_tables(dictionary, codes, times.astype(np.int64)), 2):
                back = _more(back, dictionary[codes[k - 1]])
                taken = _taken(counts, cuts[lang][k - 2])
                contexts, _, which = _ranked(back[rows])
                total = np.bincount(which, weights=counts, minlength=len(contexts))
                weight = np.bincount(which, weights=taken, minlength=len(contexts)) / total
                lower = lowest[codes[0][rows]] if k == 2 else out[-1][1][below]
                out.append((_Keys(grams), (counts - taken) / total[which] + weight[which] * lower, _Keys(contexts), weight))
            return out

        def logs(dictionary: np.ndarray, codes: list[np.ndarray], lang: str, tables: list[tuple]) -> np.ndarray:
            words, probs, unknown = sent.value[lang]
            at, hit = _find(words, dictionary)
            p = np.where(hit, probs[at], unknown)[codes[0]]
            key, back, here = _more(np.zeros(len(p), np.uint64), dictionary[codes[0]]), np.zeros(len(p), np.uint64), np.arange(len(p))
            for k, (grams, prob, contexts, weight) in enumerate(tables, 2):
                word = dictionary[codes[k - 1][here]]
                back = _more(back, word)
                near, go_on = contexts.find(back)
                # A context that no sentence of the model has is part of none that is longer.
                go_on &= word != 0
                here, key, back, near = here[go_on], _more(key[go_on], word[go_on]), back[go_on], near[go_on]
                if not len(here):
                    break
                at, hit = grams.find(key)
                p[here] = np.where(hit, prob[at], weight[near] * p[here])
            return np.log10(p)

        def score(key: tuple, table: pa.Table) -> pa.Table:
            lang, out = key[0].as_py(), [[np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]]
            if lang in cuts:
                kinds = table.column("kind").to_numpy()
                mine = np.flatnonzero(kinds == TABLE)
                scored = np.flatnonzero(kinds == SCORED)
                tables = model(table.column("data")[int(mine[0])].as_py(), lang) if len(mine) and len(scored) else []
                for i in scored:
                    dictionary, *codes, ids, which = _get(table.column("data")[int(i)].as_py())
                    out.append([np.cumsum(ids), np.bincount(which, minlength=len(ids)), np.bincount(which, weights=logs(dictionary, codes, lang, tables), minlength=len(ids))])
                del tables
                _free()
            ids, n, sums = (np.concatenate(x) for x in zip(*out, strict=True))
            return pa.table({"doc_id": pa.array(ids.astype(np.int64)), "lang": pa.array([lang] * len(ids), pa.string()), "n": pa.array(n.astype(np.int64)), "s": pa.array(sums)})

        packets = self.made.filter(F.col("kind") == TABLE).unionByName(_packets(seqs, order, self.buckets, docs=True))
        sums = packets.groupBy("lang", "bucket").applyInArrow(score, "doc_id long, lang string, n long, s double")
        return sums.groupBy("doc_id", "lang").agg(F.sum("n").alias("tokens"), F.pow(F.lit(10.0), -F.sum("s") / F.sum("n")).alias("ppl"))
