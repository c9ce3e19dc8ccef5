"""Exact and fuzzy deduplication per language: shingles, MinHash bands, verified pairs, clusters, survivors.

At scale: one map pass makes, per document, the identity of its shingle set and its band hashes. Documents of equal sets become one
representative (combined map-side). Buckets propose pairs: each member with the bucket's least one, and, after
components are known, whatever may still link two of them: all pairs of small buckets, and in large ones the pairs
whose rarest shingles meet (a prefix filter, which loses no pair at the threshold). Pairs are verified on the whole
sets, made for documents that share a bucket only. Nothing is sampled, capped or collected.
`band_pairs`, by which the bands are judged, has all pairs of all buckets and no filter.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cached_property, reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import DEDUP_NGRAM, DEDUP_RECALL, DEDUP_THRESHOLD
from ..functions import text as T
from ..functions.arrays import buffers, distinct_per_row, grams, mix, segment_min, steps, token_hashes, tokens
from ..shared import Workspace
from . import lm, lm_buckets

PRIME = (1 << 31) - 1
PERMUTATIONS = 128
#: Shingles of the sample that finds common ones, and common ones kept at most (16 bytes each, broadcast).
SAMPLE, COMMON = 20_000_000, 1_000_000
#: Buckets of at most this many members are compared pair by pair.
SMALL = 32
#: Buckets of more members than this are paired in parts of about so many, each two parts by themselves.
TILE = 1024


def shingles(text: Column, n: int = DEDUP_NGRAM) -> Column:
    """Distinct word n-grams of the folded text; short texts give one shingle of all words."""
    return F.array_distinct(T.ngrams(T.folded_words(text), n))


def char_shingles(text: Column, n: int = DEDUP_NGRAM) -> Column:
    """Variant: distinct character n-grams of the folded text."""
    return F.array_distinct(T.char_grams(F.array_join(T.folded_words(text), " "), n))


def permutations(count: int, seed: int = 1) -> list[tuple[int, int]]:
    rng = np.random.default_rng(seed)
    return [(int(a), int(b)) for a, b in zip(rng.integers(1, PRIME, count), rng.integers(0, PRIME, count), strict=True)]


def minhash(hashes: Column, pairs: list[tuple[int, int]]) -> Column:
    """Signature as column expression (the reference form; `signatures` is the fast one)."""
    p = F.array(*(F.struct(F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b")) for a, b in pairs))
    return T.let(hashes, lambda h: F.transform(p, lambda q: F.array_min(F.transform(h, lambda x: (q["a"] * x + q["b"]) % PRIME))))


def choose_bands(threshold: float = DEDUP_THRESHOLD, permutations: int = PERMUTATIONS, weight_false: float = 0.1, weight_missed: float = 0.9) -> tuple[int, int]:
    """Bands and rows of least weighted false-positive and false-negative area."""
    s = np.linspace(0, 1, 1001)
    best, least = (1, 1), np.inf
    for b in range(1, permutations + 1):
        for r in range(1, permutations // b + 1):
            hit = 1 - (1 - s**r) ** b
            loss = weight_false * np.trapezoid(hit[s <= threshold], s[s <= threshold]) + weight_missed * np.trapezoid(1 - hit[s >= threshold], s[s >= threshold])
            if loss < least - 1e-12:
                best, least = (b, r), loss
    return best


def bands_at_recall(threshold: float = DEDUP_THRESHOLD, recall: float = DEDUP_RECALL, permutations: int = PERMUTATIONS) -> tuple[int, int]:
    """Bands and rows: as many rows as the permutations allow while a pair at the threshold is proposed with this probability."""
    best = (permutations, 1)
    for r in range(1, permutations + 1):
        bands = max(1, math.ceil(math.log(1 - recall) / math.log1p(-(threshold**r)))) if threshold < 1 else 1
        if bands * r <= permutations:
            best = (bands, r)
    return best


def _plain(docs: DataFrame) -> DataFrame:
    """doc_id, lang, and the folded words with single blanks between."""
    return docs.select("doc_id", "lang", F.regexp_replace(F.lower("text"), r"[^\p{L}\p{N}_]+", " ").alias("text"))


def _sets(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    raw, offsets = buffers(column)
    s, e, first = tokens(raw, offsets)
    return distinct_per_row(*grams(token_hashes(raw, s, e, fold=False), first, n))


def signatures(docs: DataFrame, n: int, bands: int, rows: int, outlines: bool = False) -> DataFrame:
    """(doc_id, lang, a, b, n, bands): identity of the shingle set, its size, and its band hashes; documents without words have no row. *outlines*: and o, as `_outlines` has it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values_of = mix(np.arange(1, 2 * bands * rows + 1, dtype=np.uint64))
        factor, shift = values_of[: bands * rows] | np.uint64(1), values_of[bands * rows :]
        for part in steps(batches, "text"):
            values, begin = _sets(part.column("text"), n)
            size = np.diff(begin)
            some = np.flatnonzero(size)
            sums = [np.concatenate([[np.uint64(0)], np.cumsum(mix(values + np.uint64(c)))]) for c in (1, 2)]
            a, b = (t[begin[1:]] - t[begin[:-1]] for t in sums)
            out = np.zeros((len(size), bands), np.uint64)
            for k in range(bands):
                for r in range(rows):
                    out[:, k] = mix(out[:, k] ^ segment_min(values * factor[k * rows + r] + shift[k * rows + r], begin, np.uint64(0)))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(some) * bands + 1, bands, dtype=np.int32)), pa.array(out[some].reshape(-1).view(np.int64)))
            keep = pa.array(some)
            columns = [part.column("doc_id").take(keep), part.column("lang").take(keep), pa.array(a[some].view(np.int64)), pa.array(b[some].view(np.int64)), pa.array(size[some].astype(np.int32)), lists]
            if outlines:
                columns.append(_outline(values, begin, some))
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "lang", "a", "b", "n", "bands", "o"][: len(columns)])

    return _plain(docs).mapInArrow(run, "doc_id long, lang string, a long, b long, n int, bands array<long>" + ", o binary" * outlines)


def shingle_sets(docs: DataFrame, n: int = DEDUP_NGRAM) -> DataFrame:
    """(doc_id, s): sorted hashes of the distinct shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text"):
            values, begin = _sets(part.column("text"), n)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(pa.array(begin.astype(np.int32)), pa.array(values.view(np.int64)))], ["doc_id", "s"])

    return _plain(docs).mapInArrow(run, "doc_id long, s array<long>")


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Adds the exact Jaccard of pairs (src, dst)."""
    both = pairs.join(sets.select(F.col("doc_id").alias("src"), F.col("s").alias("a")), "src").join(sets.select(F.col("doc_id").alias("dst"), F.col("s").alias("b")), "dst")
    both = both.withColumn("i", F.size(F.array_intersect("a", "b")))
    return both.select(*pairs.columns, (F.col("i") / (F.size("a") + F.size("b") - F.col("i"))).alias("jaccard"))


class Buckets:
    """Buckets of a corpus: copies, members of shared buckets with their group, shingle sets."""

    def __init__(self, docs: DataFrame, name: str, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD, groups: Column | None = None, outlines: bool = False) -> None:
        """*groups*: pairs are wanted between different values only; each document is a group of its own by default. *outlines*: `signed` has them, for `Exact`."""
        self.space, self.threshold = Workspace(docs.sparkSession, name), threshold
        signed = signatures(docs, n, *bands_at_recall(threshold), outlines)
        if groups is not None:
            signed = signed.join(docs.select("doc_id", groups.alias("grp")), "doc_id")
        self.signed = self.space.write(signed)
        by = ["lang", "a", "b", "n"] + (["grp"] if groups is not None else [])
        self.classes = self.space.write(self.signed.groupBy(*by).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("bands").alias("bands")))
        grp = F.col("grp") if groups is not None else F.col("rep")
        held = self.classes.select("lang", "rep", "n", grp.cast("long").alias("grp"), F.posexplode("bands").alias("band", "h"))
        shared = held.groupBy("lang", "band", "h").agg(F.count(F.lit(1)).alias("c")).filter("c > 1")
        self.held = self.space.write(held.join(shared, ["lang", "band", "h"]))
        self.docs, self.n = docs, n

    @cached_property
    def sets(self) -> DataFrame:
        """Shingle sets of the documents that share a bucket, made when pairs are verified."""
        ids = self.held.select(F.col("rep").alias("_id")).distinct()
        return self.space.write(shingle_sets(self.docs.join(ids.hint("shuffle_hash"), F.col("doc_id") == F.col("_id"), "left_semi"), self.n))

    def meeting(self) -> DataFrame:
        """All pairs (lang, src, dst) that share a bucket, whatever its size: each once, from its first shared band, so that no pair is shuffled to be made distinct."""
        bands = bands_at_recall(self.threshold)[0]
        part = lambda rep: F.pmod(F.xxhash64(rep), F.col("parts"))
        shared = self.held.select("lang", "band", "h", "c").distinct()
        held = self.classes.select("lang", "rep", "bands", F.posexplode("bands").alias("band", "h")).join(shared, ["lang", "band", "h"])
        held = held.select("lang", "band", "h", "rep", F.slice("bands", F.lit(1), F.col("band")).alias("before"), F.ceil(F.col("c") / TILE).alias("parts")).withColumn("own", part("rep"))
        parts = F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1))
        one = held.select("lang", "band", "h", F.col("own").alias("p"), parts.alias("q"), F.col("rep").alias("src"), "before")
        two = held.select("lang", "band", "h", parts.alias("p"), F.col("own").alias("q"), F.col("rep").alias("dst"), F.col("before").alias("before2"))
        met = [F.coalesce(F.get("before", F.lit(k)) == F.get("before2", F.lit(k)), F.lit(False)) for k in range(bands - 1)]
        return one.join(two, ["lang", "band", "h", "p", "q"]).filter((F.col("src") < F.col("dst")) & ~reduce(or_, met, F.lit(False))).select("lang", "src", "dst")

    def _pairs(self, rows: DataFrame) -> DataFrame:
        """Pairs (lang, src, dst) of sizes that can reach the threshold."""
        fits = F.least("n", "n2") >= self.threshold * F.greatest("n", "n2") - 1e-9
        return rows.filter(fits & (F.col("rep") != F.col("rep2"))).select("lang", F.least("rep", "rep2").alias("src"), F.greatest("rep", "rep2").alias("dst")).distinct()

    def stars(self) -> DataFrame:
        """Each member with the least one of its bucket: linear in the buckets."""
        least = self.held.groupBy("lang", "band", "h").agg(F.min(F.struct("rep", "n")).alias("p"))
        return self._pairs(self.held.join(least.select("lang", "band", "h", F.col("p.rep").alias("rep2"), F.col("p.n").alias("n2")), ["lang", "band", "h"]))

    def between(self, held: DataFrame | None = None) -> DataFrame:
        """All pairs of different groups that share a bucket and can reach the threshold."""
        held = self.held if held is None else held
        mixed = held.groupBy("lang", "band", "h").agg(F.min("grp").alias("lo"), F.max("grp").alias("hi")).filter("lo < hi").select("lang", "band", "h")
        held = self.space.write(held.join(mixed, ["lang", "band", "h"]))
        few = held.filter(F.col("c") <= SMALL)
        other = few.select("lang", "band", "h", F.col("rep").alias("rep2"), F.col("n").alias("n2"), F.col("grp").alias("grp2"))
        small = few.join(other, ["lang", "band", "h"]).filter("grp < grp2")
        many = self.space.write(held.filter(F.col("c") > SMALL).select("lang", "rep", "n", "grp").distinct())
        columns = ("lang", "rep", "n", "rep2", "n2")
        return self._pairs(small.select(*columns).unionByName(self._by_prefix(many).select(*columns)))

    def _by_prefix(self, members: DataFrame) -> DataFrame:
        """Pairs of different groups that share one of the first n - ceil(s n) + 1 shingles, shingles of one group first, then rare ones first."""
        held = self.space.write(members.join(self.sets, members["rep"] == self.sets["doc_id"]).select("lang", "rep", "n", "grp", F.explode("s").alias("g")))
        known = held.groupBy("lang", "g").agg(F.count(F.lit(1)).alias("f"), (F.min("grp") < F.max("grp")).alias("bridge"))
        ranked = held.join(known, ["lang", "g"]).groupBy("lang", "rep", "n", "grp").agg(F.array_sort(F.collect_list(F.struct("bridge", "f", "g"))).alias("s"))
        size = (F.col("n") - F.ceil(F.col("n") * F.lit(self.threshold) - 1e-9) + 1).cast("int")
        first = F.posexplode(F.slice("s", F.lit(1), size)).alias("at", "t")
        first = self.space.write(ranked.select("lang", "rep", "n", "grp", first).filter("t.bridge").select("lang", "rep", "n", "grp", "at", F.col("t.g").alias("g")))
        other = first.select("lang", "g", F.col("rep").alias("rep2"), F.col("n").alias("n2"), F.col("grp").alias("grp2"), F.col("at").alias("at2"))
        # What follows the first common shingle bounds the overlap.
        reach = F.least(F.col("n") - F.col("at"), F.col("n2") - F.col("at2")) >= self.threshold / (1 + self.threshold) * (F.col("n") + F.col("n2")) - 1e-9
        return first.join(other, ["lang", "g"]).filter((F.col("grp") < F.col("grp2")) & reach)

    def links(self, pairs: DataFrame) -> DataFrame:
        """The pairs whose exact Jaccard reaches the threshold."""
        return self.space.write(verify(self.space.write(pairs), self.sets).filter(F.col("jaccard") >= self.threshold))


def verified_pairs(docs: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD) -> DataFrame:
    """(lang, src, dst, jaccard): near-duplicate pairs of representatives (least ids of equal shingle sets) that the bands propose."""
    buckets = Buckets(docs, "pairs", n, threshold)
    return buckets.links(buckets.between())


def clusters(docs: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD) -> DataFrame:
    """(node, root) of the documents that have a near-duplicate; root is the least id of the cluster."""
    b = Buckets(docs, "clusters", n, threshold)
    links = b.links(b.stars())
    roots = b.space.write(components(links))
    # What may still link two components.
    label = b.held.join(roots, b.held["rep"] == roots["node"], "left").select("lang", "band", "h", "rep", "n", "c", F.coalesce("root", "rep").alias("grp"))
    more = b.links(b.between(b.space.write(label)))
    if not more.isEmpty():
        roots = b.space.write(components(links.unionByName(more)))
    member = b.classes.join(roots, F.col("rep") == F.col("node"), "left").filter(F.col("root").isNotNull() | (F.col("copies") > 1))
    member = b.space.write(member.select("lang", "a", "b", "n", F.coalesce("root", "rep").alias("root")))
    return b.signed.select("lang", "a", "b", "n", F.col("doc_id").alias("node")).join(member, ["lang", "a", "b", "n"]).select("node", "root")


def dedup_against(new: DataFrame, base: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD) -> DataFrame:
    """doc_id of the documents of *new* that are near-duplicates of any document of *base*; ids of both are distinct."""
    side = lambda df, k: df.select("doc_id", "lang", "text", F.lit(k).alias("side"))
    b = Buckets(side(base, 0).unionByName(side(new, 1)), "against", n, threshold, groups=F.col("side"))
    links = b.links(b.between())
    ends = links.select(F.explode(F.array("src", "dst")).alias("rep")).distinct()
    key = ["lang", "a", "b", "n"]
    same = b.classes.filter("grp = 0").select(*key)
    near = b.classes.filter("grp = 1").join(ends, "rep", "left_semi").select(*key).unionByName(b.classes.filter("grp = 1").join(same, key, "left_semi").select(*key)).distinct()
    return b.signed.filter("grp = 1").join(near, key, "left_semi").select("doc_id")


def band_pairs(docs: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD, buckets: Buckets | None = None) -> DataFrame:
    """(lang, src, dst): pairs of representatives that share a bucket, as the bands propose them, before any filter and verification. *buckets*: those of the documents, where they are made already."""
    return (buckets or Buckets(docs, "candidates", n, threshold)).meeting()


def exact_jaccard_pairs(docs: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD) -> DataFrame:
    """Ground truth through an inverted index of shingles (quadratic in posting lists: for tests and baselines)."""
    held = docs.select("lang", "doc_id", F.explode(shingles(F.col("text"), n)).alias("g"))
    size = held.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    other = held.select("lang", "g", F.col("doc_id").alias("dst"))
    common = held.withColumnRenamed("doc_id", "src").join(other, ["lang", "g"]).filter("src < dst").groupBy("lang", "src", "dst").agg(F.count(F.lit(1)).alias("i"))
    both = common.join(size.select(F.col("doc_id").alias("src"), F.col("n").alias("na")), "src").join(size.select(F.col("doc_id").alias("dst"), F.col("n").alias("nb")), "dst")
    return both.select("lang", "src", "dst", (F.col("i") / (F.col("na") + F.col("nb") - F.col("i"))).alias("jaccard")).filter(F.col("jaccard") >= threshold)


def _frequent(docs: DataFrame, n: int, total: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that a sample of documents repeats, by hash, with their counts there. They only set an order: what it misses costs time, not pairs."""
    share = max(16, math.ceil(total / SAMPLE))
    held = shingle_sets(docs.filter(F.pmod(F.xxhash64("doc_id"), F.lit(share)) == 0), n).select(F.explode("s").alias("g"))
    common = held.groupBy("g").agg(F.count(F.lit(1)).alias("c")).filter("c > 2").orderBy(F.desc("c")).limit(COMMON).toArrow()
    g, c = (common.column(x).to_numpy().astype(np.int64) for x in ("g", "c"))
    turn = np.argsort(g.view(np.uint64))
    return g.view(np.uint64)[turn], c[turn]


def _prefixes(docs: DataFrame, n: int, threshold: float, buckets: int, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """Packets (lang, bucket, data) of the first n - ceil(s n) + 1 shingles of each document, common ones last: 48 bits of each, its document and its place."""
    sent = docs.sparkSession.sparkContext.broadcast(common)

    def pack(at: np.ndarray, who: np.ndarray, g: np.ndarray, ids: np.ndarray, size: np.ndarray, lang: str) -> Iterator[tuple]:
        turn = np.argsort(g)
        g, at, who = g[turn], at[turn], who[turn]
        bucket = g // np.uint64(-(-(1 << 48) // buckets))
        ends = np.flatnonzero(np.concatenate([bucket[1:] != bucket[:-1], [True]])) + 1
        begin = 0
        for end in ends:
            own, which = np.unique(who[begin:end], return_inverse=True)
            data = lm_buckets._put(np.diff(g[begin:end], prepend=np.uint64(0)), lm_buckets._narrow(which, len(own)), at[begin:end].astype(np.uint32), ids[own], size[own].astype(np.uint32))
            yield lang, int(bucket[begin]), data
            begin = end

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, times = sent.value
        held: dict[str, list[tuple]] = {}

        def flush(lang: str) -> pa.RecordBatch:
            parts = held.pop(lang)
            shift = np.cumsum([0, *(len(p[3]) for p in parts)])
            who = np.concatenate([p[1] + s for p, s in zip(parts, shift[:-1], strict=True)])
            at, _, g, ids, size = (np.concatenate(x) for x in zip(*parts, strict=True))
            rows = list(zip(*pack(at, who, g, ids, size, lang), strict=True))
            lm_buckets._free()
            return pa.RecordBatch.from_arrays([pa.array(rows[0], pa.string()), pa.array(rows[1], pa.int32()), pa.array(rows[2], pa.binary())], ["lang", "bucket", "data"])

        for batch in batches:
            for part in steps(iter([batch]), "text"):
                values, begin = _sets(part.column("text"), n)
                if not len(values):
                    continue
                size = np.diff(begin)
                row = np.repeat(np.arange(len(size)), size)
                often = np.zeros(len(values), np.int64)
                if len(known):
                    near, hit = lm._find(known, values)
                    often = np.where(hit, times[near], 0)
                turn = np.lexsort((values, often, row))
                at = np.arange(len(values)) - np.repeat(begin[:-1], size)
                first = size - np.ceil(size * threshold - 1e-9).astype(np.int64) + 1
                keep = at < first[row]
                g, at, row = values[turn][keep] >> np.uint64(16), at[keep], row[keep]
                ids = part.column("doc_id").to_numpy(zero_copy_only=False)
                langs = part.column("lang").dictionary_encode()
                code = langs.indices.to_numpy(zero_copy_only=False)
                for i, lang in enumerate(langs.dictionary.to_pylist()):
                    mine = code[row] == i
                    if mine.any():
                        held.setdefault(lang, []).append((at[mine], row[mine], g[mine], ids, size))
                        if sum(len(p[0]) for p in held[lang]) >= lm_buckets.STEP:
                            yield flush(lang)
        for lang in list(held):
            yield flush(lang)

    return _plain(docs.filter("lang is not null")).mapInArrow(run, "lang string, bucket int, data binary")


def _meetings(packets: DataFrame, threshold: float) -> DataFrame:
    """Pairs (lang, src, dst) whose prefixes meet, and which can still reach the threshold by their sizes and by what follows."""

    def meet(key: tuple, table: pa.Table) -> pa.Table:
        parts, shift = [], 0
        for data in table.column("data"):
            g, which, at, ids, size = lm_buckets._get(data.as_py())
            parts.append((np.cumsum(g, dtype=np.uint64), which.astype(np.int64) + shift, at.astype(np.int64), ids, size.astype(np.int64)))
            shift += len(ids)
        g, who, at, ids, size = (np.concatenate(x) for x in zip(*parts, strict=True))
        parts.clear()
        # One number per document of the bucket, although several packets may hold it.
        ids, first, to = np.unique(ids, return_index=True, return_inverse=True)
        size, who = size[first], to[who]
        turn = np.lexsort((size[who], g))
        g, who, at = g[turn], who[turn], at[turn]
        n, found, fresh = size[who], [np.zeros(0, np.int64)], 0
        active = np.arange(len(g) - 1)
        step = 1
        while len(active):
            other = active + step
            # Sizes rise among equal shingles: a pair too unlike in size ends the row of the smaller one.
            going = (g[active] == g[other]) & (n[active] >= threshold * n[other] - 1e-9)
            active, other = active[going], other[going]
            reach = np.minimum(n[active] - at[active], n[other] - at[other]) >= threshold / (1 + threshold) * (n[active] + n[other]) - 1e-9
            x, y = who[active[reach]], who[other[reach]]
            pair = np.minimum(x, y) * len(ids) + np.maximum(x, y)
            found.append(pair[x != y])
            fresh += len(found[-1])
            if fresh > 1 << 22:
                found, fresh = [np.unique(np.concatenate(found))], 0
            step += 1
            active = active[active + step < len(g)]
        pair = np.unique(np.concatenate(found))
        lang = pa.array([key[0].as_py()], pa.string())
        return pa.table({"lang": pa.DictionaryArray.from_arrays(pa.array(np.zeros(len(pair), np.int32)), lang).cast(pa.string()), "src": ids[pair // len(ids)], "dst": ids[pair % len(ids)]})

    return packets.groupBy("lang", "bucket").applyInArrow(meet, "lang string, src long, dst long")


def _outline(values: np.ndarray, begin: np.ndarray, some: np.ndarray) -> pa.Array:
    out = []
    for i in some:
        own = values[begin[i] : begin[i + 1]]
        bins = 1 << int(len(own) - 1).bit_length()
        out.append(lm_buckets._put(np.bincount((own & np.uint64(bins - 1)).astype(np.int64), minlength=bins).astype(np.uint32)))
    return pa.array(out, pa.binary())


def _outlines(docs: DataFrame, n: int) -> DataFrame:
    """(doc_id, o): how many shingles fall in each of at least n bins, a power of two, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text"):
            values, begin = _sets(part.column("text"), n)
            some = np.flatnonzero(np.diff(begin))
            yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(some)), _outline(values, begin, some)], ["doc_id", "o"])

    return _plain(docs).mapInArrow(run, "doc_id long, o binary")


def _possible(pairs: DataFrame, outlines: DataFrame, threshold: float) -> DataFrame:
    """The pairs whose bins could hold enough common shingles: the lesser count of each bin bounds them, so that none at the threshold goes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x"), batch.column("y"), strict=True):
                (x,), (y,) = (lm_buckets._get(z.as_py()) for z in (x, y))
                bins = min(len(x), len(y))
                x, y = (z.reshape(-1, bins).sum(0, dtype=np.int64) for z in (x, y))
                keep.append(np.minimum(x, y).sum() >= threshold / (1 + threshold) * (x.sum() + y.sum()) - 1e-9)
            yield batch.select(["lang", "src", "dst"]).filter(pa.array(keep, pa.bool_()))

    of = lambda end, name: outlines.select(F.col("doc_id").alias(end), F.col("o").alias(name))
    return pairs.join(of("src", "x"), "src").join(of("dst", "y"), "dst").select("lang", "src", "dst", "x", "y").mapInArrow(run, "lang string, src long, dst long")


class Exact:
    """All near-duplicate pairs without bands: a prefix filter on representatives of equal shingle sets, which loses no pair, and verification."""

    def __init__(self, docs: DataFrame, n: int = DEDUP_NGRAM, threshold: float = DEDUP_THRESHOLD, signed: DataFrame | None = None) -> None:
        """*signed*: written signatures of the documents with outlines, where they are made already; their bands are not read."""
        self.space = space = Workspace(docs.sparkSession, "exact")
        key = ["lang", "a", "b", "n"]
        own = (signatures(docs, n, 1, 1) if signed is None else signed).filter("lang is not null").select("doc_id", *key)
        self.signed = space.write(own, free=True) if signed is None else own
        self.classes = space.write(self.signed.groupBy(*key).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies")), free=True)
        total = self.classes.agg(F.sum("n")).first()[0] or 0
        of = lambda ids: docs.join(ids.hint("shuffle_hash"), F.col("doc_id") == F.col("_id"), "left_semi")
        reps = of(self.classes.select(F.col("rep").alias("_id")))
        packets = _prefixes(reps, n, threshold, max(4, math.ceil(total * (1 - threshold) / lm_buckets.STEP)), _frequent(docs, n, total))
        packets = space.write(packets, free=True)
        pairs = space.write(_meetings(packets, threshold).distinct(), free=True)
        space.drop(packets)
        outlines = space.write(_outlines(docs, n), free=True) if signed is None else signed.select("doc_id", "o")
        pairs = space.write(_possible(pairs, outlines, threshold), free=True)
        if signed is None:
            space.drop(outlines)
        sets = space.write(shingle_sets(of(pairs.select(F.explode(F.array("src", "dst")).alias("_id")).distinct()), n), free=True)
        self.links = space.write(verify(pairs, sets).filter(F.col("jaccard") >= threshold), free=True)
        space.drop(sets)

    def copies(self) -> DataFrame:
        """(lang, node, rep): each document with words and its representative."""
        key = ["lang", "a", "b", "n"]
        return self.signed.join(self.classes.select(*key, "rep"), key).select("lang", F.col("doc_id").alias("node"), "rep")

    def clusters(self) -> DataFrame:
        """(node, root) of the documents that have a near-duplicate."""
        roots = self.space.write(components(self.links)).withColumnRenamed("node", "rep")
        copied = self.classes.filter("copies > 1").select("rep")
        held = self.copies().join(roots, "rep", "left").join(copied.withColumn("more", F.lit(True)), "rep", "left")
        return held.filter("root is not null or more").select("node", F.coalesce("root", "rep").alias("root"))


def components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, root) by least neighbours with pointer jumping; each round is written to the shared folder."""
    space = Workspace(edges.sparkSession, "components")
    both = space.write(edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    labels = both.groupBy(F.col("src").alias("node")).agg(F.min("dst").alias("m")).select("node", F.least("node", "m").alias("root"))
    total = None
    for _ in range(rounds):
        labels = space.write(labels)
        new = labels.agg(F.sum(F.col("root").cast("decimal(38,0)"))).first()[0]
        if new == total:
            return labels
        total = new
        near = both.join(labels, both["dst"] == labels["node"]).groupBy("src").agg(F.min("root").alias("m"))
        step = labels.join(near, labels["node"] == near["src"], "left").select("node", F.least("root", F.coalesce("m", "root")).alias("root"))
        up = labels.select(F.col("node").alias("root"), F.col("root").alias("upper"))
        labels = step.join(up, "root", "left").select("node", F.least("root", F.coalesce("upper", "root")).alias("root"))
    raise RuntimeError("components did not settle")


def keep_one(docs: DataFrame, clusters: DataFrame, policy: str = "min_id") -> DataFrame:
    """(root, doc_id) of the survivor of each cluster: least id, longest text, or best of a column `quality`."""
    j = docs.join(clusters, docs["doc_id"] == clusters["node"])
    order = {"min_id": -F.col("doc_id"), "longest": F.struct(F.length("text"), -F.col("doc_id")), "best_quality": F.struct("quality", -F.col("doc_id")) if "quality" in docs.columns else None}[policy]
    return j.groupBy("root").agg(F.max_by("doc_id", order).alias("doc_id"))


def fuzzy_dedup(docs: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """(kept documents, removed ids with their root), per language; the least id of a cluster stays."""
    removed = clusters(docs, **options).filter("node <> root")
    return docs.join(removed.select(F.col("node").alias("doc_id")).hint("shuffle_hash"), "doc_id", "left_anti"), removed


def exact_dedup(docs: DataFrame, normalise: bool = False) -> DataFrame:
    """One document per (normalised) text: least id; only hashes are shuffled."""
    text = F.lower(F.regexp_replace(F.trim("text"), r"\s+", " ")) if normalise else F.col("text")
    return docs.groupBy(F.sha2(text, 256).alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).select("doc_id", "copies")
