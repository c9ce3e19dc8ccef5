"""Perplexity filtering: per-language Kneser-Ney models, thresholds by quantile, reports.

Counts come from one explode of the highest order and combined aggregations; lower orders are counts of distinct left words. Probabilities are
interpolated from the lowest order up in joins of the model's own tables, so a finished model has one probability per n-gram and one
back-off weight per context. Scoring is a map pass with the model compiled into sorted arrays where it has at most
`COMPILED` rows, and joins of positions with the model's tables beyond that; both give the same numbers.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .. import config
from ..functions import text as T
from ..functions.arrays import buffers, mix, token_hashes
from ..shared import Workspace

ACCENTED, PLAIN = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy"
#: Unicode punctuation and its ASCII form.
MARKS = (("“", '"'), ("”", '"'), ("„", '"'), ("’", "'"), ("‘", "'"), ("–", "-"), ("—", "-"), ("…", "..."), ("«", '"'), ("»", '"'), ("।", "."))
#: Rows of n-grams and contexts up to which a model is compiled and broadcast (16 bytes each).
COMPILED = 20_000_000
#: Discounts where the counts of counts cannot give them.
FALLBACK = (0.5, 1.0, 1.5)


def normalize(text: Column) -> Column:
    """Lower case, accents off, digits to 0, Unicode punctuation to ASCII, no control characters."""
    text = F.regexp_replace(F.translate(F.lower(text), ACCENTED, PLAIN), r"\p{Nd}", "0")
    for a, b in MARKS:
        text = F.replace(text, F.lit(a), F.lit(b))
    return F.regexp_replace(text, r"[\x00-\x08\x0B\x0C\x0E-\x1F\x7F​‌‍﻿]", "")


def part(doc_id: Column, share: float = 0.6) -> Column:
    """`train` or `valid` by a hash of the id: disjoint, reproducible, and growing with the corpus."""
    return F.when(T.md5_int(doc_id) % 100 < round(share * 100), "train").otherwise("valid")


def sample_per_lang(docs: DataFrame, n: int = config.LM_TRAIN_DOCS, skip: int = 0) -> DataFrame:
    """n documents per language in hash order after *skip*: reproducible and disjoint from the first *skip*.

    Ids alone are ranked, and of a large language only those whose hash is low enough to come among the first ones.
    """
    h = T.md5_int(F.col("doc_id"))
    total = docs.groupBy("lang").agg(F.count(F.lit(1)).alias("_t"))
    # Ids expected under the cut: half as many again as are wanted, and a thousand.
    near = docs.select("doc_id", "lang", h.alias("_h")).join(F.broadcast(total), "lang").filter(F.col("_h") * F.col("_t") <= F.lit((1.5 * (n + skip) + 1000) * 2.0**32))
    w = Window.partitionBy("lang").orderBy("_h", "doc_id")
    ids = near.withColumn("_r", F.row_number().over(w)).filter((F.col("_r") > skip) & (F.col("_r") <= skip + n)).select("doc_id")
    return docs.join(ids, "doc_id", "left_semi")


def sequences(docs: DataFrame, text: str = "text") -> DataFrame:
    """doc_id, lang, s: word arrays of sentences with marks at both ends."""
    s = F.transform(T.sentences(normalize(F.col(text))), lambda x: F.concat(F.array(F.lit("<s>")), T.folded_words(x), F.array(F.lit("</s>"))))
    return docs.select("doc_id", "lang", F.explode(s).alias("s"))


def subword_sequences(docs: DataFrame, model_file: str, text: str = "text") -> DataFrame:
    """The same with the pieces of a public subword vocabulary (a sentencepiece file; none is trained here) in place of words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import sentencepiece

        pieces = sentencepiece.SentencePieceProcessor(model_file=model_file)
        for batch in batches:
            cut = [["<s>", *p, "</s>"] for p in pieces.encode(batch.column("x").to_pylist(), out_type=str, num_threads=1)] if batch.num_rows else []
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("lang"), pa.array(cut, pa.list_(pa.string()))], ["doc_id", "lang", "s"])

    return Subwords(docs, model_file, text).sentences().mapInArrow(run, "doc_id long, lang string, s array<string>")


BLANK = "\u2581"


def separable(model_file: str) -> bool:
    """Whether blanks and the word after them are always cut by themselves: text is taken as it is, pieces are made by merges, and none has a blank after another character."""
    try:
        from sentencepiece import sentencepiece_model_pb2
    except ImportError:
        return False
    model = sentencepiece_model_pb2.ModelProto()
    with open(model_file, "rb") as f:
        model.ParseFromString(f.read())
    spec, trainer = model.normalizer_spec, model.trainer_spec
    plain = spec.add_dummy_prefix and spec.escape_whitespaces and not (spec.remove_extra_whitespaces or spec.precompiled_charsmap or spec.normalization_rule_tsv)
    merged = trainer.model_type == trainer.BPE and not trainer.treat_whitespace_as_suffix and all(p.type != p.USER_DEFINED for p in model.pieces)
    names = {p.piece for p in model.pieces}
    return plain and merged and BLANK in names and not any(BLANK in name.lstrip(BLANK) for name in names)


class Pieces:
    """Pieces of sentences as numbers, and the hash of each number's piece; the marks of a sentence come after the vocabulary.

    Where words are cut by themselves, each distinct word is cut once, by its 64-bit hash.
    """

    #: Distinct words that are kept; beyond, they are cut anew.
    MOST = 1 << 18

    def __init__(self, model_file: str) -> None:
        import sentencepiece

        self.model, self.apart = sentencepiece.SentencePieceProcessor(model_file=model_file), separable(model_file)
        names = [self.model.id_to_piece(i) for i in range(self.model.get_piece_size())]
        if not any(self.model.is_byte(i) for i in range(len(names))):
            raise ValueError("a vocabulary without bytes has one number for all unknown pieces: use subword_sequences")
        self.marks, self.hashes = (len(names), len(names) + 1), _hashes(pa.array([*names, "<s>", "</s>"]))
        self._forget()

    def _forget(self) -> None:
        self.known: dict[int, int] = {}
        self.begin, self.pieces = np.zeros(1, np.int64), np.zeros(0, np.uint32)

    def _encode(self, texts: list[str], alone: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """Sizes and pieces of texts; *alone* is what a blank by itself is, of which the library makes nothing."""
        cut = [c or alone for c in self.model.encode(texts, out_type=int, num_threads=1)]
        size = np.fromiter(map(len, cut), np.int64, len(cut))
        return size, np.fromiter(chain.from_iterable(cut), np.uint32, int(size.sum()))

    def _by_words(self, sentences: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """A blank before each sentence is what the library adds; so it does for each word, which goes without its first blank."""
        raw, at = buffers(pc.binary_join_element_wise("", pc.replace_substring(sentences, BLANK, " "), " "))
        blank = raw == 32
        begins = blank.copy()
        begins[1:] &= ~blank[:-1]
        begins[at[:-1]] = True
        first = np.flatnonzero(begins)
        last = np.append(first[1:], len(raw))
        words, example, which = np.unique(token_hashes(raw, first, last, fold=False), return_index=True, return_inverse=True)
        if len(self.known) + len(words) > self.MOST:
            self._forget()
        place = np.array([self.known.get(h, -1) for h in words.tolist()], np.int64)
        fresh = np.flatnonzero(place < 0)
        if len(fresh):
            data = raw.tobytes()
            size, pieces = self._encode([data[i + 1 : j].decode() for i, j in zip(first[example[fresh]].tolist(), last[example[fresh]].tolist(), strict=True)], [self.model.piece_to_id(BLANK)])
            place[fresh] = np.arange(len(self.known), len(self.known) + len(fresh))
            self.known.update(zip(words[fresh].tolist(), place[fresh].tolist(), strict=True))
            self.begin = np.concatenate([self.begin, self.begin[-1] + np.cumsum(size)])
            self.pieces = np.concatenate([self.pieces, pieces])
        word = place[which]
        size = self.begin[word + 1] - self.begin[word]
        ends = np.cumsum(size)
        pieces = self.pieces[np.arange(int(ends[-1])) + np.repeat(self.begin[word] - ends + size, size)]
        return np.add.reduceat(size, np.searchsorted(first, at[:-1])), pieces

    def cut(self, sentences: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Sizes of sentences (one or more, none empty) with marks at both ends, and the pieces of all."""
        size, pieces = self._by_words(sentences) if self.apart else self._encode(sentences.to_pylist(), [])
        stops = np.cumsum(size + 2)
        out, inside = np.empty(int(stops[-1]), np.uint32), np.ones(int(stops[-1]), bool)
        for places, mark in zip((stops - size - 2, stops - 1), self.marks, strict=True):
            out[places], inside[places] = mark, False
        out[inside] = pieces
        return size + 2, out


@dataclass
class Subwords:
    """The sentences of `subword_sequences`, cut where they are read."""

    docs: DataFrame
    model_file: str
    text: str = "text"

    def sequences(self) -> DataFrame:
        return subword_sequences(self.docs, self.model_file, self.text)

    def sentences(self) -> DataFrame:
        return self.docs.select("doc_id", "lang", F.explode(T.sentences(normalize(F.col(self.text)))).alias("x"))


def ngram_counts(seqs: DataFrame, n: int) -> DataFrame:
    """lang, g, c: counts of n-grams, words joined by blanks."""
    windows = F.when(F.size("s") >= n, F.transform(F.sequence(F.lit(n), F.size("s")), lambda j: F.array_join(F.slice("s", j - n + 1, F.lit(n)), " ")))
    return seqs.select("lang", F.explode(windows).alias("g")).groupBy("lang", "g").agg(F.count(F.lit(1)).alias("c"))


def _rest(g: Column) -> Column:
    """All words but the first."""
    return F.regexp_replace(g, "^[^ ]+ ", "")


def _context(g: Column) -> Column:
    """All words but the last."""
    return F.regexp_replace(g, " [^ ]+$", "")


def continuation(counts: DataFrame) -> DataFrame:
    """From k-grams to (k-1)-grams: the number of distinct words on the left."""
    return counts.groupBy("lang", _rest(F.col("g")).alias("g")).agg(F.count(F.lit(1)).alias("c"))


def count_tables(seqs: DataFrame, order: int = config.LM_ORDER, space: Workspace | None = None) -> list[DataFrame]:
    """(lang, g, c) of orders 1 to *order*: raw counts on top and for n-grams that begin a sentence, distinct left words for all others.

    Sentences and each table are written once, since the next lower table is made from them.
    """
    space = space or Workspace(seqs.sparkSession, "counts")
    seqs = space.write(seqs)
    tables = [space.write(ngram_counts(seqs, order))]
    for k in range(order - 1, 0, -1):
        lower = continuation(tables[-1])
        if k > 1:
            starts = seqs.filter(F.size("s") >= k).groupBy("lang", F.array_join(F.slice("s", 1, k), " ").alias("g")).agg(F.count(F.lit(1)).alias("c"))
            lower = lower.unionByName(starts)
        tables.append(space.write(lower))
    return tables[::-1]


def discounts(counts: DataFrame, modified: bool = True) -> DataFrame:
    """lang, d1, d2, d3 from the counts of counts; one discount for all counts where not *modified*."""
    n = counts.groupBy("lang").agg(*(F.count_if(F.col("c") == i).cast("double").alias(f"n{i}") for i in range(1, 5)))
    y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))
    if not modified:
        return n.select("lang", *(F.when((F.col("n1") > 0) & (F.col("n2") > 0), y).otherwise(F.lit(0.75)).alias(f"d{i}") for i in (1, 2, 3)))
    enough = (F.col("n1") > 0) & (F.col("n2") > 0) & (F.col("n3") > 0) & (F.col("n4") > 0)
    d = [i - (i + 1) * y * F.col(f"n{i + 1}") / F.col(f"n{i}") for i in (1, 2, 3)]
    sound = enough & (d[0] >= 0) & (d[1] >= 0) & (d[2] >= 0)
    return n.select("lang", *(F.when(sound, d[i]).otherwise(F.lit(FALLBACK[i])).alias(f"d{i + 1}") for i in range(3)))


def _discount() -> Column:
    return F.when(F.col("c") == 1, F.col("d1")).when(F.col("c") == 2, F.col("d2")).otherwise(F.col("d3"))


def _left_over() -> Column:
    """What all discounts of a context take."""
    return F.sum(_discount())


@dataclass
class Model:
    """probs[k-1]: (lang, g, p); backs[k-1]: (lang, x, b) of contexts (order 1: the share of unknown words as b, x empty)."""

    probs: list[DataFrame]
    backs: list[DataFrame]

    @property
    def order(self) -> int:
        return len(self.probs)


def kneser_ney(seqs: DataFrame, order: int = config.LM_ORDER, modified: bool = True) -> Model:
    """Interpolated Kneser-Ney; each table is written once, and languages have a row each in what is broadcast."""
    space = Workspace(seqs.sparkSession, "lm")
    probs, backs = [], []
    for k, counts in enumerate(count_tables(seqs, order, space), 1):
        c = counts.join(F.broadcast(discounts(counts, modified)), "lang")
        if k == 1:
            total = c.groupBy("lang").agg(F.sum("c").alias("t"), _left_over().alias("taken"), F.count(F.lit(1)).alias("v"))
            total = total.select("lang", "t", (F.col("taken") / F.col("t") / (F.col("v") + 1)).alias("b"))
            p = c.join(F.broadcast(total), "lang").select("lang", "g", ((F.col("c") - _discount()) / F.col("t") + F.col("b")).alias("p"))
            back = total.select("lang", F.lit("").alias("x"), "b")
        else:
            c = c.withColumn("x", _context(F.col("g")))
            by_context = c.groupBy("lang", "x").agg(F.sum("c").alias("t"), _left_over().alias("taken"))
            by_context = space.write(by_context.select("lang", "x", "t", (F.col("taken") / F.col("t")).alias("b")))
            lower = probs[-1].select("lang", F.col("g").alias("r"), F.col("p").alias("q"))
            c = c.withColumn("r", _rest(F.col("g"))).join(by_context, ["lang", "x"]).join(lower, ["lang", "r"])
            p = c.select("lang", "g", ((F.col("c") - _discount()) / F.col("t") + F.col("b") * F.col("q")).alias("p"))
            back = by_context.select("lang", "x", "b")
        probs.append(space.write(p))
        backs.append(back if k > 1 else space.write(back))
    return Model(probs, backs)


def _hashes(words: pa.Array) -> np.ndarray:
    """64-bit hash of each string of an array."""
    words = words.cast(pa.large_string())
    _, offsets, data = words.buffers()
    at = np.frombuffer(offsets, np.int64)[words.offset : words.offset + len(words) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return token_hashes(raw, at[:-1], at[1:], fold=False) if len(words) else np.zeros(0, np.uint64)


def _more(key: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Hash of words and one more of them on the left."""
    return mix(key * np.uint64(0x9E3779B97F4A7C15) + word)


def compile_model(model: Model) -> dict[str, list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]]:
    """Per language and order: sorted hashes of n-grams with their probabilities, sorted hashes of contexts with their back-off weights."""
    out: dict[str, list] = {}
    for k in range(1, model.order + 1):
        for table, column, value, slot in ((model.probs[k - 1], "g", "p", 0), (model.backs[k - 1], "x", "b", 2)):
            words = F.reverse(F.split(column, " "))
            rows = table.select("lang", words.alias("w"), F.col(value).alias("v")).toArrow().combine_chunks()
            lists = rows.column("w").combine_chunks()
            size = k if slot == 0 else max(k - 1, 1)
            h = _hashes(lists.flatten()).reshape(-1, size)
            key = np.zeros(len(h), np.uint64)
            for j in range(size):
                key = _more(key, h[:, j])
            coded, values = rows.column("lang").combine_chunks().dictionary_encode(), rows.column("v").to_numpy()
            for i, lang in enumerate(coded.dictionary.to_pylist()):
                mine = np.flatnonzero(coded.indices.to_numpy() == i)
                order = mine[np.argsort(key[mine])]
                held = out.setdefault(lang, [[None] * 4 for _ in range(model.order)])[k - 1]
                held[slot], held[slot + 1] = key[order], values[order]
    return out


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return at, keys[at] == wanted


def _score_compiled(seqs: DataFrame, tables: dict) -> DataFrame:
    """doc_id, lang, n, s: positions and sum of log10 of their probabilities, per sentence."""

    def logs(words: np.ndarray, place: np.ndarray, orders: list) -> np.ndarray:
        """log10 of all positions; *place* counts from 1 in each sentence."""
        key, back, p = np.zeros(len(words), np.uint64), np.zeros(len(words), np.uint64), None
        for k, (grams, prob, contexts, weight) in enumerate(orders, 1):
            shifted = np.concatenate([np.zeros(k - 1, np.uint64), words])[: len(words)]
            key = _more(key, shifted)
            fits = place >= max(k, 2)
            if k == 1:
                at, hit = _find(grams, key)
                p = np.where(hit, prob[at], weight[0])
                continue
            back = _more(back, shifted)
            if grams is None or not len(grams):
                continue
            at, hit = _find(grams, key)
            near, seen = _find(contexts, back)
            p = np.where(fits, np.where(hit, prob[at], np.where(seen, weight[near], 1.0) * p), p)
        return np.log10(p)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("s")
            size, words = np.diff(lists.offsets.to_numpy()).astype(np.int64), _hashes(lists.flatten())
            ends = np.cumsum(size)
            place = np.arange(len(words)) - np.repeat(ends - size, size) + 1
            langs = np.array(batch.column("lang").to_pylist(), object)
            total, known = np.zeros(len(size)), np.zeros(len(size), bool)
            for lang in set(langs.tolist()) & tables.keys():
                mine = langs == lang
                at = np.repeat(mine, size)
                value = np.where(place[at] > 1, logs(words[at], place[at], tables[lang]), 0.0)
                first = np.concatenate([[0], np.cumsum(size[mine])])
                sums = np.concatenate([[0.0], np.cumsum(value)])
                total[mine], known[mine] = sums[first[1:]] - sums[first[:-1]], True
            keep = pa.array(np.flatnonzero(known))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(keep), batch.column("lang").take(keep), pa.array(size[known] - 1), pa.array(total[known])], ["doc_id", "lang", "n", "s"])

    return seqs.mapInArrow(run, "doc_id long, lang string, n long, s double")


def _score_joined(seqs: DataFrame, model: Model) -> DataFrame:
    """The same by joins: one row per position meets the tables of each order."""
    n = model.order
    window = lambda j, k: F.when(j >= k, F.array_join(F.slice("s", F.greatest(j - k + 1, F.lit(1)), F.lit(k)), " "))
    at = F.transform(F.sequence(F.lit(2), F.size("s")), lambda j: F.struct(*(window(j, k).alias(f"g{k}") for k in range(1, n + 1))))
    p = seqs.select("doc_id", "lang", F.explode(at).alias("a")).select("doc_id", "lang", "a.*")
    unknown = model.backs[0].select("lang", F.col("b").alias("u"))
    p = p.join(F.broadcast(unknown), "lang").join(model.probs[0].select("lang", F.col("g").alias("g1"), "p"), ["lang", "g1"], "left")
    p = p.withColumn("p", F.coalesce("p", "u")).drop("u", "g1")
    for k in range(2, n + 1):
        p = p.withColumn("x", _context(F.col(f"g{k}")))
        p = p.join(model.probs[k - 1].select("lang", F.col("g").alias(f"g{k}"), F.col("p").alias("q")), ["lang", f"g{k}"], "left").join(model.backs[k - 1], ["lang", "x"], "left")
        lower = F.coalesce("b", F.lit(1.0)) * F.col("p")
        p = p.withColumn("p", F.when(F.col(f"g{k}").isNull(), F.col("p")).otherwise(F.coalesce("q", lower))).drop("q", "b", "x", f"g{k}")
    return p.groupBy("doc_id", "lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.log10("p")).alias("s"))


def perplexity(seqs: DataFrame, model: Model, backend: str | None = None) -> DataFrame:
    """doc_id, lang, tokens, ppl; *backend* `compiled` or `join`, by the size of the model where not given."""
    if backend is None:
        rows = sum(t.count() for t in [*model.probs, *model.backs])
        backend = "compiled" if rows <= COMPILED else "join"
    scored = _score_compiled(seqs, compile_model(model)) if backend == "compiled" else _score_joined(seqs, model)
    return scored.groupBy("doc_id", "lang").agg(F.sum("n").alias("tokens"), F.pow(F.lit(10.0), -F.sum("s") / F.sum("n")).alias("ppl"))


def thresholds(scored: DataFrame, q: float = config.PPL_QUANTILE, exact: bool = True) -> DataFrame:
    """Per language; the exact quantile needs a language's perplexities in one task, the approximate one does not."""
    f = F.percentile("ppl", F.lit(q)) if exact else F.percentile_approx("ppl", F.lit(q), F.lit(10_000))
    return scored.groupBy("lang").agg(f.alias("threshold"))


def ppl_filter(scored: DataFrame, limits: DataFrame) -> DataFrame:
    """Keeps documents at or under their language's threshold (a row per language is broadcast)."""
    return scored.join(F.broadcast(limits), "lang").filter(F.col("ppl") <= F.col("threshold"))


def ppl_report(scored: DataFrame, limits: DataFrame) -> DataFrame:
    j = scored.join(F.broadcast(limits), "lang")
    kept = F.count_if(F.col("ppl") <= F.col("threshold"))
    return j.groupBy("lang").agg(F.min("ppl").alias("min_ppl"), F.max("ppl").alias("max_ppl"), F.avg("ppl").alias("mean_ppl"), F.max("threshold").alias("threshold"), F.count(F.lit(1)).alias("docs"), kept.alias("chosen"), (1 - kept / F.count(F.lit(1))).alias("rate"))


def ppl_buckets(scored: DataFrame, k: int = 3) -> DataFrame:
    """doc_id, lang, bucket 1 (head) to k (tail), by quantiles of the language's perplexities: one narrow aggregation, and no sort of a language."""
    cuts = scored.groupBy("lang").agg(F.percentile("ppl", F.array(*(F.lit(i / k) for i in range(1, k)))).alias("cuts"))
    j = scored.join(F.broadcast(cuts), "lang")
    return j.select("doc_id", "lang", (1 + F.size(F.filter("cuts", lambda c: F.col("ppl") > c))).alias("bucket"))
