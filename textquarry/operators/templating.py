"""Structure-preserving translation and dictionary romanization as segment / infer / replace passes.

Only slots (sentences) and words that change travel: they are exploded, joined with their results, gathered per document, and put back by position
into the document's own segments. Structure, separators and unchanged words never leave the row.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import let

#: What no translator sees: fenced and back-ticked code, marks at the start of a line (headings, bullets, quotes, numbers, Roman numerals), markdown
#: marks, brackets, paragraph marks. Everything else is text.
STRUCTURE = r"```[\s\S]*?```|`[^`\n]*`|({line}^[ \t]*(?:(?:#{{1,6}}|[-+•>*]|\d{{1,3}}[.)]|[IVXLCDM]{{1,7}}[.)])[ \t]+)+)|[|*_\[\]()#\n\t]+|`"
TEXT = r"[^`|*_\[\]()#\n\t]+"
ROMAN_FROM, ROMAN_TO = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy"


def _marked(text: Column, pattern: str, groups: str) -> Column:
    return F.regexp_replace(text, F.lit(pattern), F.lit(groups))


def segments(text: Column) -> Column:
    """array<struct<is_slot, text>> whose texts concatenate to the input; a slot is a sentence that holds a letter."""
    structure = STRUCTURE.format(line="?dm:")
    runs = F.split(F.replace(_marked(text, f"({structure})|({TEXT})", "$1\x01$2\x02"), F.lit("\x01\x02"), F.lit("")), "\x01|(?<=\x02)")
    # A run of text: sentences, with the white space between them apart.
    cut = lambda run: F.split(_marked(_marked(F.replace(run, F.lit("\x02"), F.lit("")), r"^(\s+)|(\s+)$", "\x01$1$2\x01"), r"([.!?…।])(\s+)", "$1\x01$2\x01"), "\x01")
    pieces = F.flatten(F.transform(runs, lambda r: F.when(r.endswith("\x02"), F.transform(cut(r), lambda s: F.struct(s.rlike(r"\p{L}").alias("is_slot"), s.alias("text")))).otherwise(F.array(F.struct(F.lit(False).alias("is_slot"), r.alias("text"))))))
    return F.filter(pieces, lambda s: s["text"] != "")


def _compose(text: pd.Series) -> pd.Series:
    return text.map(lambda t: unicodedata.normalize("NFC", t), na_action="ignore")


def composed(text: Column) -> Column:
    """Canonical composition, so that equal sentences are equal strings."""
    return F.pandas_udf(_compose, "string")(text)


def slots(docs: DataFrame, *keys: str) -> DataFrame:
    """keys, ord, src: the sentences of each text by position, composed."""
    held = docs.select(*keys, F.posexplode(segments(F.col("text"))).alias("ord", "s")).filter("s.is_slot").select(*keys, "ord", F.col("s.text").alias("t"))
    ascii_only = F.octet_length("t") == F.length("t")
    return held.withColumn("c", composed(F.when(~ascii_only, F.col("t")))).select(*keys, "ord", F.coalesce("c", "t").alias("src"))


def sentence_dataset(docs: DataFrame) -> DataFrame:
    """Distinct sentences of the whole corpus: what is sent to a translator."""
    return slots(docs).groupBy("src").agg(F.count(F.lit(1)).alias("uses"))


def stub_translator(src: Column, target: Column) -> Column:
    """Deterministic stand-in: reversed text, tagged with the language."""
    return F.concat(target, F.lit(":"), F.reverse(src))


def infer(sentences: DataFrame, targets: tuple[str, ...], translate: Callable[[Column, Column], Column] = stub_translator) -> DataFrame:
    """src, lang, out: a translator as a column function."""
    return sentences.select("src", F.explode(F.array(*map(F.lit, targets))).alias("lang")).withColumn("out", translate(F.col("src"), F.col("lang")))


def infer_batches(sentences: DataFrame, targets: tuple[str, ...], load: Callable[[], Callable[[list[str], str], list[str]]]) -> DataFrame:
    """The same for a model that is loaded once per task and translates lists of sentences."""

    def run(parts):
        translate = load()
        for part in parts:
            for lang, rows in part.groupby("lang"):
                yield pd.DataFrame({"src": rows.src, "lang": lang, "out": translate(rows.src.tolist(), lang)})

    return sentences.select("src", F.explode(F.array(*map(F.lit, targets))).alias("lang")).mapInPandas(run, "src string, lang string, out string")


def restore(docs: DataFrame, translations: DataFrame, target: str, keys: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Put translated sentences back by position; structure is untouched. *keys* are unique and not null."""
    t = translations.filter(F.col("lang") == target).select("src", "out")
    found = slots(docs, *keys).join(t, "src").groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("ord", "out"))).alias("_found"))
    back = docs.select(*keys, "text").join(found, list(keys), "left")
    new = F.array_join(F.transform(segments(F.col("text")), lambda s, i: F.when(s["is_slot"], F.coalesce(F.try_element_at("_found", i), s["text"])).otherwise(s["text"])), "")
    return back.select(*keys, new.alias("text"))


def restore_by_replace(docs: DataFrame, translations: DataFrame, target: str) -> DataFrame:
    """Variant: every sentence replaced wherever it stands in the text, longest first. Equal to `restore` where no sentence stands inside another or inside a result."""
    t = translations.filter(F.col("lang") == target).select("src", "out")
    pairs = slots(docs, "doc_id").select("doc_id", "src").distinct().join(t, "src")
    order = F.array_sort(F.collect_list(F.struct((-F.length("src")).alias("n"), "src", "out")))
    back = docs.select("doc_id", "text").join(pairs.groupBy("doc_id").agg(order.alias("_pairs")), "doc_id", "left")
    new = F.aggregate("_pairs", F.col("text"), lambda acc, p: F.replace(acc, p["src"], p["out"]))
    return back.select("doc_id", F.when(F.col("_pairs").isNull(), F.col("text")).otherwise(new).alias("text"))


def romanize_letters(word: Column) -> Column:
    """Letter table: the inference stub for words without a mapping."""
    return F.replace(F.translate(word, ROMAN_FROM, ROMAN_TO), F.lit("ß"), F.lit("ss"))


def word_pieces(text: Column) -> Column:
    """Alternating words and separators that concatenate to the text."""
    mark = F.regexp_replace(text, r"(\p{L}+)", "\x01$1\x02")
    return F.filter(F.split(mark, "[\x01\x02]"), lambda p: p != "")


def foreign_words(text: Column) -> Column:
    """Distinct lower-case words with letters outside ASCII."""
    return F.array_distinct(F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w.rlike(r"[^\x00-\x7F]")))


def vocabulary(docs: DataFrame) -> DataFrame:
    """lang, word: distinct lower-case words with letters outside ASCII."""
    return docs.select("lang", F.explode(foreign_words(F.col("text"))).alias("word")).distinct()


def infer_words(words: DataFrame, transliterate: Callable[[Column], Column] = romanize_letters) -> DataFrame:
    """lang, word, roman by a pluggable model."""
    return words.select("lang", "word", transliterate(F.col("word")).alias("roman"))


def grow_map(words: DataFrame, known: DataFrame, rounds: int = 3, transliterate: Callable[[Column], Column] = romanize_letters) -> DataFrame:
    """Map plus inferred words: log what is unmapped, infer it, repeat until nothing is left (one round with a total model)."""
    out = known.withColumn("generation", F.lit(0))
    for g in range(1, rounds + 1):
        missing = words.join(out, ["lang", "word"], "left_anti")
        if missing.isEmpty():
            break
        out = out.unionByName(infer_words(missing, transliterate).withColumn("generation", F.lit(g)))
    return out


def _cased(word: Column, roman: Column) -> Column:
    """The Roman form with capitals where the word has them; in a longer form, letters that match in place, and the last ones."""
    letters = lambda x: F.filter(F.split(x, ""), lambda c: c != "")

    def spell(w: Column, r: Column) -> Column:
        placed = lambda c, i: (F.size(r) == F.size(w)) | (F.lower(F.get(w, i)) == c)
        own = lambda c, i: F.coalesce(F.when(i >= F.size(w), F.get(w, F.size(w) - F.size(r) + i)).when(placed(c, i), F.get(w, i)), F.lit(""))
        return F.array_join(F.transform(r, lambda c, i: F.when(own(c, i) != F.lower(own(c, i)), F.upper(c)).otherwise(c)), "")

    return F.when(word == F.lower(word), roman).otherwise(let(letters(word), lambda w: let(letters(roman), lambda r: spell(w, r))))


def replace_words(docs: DataFrame, word_map: DataFrame) -> DataFrame:
    """Whole words replaced by (lang, word, roman), by position; all other characters stay."""
    held = docs.select("doc_id", "lang", F.explode(foreign_words(F.col("text"))).alias("word"))
    found = held.join(word_map.select("lang", "word", "roman"), ["lang", "word"]).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("word", "roman"))).alias("_map"))
    back = docs.select("doc_id", "text").join(found, "doc_id", "left")
    one = lambda p: let(F.try_element_at("_map", F.lower(p)), lambda r: F.when(r.isNull(), p).otherwise(_cased(p, r)))
    new = F.array_join(F.transform(word_pieces(F.col("text")), lambda p: F.when(p.rlike(r"[^\x00-\x7F]"), one(p)).otherwise(p)), "")
    return back.select("doc_id", F.when(F.col("_map").isNull(), F.col("text")).otherwise(new).alias("text"))


def replace_unordered(docs: DataFrame, word_map: DataFrame) -> DataFrame:
    """Baseline: each mapped word replaced as a substring, short words first, which changes words that hold them."""
    held = docs.select("doc_id", "lang", F.explode(foreign_words(F.col("text"))).alias("word"))
    pairs = held.join(word_map.select("lang", "word", "roman"), ["lang", "word"]).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct(F.length("word").alias("n"), "word", "roman"))).alias("_pairs"))
    back = docs.select("doc_id", F.lower("text").alias("text")).join(pairs, "doc_id", "left")
    new = F.aggregate("_pairs", F.col("text"), lambda acc, p: F.replace(acc, p["word"], p["roman"]))
    return back.select("doc_id", F.when(F.col("_pairs").isNull(), F.col("text")).otherwise(new).alias("text"))
