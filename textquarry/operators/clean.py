"""In-document cleaning: code spans, symbol-heavy documents, unterminated, symbol-only, repeated and short chunks.

Everything is one projection per document: no shuffle, linear in the text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import let

CODE_PATTERNS = (
    r"(?s)<(script|style)[^>]*>.*?</(script|style)>",
    r"function\s*\w*\s*\([^)]*\)\s*\{[^}]*\}",
    r"(?:var|let|const)\s+\w+\s*=\s*[^;\n]*;",
    r"[.#]?\w+\s*\{[^{}\n]*:[^{}\n]*\}",
    r"</?[a-zA-Z][^>\n]*>",
    r"&[a-z]{2,8};",
)
TERMINAL = r"[.!?…।][\"'»”’)]*\s*$"


def remove_code_spans(text: Column, patterns: tuple[str, ...] = CODE_PATTERNS) -> Column:
    for p in patterns:
        text = F.regexp_replace(text, p, "")
    return text


def symbol_count(text: Column) -> Column:
    """Characters other than letters, digits, combining marks and white space."""
    return F.length(F.regexp_replace(text, r"[\p{L}\p{N}\p{M}\s]", ""))


def symbol_ratio(text: Column) -> Column:
    return F.when(F.length(text) > 0, symbol_count(text) / F.length(text)).otherwise(F.lit(0.0))


def keep_terminated(text: Column, terminal: str = TERMINAL) -> Column:
    return F.array_join(F.filter(F.split(text, "\n"), lambda x: x.rlike(terminal)), "\n")


def drop_symbol_chunks(text: Column) -> Column:
    return F.array_join(F.filter(F.split(text, "\n"), lambda x: x.rlike(r"\p{L}")), "\n")


def drop_repeated_chunks(text: Column, mode: str = "first", k: int = 2) -> Column:
    """`first` keeps the first of equal chunks; `all` drops every chunk seen k times or more."""
    chunks = F.split(text, "\n")
    if mode == "first":
        return F.array_join(F.array_distinct(chunks), "\n")
    return let(chunks, lambda c: F.array_join(F.filter(c, lambda x: F.size(F.filter(c, lambda y: y == x)) < k), "\n"))


def drop_short_chunks(text: Column, min_words: int = 5) -> Column:
    return F.array_join(F.filter(F.split(text, "\n"), lambda x: F.size(F.filter(F.split(x, r"\s+"), lambda w: w != "")) >= min_words), "\n")


def clean(df: DataFrame, modality: Column, max_symbols: float = 0.08, min_words: int = 5) -> DataFrame:
    """Adds `clean_text` (null where the document is discarded) by the filters of its modality.

    web: code, symbols, terminal marks, symbol-only chunks; pdf: symbols, symbol-only, repeated, short chunks; speech: symbols, symbol-only.
    """
    text = F.col("text")
    web = drop_symbol_chunks(keep_terminated(remove_code_spans(text)))
    pdf = drop_short_chunks(drop_repeated_chunks(drop_symbol_chunks(text)), min_words)
    speech = drop_symbol_chunks(text)
    out = F.when(modality == "web", web).when(modality == "pdf", pdf).otherwise(speech)
    cleaned = df.withColumn("_c", F.when(symbol_ratio(text) <= max_symbols, out))
    return cleaned.withColumn("clean_text", F.when(F.col("_c") != "", F.col("_c"))).drop("_c")
