"""Removal of lines that many documents share, with DataFrame functions only.

Plan: each document's normalised long lines, once each, are hashed to 128 bits and written as a narrow table of ids and hashes. The
documents and the largest id per hash are counted from it, first by hash and id, then by hash. The hashes over the threshold
are joined back to the lines that lose, the losing hashes are gathered per document, and each text's own line array is
filtered, which keeps the order. Only hashes and ids are shuffled for counting; texts move once, to meet the list
of what they lose, and the join's build side is that (small) list.

Hot lines: equal hashes are counted by (hash, id) first, so a line that a third of the rows hold is dealt by its ids. For the join back
the `HOT` most common hashes (a fixed number, whatever the table) are broadcast: their lines are decided where they are
read and dealt by id, so no task gets all rows of a common line. A document's list is bounded by its own lines.

Defined cases: null or empty text is one empty line; texts without a newline are one line; keys under `min_chars`
code points are never dropped; a document that holds a line several times counts once; rows that repeat an id are
one document for the counts, and each keeps or loses lines as its id does; a null id counts as one document, under all others; an
empty table gives an empty result; other columns are carried by `drop_shared_lines`, whatever their names, but those that are named as
the two counts it adds, which are replaced (`counts=None` adds none).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace, unused

#: So many hashes, the most common ones, are joined by broadcast.
HOT = 1024
_SPACE = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def line_key(line: Column) -> Column:
    """The line without white space at its ends, A-Z in lower case (other letters as they are)."""
    return _folded(F.btrim(line, F.lit(_SPACE)))


def key_hash(key: Column) -> Column:
    return F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit(7), key).alias("b"))


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _trimmed(lines: Column) -> Column:
    return F.transform(lines, lambda x: F.btrim(x, F.lit(_SPACE)))


def _folded(key: Column) -> Column:
    return F.when(F.octet_length(key) == F.length(key), F.lower(key)).otherwise(F.translate(key, _UPPER, _LOWER))


def held_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40) -> DataFrame:
    """(id, a, b): hashes of the long lines of each document, once per row."""
    keys = F.filter(_trimmed(lines_of(F.col(text_col))), lambda x: F.length(x) >= min_chars)
    hashes = F.array_distinct(F.transform(F.transform(keys, _folded), key_hash))
    return docs.select(F.col(id_col).alias("id"), F.explode(hashes).alias("h")).select("id", "h.a", "h.b")


def shared_lines(held: DataFrame, min_docs: int = 5) -> DataFrame:
    """(a, b, n, keeper): hashes of lines that so many documents hold, and the largest id that holds them."""
    counts = held.distinct().groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.max("id").alias("keeper"))
    return counts.filter(F.col("n") >= min_docs)


def losing_lines(held: DataFrame, shared: DataFrame, hot: int = HOT) -> DataFrame:
    """(id, a, b) of the lines that go."""
    common = shared.orderBy(F.col("n").desc(), "a", "b").limit(hot).select(F.col("a").alias("ha"), F.col("b").alias("hb"), F.col("keeper").alias("hot_keeper"), F.lit(True).alias("hot"))
    tagged = held.join(F.broadcast(common), (F.col("a") == F.col("ha")) & (F.col("b") == F.col("hb")), "left")
    # A hot line is decided already; it travels under a key made of its id.
    known = F.col("hot").isNotNull()
    tagged = tagged.select("id", "a", "b", "hot", "hot_keeper", F.when(known, F.xxhash64("id", "a")).otherwise(F.col("a")).alias("ka"), F.when(known, F.xxhash64("id", "b")).otherwise(F.col("b")).alias("kb"))
    rest = shared.select(F.col("a").alias("ka"), F.col("b").alias("kb"), F.col("keeper"), F.lit(True).alias("over"))
    both = tagged.join(rest, ["ka", "kb"], "left")
    keeper = F.when(F.col("hot").isNotNull(), F.col("hot_keeper")).otherwise(F.col("keeper"))
    return both.filter((F.col("hot").isNotNull() | F.col("over").isNotNull()) & ~F.col("id").eqNullSafe(keeper)).select("id", "a", "b")


def drop_shared_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5, counts: tuple[str, str] | None = ("n_lines", "n_dropped")) -> DataFrame:
    """The documents with `text` rewritten, plus `n_lines` (before) and `n_dropped`."""
    held = Workspace(docs.sparkSession, "linededup").write(held_lines(docs, id_col, text_col, min_chars))
    lost = losing_lines(held, shared_lines(held, min_docs))
    loser, gone, kept_col = unused("_loser", docs), unused("_gone_lines", docs), unused("_kept_lines", docs)
    per_doc = lost.groupBy(F.col("id").alias(loser)).agg(F.collect_set(F.struct("a", "b")).alias(gone))
    joined = docs.join(per_doc.hint("shuffle_hash"), docs[id_col].eqNullSafe(per_doc[loser]), "left")
    keep = lambda x: (F.length(F.btrim(x, F.lit(_SPACE))) < min_chars) | ~F.array_contains(F.col(gone), key_hash(line_key(x)))
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = joined.withColumn(kept_col, F.when(F.col(gone).isNotNull(), F.filter(lines_of(F.col(text_col)), keep)))
    if counts:
        n_lines = (F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1).cast("long")
        out = out.withColumn(counts[0], n_lines)
        out = out.withColumn(counts[1], F.when(F.col(kept_col).isNull(), F.lit(0)).otherwise(F.col(counts[0]) - F.size(kept_col)).cast("long"))
    out = out.withColumn(text_col, F.when(F.col(kept_col).isNull(), F.col(text_col)).otherwise(F.array_join(kept_col, "\n")))
    return out.drop(loser, gone, kept_col)


def line_digest(docs: DataFrame) -> DataFrame:
    out = drop_shared_lines(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


ORACLE = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
k AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM l),
shared AS (
  SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 40
  GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
m AS (
  SELECT k.doc_id, k.pos, k.line, s.key IS NOT NULL AND k.doc_id <> s.keeper AS lost
  FROM k LEFT JOIN shared s ON k.key = s.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (lost) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT lost), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
