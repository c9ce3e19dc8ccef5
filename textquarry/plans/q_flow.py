"""Queries: whole flows over the splits."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import clean, dedup, flags, lm, report, signals
from ..registry import query, table
from ..shared import Workspace
from . import q_lm
from .q_curation import CLEAN, FLAGGED, FOLDED, REPETITION, SIGNALS, SPLIT, WORDS, grams_sql

STAGE_NAMES = ["prepared", "cleaned", "identified", "flagged", "deduplicated"]


def prepared(spark: SparkSession, d: str, space: Workspace) -> DataFrame:
    """One pass over the texts, written once: cleaned text, identified language, flags, words before and after cleaning."""
    docs = clean.clean(report.with_split(table(spark, d, "documents")), F.col("modality")).drop("n_chars", "source", "modality")
    said = q_lm._decided(spark, d).select("doc_id", F.col("lang").alias("new_lang"))
    docs = docs.join(said, "doc_id")
    count = lambda c: F.size(T.words(F.coalesce(F.col(c), F.lit("")))).cast("long")
    base = space.write(docs.select("doc_id", "lang", "new_lang", "split", "corpus", "clean_text", count("text").alias("words_0"), count("clean_text").alias("words_1")))
    sig = signals.signals(base.select("doc_id", F.col("new_lang").alias("lang"), F.col("clean_text").alias("text")))
    keep = flags.flag(sig, flags.thresholds(spark)).select("doc_id", "keep")
    return space.write(base.join(keep, "doc_id"))


def died_at(spark: SparkSession, d: str) -> DataFrame:
    """Which stage removes each document (0 prepared, 1 cleaned, 2 identified, 3 flagged, 4 deduplicated), and its words per stage."""
    space = Workspace(spark, "attrition")
    base = prepared(spark, d, space)
    alive = base.filter(F.col("clean_text").isNotNull() & F.col("keep")).select("doc_id", F.col("new_lang").alias("lang"), F.col("clean_text").alias("text"))
    gone = dedup.clusters(alive).filter("node <> root").select(F.col("node").alias("doc_id"), F.lit(True).alias("copy"))
    died = F.when(F.col("clean_text").isNull(), 1).when(~F.col("keep"), 3).when(F.col("copy"), 4)
    later = [F.col("words_1").alias(f"words_{i}") for i in (2, 3, 4)]
    return base.join(gone, "doc_id", "left").select("doc_id", "lang", "new_lang", "split", "corpus", "words_0", "words_1", *later, died.alias("died_at"))


_SIG_CLEAN = SIGNALS.replace("FROM documents)", "FROM (SELECT doc_id, new_lang AS lang, '' AS source, coalesce(clean_text, '') AS text FROM cl))")
_STAGED = f"""{CLEAN}, {q_lm.VOTES.replace('v AS (', 'lv AS (').replace('FROM v)', 'FROM lv)')}, cl AS (SELECT cleaned.*, en.lang AS new_lang FROM cleaned JOIN en USING (doc_id)), {_SIG_CLEAN.replace('base AS', 'base AS MATERIALIZED')}, {REPETITION}, {FLAGGED},
b AS MATERIALIZED (SELECT c.doc_id, c.lang, new_lang, c.split, c.corpus, c.clean_text, len(flags) = 0 AS keep, len({WORDS.format(x='c.text')}) AS w0, len({WORDS.format(x="coalesce(c.clean_text, '')")}) AS w1 FROM cl c JOIN flagged f ON c.doc_id = f.doc_id)"""
_SETS = f"ss AS MATERIALIZED (SELECT doc_id, lang, list_distinct({grams_sql('f', 5)}) AS s FROM (SELECT doc_id, new_lang AS lang, {FOLDED.format(x='clean_text')} AS f FROM b WHERE clean_text IS NOT NULL AND keep)), hh AS MATERIALIZED (SELECT doc_id, lang, unnest(s) AS g FROM ss), nn AS (SELECT doc_id, len(s) AS n FROM ss)"
_ATTRITION = f"""WITH RECURSIVE {_STAGED}, {_SETS},
cc AS (SELECT a.doc_id AS src, o.doc_id AS dst, count(*) AS i FROM hh a JOIN hh o ON a.lang = o.lang AND a.g = o.g AND a.doc_id < o.doc_id GROUP BY ALL),
ee AS MATERIALIZED (SELECT src, dst FROM cc JOIN nn x ON x.doc_id = src JOIN nn y ON y.doc_id = dst WHERE i / (x.n + y.n - i)::DOUBLE >= 0.7), e AS (SELECT src AS a, dst AS b FROM ee UNION SELECT dst, src FROM ee),
reach(node, other) AS (SELECT a, a FROM e UNION SELECT r.node, e.b FROM reach r JOIN e ON r.other = e.a), comp AS (SELECT node, min(other) AS root FROM reach GROUP BY node),
dd AS (SELECT b.*, CASE WHEN clean_text IS NULL THEN 1 WHEN NOT keep THEN 3 WHEN node <> root THEN 4 END AS died FROM b LEFT JOIN comp ON node = doc_id),
l AS (SELECT CASE WHEN stage_no >= {{moved}} THEN new_lang ELSE {{by}} END AS grp, stage_no, stage, CASE WHEN died IS NULL OR died > stage_no THEN CASE WHEN stage_no = 0 THEN w0 ELSE w1 END END AS w FROM dd, (VALUES (0,'prepared'),(1,'cleaned'),(2,'identified'),(3,'flagged'),(4,'deduplicated')) s(stage_no, stage) {{where}}),
a AS (SELECT grp, stage_no, stage, count(w) AS docs, coalesce(sum(w), 0)::BIGINT AS words FROM l GROUP BY ALL)
SELECT grp AS {{by}}, stage_no, stage, docs, words,
 CASE WHEN lag(docs) OVER p > 0 THEN 1 - docs / (lag(docs) OVER p)::DOUBLE ELSE 0.0 END AS docs_drop,
 CASE WHEN lag(words) OVER p > 0 THEN 1 - words / (lag(words) OVER p)::DOUBLE ELSE 0.0 END AS words_drop
FROM a WINDOW p AS (PARTITION BY grp ORDER BY stage_no)"""


@query(_ATTRITION.replace("{by}", "lang").replace("{moved}", "2").replace("{where}", ""))
def q_attrition(spark, d):
    """Documents and words alive after each stage, per language; documents move to their identified language at that stage."""
    return report.attrition(died_at(spark, d), STAGE_NAMES, moved=("new_lang", 2))


@query(_ATTRITION.replace("{by}", "corpus").replace("{moved}", "9").replace("{where}", "WHERE split = 'unverified'"))
def q_attrition_unverified(spark, d):
    """How unclean two public corpora are: the same stages on the unverified split."""
    return report.attrition(died_at(spark, d).filter("split = 'unverified'"), STAGE_NAMES, by="corpus")


_NEW = f"""{_SETS}, sides AS (SELECT hh.*, split FROM hh JOIN b USING (doc_id)),
cross_pairs AS (SELECT u.doc_id AS src, v.doc_id AS dst, count(*) AS i FROM (SELECT * FROM sides WHERE split = 'unverified') u JOIN (SELECT * FROM sides WHERE split = 'verified') v ON u.lang = v.lang AND u.g = v.g GROUP BY ALL),
seen AS (SELECT DISTINCT src AS doc_id FROM cross_pairs JOIN nn x ON x.doc_id = src JOIN nn y ON y.doc_id = dst WHERE i / (x.n + y.n - i)::DOUBLE >= 0.7),
fresh AS (SELECT doc_id, new_lang AS lang, clean_text FROM b WHERE split = 'unverified' AND clean_text IS NOT NULL AND keep AND doc_id NOT IN (SELECT doc_id FROM seen))"""


@query(f"""WITH {_STAGED}, {_NEW}, {q_lm.BASE}, {q_lm.model_sql(q_lm.ORDER)}, {q_lm.score_sql('val', 'valid', q_lm.ORDER)}, thr AS (SELECT lang, quantile_cont(ppl, 0.8) AS threshold FROM val GROUP BY lang),
{q_lm.sequences_sql('fs', 'fresh', 'clean_text')}, {q_lm.score_sql('new', 'fs', q_lm.ORDER)} SELECT doc_id, new.lang, ppl FROM new JOIN thr ON new.lang = thr.lang WHERE ppl <= threshold""")
def q_unverified_flow(spark, d):
    """The unverified split as one flow: cleaned, identified, flagged, without what the verified split holds already, and of those the documents under the perplexity threshold."""
    base = prepared(spark, d, Workspace(spark, "unverified"))
    alive = base.filter(F.col("clean_text").isNotNull() & F.col("keep")).select("doc_id", F.col("new_lang").alias("lang"), F.col("clean_text").alias("text"), "split")
    new = alive.filter("split = 'unverified'")
    fresh = new.join(dedup.dedup_against(new, alive.filter("split = 'verified'")), "doc_id", "left_anti")
    train, valid, _ = q_lm.parts(spark, d)
    model = q_lm.in_buckets(train)
    columns = ["doc_id", "lang", "text"]
    both = model.space.write(model.perplexity(lm.sequences(valid.select(*columns).unionByName(fresh.select(*columns)))))
    ids = valid.select("doc_id")
    return lm.ppl_filter(both.join(ids, "doc_id", "left_anti"), lm.thresholds(both.join(ids, "doc_id", "left_semi"))).select("doc_id", "lang", "ppl")


@query(f"""WITH {CLEAN} SELECT 'read' AS stage, count(*) AS rows_out, coalesce(sum(octet_length(encode(text))), 0)::BIGINT AS bytes_out FROM ({SPLIT}) UNION ALL SELECT 'cleaned', count(*), coalesce(sum(octet_length(encode(clean_text))), 0)::BIGINT FROM cleaned WHERE clean_text IS NOT NULL""")
def q_stage_metrics(spark, d):
    """Rows and bytes that pass each stage, observed while the result is written; no further pass."""
    read, first = report.stage_metrics(report.with_split(table(spark, d, "documents")), "read")
    cleaned = clean.clean(read, F.col("modality")).filter("clean_text is not null").select("doc_id", F.col("clean_text").alias("text"))
    out, second = report.stage_metrics(cleaned, "cleaned")
    Workspace(spark, "metrics").write(out)
    return spark.createDataFrame([(name, seen.get["rows"], seen.get["bytes"]) for name, seen in (("read", first), ("cleaned", second))], "stage string, rows_out long, bytes_out long")
