"""Queries: cleaning, statistics, flags, reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import config
from ..functions import text as T
from ..operators import clean, flags, report, signals
from ..registry import query, table

WORDS = r"list_filter(regexp_split_to_array({x}, '\s+'), lambda w: w <> '')"
FOLDED = r"list_filter(regexp_split_to_array(lower({x}), '[^\p{{L}}\p{{N}}_]+'), lambda w: w <> '')"
SENTENCES = r"list_filter(list_transform(string_split(regexp_replace({x}, '([.!?…।])\s+', '\1' || chr(10), 'g'), chr(10)), lambda s: trim(s)), lambda s: s <> '')"
SYMBOLS = r"(CASE WHEN length({x}) > 0 THEN length(regexp_replace({x}, '[\p{{L}}\p{{N}}\p{{M}}\s]', '', 'g')) / length({x})::DOUBLE ELSE 0.0 END)"
SPLIT = """SELECT *, CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) AS sn,
  CASE WHEN CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) <= 11 THEN 'verified' WHEN CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) <= 17 THEN 'unverified' ELSE 'synthetic' END AS split,
  CASE WHEN CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) <= 11 THEN 'own' WHEN CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) <= 14 THEN 'A' WHEN CAST(regexp_extract(source, '(\\d+)', 1) AS INTEGER) <= 17 THEN 'B' ELSE 'own' END AS corpus,
  CASE doc_id % 3 WHEN 0 THEN 'web' WHEN 1 THEN 'pdf' ELSE 'speech' END AS modality
  FROM documents"""


def words_sql(x: str) -> str:
    return WORDS.format(x=x)


def repeated_sql(grams: str, least: int = 2) -> str:
    """Share of occurrences of list elements seen *least* times or more."""
    return f"""(SELECT coalesce(sum(c) FILTER (c >= {least}) / sum(c)::DOUBLE, 0.0) FROM (SELECT count(*) AS c FROM (SELECT unnest({grams}) AS g) GROUP BY g))"""


def grams_sql(items: str, n: int) -> str:
    return f"""(CASE WHEN len({items}) >= {n} THEN list_transform(range(1, len({items}) - {n} + 2), lambda i: array_to_string({items}[i:i + {n - 1}], ' ')) WHEN len({items}) > 0 THEN [array_to_string({items}, ' ')] ELSE [] END)"""


SIGNALS = f"""
base AS (SELECT doc_id, lang, source, text, {WORDS.format(x='text')} AS w, {FOLDED.format(x='text')} AS f,
  list_transform({SENTENCES.format(x='text')}, lambda s: len({WORDS.format(x='s')})) AS s FROM documents),
sig AS (SELECT doc_id, lang, source, octet_length(encode(text)) AS bytes, len(w) AS word_count, length(text) AS char_count, len(s) AS lines_count,
  CASE WHEN len(s) > 0 THEN list_sum(s) / len(s)::DOUBLE ELSE 0.0 END AS mean_line_length,
  coalesce(list_min(s), 0) AS min_line_length, coalesce(list_max(s), 0) AS max_line_length,
  CASE WHEN lang = 'en' THEN len(list_filter(f, lambda x: x IN {config.NSFW_EN})) ELSE 0 END AS nsfw_words_count,
  length(regexp_replace(text, '[\\p{{Latin}}\\p{{N}}\\p{{P}}\\p{{S}}\\p{{Z}}\\p{{M}}\\s]', '', 'g')) AS non_target_count,
  {SYMBOLS.format(x='text')} AS symbol_ratio FROM base)"""

REPETITION = r"""
wg AS (SELECT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM base),
wr AS (SELECT doc_id, coalesce(sum(c) FILTER (c >= 2), 0) / sum(c)::DOUBLE AS word_rep FROM (SELECT doc_id, g, count(*) AS c FROM wg GROUP BY ALL) GROUP BY doc_id),
cg AS (SELECT doc_id, substr(text, i, 10) AS g FROM (SELECT doc_id, text, unnest(range(1, length(text) - 8)) AS i FROM base WHERE length(text) >= 10)),
cr AS (SELECT doc_id, coalesce(sum(c) FILTER (c >= 2), 0) / sum(c)::DOUBLE AS char_rep FROM (SELECT doc_id, g, count(*) AS c FROM cg GROUP BY ALL) GROUP BY doc_id),
full_sig AS (SELECT sig.*, coalesce(word_rep, 0.0) AS word_rep, coalesce(char_rep, 0.0) AS char_rep FROM sig LEFT JOIN wr USING (doc_id) LEFT JOIN cr USING (doc_id))"""

_T = config.THRESHOLDS["*"]
FLAGGED = f"""
flagged AS (SELECT *, list_sort(list_filter([
  CASE WHEN word_count > 0 AND nsfw_words_count / word_count::DOUBLE > {_T['nsfw_ratio']} THEN 'nsfw' END,
  CASE WHEN char_count > 0 AND non_target_count / char_count::DOUBLE > {_T['non_target_ratio']} THEN 'script' END,
  CASE WHEN lines_count < {_T['min_lines']} THEN 'few_lines' END,
  CASE WHEN mean_line_length < CASE lang WHEN 'fr' THEN {config.THRESHOLDS['fr']['min_mean_len']} ELSE {_T['min_mean_len']} END THEN 'short_lines' END,
  CASE WHEN word_rep > {_T['word_rep']} THEN 'word_rep' END,
  CASE WHEN char_rep > {_T['char_rep']} THEN 'char_rep' END,
  CASE WHEN symbol_ratio > {_T['symbol_ratio']} THEN 'symbols' END], lambda x: x IS NOT NULL)) AS flags FROM full_sig)"""


def _docs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents")


def _flagged(spark: SparkSession, d: str) -> DataFrame:
    return flags.flag(signals.signals(_docs(spark, d)), flags.thresholds(spark))


@query(f"WITH {SIGNALS} SELECT * EXCLUDE (source) FROM sig")
def q_signals(spark, d):
    return signals.signals(_docs(spark, d), repetition=False).drop("source")


@query(f"WITH {SIGNALS}, {REPETITION} SELECT doc_id, word_rep FROM full_sig")
def q_sig_word_rep(spark, d):
    return _docs(spark, d).select("doc_id", signals.word_repetition(F.col("text")).alias("word_rep"))


@query(f"WITH {SIGNALS}, {REPETITION} SELECT doc_id, char_rep FROM full_sig")
def q_sig_char_rep(spark, d):
    return _docs(spark, d).select("doc_id", signals.char_repetition(F.col("text")).alias("char_rep"))


@query(f"WITH {SIGNALS}, {REPETITION}, top AS (SELECT doc_id, c, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC, g) AS r, count(*) OVER (PARTITION BY doc_id) AS n, sum(c) OVER (PARTITION BY doc_id) AS total FROM (SELECT doc_id, g, count(*) AS c FROM cg GROUP BY ALL)) SELECT doc_id, sum(c) FILTER (r <= floor(sqrt(n))) / any_value(total)::DOUBLE AS char_rep_top FROM top GROUP BY doc_id")
def q_flag_charrep(spark, d):
    """Variant: the floor(sqrt(distinct)) commonest 10-grams' share. Grams are counted inside the row's own task and never shuffled."""
    return _docs(spark, d).filter(F.length("text") >= 10).select("doc_id", F.pandas_udf(signals.top_gram_share, "double")("text").alias("char_rep_top"))


@query(f"WITH {SIGNALS}, {REPETITION}, {FLAGGED} SELECT lang, flag, count(*) AS n FROM (SELECT lang, unnest(flags) AS flag FROM flagged) GROUP BY ALL")
def q_flags(spark, d):
    """Flagged documents per language and reason."""
    return _flagged(spark, d).select("lang", F.explode("flags").alias("flag")).groupBy("lang", "flag").agg(F.count(F.lit(1)).alias("n"))


_PART = FLAGGED.replace("FROM full_sig", "FROM part_sig")
_NO_REP = f"WITH {SIGNALS}, part_sig AS (SELECT *, 0.0 AS word_rep, 0.0 AS char_rep FROM sig), {_PART}"
_WORD_REP = f"WITH {SIGNALS}, {REPETITION[: REPETITION.index('cg AS')]} part_sig AS (SELECT sig.*, coalesce(word_rep, 0.0) AS word_rep, 0.0 AS char_rep FROM sig LEFT JOIN wr USING (doc_id)), {_PART}"


def _single(name: str, flag: str, prelude: str) -> None:
    def run(spark, d):
        return _flagged(spark, d).filter(F.array_contains("flags", flag)).select("doc_id", "lang")

    run.__name__ = name
    query(f"{prelude} SELECT doc_id, lang FROM flagged WHERE list_contains(flags, '{flag}')")(run)


for _name, _flag in (("q_flag_nsfw", "nsfw"), ("q_flag_script", "script"), ("q_flag_lines", "few_lines"), ("q_flag_meanlen", "short_lines")):
    _single(_name, _flag, _NO_REP)
_single("q_flag_wordrep", "word_rep", _WORD_REP)


@query(f"WITH {SIGNALS}, {REPETITION}, {FLAGGED} SELECT array_to_string(flags, '+') AS flag_set, count(*) AS n FROM flagged GROUP BY ALL")
def q_flag_matrix(spark, d):
    return flags.flag_matrix(_flagged(spark, d))


@query("SELECT lang, t::DOUBLE AS t_min_mean_len, count(*) AS docs, sum(n_chars)::BIGINT AS chars FROM documents JOIN (VALUES ('en',3.0),('fr',2.5),('de',3.0),('es',3.0)) t(l, t) ON lang = l GROUP BY ALL")
def q_thresholds(spark, d):
    """The threshold of each language, and what it is applied to."""
    limits = flags.thresholds(spark).select("lang", "t_min_mean_len")
    held = _docs(spark, d).join(F.broadcast(limits), "lang")
    return held.groupBy("lang", "t_min_mean_len").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").cast("long").alias("chars"))


@query(f"WITH {SIGNALS} SELECT lang, quantile_cont(symbol_ratio, 0.95) AS threshold FROM sig GROUP BY lang")
def q_calibrate(spark, d):
    return flags.calibrate(_docs(spark, d).select("lang", clean.symbol_ratio(F.col("text")).alias("symbol_ratio")), "symbol_ratio", 0.95)


@query(f"""WITH {SIGNALS}, {REPETITION}, {FLAGGED}, j AS (SELECT len(list_filter(flags, lambda x: x NOT IN ('nsfw', 'few_lines'))) > 0 AS bad, quality FROM flagged JOIN labels USING (doc_id))
SELECT count(*) FILTER (bad AND quality = 0) AS tp, count(*) FILTER (bad AND quality = 1) AS fp, count(*) FILTER (NOT bad AND quality = 0) AS fn, count(*) FILTER (NOT bad AND quality = 1) AS tn FROM j""")
def q_flag_vs_labels(spark, d):
    """Agreement of the flags with human quality labels."""
    bad = F.size(F.filter("flags", lambda x: ~x.isin("nsfw", "few_lines"))) > 0
    j = _flagged(spark, d).join(table(spark, d, "labels"), "doc_id").select(bad.alias("bad"), "quality")
    n = lambda b, q: F.count_if((F.col("bad") == b) & (F.col("quality") == q))
    return j.agg(n(True, 0).alias("tp"), n(True, 1).alias("fp"), n(False, 0).alias("fn"), n(False, 1).alias("tn"))


@query(f"""WITH h AS (SELECT d.lang, toxic, unnest(list_distinct({FOLDED.format(x='text')})) AS word FROM documents d JOIN labels l USING (doc_id) WHERE doc_id % 2 = 0),
p AS (SELECT lang, word, sum(toxic)::BIGINT AS pos, sum(1 - toxic)::BIGINT AS neg FROM h GROUP BY ALL HAVING sum(toxic) >= 3),
t AS (SELECT lang, sum(toxic)::BIGINT AS n_pos, sum(1 - toxic)::BIGINT AS n_neg FROM documents JOIN labels USING (doc_id) WHERE doc_id % 2 = 0 GROUP BY lang),
r AS (SELECT lang, word, pos, neg, ((pos + 0.5::DOUBLE) / (n_pos + 1.0::DOUBLE)) / ((neg + 0.5::DOUBLE) / (n_neg + 1.0::DOUBLE)) AS lift FROM p JOIN t USING (lang))
SELECT * FROM r WHERE lift >= 5.0""")
def q_nsfw_candidates(spark, d):
    return flags.build_word_list(_docs(spark, d), table(spark, d, "labels"))


CODE = "regexp_replace(" * 6 + "text"
for _p in clean.CODE_PATTERNS:
    CODE += ", '" + _p.replace("'", "''") + "', '', 'g')"
TERM = clean.TERMINAL.replace("'", "''")


def _lines(name: str, spark_column, sql_expr: str) -> None:
    def run(spark, d):
        return _docs(spark, d).select("doc_id", spark_column(F.col("text")).alias("out"))

    run.__name__ = name
    query(f"SELECT doc_id, {sql_expr} AS out FROM documents")(run)


def _keep(condition: str, x: str = "text") -> str:
    return f"array_to_string(list_filter(string_split({x}, chr(10)), lambda x: {condition}), chr(10))"


_TERMINATED = f"regexp_matches(x, '{TERM}')"
_LETTER = r"regexp_matches(x, '\p{L}')"
_LONG = f"len({WORDS.format(x='x')}) >= 5"


def _first_of(x: str) -> str:
    return f"(SELECT string_agg(l, chr(10) ORDER BY p) FROM (SELECT l, min(p) AS p FROM (SELECT unnest(string_split({x}, chr(10))) AS l, generate_subscripts(string_split({x}, chr(10)), 1) AS p) GROUP BY l))"


_lines("q_clean_terminal", clean.keep_terminated, _keep(_TERMINATED))
_lines("q_clean_symbol_chunks", clean.drop_symbol_chunks, _keep(_LETTER))
_lines("q_clean_repeated", clean.drop_repeated_chunks, _first_of("text"))
_lines("q_clean_short", clean.drop_short_chunks, _keep(_LONG))

_CODED = "CASE doc_id % 17 WHEN 0 THEN concat(split_part(text, chr(10), 1), chr(10), 'function go(a){return a;} var x = 1; p{margin:0} <b>x</b> &amp;', substr(text, length(split_part(text, chr(10), 1)) + 1)) ELSE text END"


def with_code(docs: DataFrame) -> DataFrame:
    """Fixture: a line of script and style after the first line of every 17th document."""
    first = F.substring_index("text", "\n", 1)
    coded = F.concat(first, F.lit("\nfunction go(a){return a;} var x = 1; p{margin:0} <b>x</b> &amp;"), F.substring(F.col("text"), F.length(first) + 1, F.length("text")))
    return docs.withColumn("text", F.when(F.col("doc_id") % 17 == 0, coded).otherwise(F.col("text")))


@query(f"WITH c AS (SELECT doc_id, {_CODED} AS text FROM documents) SELECT doc_id, {CODE} AS out FROM c")
def q_clean_code(spark, d):
    return with_code(_docs(spark, d)).select("doc_id", clean.remove_code_spans(F.col("text")).alias("out"))


@query(f"SELECT doc_id, {SYMBOLS.format(x='text')} AS ratio FROM documents WHERE {SYMBOLS.format(x='text')} > 0.08")
def q_clean_symbol_heavy(spark, d):
    return _docs(spark, d).select("doc_id", clean.symbol_ratio(F.col("text")).alias("ratio")).filter("ratio > 0.08")


CLEAN = f"""
split AS ({SPLIT}), coded AS (SELECT doc_id, lang, split, corpus, modality, text, {SYMBOLS.format(x='text')} AS sr, {CODE} AS nocode FROM split),
step AS (SELECT *, CASE WHEN sr > 0.08 THEN NULL WHEN modality = 'web' THEN {_keep(_LETTER, _keep(_TERMINATED, 'nocode'))}
  WHEN modality = 'pdf' THEN {_keep(_LONG, _first_of(_keep(_LETTER)))} ELSE {_keep(_LETTER)} END AS ct FROM coded),
cleaned AS (SELECT doc_id, lang, split, corpus, modality, text, nullif(ct, '') AS clean_text FROM step)"""


@query(f"WITH {CLEAN} SELECT doc_id, modality, clean_text FROM cleaned")
def q_clean_document(spark, d):
    docs = report.with_split(_docs(spark, d))
    return clean.clean(docs, F.col("modality")).select("doc_id", "modality", "clean_text")


_W = f"len({WORDS.format(x='text')})"


@query(f"SELECT coalesce(lang, 'all') AS lang, coalesce(split, 'all') AS split, sum({_W})::BIGINT AS tokens, count(*) AS docs FROM ({SPLIT}) GROUP BY CUBE (lang, split)")
def q_token_cube(spark, d):
    return report.token_cube(report.with_split(_docs(spark, d)), F.size(T.words(F.col("text"))))


@query(f"SELECT lang, coalesce(sum({_W}) FILTER (modality = 'web'), 0)::BIGINT AS web, coalesce(sum({_W}) FILTER (modality = 'pdf'), 0)::BIGINT AS pdf, coalesce(sum({_W}) FILTER (modality = 'speech'), 0)::BIGINT AS speech FROM ({SPLIT}) WHERE split = 'verified' GROUP BY lang")
def q_token_components(spark, d):
    """Verified tokens by modality."""
    docs = report.with_split(_docs(spark, d)).filter("split = 'verified'").withColumn("t", F.size(T.words(F.col("text"))))
    kinds = ["web", "pdf", "speech"]
    out = docs.groupBy("lang").pivot("modality", kinds).agg(F.sum("t"))
    return out.select("lang", *(F.coalesce(k, F.lit(0)).cast("long").alias(k) for k in kinds))


@query(f"""SELECT coalesce(a.lang, b.lang) AS lang, coalesce(a.t, 0)::BIGINT AS tokens_a, coalesce(b.t, 0)::BIGINT AS tokens_b, a.t / nullif(b.t, 0)::DOUBLE AS ratio
FROM (SELECT lang, sum({_W}) AS t FROM ({SPLIT}) WHERE split = 'verified' GROUP BY lang) a FULL JOIN (SELECT lang, sum({_W}) AS t FROM ({SPLIT}) WHERE corpus = 'A' GROUP BY lang) b ON a.lang = b.lang""")
def q_corpus_compare(spark, d):
    docs = report.with_split(_docs(spark, d)).withColumn("t", F.size(T.words(F.col("text"))))
    a = docs.filter("split = 'verified'").groupBy("lang").agg(F.sum("t").alias("ta"))
    b = docs.filter("corpus = 'A'").groupBy("lang").agg(F.sum("t").alias("tb"))
    return a.join(b, "lang", "full").select("lang", F.coalesce("ta", F.lit(0)).cast("long").alias("tokens_a"), F.coalesce("tb", F.lit(0)).cast("long").alias("tokens_b"), (F.col("ta") / F.nullif(F.col("tb"), F.lit(0))).alias("ratio"))


@query(f"SELECT lang, modality, avg({_W})::DOUBLE AS mean_words, count(*) AS docs FROM ({SPLIT}) GROUP BY ALL")
def q_doc_length(spark, d):
    return report.with_split(_docs(spark, d)).groupBy("lang", "modality").agg(F.avg(F.size(T.words(F.col("text")))).alias("mean_words"), F.count(F.lit(1)).alias("docs"))


@query(f"SELECT lang, sum(ceil(length(w) / 4.0))::BIGINT AS pieces, count(*) AS words, sum(ceil(length(w) / 4.0)) / count(*)::DOUBLE AS fertility FROM (SELECT lang, unnest({WORDS.format(x='text')}) AS w FROM documents) GROUP BY lang")
def q_fertility(spark, d):
    """Pieces per word with a fixed-width word-piece stand-in of four characters; no explode is needed."""
    w = T.words(F.col("text"))
    per = _docs(spark, d).select("lang", F.size(w).alias("n"), F.aggregate(w, F.lit(0).cast("long"), lambda a, x: a + F.ceil(F.length(x) / 4)).alias("p"))
    return per.groupBy("lang").agg(F.sum("p").cast("long").alias("pieces"), F.sum("n").cast("long").alias("words"), (F.sum("p") / F.sum("n")).alias("fertility"))


@query(f"""WITH {CLEAN}, r AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, string_split(coalesce(clean_text, ''), chr(10)) AS kept FROM cleaned WHERE modality <> 'web')
SELECT doc_id, count(DISTINCT line) AS removed FROM r WHERE NOT list_contains(kept, line) GROUP BY doc_id ORDER BY removed DESC, doc_id LIMIT 20""")
def q_removed_lines(spark, d):
    """Documents that lose most lines to cleaning (a top-k report)."""
    c = clean.clean(report.with_split(_docs(spark, d)), F.col("modality")).filter("modality <> 'web'")
    lost = F.array_except(F.split("text", "\n"), F.split(F.coalesce("clean_text", F.lit("")), "\n"))
    return c.select("doc_id", F.size(lost).cast("long").alias("removed")).filter("removed > 0").orderBy(F.col("removed").desc(), "doc_id").limit(20)


@query(f"""WITH b AS (SELECT lang, source, count(*) AS n FROM documents GROUP BY ALL), a AS (SELECT lang, source, count(*) AS m FROM documents WHERE {SYMBOLS.format(x='text')} <= 0.08 GROUP BY ALL)
SELECT lang, source, n / (sum(n) OVER ())::DOUBLE AS share_before, coalesce(m, 0) / (sum(m) OVER ())::DOUBLE AS share_after FROM b LEFT JOIN a USING (lang, source)""")
def q_mixture(spark, d):
    """Share of each source and language before and after a filter; totals are one-row aggregates, not a global window."""
    docs = _docs(spark, d).select("lang", "source", (clean.symbol_ratio(F.col("text")) <= 0.08).alias("kept"))
    per = docs.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.count_if("kept").alias("m"))
    total = docs.agg(F.count(F.lit(1)).alias("tn"), F.count_if("kept").alias("tm"))
    return per.crossJoin(F.broadcast(total)).select("lang", "source", (F.col("n") / F.col("tn")).alias("share_before"), (F.col("m") / F.col("tm")).alias("share_after"))
