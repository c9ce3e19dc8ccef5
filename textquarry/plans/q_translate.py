"""Queries: translation templates and romanization."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import templating as tp
from ..registry import query, table

_STRUCT = tp.STRUCTURE.format(line="?m:")
_CUT = r"string_split(regexp_replace(regexp_replace(replace(r, chr(2), ''), '^(\s+)|(\s+)$', chr(1) || '\1\2' || chr(1), 'g'), '([.!?…।])(\s+)', '\1' || chr(1) || '\2' || chr(1), 'g'), chr(1))"


def pieces_sql(text: str) -> str:
    """List of structs (is_slot, text) whose texts concatenate to the text."""
    marked = f"replace(regexp_replace({text}, '({_STRUCT})|({tp.TEXT})', '\\1' || chr(1) || '\\2' || chr(2), 'g'), chr(1) || chr(2), '')"
    runs = f"string_split(replace({marked}, chr(2), chr(2) || chr(1)), chr(1))"
    cut = f"list_transform({_CUT}, lambda s: {{'is_slot': regexp_matches(s, '\\p{{L}}'), 'text': s}})"
    return f"list_filter(flatten(list_transform({runs}, lambda r: CASE WHEN ends_with(r, chr(2)) THEN {cut} ELSE [{{'is_slot': false, 'text': r}}] END)), lambda s: s['text'] <> '')"


def translated_sql(text: str, lang: str) -> str:
    return f"array_to_string(list_transform({pieces_sql(text)}, lambda s: CASE WHEN s['is_slot'] THEN '{lang}:' || reverse(nfc_normalize(s['text'])) ELSE s['text'] END), '')"


# Marked up on the way, so that all protected forms occur: headings, bullets, numbers, Roman numerals, code, emphasis.
MARKED = "CASE doc_id % 5 WHEN 0 THEN '# ' || text || chr(10) || '- Run `import os. Then x` now. It works.' WHEN 1 THEN 'IV. ' || text || chr(10) || chr(9) || '2) *Bold* words | cell.' ELSE text END"
SEG = f"""dm AS (SELECT doc_id, lang, {MARKED} AS text FROM documents), sg AS (SELECT doc_id, {pieces_sql('text')} AS ps FROM dm),
sl AS (SELECT doc_id, ord, p['is_slot'] AS is_slot, CASE WHEN p['is_slot'] THEN nfc_normalize(p['text']) ELSE p['text'] END AS text FROM (SELECT doc_id, unnest(ps) AS p, generate_subscripts(ps, 1) - 1 AS ord FROM sg))"""


def _docs(spark, d):
    return table(spark, d, "documents")


def _marked(spark, d):
    """Documents with markdown: the fixture of the templates."""
    kind, text = F.col("doc_id") % 5, F.col("text")
    a = F.concat(F.lit("# "), text, F.lit("\n- Run `import os. Then x` now. It works."))
    b = F.concat(F.lit("IV. "), text, F.lit("\n\t2) *Bold* words | cell."))
    return _docs(spark, d).select("doc_id", "lang", F.when(kind == 0, a).when(kind == 1, b).otherwise(text).alias("text"))


@query(f"WITH {SEG} SELECT doc_id, count(*) AS n, count(*) FILTER (is_slot) AS slots, md5(string_agg(CASE WHEN is_slot THEN '#' ELSE text END, '' ORDER BY ord)) AS structure FROM sl GROUP BY doc_id")
def q_tpl_segments(spark, d):
    """Segments, slots and the structure with its slots blanked."""
    s = _marked(spark, d).select("doc_id", tp.segments(F.col("text")).alias("s")).filter(F.size("s") > 0)
    return s.select("doc_id", F.size("s").cast("long").alias("n"), F.size(F.filter("s", lambda x: x["is_slot"])).cast("long").alias("slots"), F.md5(F.array_join(F.transform("s", lambda x: F.when(x["is_slot"], "#").otherwise(x["text"])), "").cast("binary")).alias("structure"))


@query(f"WITH {SEG} SELECT text AS src, count(*) AS uses FROM sl WHERE is_slot GROUP BY text")
def q_tpl_sentences(spark, d):
    """The global dataset of distinct sentences."""
    return tp.sentence_dataset(_marked(spark, d))


@query(f"WITH {SEG} SELECT DISTINCT src, lang, lang || ':' || reverse(src) AS out FROM (SELECT text AS src, unnest(['fr', 'de', 'es']) AS lang FROM sl WHERE is_slot)")
def q_tpl_infer(spark, d):
    return tp.infer(tp.sentence_dataset(_marked(spark, d)), ("fr", "de", "es"))


def _reverser():
    """A stub model that works on lists of sentences."""
    return lambda sentences, lang: [f"{lang}:{s[::-1]}" for s in sentences]


@query(f"WITH {SEG} SELECT DISTINCT src, lang, lang || ':' || reverse(src) AS out FROM (SELECT text AS src, unnest(['fr', 'de']) AS lang FROM sl WHERE is_slot)")
def q_tpl_infer_batches(spark, d):
    """The same through a model that is loaded once per task."""
    return tp.infer_batches(tp.sentence_dataset(_marked(spark, d)), ("fr", "de"), _reverser)


@query(f"WITH {SEG} SELECT doc_id, {translated_sql('text', 'fr')} AS text FROM dm")
def q_tpl_roundtrip(spark, d):
    docs = _marked(spark, d)
    return tp.restore(docs, tp.infer(tp.sentence_dataset(docs), ("fr",)), "fr")


@query(f"""WITH {SEG}, pr AS (SELECT doc_id, list(text || chr(3) || 'fr:' || reverse(text) ORDER BY -length(text), text) AS ps FROM (SELECT DISTINCT doc_id, text FROM sl WHERE is_slot) GROUP BY doc_id)
SELECT dm.doc_id, CASE WHEN ps IS NULL THEN text ELSE list_reduce([text] || ps, lambda a, p: replace(a, split_part(p, chr(3), 1), split_part(p, chr(3), 2))) END AS text FROM dm LEFT JOIN pr USING (doc_id)""")
def q_tpl_replace(spark, d):
    """Variant: global replacement, longest sentences first."""
    docs = _marked(spark, d)
    return tp.restore_by_replace(docs, tp.infer(tp.sentence_dataset(docs), ("fr",)), "fr")


@query(f"WITH {SEG} SELECT count(*) AS total, count(DISTINCT text) AS distinct_slots, sum(length(text))::BIGINT AS chars, (SELECT sum(length(text))::BIGINT FROM (SELECT DISTINCT text FROM sl WHERE is_slot)) AS chars_sent FROM sl WHERE is_slot")
def q_tpl_savings(spark, d):
    """What deduplicating sentences saves."""
    return tp.sentence_dataset(_marked(spark, d)).agg(F.sum("uses").alias("total"), F.count(F.lit(1)).alias("distinct_slots"), F.sum(F.col("uses") * F.length("src")).alias("chars"), F.sum(F.length("src")).cast("long").alias("chars_sent"))


_NAIVE = r"list_filter(list_transform(string_split(regexp_replace(text, '([.!?…।])\s+', '\1' || chr(10), 'g'), chr(10)), lambda s: trim(s)), lambda s: s <> '')"


@query(f"WITH {SEG} SELECT count(*) AS docs, count(*) FILTER (array_to_string({_NAIVE}, ' ') = text) AS kept, (1 - count(*) FILTER (array_to_string({_NAIVE}, ' ') = text) / count(*)::DOUBLE) AS loss FROM dm")
def q_tpl_structure(spark, d):
    """Baseline: plain sentence splitting keeps the separators of few documents."""
    same = F.array_join(T.sentences(F.col("text")), " ") == F.col("text")
    return _marked(spark, d).agg(F.count(F.lit(1)).alias("docs"), F.count_if(same).alias("kept"), (1 - F.count_if(same) / F.count(F.lit(1))).alias("loss"))


@query(f"SELECT conv_id, turn, role, {translated_sql('text', 'es')} AS text FROM conversations")
def q_tpl_conversations(spark, d):
    """Each turn through the dataset of sentences: roles and order stay."""
    c = table(spark, d, "conversations")
    return c.select("conv_id", "turn", "role").join(tp.restore(c, tp.infer(tp.sentence_dataset(c), ("es",)), "es", ("conv_id", "turn")), ["conv_id", "turn"])


def letters_sql(x: str) -> str:
    """Letters outside ASCII in Roman form, in the case of the word."""
    return f"replace(translate({x}, '{tp.ROMAN_FROM}{tp.ROMAN_FROM.upper()}', '{tp.ROMAN_TO}{tp.ROMAN_TO.upper()}'), 'ß', 'ss')"


_TARGETS = "(VALUES ('fr'), ('de'), ('es')) l(target)"


@query(f"""SELECT doc_id, target AS lang, {translated_sql('text', 'xx')} AS text FROM documents, {_TARGETS} WHERE lang = 'en'
UNION ALL SELECT doc_id, target || '-latin', lower({letters_sql(translated_sql('text', 'xx'))}) FROM documents, {_TARGETS} WHERE lang = 'en'""".replace("'xx:'", "target || ':'"))
def q_synthetic_split(spark, d):
    """Source documents translated into each target, and the results romanized."""
    en = _docs(spark, d).filter("lang = 'en'")
    targets = ("fr", "de", "es")
    translations = tp.infer(tp.sentence_dataset(en), targets)
    native = None
    for target in targets:
        one = tp.restore(en, translations, target).withColumn("lang", F.lit(target))
        native = one if native is None else native.unionByName(one)
    # A document's key is its id and target; the map of words is made once for all targets.
    keyed = native.select(F.concat_ws(":", "doc_id", "lang").alias("doc_id"), "lang", "text")
    latin = tp.replace_words(keyed, tp.infer_words(tp.vocabulary(keyed)))
    parts = F.split("doc_id", ":")
    latin = latin.select(parts[0].cast("long").alias("doc_id"), F.concat(parts[1], F.lit("-latin")).alias("lang"), F.lower("text").alias("text"))
    return native.select("doc_id", "lang", "text").unionByName(latin)


_VOC = r"voc AS (SELECT DISTINCT lang, unnest(list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda w: regexp_matches(w, '[^\x00-\x7F]'))) AS word FROM documents WHERE lang <> 'en')"
_ROM = f"replace(translate(word, '{tp.ROMAN_FROM}', '{tp.ROMAN_TO}'), 'ß', 'ss')"
_H = "CAST('0x' || substr(md5(word), 1, 8) AS BIGINT) % 2"


def _words(spark, d):
    return tp.vocabulary(_docs(spark, d).filter("lang <> 'en'"))


def _known(spark, d):
    w = _words(spark, d)
    return w.filter(T.md5_int(F.col("word")) % 2 == 0).select("lang", "word", tp.romanize_letters(F.col("word")).alias("roman"))


@query(f"WITH {_VOC} SELECT lang, substr(word, 1, 2) AS prefix, word, {_ROM} AS roman FROM voc WHERE {_H} = 0")
def q_rom_map(spark, d):
    """Initial map in prefix levels."""
    return _known(spark, d).select("lang", F.substring("word", 1, 2).alias("prefix"), "word", "roman")


@query(f"WITH {_VOC} SELECT lang, word FROM voc WHERE {_H} = 1")
def q_rom_unmapped(spark, d):
    return _words(spark, d).join(_known(spark, d), ["lang", "word"], "left_anti")


@query(f"WITH {_VOC} SELECT lang, word, {_ROM} AS roman FROM voc WHERE {_H} = 1")
def q_rom_infer(spark, d):
    """Roman forms of the words without a mapping, by a pluggable model."""
    return tp.infer_words(_words(spark, d).join(_known(spark, d), ["lang", "word"], "left_anti"))


@query(f"WITH {_VOC} SELECT lang, word, {_ROM} AS roman, ({_H})::INTEGER AS generation FROM voc")
def q_romanize(spark, d):
    """The map at its fixpoint, with the round in which a word came."""
    return tp.grow_map(_words(spark, d), _known(spark, d))


@query(f"SELECT doc_id, lower({letters_sql('text')}) AS text FROM documents WHERE lang <> 'en'")
def q_rom_replace(spark, d):
    """Whole words replaced by the map, rebuilt by position; separators and all other words stay (in small letters here; the case is tested)."""
    out = tp.replace_words(_docs(spark, d).filter("lang <> 'en'"), tp.grow_map(_words(spark, d), _known(spark, d)))
    return out.select("doc_id", F.lower("text").alias("text"))


@query(rf"""WITH {_VOC}, held AS (SELECT DISTINCT doc_id, lang, unnest(list_filter(regexp_split_to_array(lower(text), '[^\p{{L}}]+'), lambda w: regexp_matches(w, '[^\x00-\x7F]'))) AS word FROM documents WHERE lang <> 'en'),
pr AS (SELECT doc_id, list(word || chr(3) || {_ROM} ORDER BY length(word), word) AS ps FROM held WHERE {_H} = 0 GROUP BY doc_id)
SELECT d.doc_id, CASE WHEN ps IS NULL THEN lower(text) ELSE list_reduce([lower(text)] || ps, lambda a, p: replace(a, split_part(p, chr(3), 1), split_part(p, chr(3), 2))) END AS text FROM documents d LEFT JOIN pr USING (doc_id) WHERE lang <> 'en'""")
def q_rom_unordered(spark, d):
    """Baseline: the initial map replaced as substrings without order, which corrupts words that hold others."""
    return tp.replace_unordered(_docs(spark, d).filter("lang <> 'en'"), _known(spark, d))
