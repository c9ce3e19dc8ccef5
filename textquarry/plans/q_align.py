"""Queries: alignment and safety data."""

from __future__ import annotations

from pyspark.sql import Column, Window
from pyspark.sql import functions as F

from .. import config
from ..config import NSFW_EN
from ..functions import text as T
from ..operators import align, lid
from ..operators import templating as tp
from ..registry import query, table
from .q_curation import FOLDED, words_sql
from .q_lm import WORD_PROFILES
from .q_translate import letters_sql, translated_sql

H = "CAST('0x' || substr(md5({x}), 1, 8) AS BIGINT)"


def _conv(spark, d):
    return table(spark, d, "conversations")


_FIRST = "fp AS (SELECT conv_id, arg_min(text, turn) AS prompt FROM conversations WHERE role = 'user' GROUP BY conv_id)"


@query(f"WITH {_FIRST} SELECT conv_id, prompt FROM fp")
def q_first_prompts(spark, d):
    return align.first_prompts(_conv(spark, d))


@query(f"WITH {_FIRST}, v AS (SELECT conv_id, prompt, l, len(list_filter({FOLDED.format(x='prompt')}, lambda w: list_contains(ws, w))) AS n FROM fp, ({WORD_PROFILES})), b AS (SELECT conv_id, any_value(prompt) AS prompt, arg_max(l, (n, l)) AS l, max(n) AS n FROM v GROUP BY conv_id) SELECT conv_id FROM b WHERE (n = 0 OR l = 'en') AND len({words_sql('prompt')}) BETWEEN 3 AND 60 AND NOT regexp_matches(prompt, '[0-9]{{4,}}|[{{}};=]')")
def q_prompts_kept(spark, d):
    """Prompts in English (or of no known language), without code, mathematics or odd lengths."""
    p = align.first_prompts(_conv(spark, d))
    said = lid.predict_words(p.select(F.col("conv_id").alias("doc_id"), F.col("prompt").alias("text"))).filter("conf = 0 or lang = 'en'").select(F.col("doc_id").alias("conv_id"))
    return p.join(said, "conv_id", "left_semi").filter(F.size(T.words(F.col("prompt"))).between(3, 60) & ~F.col("prompt").rlike(r"[0-9]{4,}|[{};=]")).select("conv_id")


@query(f"""WITH {_FIRST} SELECT conv_id, list_sort(list_filter([CASE WHEN len({words_sql('prompt')}) < 3 THEN 'short' END, CASE WHEN len({words_sql('prompt')}) > 60 THEN 'long' END, CASE WHEN NOT regexp_matches(prompt, '\\p{{L}}') THEN 'no_letters' END, CASE WHEN count(*) OVER (PARTITION BY prompt) > 1 THEN 'duplicate' END], lambda x: x IS NOT NULL))::VARCHAR AS flags FROM fp""")
def q_prompt_quality(spark, d):
    p = align.first_prompts(_conv(spark, d))
    n = p.groupBy(F.xxhash64("prompt").alias("h")).agg(F.count(F.lit(1)).alias("k"))
    j = p.withColumn("h", F.xxhash64("prompt")).join(n, "h").withColumn("w", F.size(T.words(F.col("prompt"))))
    flags = F.array_sort(F.array_compact(F.array(F.when(F.col("w") < 3, "short"), F.when(F.col("w") > 60, "long"), F.when(~F.col("prompt").rlike(r"\p{L}"), "no_letters"), F.when(F.col("k") > 1, "duplicate"))))
    return j.select("conv_id", F.concat(F.lit("["), F.array_join(flags, ", "), F.lit("]")).alias("flags"))


@query("SELECT conv_id, string_agg(substr(role, 1, 1), '' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id HAVING regexp_matches(string_agg(substr(role, 1, 1), '' ORDER BY turn), '^s?(ua)+u?$') AND min(length(text)) > 0")
def q_conv_valid(spark, d):
    return align.valid_conversations(_conv(spark, d))


_LEN = words_sql("text")


def _compare_sql(key: str, name: str) -> str:
    ratio = f"len(list_distinct({FOLDED.format(x='text')})) / greatest(len({FOLDED.format(x='text')}), 1)::DOUBLE"
    return f"SELECT {name}, count(*) AS examples, avg(turns)::DOUBLE AS mean_turns, avg(ins)::DOUBLE AS instruction_len, avg(outs)::DOUBLE AS output_len, avg(r)::DOUBLE AS diversity FROM (SELECT {key} AS {name}, conv_id, count(*) FILTER (role = 'user') AS turns, avg(len({_LEN})) FILTER (role = 'user') AS ins, avg(len({_LEN})) FILTER (role = 'assistant') AS outs, avg({ratio}) FILTER (role = 'user') AS r FROM conversations GROUP BY ALL) GROUP BY {name}"


@query(_compare_sql("conv_id % 2", "model"))
def q_conv_compare(spark, d):
    """Two generators: examples, turns, instruction and output length in words, lexical diversity."""
    return align.compare(_conv(spark, d), F.col("conv_id") % 2, "model")


_COMPONENT = "CASE conv_id % 4 WHEN 0 THEN 'shared prompts' WHEN 1 THEN 'translated' WHEN 2 THEN 'crowd' ELSE 'generated' END"


def _component() -> Column:
    k = F.col("conv_id") % 4
    return F.when(k == 0, "shared prompts").when(k == 1, "translated").when(k == 2, "crowd").otherwise("generated")


@query(f"SELECT r.*, CASE component WHEN 'crowd' THEN 'H' ELSE 'M' END AS made_by, CASE component WHEN 'translated' THEN 'T' ELSE 'O' END AS origin, CASE component WHEN 'translated' THEN 7 WHEN 'crowd' THEN 4 ELSE 1 END AS languages FROM ({_compare_sql(_COMPONENT, 'component')}) r")
def q_alignment_report(spark, d):
    """A row per component: sizes, lengths, diversity, made by people or models, original or translated, languages."""
    r, c = align.compare(_conv(spark, d), _component(), "component"), F.col("component")
    return r.withColumns({"made_by": F.when(c == "crowd", "H").otherwise("M"), "origin": F.when(c == "translated", "T").otherwise("O"), "languages": F.when(c == "translated", 7).when(c == "crowd", 4).otherwise(1)})


@query()
def q_alignment_mtld(spark, d):
    """Lexical diversity of the instructions per component (worked values are tested)."""
    u = _conv(spark, d).filter("role = 'user'").select(_component().alias("component"), F.pandas_udf(align.mtld, "double")("text").alias("m"))
    return u.groupBy("component").agg(F.avg("m").alias("mtld"))


@query(f"SELECT role, count(*) AS turns, avg(len({_LEN}))::DOUBLE AS mean_words, max(len({_LEN}))::BIGINT AS max_words FROM conversations GROUP BY role")
def q_conv_stats(spark, d):
    w = F.size(T.words(F.col("text")))
    return _conv(spark, d).groupBy("role").agg(F.count(F.lit(1)).alias("turns"), F.avg(w).alias("mean_words"), F.max(w).cast("long").alias("max_words"))


@query("SELECT n AS turns, count(*) AS conversations FROM (SELECT conv_id, count(*) AS n FROM conversations GROUP BY 1) GROUP BY 1")
def q_turn_hist(spark, d):
    return _conv(spark, d).groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns")).groupBy("turns").agg(F.count(F.lit(1)).alias("conversations"))


@query(f"SELECT conv_id, turn, len(list_distinct({FOLDED.format(x='text')})) / greatest(len({FOLDED.format(x='text')}), 1)::DOUBLE AS ttr FROM conversations")
def q_ttr(spark, d):
    """Type-token ratio, the length-biased baseline."""
    return _conv(spark, d).select("conv_id", "turn", T.folded_words(F.col("text")).alias("f")).select("conv_id", "turn", (F.size(F.array_distinct("f")) / F.greatest(F.size("f"), F.lit(1))).alias("ttr"))


@query()
def q_mtld(spark, d):
    """Lexical diversity per utterance: mean of both directions."""
    return _conv(spark, d).select("conv_id", "turn", F.pandas_udf(align.mtld, "double")("text").alias("mtld"))


_RED = "text"
for _name, _pattern in align.PERSONAL.items():
    _RED = f"regexp_replace({_RED}, '{_pattern}', '<{_name}>', 'g')"


@query(f"SELECT doc_id, md5({_RED}) AS h FROM documents WHERE {_RED} <> text")
def q_pii_redact(spark, d):
    return table(spark, d, "documents").withColumn("r", align.redact(F.col("text"))).filter("r <> text").select("doc_id", F.md5(F.col("r").cast("binary")).alias("h"))


@query("SELECT " + ", ".join(f"sum(len(regexp_extract_all(text, '{p}')))::BIGINT AS {n.lower()}" for n, p in align.PERSONAL.items()) + ", lang FROM documents GROUP BY lang")
def q_pii_counts(spark, d):
    """Findings of each kind per language."""
    found = align.find_personal(F.col("text"))
    return table(spark, d, "documents").groupBy("lang").agg(*(F.sum(c).cast("long").alias(n.lower()) for n, c in found.items()))


@query(f"SELECT doc_id, CAST(i AS INTEGER) AS part, array_to_string(w[i * 1000 + 1:i * 1000 + 1000], ' ') AS passage FROM (SELECT doc_id, w, unnest(range(0, (len(w) + 999) // 1000)) AS i FROM (SELECT doc_id, {_LEN} AS w FROM documents))")
def q_passages(spark, d):
    """Context passages of a fixed number of words."""
    size = config.PASSAGE_WORDS
    w = table(spark, d, "documents").select("doc_id", T.words(F.col("text")).alias("w")).filter(F.size("w") > 0)
    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size("w") - 1) / size).cast("int")), lambda i: F.array_join(F.slice("w", i * size + 1, F.lit(size)), " "))
    return w.select("doc_id", F.posexplode(parts).alias("part", "passage"))


@query("SELECT p_partkey, 'name: ' || p_name || chr(10) || 'brand: ' || p_brand || chr(10) || 'type: ' || p_type || chr(10) || 'size: ' || p_size AS context FROM part")
def q_infobox(spark, d):
    """Key and value lines of an info-box as context."""
    return table(spark, d, "part").select("p_partkey", F.concat_ws("\n", *(F.concat(F.lit(f"{k}: "), F.col(f"p_{k}").cast("string")) for k in ("name", "brand", "type", "size"))).alias("context"))


def _expand(texts, keys: tuple[str, ...], targets: tuple[str, ...] = ("fr", "de", "es")):
    """keys, lang, text: each text in each target, native and romanized (in small letters), through the dataset of distinct sentences."""
    translations = tp.infer(tp.sentence_dataset(texts), targets)
    native = None
    for target in targets:
        one = tp.restore(texts, translations, target, keys).withColumn("lang", F.lit(target))
        native = one if native is None else native.unionByName(one)
    keyed = native.select(F.struct(*keys, "lang").alias("doc_id"), "lang", "text")
    latin = tp.replace_words(keyed, tp.infer_words(tp.vocabulary(keyed)))
    latin = latin.select(*(F.col(f"doc_id.{k}").alias(k) for k in keys), F.lower("text").alias("text"), F.concat("doc_id.lang", F.lit("-latin")).alias("lang"))
    return native.unionByName(latin)


_EXPANDED = f"SELECT {{keys}}, target AS lang, {translated_sql('text', 'xx')} AS text FROM {{source}}, (VALUES ('fr'), ('de'), ('es')) l(target) UNION ALL SELECT {{keys}}, target || '-latin', lower({letters_sql(translated_sql('text', 'xx'))}) FROM {{source}}, (VALUES ('fr'), ('de'), ('es')) l(target)".replace("'xx:'", "target || ':'")


def expanded_sql(keys: str, source: str) -> str:
    return _EXPANDED.replace("{keys}", keys).replace("{source}", source)


@query(expanded_sql("conv_id, turn", "(SELECT * FROM conversations WHERE role <> 'system')"))
def q_lang_expansion(spark, d):
    """Turns in three further languages, native and romanized."""
    return _expand(_conv(spark, d).filter("role <> 'system'").select("conv_id", "turn", "text"), ("conv_id", "turn"))


@query("SELECT doc_id, split_part(text, chr(10), 1) AS question, array_to_string(string_split(text, chr(10))[2:3], chr(10)) AS lead, array_to_string(string_split(text, chr(10))[4:], chr(10)) AS rest FROM documents WHERE len(string_split(text, chr(10))) >= 4")
def q_completion_pairs(spark, d):
    """How-to completion: first line as question, the next two given, the rest as answer."""
    lines = F.split("text", "\n")
    return table(spark, d, "documents").withColumn("l", lines).filter(F.size("l") >= 4).select("doc_id", F.element_at("l", 1).alias("question"), F.array_join(F.slice("l", 2, 2), "\n").alias("lead"), F.array_join(F.slice("l", F.lit(4), F.size("l")), "\n").alias("rest"))


_TOX = f"len(list_filter({FOLDED.format(x='text')}, lambda w: w IN {NSFW_EN}))"


@query(f"SELECT doc_id, 'matched: ' || array_to_string(list_sort(list_distinct(list_filter({FOLDED.format(x='text')}, lambda w: w IN {NSFW_EN}))), ', ') AS rationale FROM documents WHERE {_TOX} > 0")
def q_toxic_judge(spark, d):
    """Judge stand-in with a rationale."""
    hits = F.filter(T.folded_words(F.col("text")), lambda w: w.isin(*NSFW_EN))
    return table(spark, d, "documents").select("doc_id", hits.alias("h")).filter(F.size("h") > 0).select("doc_id", F.concat(F.lit("matched: "), F.array_join(F.array_sort(F.array_distinct("h")), ", ")).alias("rationale"))


@query(f"SELECT count(*) FILTER (p AND toxic = 1) AS tp, count(*) FILTER (p AND toxic = 0) AS fp, count(*) FILTER (NOT p AND toxic = 1) AS fn FROM (SELECT {_TOX} > 0 AS p, toxic FROM documents JOIN labels USING (doc_id))")
def q_toxic_quality(spark, d):
    p = F.size(F.filter(T.folded_words(F.col("text")), lambda w: w.isin(*NSFW_EN))) > 0
    j = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select(p.alias("p"), "toxic")
    return j.agg(F.count_if(F.col("p") & (F.col("toxic") == 1)).alias("tp"), F.count_if(F.col("p") & (F.col("toxic") == 0)).alias("fp"), F.count_if(~F.col("p") & (F.col("toxic") == 1)).alias("fn"))


_AXES = f"ax AS (SELECT content || '|' || grp || '|' || style AS combo FROM (SELECT DISTINCT p_type AS content FROM part), (SELECT n_name AS grp FROM nation), (SELECT DISTINCT o_orderpriority AS style FROM orders)), pick AS (SELECT combo FROM ax ORDER BY {H.format(x='combo')}, combo LIMIT 100000)"


def _combos(spark, d):
    c = table(spark, d, "part").select("p_type").distinct().crossJoin(F.broadcast(table(spark, d, "nation").select("n_name"))).crossJoin(F.broadcast(table(spark, d, "orders").select("o_orderpriority").distinct()))
    return c.select(F.concat_ws("|", "p_type", "n_name", "o_orderpriority").alias("combo")).orderBy(T.md5_int(F.col("combo")), "combo").limit(config.COMBINATIONS)


@query(f"WITH {_AXES} SELECT combo FROM pick")
def q_axes_combos(spark, d):
    """Random combinations of three small axes (a sampling operator)."""
    return _combos(spark, d)


@query(f"WITH {_AXES} SELECT combo, CAST(k AS INTEGER) AS k, combo || '#' || k AS prompt FROM pick, range(1, 6) r(k)")
def q_axes_prompts(spark, d):
    """Five prompts per combination, by a stub."""
    return _combos(spark, d).select("combo", F.explode(F.sequence(F.lit(1), F.lit(5))).alias("k")).withColumn("prompt", F.concat_ws("#", "combo", F.col("k").cast("string")))


@query(f"WITH {_AXES}, q AS (SELECT combo, combo || '#' || k AS prompt FROM pick, range(1, 6) r(k)) SELECT combo, arg_min(prompt, ({H.format(x='prompt')}, prompt)) AS prompt FROM q GROUP BY combo")
def q_axes_sample(spark, d):
    p = _combos(spark, d).select("combo", F.explode(F.sequence(F.lit(1), F.lit(5))).alias("k")).withColumn("prompt", F.concat_ws("#", "combo", F.col("k").cast("string")))
    return p.groupBy("combo").agg(F.min_by("prompt", F.struct(T.md5_int(F.col("prompt")), "prompt")).alias("prompt"))


# Openers, second-hand prompts and repeats put in by hash: the fixture of the cleaning.
_NOISY = f"(SELECT conv_id, turn, role, CASE WHEN role = 'user' AND {H.format(x='conv_id || chr(58) || turn')} % 6 = 0 THEN 'Sure, ' || text WHEN role = 'user' AND {H.format(x='conv_id || chr(58) || turn')} % 8 = 1 THEN 'Ask the assistant to ' || text ELSE text END AS text FROM conversations)"


@query(f"""SELECT conv_id, min(turn) AS turn, text FROM (SELECT conv_id, turn, regexp_replace(text, '{align.OPENER}', '') AS text FROM {_NOISY} WHERE role = 'user') WHERE NOT regexp_matches(text, '{align.SECOND_HAND}') AND trim(text) <> '' GROUP BY conv_id, text""")
def q_conv_clean(spark, d):
    """Assistant-like openers cut, second-hand prompts and repeats dropped; good prompts stay as they are."""
    h, user = T.md5_int(F.concat_ws(":", "conv_id", "turn")), F.col("role") == "user"
    noisy = F.when(user & (h % 6 == 0), F.concat(F.lit("Sure, "), "text")).when(user & (h % 8 == 1), F.concat(F.lit("Ask the assistant to "), "text")).otherwise(F.col("text"))
    return align.clean_generated(_conv(spark, d).withColumn("text", noisy))


@query(f"WITH {_FIRST}, t AS (SELECT split_part(lower(prompt), ' ', 1) AS verb, split_part(lower(prompt), ' ', 2) AS noun FROM (SELECT * FROM fp ORDER BY {H.format(x='CAST(conv_id AS VARCHAR)')}, conv_id LIMIT 20000)), g AS (SELECT verb, noun, count(*) AS n FROM t GROUP BY verb, noun), v AS (SELECT *, sum(n) OVER (PARTITION BY verb) AS total FROM g), r AS (SELECT *, row_number() OVER (PARTITION BY verb ORDER BY n DESC, noun) AS rn FROM v), k AS (SELECT verb FROM (SELECT DISTINCT verb, total FROM v) ORDER BY total DESC, verb LIMIT 20) SELECT verb, noun, n FROM r WHERE rn <= 4 AND verb IN (SELECT verb FROM k)")
def q_verb_noun(spark, d):
    """Twenty top verbs with four nouns each on 20,000 random prompts, by a stub tagger (first and second word)."""
    p = F.split(F.lower("prompt"), " ")
    v = align.first_prompts(_conv(spark, d)).orderBy(T.md5_int(F.col("conv_id")), "conv_id").limit(config.VERB_PROMPTS).select(F.get(p, F.lit(0)).alias("verb"), F.coalesce(F.get(p, F.lit(1)), F.lit("")).alias("noun")).groupBy("verb", "noun").agg(F.count(F.lit(1)).alias("n"))
    top = v.groupBy("verb").agg(F.sum("n").alias("t")).orderBy(F.col("t").desc(), "verb").limit(20).select("verb")
    w = Window.partitionBy("verb").orderBy(F.col("n").desc(), "noun")
    return v.withColumn("r", F.row_number().over(w)).filter("r <= 4").join(F.broadcast(top), "verb", "left_semi").select("verb", "noun", "n")


@query(f"WITH {_FIRST} SELECT intent, count(*) AS n, count(*) / (sum(count(*)) OVER ())::DOUBLE AS share FROM (SELECT CASE WHEN prompt LIKE '%?%' THEN 'question' WHEN length(prompt) < 80 THEN 'short request' WHEN prompt LIKE '%' || chr(10) || '%' THEN 'with context' ELSE 'request' END AS intent FROM fp) GROUP BY intent")
def q_intents(spark, d):
    """Share of intents by keyword rules."""
    p = F.col("prompt")
    i = align.first_prompts(_conv(spark, d)).select(F.when(p.contains("?"), "question").when(F.length(p) < 80, "short request").when(p.contains("\n"), "with context").otherwise("request").alias("intent"))
    n = i.groupBy("intent").agg(F.count(F.lit(1)).alias("n"))
    return n.crossJoin(F.broadcast(i.agg(F.count(F.lit(1)).alias("t")))).select("intent", "n", (F.col("n") / F.col("t")).alias("share"))


@query("""WITH RECURSIVE n AS (SELECT conv_id % 20 AS tree_id, conv_id || ':' || turn AS node_id, CASE WHEN turn = 0 THEN 'root' ELSE conv_id || ':' || (turn - 1) END AS parent_id FROM conversations),
 a AS (SELECT tree_id, node_id, parent_id FROM n UNION SELECT DISTINCT tree_id, 'root', NULL FROM n),
 p(tree_id, node_id, path) AS (SELECT tree_id, node_id, node_id FROM a WHERE parent_id IS NULL UNION ALL SELECT a.tree_id, a.node_id, p.path || '/' || a.node_id FROM p JOIN a ON a.tree_id = p.tree_id AND a.parent_id = p.node_id)
SELECT tree_id, node_id AS leaf, path FROM p WHERE NOT EXISTS (SELECT 1 FROM a WHERE a.tree_id = p.tree_id AND a.parent_id = p.node_id)""")
def q_tree_paths(spark, d):
    """Root-to-leaf paths of conversation trees: conversations with one root per twenty, a turn under the turn before it."""
    c, turn = _conv(spark, d), F.col("turn").cast("long")
    at = lambda t: F.concat_ws(":", "conv_id", t)
    nodes = c.select((F.col("conv_id") % 20).alias("tree_id"), at(turn).alias("node_id"), F.when(turn == 0, "root").otherwise(at(turn - 1)).alias("parent_id"))
    roots = nodes.select("tree_id", F.lit("root").alias("node_id"), F.lit(None).cast("string").alias("parent_id")).distinct()
    return align.tree_paths(nodes.unionByName(roots)).select("tree_id", "leaf", F.array_join("path", "/").alias("path"))


_LEX = f"""lex AS (SELECT lang, word, count(*) AS n, arg_min(line, doc_id) AS gloss, CASE WHEN count(DISTINCT line) > 1 THEN arg_max(line, doc_id) END AS example, ['noun', 'verb', 'adjective', 'adverb'][({H.format(x='word')} % 4 + 1)::INTEGER] AS pos
 FROM (SELECT doc_id, lang, split_part(text, chr(10), 1) AS line, unnest(list_distinct({FOLDED.format(x='text')})) AS word FROM documents) GROUP BY lang, word HAVING count(*) >= 50),
syn AS (SELECT lang, substr(word, 1, 3) AS synset, list(word ORDER BY word) AS ws FROM lex GROUP BY ALL),
full_lex AS (SELECT lex.*, nullif(array_to_string(list_filter(ws, lambda w: w <> word), ', '), '') AS synonyms FROM lex JOIN syn ON syn.lang = lex.lang AND syn.synset = substr(word, 1, 3))"""
_FIELD = "['gloss: ' || gloss, 'synonyms: ' || synonyms, 'example: ' || example, 'class: ' || pos, 'language: ' || lang][t % 5 + 1]"


def _lexicon(spark, d):
    """Words of fifty documents or more with a gloss, an example, a class and the words that share their beginning."""
    line = F.substring_index("text", "\n", 1)
    words = table(spark, d, "documents").select("doc_id", "lang", line.alias("line"), F.explode(F.array_distinct(T.folded_words(F.col("text")))).alias("word"))
    found = words.groupBy("lang", "word").agg(F.count(F.lit(1)).alias("n"), F.min_by("line", "doc_id").alias("gloss"), F.when(F.min("line") < F.max("line"), F.max_by("line", "doc_id")).alias("example")).filter("n >= 50")
    found = found.withColumn("pos", F.element_at(F.array(*map(F.lit, ("noun", "verb", "adjective", "adverb"))), (T.md5_int(F.col("word")) % 4 + 1).cast("int")))
    synset = found.groupBy("lang", F.substring("word", 1, 3).alias("synset")).agg(F.array_sort(F.collect_list("word")).alias("ws"))
    joined = found.withColumn("synset", F.substring("word", 1, 3)).join(synset, ["lang", "synset"])
    others = F.array_join(F.filter("ws", lambda w: w != F.col("word")), ", ")
    return joined.withColumn("synonyms", F.nullif(others, F.lit("")))


def _pairs(spark, d):
    """Templates 21 x 5 (intent and form), filled from the word's fields; those whose field is missing are skipped, and of the rest the least hashes are taken."""
    field = lambda t: F.get(F.array(F.concat(F.lit("gloss: "), "gloss"), F.concat(F.lit("synonyms: "), "synonyms"), F.concat(F.lit("example: "), "example"), F.concat(F.lit("class: "), "pos"), F.concat(F.lit("language: "), "lang")), t % 5)
    ids = F.filter(F.sequence(F.lit(0), F.lit(104)), lambda t: field(t).isNotNull())
    ranked = F.slice(F.array_sort(F.transform(ids, lambda t: F.struct(T.md5_int(F.concat("word", t.cast("string"))).alias("h"), t.alias("t")))), 1, config.TEMPLATES_PER_WORD)
    picked = _lexicon(spark, d).withColumn("t", F.explode(F.transform(ranked, lambda x: x["t"])))
    prompt = F.concat(F.lit("Intent "), F.floor(F.col("t") / 5).cast("string"), F.lit(", form "), (F.col("t") % 5).cast("string"), F.lit(": "), "word")
    return picked.select("lang", "word", F.col("t").alias("template_id"), prompt.alias("prompt"), field(F.col("t")).alias("response"))


_PAIRS = f"""{_LEX}, filled AS (SELECT lang, word, t AS template_id, 'Intent ' || (t // 5) || ', form ' || (t % 5) || ': ' || word AS prompt, {_FIELD} AS response FROM full_lex, range(0, 105) r(t)),
prs AS (SELECT * FROM filled WHERE response IS NOT NULL QUALIFY row_number() OVER (PARTITION BY lang, word ORDER BY {H.format(x='word || template_id')}, template_id) <= {config.TEMPLATES_PER_WORD})"""


@query(f"WITH {_PAIRS} SELECT lang, word, template_id::INTEGER AS template_id, prompt, response FROM prs")
def q_lexicon_pairs(spark, d):
    """100 of the 105 templates per word, chosen by hash inside the row: no shuffle of the product."""
    return _pairs(spark, d)


@query(f"WITH {_PAIRS} SELECT lang, count(DISTINCT word) AS words, count(*) AS pairs FROM prs GROUP BY lang")
def q_lexicon_counts(spark, d):
    return _pairs(spark, d).groupBy("lang").agg(F.count_distinct("word").alias("words"), F.count(F.lit(1)).alias("pairs"))


@query("SELECT conv_id, CAST(k - 1 AS INTEGER) AS turn, split_part(l, ': ', 1) AS role, substr(l, instr(l, ': ') + 2) AS text FROM (SELECT conv_id, unnest(list_transform(a, x -> x)) AS l, generate_subscripts(a, 1) AS k FROM (SELECT conv_id, list(role || ': ' || replace(text, chr(10), ' ') ORDER BY turn) AS a FROM conversations GROUP BY conv_id))".replace("list_transform(a, x -> x)", "a"))
def q_parse_dialogue(spark, d):
    """A generated dialogue in one text, with a role mark per line, back to turns."""
    c = _conv(spark, d).groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", F.concat("role", F.lit(": "), F.replace("text", F.lit("\n"), F.lit(" "))).alias("l")))).alias("a"))
    whole = c.select("conv_id", F.array_join(F.transform("a", lambda x: x["l"]), "\n").alias("dialogue"))
    lines = whole.select("conv_id", F.posexplode(F.split("dialogue", "\n")).alias("turn", "l"))
    return lines.select("conv_id", "turn", F.substring_index("l", ": ", 1).alias("role"), F.expr("substring(l, instr(l, ': ') + 2)").alias("text"))


@query("SELECT split, lang, count(*) AS docs FROM (SELECT 'src' AS split, lang FROM documents WHERE lang = 'en' UNION ALL SELECT 'synthetic', l FROM documents, (VALUES ('fr'), ('de'), ('es'), ('fr-latin'), ('de-latin'), ('es-latin')) t(l) WHERE lang = 'en') GROUP BY ALL")
def q_synthetic_counts(spark, d):
    """Documents of the synthetic split: each source document in every target, native and romanized."""
    en = table(spark, d, "documents").filter("lang = 'en'")
    out = en.select(F.lit("synthetic").alias("split"), F.explode(F.array(*(F.lit(x) for x in ("fr", "de", "es", "fr-latin", "de-latin", "es-latin")))).alias("lang"))
    return out.unionByName(en.select(F.lit("src").alias("split"), "lang")).groupBy("split", "lang").agg(F.count(F.lit(1)).alias("docs"))


_AXES = {"intent": ("explain", "list", "compare", "write"), "topic": ("farming", "law", "health", "sport", "art"), "form": ("english", "native", "romanized", "mixed")}
_DRAWN = " || '/' || ".join(f"{list(v)!r}[1 + {H.format(x=f'conv_id || {chr(39)}/{k}{chr(39)}')} % {len(v)}]" for k, v in _AXES.items())


@query(f"SELECT conv_id, {_DRAWN} AS axes, {H.format(x='conv_id || ' + repr('/free'))} % 10 = 0 AS unrestricted FROM (SELECT DISTINCT conv_id FROM conversations)")
def q_crowd_axes(spark, d):
    """An instruction for the writers of each conversation: intent, topic and language form drawn by hash, a tenth of them unrestricted."""
    drawn = lambda salt: T.md5_int(F.concat(F.col("conv_id").cast("string"), F.lit(f"/{salt}")))
    axes = [F.element_at(F.array(*map(F.lit, v)), (1 + drawn(k) % len(v)).cast("int")) for k, v in _AXES.items()]
    return table(spark, d, "conversations").select("conv_id").distinct().select("conv_id", F.concat_ws("/", *axes).alias("axes"), (drawn("free") % 10 == 0).alias("unrestricted"))


@query(f"WITH {_FIRST} SELECT conv_id, 'xx:' || reverse('Answer to: en:' || reverse(prompt)) AS answer FROM fp")
def q_translate_test(spark, d):
    """Translate the prompt, answer in English, translate back, by stubs."""
    english = tp.stub_translator(F.col("prompt"), F.lit("en"))
    return align.first_prompts(_conv(spark, d)).select("conv_id", tp.stub_translator(F.concat(F.lit("Answer to: "), english), F.lit("xx")).alias("answer"))


@query(f"""WITH c AS (SELECT doc_id AS conv_id, split_part(text, chr(10), 1) AS context, {H.format(x='CAST(doc_id AS VARCHAR)')} % 5 + 1 AS turns FROM documents),
t AS (SELECT conv_id, context, unnest(range(0, turns * 2)) AS turn FROM c)
SELECT conv_id, turn::INTEGER AS turn, CASE turn % 2 WHEN 0 THEN 'user' ELSE 'assistant' END AS role, CASE turn % 2 WHEN 0 THEN 'about ' || length(context) || ', after ' || turn || ' turns' ELSE 'answer ' || turn || ' on ' || substr(context, 1, 10) END AS text FROM t""")
def q_agent_loop(spark, d):
    """Intent, user and assistant agents in turns over contexts, by stub agents."""
    contexts = table(spark, d, "documents").select(F.col("doc_id").alias("conv_id"), F.substring_index("text", "\n", 1).alias("context"))
    intent = lambda context: F.concat(F.lit("about "), F.length(context).cast("string"))
    user = lambda context, intent, history: F.concat(intent, F.lit(", after "), F.size(history).cast("string"), F.lit(" turns"))
    assistant = lambda context, history: F.concat(F.lit("answer "), F.size(history).cast("string"), F.lit(" on "), F.substring(context, 1, 10))
    return align.simulate(contexts, intent, user, assistant)


_JUDGED = f"judged AS (SELECT doc_id, split_part(text, chr(10), 1) AS prompt, 'matched: ' || array_to_string(list_sort(list_distinct(list_filter({FOLDED.format(x='text')}, lambda w: w IN {NSFW_EN}))), ', ') AS rationale FROM documents WHERE {_TOX} > 0)"


def _judged(spark, d):
    prompts = table(spark, d, "documents").select("doc_id", F.substring_index("text", "\n", 1).alias("prompt"))
    return prompts.join(q_toxic_judge(spark, d), "doc_id")


@query(f"WITH {_JUDGED} SELECT doc_id, prompt, 'I cannot help with this. ' || rationale AS answer FROM judged")
def q_safety_pairs(spark, d):
    """A toxic prompt and the judge's rationale as its answer."""
    return _judged(spark, d).select("doc_id", "prompt", F.concat(F.lit("I cannot help with this. "), "rationale").alias("answer"))


@query(expanded_sql("doc_id", f"(WITH {_JUDGED} SELECT doc_id, prompt || chr(10) || 'I cannot help with this. ' || rationale AS text FROM judged)"))
def q_safety_languages(spark, d):
    """Safety pairs in three further languages, native and romanized."""
    pairs = q_safety_pairs(spark, d).select("doc_id", F.concat_ws("\n", "prompt", "answer").alias("text"))
    return _expand(pairs, ("doc_id",))


@query(f"WITH {_AXES}, q AS (SELECT combo, combo || '#' || k AS prompt FROM pick, range(1, 6) r(k)), one AS (SELECT combo, arg_min(prompt, ({H.format(x='prompt')}, prompt)) AS prompt FROM q GROUP BY combo), a AS (SELECT combo, prompt, CASE WHEN {H.format(x='prompt')} % 4 = 0 THEN 'Here is an answer to ' || prompt ELSE 'I cannot answer this, because it is about ' || combo END AS answer FROM one) SELECT *, regexp_matches(answer, '{align.REFUSAL.replace(chr(39), chr(39) * 2)}') AS refused FROM a")
def q_axes_answers(spark, d):
    """Answers of a strongly aligned stub: refusals with a rationale, and their detection."""
    p = q_axes_sample(spark, d)
    answer = F.when(T.md5_int(F.col("prompt")) % 4 == 0, F.concat(F.lit("Here is an answer to "), "prompt")).otherwise(F.concat(F.lit("I cannot answer this, because it is about "), "combo"))
    return p.withColumn("answer", answer).withColumn("refused", F.col("answer").rlike(align.REFUSAL))
