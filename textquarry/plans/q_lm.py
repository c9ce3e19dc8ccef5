"""Queries: perplexity filtering and language identification."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import config
from ..functions import text as T
from ..operators import lid, lm, lm_buckets, report
from ..registry import query, table
from .q_curation import FOLDED, SENTENCES, SPLIT

H = "CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT)"
_NORM = "text"
_NORM = f"regexp_replace(translate(lower({_NORM}), '{lm.ACCENTED}', '{lm.PLAIN}'), '\\p{{Nd}}', '0', 'g')"
for _a, _b in lm.MARKS:
    _NORM = "replace({}, '{}', '{}')".format(_NORM, _a, _b.replace("'", "''"))
_NORM = f"regexp_replace({_NORM}, '[\\x00-\\x08\\x0B\\x0C\\x0E-\\x1F\\x7F​‌‍﻿]', '', 'g')"
PART = f"CASE WHEN {H} % 100 < 60 THEN 'train' ELSE 'valid' END"


def sequences_sql(name: str, source: str, text: str = "text") -> str:
    """Sentences of *source* as word lists with marks."""
    norm = _NORM.replace("lower(text)", f"lower({text})")
    return f"""{name}_t AS (SELECT doc_id, lang, unnest({SENTENCES.format(x='t')}) AS snt FROM (SELECT doc_id, lang, {norm} AS t FROM {source})),
{name} AS (SELECT doc_id, lang, ['<s>'] || {FOLDED.format(x='snt')} || ['</s>'] AS s FROM {name}_t)"""


def model_sql(order: int, modified: bool = True) -> str:
    """Tables c1.. (counts), p1.. (probabilities) and b1.. (back-off weights) from `train`. An n-gram's key begins with its language, so that joins have one key."""
    out = [f"c{order} AS MATERIALIZED (SELECT lang, g, count(*) AS c FROM (SELECT lang, unnest(list_transform(range({order}, len(s) + 1), lambda j: lang || ' ' || array_to_string(s[j - {order - 1}:j], ' '))) AS g FROM train WHERE len(s) >= {order}) GROUP BY ALL)"]
    rest = "regexp_replace(g, '^([^ ]+) [^ ]+ ', '\\1 ')"
    for k in range(order - 1, 0, -1):
        starts = f" UNION ALL SELECT lang, lang || ' ' || array_to_string(s[1:{k}], ' ') AS g, count(*) AS c FROM train WHERE len(s) >= {k} GROUP BY ALL" if k > 1 else ""
        out.append(f"c{k} AS MATERIALIZED (SELECT lang, {rest} AS g, count(*) AS c FROM c{k + 1} GROUP BY ALL{starts})")
    for k in range(1, order + 1):
        out.append(f"n{k} AS MATERIALIZED (SELECT lang, " + ", ".join(f"count(*) FILTER (c = {i})::DOUBLE AS n{i}" for i in range(1, 5)) + f" FROM c{k} GROUP BY lang)")
        y = "n1 / (n1 + 2 * n2)"
        if modified:
            raw = [f"{i} - {i + 1} * {y} * n{i + 1} / n{i}" for i in (1, 2, 3)]
            sound = "n1 > 0 AND n2 > 0 AND n3 > 0 AND n4 > 0 AND " + " AND ".join(f"{x} >= 0" for x in raw)
            d = ", ".join(f"CASE WHEN {sound} THEN {raw[i]} ELSE {lm.FALLBACK[i]}::DOUBLE END AS d{i + 1}" for i in range(3))
        else:
            d = ", ".join(f"CASE WHEN n1 > 0 AND n2 > 0 THEN {y} ELSE 0.75::DOUBLE END AS d{i}" for i in (1, 2, 3))
        out.append(f"d{k} AS MATERIALIZED (SELECT lang, {d} FROM n{k})")
        out.append(f"x{k} AS MATERIALIZED (SELECT lang, g, c, CASE c WHEN 1 THEN d1 WHEN 2 THEN d2 ELSE d3 END AS cut, regexp_replace(g, ' [^ ]+$', '') AS x, {rest} AS r FROM c{k} JOIN d{k} USING (lang))")
        if k == 1:
            out.append("b1 AS MATERIALIZED (SELECT lang, sum(c) AS t, sum(cut) / sum(c) / (count(*) + 1) AS b FROM x1 GROUP BY lang)")
            out.append("p1 AS MATERIALIZED (SELECT g, (c - cut) / t + b AS p FROM x1 JOIN b1 USING (lang))")
        else:
            out.append(f"b{k} AS MATERIALIZED (SELECT x, sum(c) AS t, sum(cut) / sum(c) AS b FROM x{k} GROUP BY x)")
            out.append(f"p{k} AS MATERIALIZED (SELECT z.g, (c - cut) / t + b * q.p AS p FROM x{k} z JOIN b{k} w ON w.x = z.x JOIN p{k - 1} q ON q.g = z.r)")
    return ", ".join(out)


def score_sql(name: str, source: str, order: int) -> str:
    """doc_id, lang, tokens, ppl of the sentences in *source*."""
    grams = ", ".join(f"'g{k}': CASE WHEN j >= {k} THEN lang || ' ' || array_to_string(s[greatest(j - {k - 1}, 1):j], ' ') END" for k in range(1, order + 1))
    out = [f"{name}0 AS MATERIALIZED (SELECT doc_id, lang, unnest(list_transform(range(2, len(s) + 1), lambda j: {{{grams}}})) AS a FROM {source})"]
    out.append(f"{name}1 AS MATERIALIZED (SELECT z.doc_id, z.lang, a, coalesce(p, b) AS p FROM (SELECT * FROM {name}0 JOIN b1 USING (lang)) z LEFT JOIN p1 ON p1.g = a.g1)")
    for k in range(2, order + 1):
        out.append(f"{name}{k} AS MATERIALIZED (SELECT z.doc_id, z.lang, a, CASE WHEN a.g{k} IS NULL THEN z.p ELSE coalesce(q.p, coalesce(w.b, 1.0) * z.p) END AS p FROM {name}{k - 1} z LEFT JOIN p{k} q ON q.g = a.g{k} LEFT JOIN b{k} w ON w.x = regexp_replace(a.g{k}, ' [^ ]+$', ''))")
    out.append(f"{name} AS MATERIALIZED (SELECT doc_id, lang, count(*) AS tokens, pow(10.0, -sum(log10(p)) / count(*)) AS ppl FROM {name}{order} GROUP BY ALL)")
    return ", ".join(out)


_LANG, _GRAM = "split_part(g, ' ', 1) AS lang", "substr(g, instr(g, ' ') + 1) AS g"
ORDER = config.LM_ORDER
BASE = f"sp AS ({SPLIT}), {sequences_sql('seq', 'sp')}, ver AS (SELECT doc_id, {PART} AS part FROM sp WHERE split = 'verified'), train AS (SELECT seq.* FROM seq JOIN ver USING (doc_id) WHERE part = 'train'), valid AS (SELECT seq.* FROM seq JOIN ver USING (doc_id) WHERE part = 'valid'), new_docs AS (SELECT seq.* FROM seq JOIN sp USING (doc_id) WHERE split = 'unverified')"
FLOW = f"{BASE}, {model_sql(ORDER)}, {score_sql('val', 'valid', ORDER)}, {score_sql('new', 'new_docs', ORDER)}, thr AS (SELECT lang, quantile_cont(ppl, 0.8) AS threshold FROM val GROUP BY lang)"


def parts(spark, d):
    """Training and validation sentences of the verified split (60 and 40 per cent by hash, whatever its size), and the unverified documents."""
    docs = report.with_split(table(spark, d, "documents"))
    verified = docs.filter("split = 'verified'").withColumn("part", lm.part(F.col("doc_id")))
    return verified.filter("part = 'train'"), verified.filter("part = 'valid'"), docs.filter("split = 'unverified'")


def model_of(spark, d, order: int = ORDER, modified: bool = True):
    return lm.kneser_ney(lm.sequences(parts(spark, d)[0]), order, modified)


def in_buckets(train, sequences=lm.sequences):
    """The model of training documents by buckets."""
    return lm_buckets.Bucketed(sequences(train), lm_buckets.bucket_count(train))


def scored(spark, d):
    """Perplexities of the validation and of the unverified documents, in one pass written once."""
    train, valid, new = parts(spark, d)
    model = in_buckets(train)
    both = model.space.write(model.perplexity(lm.sequences(valid.drop("part").unionByName(new))), free=True)
    ids = valid.select("doc_id")
    return both.join(ids, "doc_id", "left_semi"), both.join(ids, "doc_id", "left_anti")


def scored_valid(spark, d):
    train, valid, _ = parts(spark, d)
    return in_buckets(train).perplexity(lm.sequences(valid))


def scored_new(spark, d):
    train, _, new = parts(spark, d)
    model = in_buckets(train)
    return model.space.write(model.perplexity(lm.sequences(new)), free=True)


@query(f"SELECT doc_id, lang, {PART} AS part FROM ({SPLIT}) WHERE split = 'verified'")
def q_lm_sample(spark, d):
    train, valid, _ = parts(spark, d)
    return train.select("doc_id", "lang", "part").unionByName(valid.select("doc_id", "lang", "part"))


@query(f"SELECT doc_id, lang, CASE WHEN r <= {config.LM_TRAIN_DOCS} THEN 'train' ELSE 'valid' END AS part FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY {H}, doc_id) AS r FROM ({SPLIT}) WHERE split = 'verified') WHERE r <= {config.LM_TRAIN_DOCS + config.LM_VALID_DOCS}")
def q_lm_sample_fixed(spark, d):
    """Variant: samples of the published sizes per language (a sampling operator)."""
    verified = report.with_split(table(spark, d, "documents")).filter("split = 'verified'")
    pick = lambda n, skip, name: lm.sample_per_lang(verified, n, skip).select("doc_id", "lang", F.lit(name).alias("part"))
    return pick(config.LM_TRAIN_DOCS, 0, "train").unionByName(pick(config.LM_VALID_DOCS, config.LM_TRAIN_DOCS, "valid"))


@query(f"SELECT doc_id, {_NORM} AS text FROM documents")
def q_lm_normalize(spark, d):
    return table(spark, d, "documents").select("doc_id", lm.normalize(F.col("text")).alias("text"))


_COUNTS = f"WITH {BASE}, {model_sql(ORDER)}"


@query(f"{_COUNTS} SELECT {_LANG}, {_GRAM}, c FROM c{ORDER}")
def q_ngram_counts(spark, d):
    """Counts of the highest order."""
    return lm.ngram_counts(lm.sequences(parts(spark, d)[0]), ORDER)


@query(f"{_COUNTS} " + " UNION ALL ".join(f"SELECT {k} AS k, {_LANG}, {_GRAM}, c FROM c{k}" for k in range(1, ORDER)))
def q_ngram_continuation(spark, d):
    """Lower orders: distinct left words, raw counts where a sentence begins."""
    tables = lm.count_tables(lm.sequences(parts(spark, d)[0]))
    out = None
    for k, t in enumerate(tables[:-1], 1):
        t = t.select(F.lit(k).alias("k"), "lang", "g", "c")
        out = t if out is None else out.unionByName(t)
    return out


@query(f"{_COUNTS} " + " UNION ALL ".join(f"SELECT {k} AS k, lang, d1, d2, d3 FROM d{k}" for k in range(1, ORDER + 1)))
def q_kn_discounts(spark, d):
    """The three discounts of each order and language."""
    out = None
    for k, t in enumerate(lm.count_tables(lm.sequences(parts(spark, d)[0])), 1):
        t = lm.discounts(t).select(F.lit(k).alias("k"), "lang", "d1", "d2", "d3")
        out = t if out is None else out.unionByName(t)
    return out


@query(f"{_COUNTS} " + " UNION ALL ".join(f"SELECT {k} AS k, {_LANG}, {_GRAM}, p FROM p{k}" for k in range(1, ORDER + 1)))
def q_kn_model(spark, d):
    """Interpolated probabilities of all n-grams."""
    out = None
    for k, t in enumerate(model_of(spark, d).probs, 1):
        t = t.select(F.lit(k).alias("k"), "lang", "g", "p")
        out = t if out is None else out.unionByName(t)
    return out


@query(f"WITH {BASE}, {model_sql(2, False)}, {score_sql('val', 'valid', 2)} SELECT doc_id, lang, tokens, ppl FROM val")
def q_ppl_bigram(spark, d):
    """Variant: order 2 and a single discount, by joins."""
    return lm.perplexity(lm.sequences(parts(spark, d)[1]), model_of(spark, d, 2, modified=False), "join")


@query(f"WITH {FLOW} SELECT doc_id, lang, tokens, ppl FROM val")
def q_ppl_5gram(spark, d):
    """Order 5 by buckets: no model reaches the driver."""
    return scored_valid(spark, d)


@query(f"WITH {FLOW} SELECT doc_id, lang, tokens, ppl FROM val")
def q_ppl_5gram_joined(spark, d):
    """Order 5 as positions that meet the model in its buckets (a join by language and context), whatever the model's size."""
    return scored_valid(spark, d)


@query()
def q_ppl_subword(spark, d):
    """Order 5 on the pieces of a public subword vocabulary (tested against a plain model)."""
    import public_tokenizers

    train, valid, _ = parts(spark, d)
    file = public_tokenizers.path("piece_bpe_32k.model")
    cut = lambda docs: lm.Subwords(docs, file)
    return in_buckets(train, cut).perplexity(cut(valid))


@query(f"WITH {FLOW} SELECT lang, threshold FROM thr")
def q_ppl_threshold(spark, d):
    return lm.thresholds(scored_valid(spark, d))


@query(f"WITH {FLOW} SELECT doc_id, new.lang, ppl FROM new JOIN thr ON new.lang = thr.lang WHERE ppl <= threshold")
def q_ppl_filter(spark, d):
    val, new = scored(spark, d)
    return lm.ppl_filter(new, lm.thresholds(val)).select("doc_id", "lang", "ppl")


@query(f"WITH {FLOW} SELECT new.lang, min(ppl) AS min_ppl, max(ppl) AS max_ppl, avg(ppl) AS mean_ppl, max(threshold) AS threshold, count(*) AS docs, count(*) FILTER (ppl <= threshold) AS chosen, 1 - count(*) FILTER (ppl <= threshold) / count(*)::DOUBLE AS rate FROM new JOIN thr ON new.lang = thr.lang GROUP BY new.lang")
def q_ppl_report(spark, d):
    val, new = scored(spark, d)
    return lm.ppl_report(new, lm.thresholds(val))


@query(f"WITH {FLOW} SELECT lang, floor(log10(ppl) * 5)::BIGINT AS bin, count(*) AS n FROM new GROUP BY ALL")
def q_ppl_hist(spark, d):
    return scored_new(spark, d).groupBy("lang", F.floor(F.log10("ppl") * 5).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {FLOW} SELECT lang, avg(log10(ppl)) AS mean_log, stddev_samp(log10(ppl)) AS deviation, quantile_cont(log10(ppl), 0.25) AS q25, quantile_cont(log10(ppl), 0.5) AS q50, quantile_cont(log10(ppl), 0.75) AS q75 FROM new GROUP BY lang")
def q_ppl_spread(spark, d):
    """How tight or dispersed the log-perplexities of a language are."""
    x = F.log10("ppl")
    return scored_new(spark, d).groupBy("lang").agg(F.avg(x).alias("mean_log"), F.stddev_samp(x).alias("deviation"), *(F.percentile(x, F.lit(q)).alias(f"q{round(q * 100)}") for q in (0.25, 0.5, 0.75)))


@query(f"WITH {FLOW} SELECT new.lang, q, count(*) FILTER (ppl <= t) AS chosen, sum(CASE WHEN ppl <= t THEN tokens ELSE 0 END)::BIGINT AS tokens FROM new JOIN (SELECT lang, unnest([0.5, 0.8, 0.95])::DOUBLE AS q, unnest(quantile_cont(ppl, [0.5, 0.8, 0.95])) AS t FROM val GROUP BY lang) s ON s.lang = new.lang GROUP BY ALL")
def q_ppl_sweep(spark, d):
    """Volume against strictness: a higher quantile is laxer."""
    val, new = scored(spark, d)
    qs = [0.5, 0.8, 0.95]
    cuts = val.groupBy("lang").agg(F.percentile("ppl", F.array(*map(F.lit, qs))).alias("t")).select("lang", F.explode(F.arrays_zip(F.array(*map(F.lit, qs)).alias("q"), "t")).alias("z")).select("lang", "z.q", "z.t")
    kept = F.col("ppl") <= F.col("t")
    return new.join(F.broadcast(cuts), "lang").groupBy("lang", "q").agg(F.count_if(kept).alias("chosen"), F.sum(F.when(kept, F.col("tokens")).otherwise(0)).alias("tokens"))


@query(f"WITH {FLOW}, cu AS (SELECT lang, quantile_cont(ppl, 1.0/3) AS a, quantile_cont(ppl, 2.0/3) AS b FROM new GROUP BY lang) SELECT doc_id, new.lang, 1 + (ppl > a)::INTEGER + (ppl > b)::INTEGER AS bucket FROM new JOIN cu ON cu.lang = new.lang")
def q_ppl_buckets(spark, d):
    """Head, middle and tail by tertiles."""
    return lm.ppl_buckets(scored_new(spark, d))


@query()
def q_fertility_pieces(spark, d):
    """Pieces of a public subword vocabulary per word and language (tested against the library)."""
    import public_tokenizers

    docs = table(spark, d, "documents").select("doc_id", "lang", "text")
    seqs = lm.subword_sequences(docs, public_tokenizers.path("piece_bpe_32k.model"))
    pieces = seqs.groupBy("lang").agg(F.sum(F.size("s") - 2).alias("pieces"))
    words = docs.select("lang", F.size(T.words(lm.normalize(F.col("text")))).alias("w")).groupBy("lang").agg(F.sum("w").alias("words"))
    return pieces.join(words, "lang").select("lang", "pieces", "words", (F.col("pieces") / F.col("words")).alias("fertility"))


WORD_PROFILES = " UNION ALL ".join(f"SELECT '{k}' AS l, {v!r} AS ws".replace("(", "[").replace(")", "]") for k, v in lid.FUNCTION_WORDS.items())
_E2 = f"""fw AS (SELECT doc_id, {FOLDED.format(x='text')} AS f FROM documents), pr AS ({WORD_PROFILES}),
e2 AS (SELECT doc_id, arg_max(l, (n, l)) AS lang, max(n) / greatest(any_value(t), 1)::DOUBLE AS conf FROM (SELECT doc_id, l, len(list_filter(f, lambda w: list_contains(ws, w))) AS n, len(f) AS t FROM fw, pr) GROUP BY doc_id)"""


@query(f"WITH {_E2} SELECT * FROM e2")
def q_lid_words(spark, d):
    return lid.predict_words(table(spark, d, "documents"))


_GRAMS = """gr AS MATERIALIZED (SELECT doc_id, lang, substr(t, i, n) AS g, count(*) AS k FROM (SELECT doc_id, lang, t, n, unnest(range(1, length(t) - n + 2)) AS i FROM (SELECT doc_id, lang, lower(text) AS t, unnest([1, 2, 3, 4]) AS n FROM documents)) GROUP BY ALL),
cn AS MATERIALIZED (SELECT lang, g, sum(k) AS c FROM gr WHERE doc_id % 3 <> 0 GROUP BY ALL), ct AS (SELECT lang, sum(c) AS t FROM cn GROUP BY lang)"""
_E1 = f"""tp AS (SELECT g FROM cn GROUP BY g ORDER BY sum(c) DESC, g LIMIT {lid.MOST}),
nb AS (SELECT tp.g, ct.lang, ln((coalesce(c, 0) + 1)::DOUBLE / (t + {lid.MOST})) AS lp FROM tp CROSS JOIN ct LEFT JOIN cn ON cn.g = tp.g AND cn.lang = ct.lang),
s1 AS (SELECT doc_id, nb.lang, sum(k * lp) / sum(k) AS s FROM gr JOIN nb ON nb.g = gr.g GROUP BY ALL),
e1 AS (SELECT doc_id, arg_max(lang, (s, lang)) AS lang, max(exp(s)) / sum(exp(s)) AS conf FROM s1 GROUP BY doc_id)"""
_E3 = f"""pf AS (SELECT lang, g, row_number() OVER (PARTITION BY lang ORDER BY c DESC, g) AS r FROM cn WHERE length(g) = 3 QUALIFY r <= {lid.RANKS}),
ow AS (SELECT doc_id, g, row_number() OVER (PARTITION BY doc_id ORDER BY k DESC, g) AS q FROM gr WHERE length(g) = 3 QUALIFY q <= {lid.RANKS}),
sz AS (SELECT doc_id, count(*) AS n FROM ow GROUP BY doc_id), gn AS (SELECT doc_id, pf.lang, sum({lid.RANKS} - abs(q - r)) AS gain FROM ow JOIN pf USING (g) GROUP BY ALL),
e3 AS (SELECT doc_id, arg_max(lang, (gain, lang)) AS lang, max(gain)::DOUBLE / ({lid.RANKS} * any_value(n)) AS conf FROM gn JOIN sz USING (doc_id) GROUP BY doc_id HAVING max(gain) > 0)"""
VOTES = f"""{_GRAMS}, {_E1}, {_E2}, {_E3},
v AS (SELECT d.doc_id, d.lang AS truth, e1.lang AS l1, CASE WHEN t > 0 THEN e2.lang END AS l2, e3.lang AS l3, e2.conf AS c2, e3.conf AS c3 FROM documents d LEFT JOIN e1 USING (doc_id) LEFT JOIN e2 USING (doc_id) LEFT JOIN e3 USING (doc_id) LEFT JOIN (SELECT doc_id, len(f) AS t FROM fw) z USING (doc_id)),
en AS (SELECT doc_id, truth, l1, l2, l3, CASE WHEN l2 = l3 AND l2 <> l1 AND least(c2, c3) > {lid.TAU} THEN l2 ELSE coalesce(l1, l2) END AS lang, CASE WHEN l2 = l3 THEN l2 ELSE coalesce(l1, l2) END AS majority FROM v)"""


def votes(spark, d):
    """Votes of the three models for every document; they learn from two thirds of the documents."""
    docs = table(spark, d, "documents").select("doc_id", "lang", "text")
    return lid.votes(docs, lid.train(docs.filter("doc_id % 3 <> 0"))).withColumnRenamed("lang", "truth")


def _decided(spark, d):
    c = F.col
    v = votes(spark, d)
    return v.withColumn("lang", lid.ensemble(c("l1"), c("l2"), c("l3"), c("c2"), c("c3"))).withColumn("majority", lid.majority(c("l1"), c("l2"), c("l3")))


@query(f"WITH {_GRAMS}, {_E1} SELECT doc_id, lang, conf FROM e1")
def q_lid_nb(spark, d):
    """First model: naive Bayes on character 1- to 4-grams."""
    return votes(spark, d).filter("l1 is not null").select("doc_id", F.col("l1").alias("lang"), F.col("c1").alias("conf"))


@query(f"WITH {_GRAMS}, {_E3} SELECT doc_id, lang, conf FROM e3")
def q_lid_ranks(spark, d):
    """Third model: rank-order trigram profiles."""
    return votes(spark, d).filter("l3 is not null").select("doc_id", F.col("l3").alias("lang"), F.col("c3").alias("conf"))


@query(f"WITH {VOTES} SELECT doc_id, lang FROM en")
def q_lid_ensemble(spark, d):
    return _decided(spark, d).select("doc_id", "lang")


@query(f"WITH {VOTES} SELECT doc_id, majority AS lang FROM en")
def q_lid_majority(spark, d):
    return _decided(spark, d).select("doc_id", F.col("majority").alias("lang"))


@query(f"WITH {VOTES} SELECT truth, lang, count(*) AS n FROM en GROUP BY ALL")
def q_lid_confusion(spark, d):
    return _decided(spark, d).groupBy("truth", "lang").agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH {VOTES}, u AS (SELECT truth, model, said FROM (SELECT truth, unnest(['first', 'words', 'ranks', 'majority', 'ensemble']) AS model, unnest([l1, l2, l3, majority, lang]) AS said FROM en WHERE doc_id % 3 = 0)),
a AS (SELECT model, avg(CASE WHEN truth = said THEN 1.0 ELSE 0.0 END)::DOUBLE AS accuracy FROM u GROUP BY model), r AS (SELECT model, truth AS lang, avg(CASE WHEN truth = said THEN 1.0 ELSE 0.0 END)::DOUBLE AS recall FROM u GROUP BY ALL),
p AS (SELECT model, said AS lang, avg(CASE WHEN truth = said THEN 1.0 ELSE 0.0 END)::DOUBLE AS precision FROM u GROUP BY ALL)
SELECT r.model, r.lang, coalesce(precision, 0.0) AS precision, recall, accuracy FROM r JOIN a ON a.model = r.model LEFT JOIN p ON p.model = r.model AND p.lang = r.lang""")
def q_lid_report(spark, d):
    """Precision, recall and accuracy of each model, the plain vote and the ensemble on documents that no model learned from (the fold of the method)."""
    held_out = _decided(spark, d).filter("doc_id % 3 = 0")
    return lid.report(held_out, "truth", {"first": "l1", "words": "l2", "ranks": "l3", "majority": "majority", "ensemble": "lang"})


@query(f"WITH {VOTES} SELECT truth AS old, lang AS new, count(*) AS n FROM en WHERE truth <> lang GROUP BY ALL")
def q_lid_flow(spark, d):
    """Documents that the ensemble moves between languages."""
    e = _decided(spark, d).select(F.col("truth").alias("old"), F.col("lang").alias("new"))
    return e.filter("old <> new").groupBy("old", "new").agg(F.count(F.lit(1)).alias("n"))
