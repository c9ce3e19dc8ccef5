"""Queries: web pages and sites."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..registry import query, table
from ..sources import html, sites
from .q_curation import FOLDED

H = "CAST('0x' || substr(md5(CAST({x} AS VARCHAR)), 1, 8) AS BIGINT)"
_DECODE = "text0"
for _a, _b in html.ENTITIES:
    _DECODE = "replace({}, '{}', '{}')".format(_DECODE, _a, _b.replace("'", "''"))
_BODY = r"""regexp_replace(regexp_replace(regexp_replace(regexp_extract(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', '', 'g'), '(?s)<(script|style|nav|footer)\b[^>]*>.*?</(script|style|nav|footer)>', '', 'g'), '(?s)<article[^>]*>(.*)</article>', 1), '(?s)<h1[^>]*>.*?</h1>', '', 'g'), '<br\s*/?>|</p>', chr(10), 'g'), '<[^>]+>', '', 'g')"""
EXTRACT = f"""ex AS (SELECT page_id, url, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS title0, regexp_extract(html, '<html[^>]*lang="([a-z]+)"', 1) AS lang_hint, {_BODY} AS text0 FROM pages),
extracted AS (SELECT page_id, url, {_DECODE.replace('text0', 'title0')} AS title, lang_hint, rtrim({_DECODE}, chr(10)) AS text FROM ex)"""
HOST = r"regexp_extract(url, '^https?://([^/?#]+)', 1)"


def _pages(spark, d):
    return table(spark, d, "pages")


@query(f"WITH {EXTRACT} SELECT * FROM extracted")
def q_html_extract(spark, d):
    return html.extract_main(_pages(spark, d))


@query(r"SELECT page_id, regexp_replace(html, '<[^>]+>', ' ', 'g') AS text FROM pages")
def q_html_strip(spark, d):
    return _pages(spark, d).select("page_id", html.strip_tags(F.col("html")).alias("text"))


@query(f"WITH {EXTRACT} SELECT page_id, text FROM extracted")
def q_html_dom(spark, d):
    return html.extract_dom(_pages(spark, d))


@query(f"WITH {EXTRACT} SELECT count(*) AS pages, count(*) FILTER (EXISTS (SELECT 1 FROM documents d WHERE d.text = e.text)) AS exact FROM extracted e")
def q_html_quality(spark, d):
    """Pages whose extracted text equals a known document, by hash."""
    truth = table(spark, d, "documents").select(F.sha2("text", 256).alias("h")).distinct().withColumn("hit", F.lit(1))
    got = html.extract_main(_pages(spark, d)).select("page_id", F.sha2("text", 256).alias("h"))
    return got.join(truth, "h", "left").agg(F.count(F.lit(1)).alias("pages"), F.count("hit").alias("exact"))


_STRIPPED = r"regexp_replace(html, '<[^>]+>', ' ', 'g')"
_TOK = f"""tk AS (SELECT page_id, method, w, count(*) AS k FROM (SELECT page_id, 'main' AS method, unnest({FOLDED.format(x='text')}) AS w FROM extracted UNION ALL SELECT page_id, 'strip', unnest({FOLDED.format(x=_STRIPPED)}) FROM pages) GROUP BY ALL),
tr AS (SELECT e.page_id, w, count(*) AS k FROM (SELECT page_id, unnest({FOLDED.format(x='d.text')}) AS w FROM extracted e JOIN (SELECT DISTINCT text FROM documents) d ON d.text = e.text) e GROUP BY ALL),
sz AS (SELECT method, sum(k) AS got FROM tk WHERE page_id IN (SELECT page_id FROM tr) GROUP BY method), ts AS (SELECT sum(k) AS wanted FROM tr),
ov AS (SELECT method, sum(least(tk.k, tr.k)) AS hits FROM tk JOIN tr ON tr.page_id = tk.page_id AND tr.w = tk.w GROUP BY method)"""


@query(f"WITH {EXTRACT}, {_TOK} SELECT method, hits / got::DOUBLE AS precision, hits / wanted::DOUBLE AS recall, 2.0 * hits / (got + wanted)::DOUBLE AS f1 FROM ov JOIN sz USING (method), ts")
def q_html_tokens(spark, d):
    """Token precision, recall and F1 of the extraction and of the plain tag strip, against the documents that the pages hold."""
    main = html.extract_main(_pages(spark, d)).select("page_id", "text")
    truth = main.join(table(spark, d, "documents").select("text").distinct(), "text", "left_semi")
    count = lambda df, *keys: df.select(*keys, F.explode(T.folded_words(F.col("text"))).alias("w")).groupBy(*keys, "w").agg(F.count(F.lit(1)).alias("k"))
    strip = _pages(spark, d).select("page_id", html.strip_tags(F.col("html")).alias("text"))
    got = count(main.withColumn("method", F.lit("main")).unionByName(strip.withColumn("method", F.lit("strip"))).join(truth.select("page_id").distinct(), "page_id", "left_semi"), "page_id", "method")
    want = count(truth, "page_id").withColumnRenamed("k", "t")
    both = got.join(want, ["page_id", "w"], "left").groupBy("method").agg(F.sum("k").alias("got"), F.sum(F.least("k", F.coalesce("t", F.lit(0)))).alias("both"))
    both = both.crossJoin(F.broadcast(want.agg(F.sum("t").alias("wanted"))))
    return both.select("method", (F.col("both") / F.col("got")).alias("precision"), (F.col("both") / F.col("wanted")).alias("recall"), (2.0 * F.col("both") / (F.col("got") + F.col("wanted"))).alias("f1"))


@query(f"WITH {EXTRACT} SELECT page_id AS doc_id, text, lang_hint AS lang, {HOST} AS source, 'web' AS modality FROM extracted WHERE text <> ''")
def q_web_documents(spark, d):
    e = html.extract_main(_pages(spark, d))
    return e.filter("text <> ''").select(F.col("page_id").alias("doc_id"), "text", F.col("lang_hint").alias("lang"), html.host(F.col("url")).alias("source"), F.lit("web").alias("modality"))


@query(r"SELECT page_id, regexp_replace(lower(regexp_extract(b, '^([^/]*)', 1)), '^(www|m)\.', '') || regexp_replace(regexp_replace(regexp_extract(b, '^[^/]*(.*)$', 1), '\.html?$', ''), '/+$', '') AS url FROM (SELECT page_id, regexp_replace(regexp_replace(url, '^https?://', ''), '[?#].*$', '') AS b FROM pages)")
def q_url_canonical(spark, d):
    return _pages(spark, d).select("page_id", html.canonical_url(F.col("url")).alias("url"))


def _hosts(spark, d):
    return _pages(spark, d).select(html.host(F.col("url")).alias("host"), "html").withColumn("o", T.md5_int(F.col("host")) % 4)


@query(f"SELECT host, array_to_string(list_sort(list(DISTINCT origin)), ',') AS origins FROM (SELECT {HOST} AS host, ['search','volunteer','crawl','government'][({H.format(x=HOST)} % 4 + 1)::INTEGER] AS origin FROM pages UNION ALL SELECT {HOST}, 'crawl' FROM pages WHERE url LIKE '%ref=%') GROUP BY host")
def q_site_candidates(spark, d):
    h = _hosts(spark, d)
    lists = {o: h.filter(F.col("o") == k) for k, o in enumerate(sites.ORIGINS)}
    lists["crawl"] = lists["crawl"].select("host").unionByName(_pages(spark, d).filter("url LIKE '%ref=%'").select(html.host(F.col("url")).alias("host")))
    return sites.candidate_sites(lists)


@query(f"WITH {EXTRACT} SELECT {HOST} AS host, sum(length(text))::BIGINT AS chars, count(*) AS pages FROM extracted GROUP BY ALL ORDER BY chars DESC, host LIMIT 10")
def q_site_top_hosts(spark, d):
    e = html.extract_main(_pages(spark, d)).select(html.host(F.col("url")).alias("host"), "text")
    return sites.top_hosts(e, 10)


_VERDICT = f"""{EXTRACT}, copies AS (SELECT text, count(*) AS k FROM extracted WHERE text <> '' GROUP BY text),
s AS (SELECT {HOST} AS host, count(*) AS n_pages, avg(CASE WHEN lang_hint IN ('en','fr') THEN 1.0 ELSE 0.0 END)::DOUBLE AS lang_share, avg(CASE WHEN k > 1 THEN 1.0 ELSE 0.0 END)::DOUBLE AS copied, sum(length(e.text)) AS chars FROM extracted e LEFT JOIN copies c ON c.text = e.text GROUP BY ALL),
v AS (SELECT host, n_pages, list_filter([CASE WHEN lang_share < 0.5 THEN 'language' END, CASE WHEN host LIKE '%pill%' OR host LIKE '%casino%' OR host LIKE '%bets%' OR host LIKE '%adult%' THEN 'adult_or_gambling' END, CASE WHEN copied > 0.5 THEN 'machine_translated' END, CASE WHEN chars < 500 THEN 'inactive' END], lambda x: x IS NOT NULL) AS r FROM s)"""


def verdicts(spark, d):
    """Rules on the pages of a host: share in the target languages, share of texts that stand on other pages too (a sign of machine-made pages), text at all."""
    h = F.col("host")
    e = html.extract_main(_pages(spark, d)).select(html.host(F.col("url")).alias("host"), F.col("lang_hint").isin("en", "fr").cast("double").alias("t"), F.length("text").alias("n"), F.when(F.col("text") != "", F.xxhash64("text")).alias("x"))
    copies = e.filter("x is not null").groupBy("x").agg((F.count(F.lit(1)) > 1).alias("copy"))
    s = e.join(copies, "x", "left").groupBy("host").agg(F.count(F.lit(1)).alias("n_pages"), F.avg("t").alias("lang_share"), F.avg(F.coalesce("copy", F.lit(False)).cast("double")).alias("copied"), F.sum("n").alias("chars"))
    r = sites.reasons(F.col("lang_share") >= 0.5, h, F.col("copied") > 0.5, F.col("chars") >= 500)
    return s.select("host", "n_pages", r.alias("r"))


@query(f"WITH {_VERDICT} SELECT host, n_pages, CASE WHEN len(r) = 0 THEN 'accept' ELSE 'reject' END AS verdict, array_to_string(r, ',') AS reasons FROM v")
def q_site_verdicts(spark, d):
    return verdicts(spark, d).select("host", "n_pages", F.when(F.size("r") == 0, "accept").otherwise("reject").alias("verdict"), F.array_join("r", ",").alias("reasons"))


@query("SELECT d.source AS site, count(*) AS votes, sum(quality)::BIGINT AS yes, CASE WHEN count(*) < 5 THEN 'open' WHEN sum(quality) >= count(*) * 0.8 THEN 'accept' ELSE 'reject' END AS decision FROM labels JOIN documents d USING (doc_id) GROUP BY ALL")
def q_site_votes(spark, d):
    votes = table(spark, d, "labels").join(table(spark, d, "documents").select("doc_id", F.col("source").alias("site")), "doc_id")
    return sites.decide(votes, "site", "quality", 5, 0.8)


@query(f"WITH {_VERDICT}, o AS (SELECT unnest(CASE WHEN len(r) = 0 THEN ['accepted'] ELSE r END) AS outcome FROM v) SELECT outcome, count(*) AS n, count(*) / (sum(count(*)) OVER ())::DOUBLE AS share FROM o GROUP BY outcome")
def q_site_outcomes(spark, d):
    o = verdicts(spark, d).select(F.explode(F.when(F.size("r") == 0, F.array(F.lit("accepted"))).otherwise(F.col("r"))).alias("outcome"))
    n = o.groupBy("outcome").agg(F.count(F.lit(1)).alias("n"))
    return n.crossJoin(F.broadcast(o.agg(F.count(F.lit(1)).alias("t")))).select("outcome", "n", (F.col("n") / F.col("t")).alias("share"))


@query(f"WITH {_VERDICT} SELECT page_id FROM pages WHERE {HOST} IN (SELECT host FROM v WHERE len(r) = 0)")
def q_pages_accepted(spark, d):
    """Only pages of accepted hosts are crawled."""
    ok = verdicts(spark, d).filter(F.size("r") == 0).select("host")
    return _pages(spark, d).select("page_id", html.host(F.col("url")).alias("host")).join(ok, "host", "left_semi").select("page_id")
