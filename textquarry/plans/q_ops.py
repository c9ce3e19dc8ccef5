"""Queries: relational operators around the methods (scans, joins, aggregates, windows, sets, samples, functions)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..registry import query, table
from ..sources import files

HASH = "CAST('0x' || substr(md5(CAST({x} AS VARCHAR)), 1, 8) AS BIGINT)"


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderstatus IN ('F', 'O')")
def q_filter_range(spark, d):
    return table(spark, d, "orders").filter(F.col("o_totalprice").between(1000, 50000) & F.col("o_orderstatus").isin("F", "O")).select("o_orderkey", "o_totalprice")


@query(r"SELECT c_custkey FROM customer WHERE regexp_matches(c_name, '#0+[1-4]\d*$')")
def q_filter_regex(spark, d):
    return table(spark, d, "customer").filter(F.col("c_name").rlike(r"#0+[1-4]\d*$")).select("c_custkey")


@query("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS size_class, TRY_CAST(substr(p_brand, 7) AS INTEGER) AS brand_no FROM part")
def q_project_case(spark, d):
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large")
    return table(spark, d, "part").select("p_partkey", size.alias("size_class"), F.substring("p_brand", 7, 99).try_cast("int").alias("brand_no"))


@query("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_quantity > 45")
def q_scan_parquet(spark, d):
    return table(spark, d, "lineitem").filter("l_shipdate >= timestamp '1997-01-01' and l_quantity > 45").select("l_orderkey", "l_quantity")


@query("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def q_join_broadcast(spark, d):
    """Nation and region have a fixed number of rows."""
    n = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@query("SELECT o_custkey, sum(l_quantity) AS quantity, count(*) AS n_lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey")
def q_join_smj(spark, d):
    j = table(spark, d, "orders").hint("merge").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_custkey").agg(F.sum("l_quantity").alias("quantity"), F.count(F.lit(1)).alias("n_lines"))


@query("SELECT s_suppkey, count(*) AS n_nations FROM supplier, nation WHERE s_nationkey > n_nationkey GROUP BY s_suppkey")
def q_join_theta(spark, d):
    return table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation")), F.col("s_nationkey") > F.col("n_nationkey")).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n_nations"))


@query("SELECT e.event_id, b.band FROM events e JOIN (VALUES (0, 5, 'low'), (5, 20, 'mid'), (20, 1000000, 'high')) b(lo, hi, band) ON e.value >= b.lo AND e.value < b.hi")
def q_join_range(spark, d):
    bands = spark.createDataFrame([(0, 5, "low"), (5, 20, "mid"), (20, 1000000, "high")], "lo int, hi int, band string")
    return table(spark, d, "events").join(F.broadcast(bands), (F.col("value") >= F.col("lo")) & (F.col("value") < F.col("hi"))).select("event_id", "band")


@query("SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_click FROM events")
def q_join_asof(spark, d):
    """Latest earlier click of the same user: a window instead of a range join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w).alias("last_click"))


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")
def q_join_semi(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").filter("o_totalprice > 100000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_join_anti(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@query("SELECT coalesce(c_custkey, o_custkey) AS custkey, n FROM (SELECT c_custkey FROM customer WHERE c_acctbal > 0) c FULL JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) o ON c_custkey = o_custkey")
def q_join_full(spark, d):
    o = table(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, d, "customer").filter("c_acctbal > 0").join(o, F.col("c_custkey") == F.col("o_custkey"), "full").select(F.coalesce("c_custkey", "o_custkey").alias("custkey"), "n")


@query("SELECT event_type, count(*) AS n, sum(e.value * u.w) AS weighted FROM events e JOIN (SELECT user_id, count(*)::DOUBLE AS w FROM events GROUP BY 1) u ON e.user_id = u.user_id GROUP BY event_type")
def q_join_salted(spark, d):
    """Salted equi-join: the hot side spreads over eight salts, the other side is repeated for each."""
    e = table(spark, d, "events").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(8)))
    u = table(spark, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).cast("double").alias("w")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return e.join(u, ["user_id", "salt"]).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("value") * F.col("w")).alias("weighted"))


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, avg(l_discount) AS avg_disc, count(*) AS n FROM lineitem GROUP BY ALL")
def q_agg_hash(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.avg("l_discount").alias("avg_disc"), F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def q_agg_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


_PRICE = "round(sum(o_totalprice), 2)"


@query(f"SELECT o_orderstatus, o_orderpriority, {_PRICE} AS total FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def q_agg_rollup(spark, d):
    return table(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def q_agg_cube(spark, d):
    return table(spark, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, source, GROUPING_ID(lang, source)::BIGINT AS gid, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def q_agg_gsets(spark, d):
    table(spark, d, "documents").createOrReplaceTempView("tq_documents")
    return spark.sql("SELECT lang, source, grouping_id(lang, source) AS gid, count(*) AS n FROM tq_documents GROUP BY lang, source GROUPING SETS ((lang), (source), ())")


@query("SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
def q_agg_pivot(spark, d):
    p = table(spark, d, "events").groupBy((F.col("user_id") % 10).alias("g")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return p.select("g", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@query("SELECT lang, quantile_cont(n_chars, 0.5) AS p50, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
def q_agg_percentile(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("p50"), F.percentile("n_chars", F.lit(0.9)).alias("p90"))


@query("SELECT lang, count(*) FILTER (n_chars > 1000) AS long_docs, count(*) AS docs FROM documents GROUP BY lang")
def q_agg_filtered(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.count_if(F.col("n_chars") > 1000).alias("long_docs"), F.count(F.lit(1)).alias("docs"))


@query("SELECT lang, arg_max(doc_id, (n_chars, -doc_id)) AS longest FROM documents GROUP BY lang")
def q_agg_maxby(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", -F.col("doc_id"))).alias("longest"))


@query()
def q_agg_sketch(spark, d):
    """Mergeable sketches: distinct users by HLL, value quantiles by approximation."""
    e = table(spark, d, "events")
    parts = e.groupBy("event_type", F.to_date("ts").alias("day")).agg(F.hll_sketch_agg("user_id").alias("s"))
    return parts.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users"))


@query("SELECT doc_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)")
def q_win_rank(spark, d):
    w = Window.partitionBy("lang").orderBy("n_chars", "doc_id")
    return table(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("quarter"))


@query("SELECT event_id, value - lag(value) OVER w AS delta, lead(event_type) OVER w AS next_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q_win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", (F.col("value") - F.lag("value").over(w)).alias("delta"), F.lead("event_type").over(w).alias("next_type"))


@query("SELECT event_id, sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last3 FROM events")
def q_win_rows(spark, d):
    return table(spark, d, "events").select("event_id", F.sum("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).alias("last3"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT *, floor(epoch(ts))::BIGINT AS s FROM events)")
def q_win_range(spark, d):
    e = table(spark, d, "events").withColumn("s", F.unix_seconds(F.date_trunc("second", "ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("last_hour"))


@query("WITH g AS (SELECT user_id, event_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS island FROM events) SELECT user_id, event_type, min(event_id) AS first_event, count(*) AS n FROM g GROUP BY user_id, event_type, island HAVING count(*) >= 2")
def q_win_islands(spark, d):
    a, b = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id")
    g = table(spark, d, "events").withColumn("island", F.row_number().over(a) - F.row_number().over(b))
    return g.groupBy("user_id", "event_type", "island").agg(F.min("event_id").alias("first_event"), F.count(F.lit(1)).alias("n")).filter("n >= 2").drop("island")


@query("WITH s AS (SELECT *, CASE WHEN ts - lag(ts) OVER w > INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), n AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sess FROM s) SELECT user_id, sess::BIGINT AS sess, count(*) AS n FROM n GROUP BY user_id, sess")
def q_win_session(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))) > 6 * 3600 * 1_000_000
    s = table(spark, d, "events").withColumn("b", F.when(F.coalesce(gap, F.lit(True)), 1).otherwise(0)).withColumn("sess", F.sum("b").over(w))
    return s.groupBy("user_id", "sess").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25")
def q_topk(spark, d):
    return table(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.col("n_chars").desc(), "doc_id").limit(25)


@query("SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def q_topk_grouped(spark, d):
    w = Window.partitionBy("lang").orderBy(F.col("n_chars").desc(), "doc_id")
    return table(spark, d, "documents").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("lang", "doc_id")


@query("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def q_set_union(spark, d):
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).union(table(spark, d, "supplier").select("s_nationkey")).distinct()


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def q_set_intersect(spark, d):
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, d, "supplier").select("s_nationkey"))


@query("SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels")
def q_set_except(spark, d):
    return table(spark, d, "documents").select("doc_id").subtract(table(spark, d, "labels").select("doc_id"))


@query(f"SELECT doc_id FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY {HASH.format(x='doc_id')}, doc_id) AS r FROM documents) WHERE r <= 20")
def q_sample_hash(spark, d):
    """Reproducible sample: the n least hashes of each language."""
    w = Window.partitionBy("lang").orderBy(T.md5_int(F.col("doc_id")), "doc_id")
    return table(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("r")).filter("r <= 20").select("doc_id")


@query(f"SELECT doc_id, CASE WHEN {HASH.format(x='doc_id')} % 100 < 90 THEN 'train' WHEN {HASH.format(x='doc_id')} % 100 < 95 THEN 'valid' ELSE 'test' END AS part FROM documents")
def q_split_hash(spark, d):
    h = T.md5_int(F.col("doc_id")) % 100
    return table(spark, d, "documents").select("doc_id", F.when(h < 90, "train").when(h < 95, "valid").otherwise("test").alias("part"))


@query("WITH c AS (SELECT lang, count(*) AS n FROM documents GROUP BY 1) SELECT lang, pow(n, 0.3) / sum(pow(n, 0.3)) OVER () AS weight FROM c")
def q_mixture_weights(spark, d):
    """Temperature-scaled share per language."""
    c = table(spark, d, "documents").groupBy("lang").agg(F.pow(F.count(F.lit(1)), F.lit(0.3)).alias("p"))
    return c.crossJoin(F.broadcast(c.agg(F.sum("p").alias("t")))).select("lang", (F.col("p") / F.col("t")).alias("weight"))


@query("SELECT c_custkey, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, levenshtein(c_mktsegment, 'BUILDING') AS dist, md5(c_name) AS h, split_part(c_name, '#', 1) AS prefix FROM customer")
def q_fn_string(spark, d):
    return table(spark, d, "customer").select("c_custkey", F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.levenshtein("c_mktsegment", F.lit("BUILDING")).cast("long").alias("dist"), F.md5(F.col("c_name").cast("binary")).alias("h"), F.substring_index("c_name", "#", 1).alias("prefix"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS days, (o_orderdate + INTERVAL 1 MONTH)::DATE AS later FROM orders")
def q_fn_date(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.trunc("o_orderdate", "month").alias("month"), F.datediff("o_orderdate", F.lit("1995-01-01")).cast("long").alias("days"), F.add_months("o_orderdate", 1).alias("later"))


@query("SELECT l_orderkey, round(log10(l_extendedprice), 6) AS lg, round(exp(l_discount), 6) AS ex, floor(l_quantity / 10)::BIGINT AS bin FROM lineitem WHERE l_extendedprice > 0")
def q_fn_math(spark, d):
    return table(spark, d, "lineitem").filter("l_extendedprice > 0").select("l_orderkey", F.round(F.log10("l_extendedprice"), 6).alias("lg"), F.round(F.exp("l_discount"), 6).alias("ex"), F.floor(F.col("l_quantity") / 10).alias("bin"))


@query("SELECT vec_id, round(list_max(embedding)::DOUBLE, 5) AS top, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_position(embedding, list_max(embedding)) AS arg FROM embeddings")
def q_fn_array(spark, d):
    return table(spark, d, "embeddings").select("vec_id", F.round(F.array_max("embedding").cast("double"), 5).alias("top"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.array_position("embedding", F.array_max("embedding")).cast("int").alias("arg"))


@query("SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def q_fn_map(spark, d):
    c = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.array_join(F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("counts"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def q_fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT source, lang, docs FROM (SELECT source, lang, docs, row_number() OVER (PARTITION BY source ORDER BY docs DESC, lang) AS r FROM (SELECT source, lang, count(*) AS docs FROM documents WHERE n_chars >= 100 GROUP BY source, lang)) WHERE r = 1")
def q_sql_flagship(spark, d):
    table(spark, d, "documents").createOrReplaceTempView("tq_documents")
    return spark.sql("SELECT source, lang, docs FROM (SELECT source, lang, count(*) AS docs, row_number() OVER (PARTITION BY source ORDER BY count(*) DESC, lang) AS r FROM tq_documents WHERE n_chars >= :least GROUP BY source, lang) WHERE r = 1", args={"least": 100})


def _nations(spark, d):
    return table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")


def _format(kind: str, **options):
    def run(spark, d):
        return files.through(_nations(spark, d), kind, **options)

    run.__name__ = f"q_source_{kind}"
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation")(run)


_format("json")
_format("csv", header="true")
_format("orc")


@query("SELECT n_name AS value FROM nation")
def q_source_text(spark, d):
    return files.through(_nations(spark, d).select(F.col("n_name").alias("value")), "text")


@query("SELECT 1 AS files, true AS whole")
def q_source_binary(spark, d):
    """A file as bytes, as scanned documents come."""
    b = files.binary_files(spark, f"{d}/region.parquet")
    return b.agg(F.count(F.lit(1)).cast("int").alias("files"), F.bool_and(F.octet_length("content") == F.col("length")).alias("whole"))


@query("SELECT doc_id AS no, coalesce(lang, '') || ' ' || coalesce(source, '') || ' ' || coalesce(CAST(n_chars AS VARCHAR), '') AS line FROM documents")
def q_source_python(spark, d):
    """A data source written in Python reads a feed with a line for each document."""
    files.register(spark)
    part = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    line = F.concat(part("lang"), F.lit(" "), part("source"), F.lit(" "), part("n_chars"))
    return spark.read.format("numbered_lines").load(files.feed(table(spark, d, "documents").select(F.col("doc_id").alias("no"), line.alias("line"))))


@query("SELECT o_orderstatus, count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders GROUP BY ALL")
def q_sink_partitioned(spark, d):
    """Written in folders by value and read back with one folder per value."""
    out = files.partitioned(table(spark, d, "orders").select("o_orderkey", "o_orderstatus"), "o_orderstatus")
    return out.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"))


@query("SELECT n_name, length(regexp_replace(n_name, '[^aeiou]', '', 'g'))::BIGINT AS vowels FROM nation")
def q_udf_scalar(spark, d):
    return table(spark, d, "nation").select("n_name", files.vowels(F.col("n_name")).alias("vowels"))


@query("SELECT o_orderstatus, max(o_totalprice) - min(o_totalprice) AS spread FROM orders GROUP BY o_orderstatus")
def q_udf_aggregate(spark, d):
    return table(spark, d, "orders").groupBy("o_orderstatus").agg(files.spread(F.col("o_totalprice")).alias("spread"))


@query("SELECT item_id, generate_subscripts(string_split(text, chr(10)), 1)::INTEGER - 1 AS no, unnest(string_split(text, chr(10))) AS line FROM benchmark")
def q_udtf(spark, d):
    """A table function beside each row."""
    spark.udtf.register("split_lines", files.split_lines_function())
    table(spark, d, "benchmark").createOrReplaceTempView("benchmark_lines")
    return spark.sql("SELECT item_id, s.no, s.line FROM benchmark_lines, LATERAL split_lines(text) s")
