"""Queries: selection of scanned files, layout tests of pages, documents from pages."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import config
from ..functions import text as T
from ..operators import layout
from ..registry import query, table

H = "CAST('0x' || substr(md5({x}), 1, 8) AS BIGINT)"
_KEYS = "o_custkey AS pdf_id, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS page_no"
# A file per customer; its number of pages is four times the square of its orders, so that every rule meets files.
_PDF = "p AS (SELECT c_custkey AS pdf_id, c_nationkey % 6 AS lang_no, c_custkey % 29 = 0 OR c_custkey % 31 = 0 AS broken, 150 + 25 * (c_custkey % 15) AS ppi, 4 * count(o_orderkey) * count(o_orderkey) AS n_pages FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY ALL)"


def files(spark, d):
    n = table(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    p = table(spark, d, "customer").join(n, F.col("c_custkey") == F.col("o_custkey"), "left")
    k, n = F.col("c_custkey"), F.coalesce("n", F.lit(0))
    return p.select(k.alias("pdf_id"), (F.col("c_nationkey") % 6).alias("lang_no"), ((k % 29 == 0) | (k % 31 == 0)).alias("broken"), (150 + 25 * (k % 15)).alias("ppi"), (4 * n * n).alias("n_pages"))


@query(f"""WITH {_PDF}, s AS (SELECT lang_no < 4 AS s1, lang_no < 4 AND NOT broken AS s2, lang_no < 4 AND NOT broken AND n_pages <= 2000 AS s3, lang_no < 4 AND NOT broken AND n_pages BETWEEN 25 AND 2000 AS s4, lang_no < 4 AND NOT broken AND n_pages BETWEEN 25 AND 2000 AND ppi >= 300 AS s5 FROM p)
SELECT count(*) AS found, count(*) FILTER (s1) AS supported, count(*) FILTER (s2) AS readable, count(*) FILTER (s3) AS not_long, count(*) FILTER (s4) AS not_short, count(*) FILTER (s5) AS sharp FROM s""")
def q_pdf_cascade(spark, d):
    """Surviving files after each selection step."""
    c = F.col
    return layout.surviving(files(spark, d), layout.selection_steps(c("lang_no") < 4, ~c("broken"), c("n_pages"), c("ppi")))


@query(f"WITH {_PDF} SELECT coalesce(lang_no::VARCHAR, 'all') AS lang, count(*) AS pdfs, sum(n_pages)::BIGINT AS pages FROM p GROUP BY ROLLUP (lang_no)")
def q_pdf_sources(spark, d):
    """Files and pages per language, and in all."""
    out = files(spark, d).rollup("lang_no").agg(F.count(F.lit(1)).alias("pdfs"), F.sum("n_pages").cast("long").alias("pages"))
    return out.select(F.coalesce(F.col("lang_no").cast("string"), F.lit("all")).alias("lang"), "pdfs", "pages")


_PAGES = f"pg AS (SELECT {_KEYS}, (o_orderkey % 100) / 100.0::DOUBLE AS area, 160 + (o_orderkey * 7) % 96 AS brightness, o_orderkey FROM orders)"


def pages(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    k = F.col("o_orderkey")
    return table(spark, d, "orders").select(F.col("o_custkey").alias("pdf_id"), F.row_number().over(w).alias("page_no"), (k % 100 / 100).alias("area"), (160 + (k * 7) % 96).alias("brightness"), k)


@query(f"WITH {_PAGES} SELECT pdf_id, avg(area) AS area, avg(brightness) AS brightness, avg(area) < 0.5 AND avg(brightness) > 200 AS gate FROM pg WHERE page_no <= 10 GROUP BY pdf_id")
def q_pdf_image_gate(spark, d):
    """Mean image area and brightness over the first ten consecutive pages."""
    return layout.image_gate(pages(spark, d))


@query(f"WITH {_PAGES}, r AS (SELECT pdf_id, avg(area) OVER w AS a, avg(brightness) OVER w AS b, count(*) OVER w AS n FROM pg WINDOW w AS (PARTITION BY pdf_id ORDER BY page_no ROWS BETWEEN CURRENT ROW AND 9 FOLLOWING)) SELECT pdf_id, bool_or(n = 10 AND a < 0.5 AND b > 200) AS gate FROM r GROUP BY pdf_id")
def q_pdf_image_gate_any(spark, d):
    """Variant: any full run of ten consecutive pages."""
    return layout.image_gate(pages(spark, d), mode="any")


_MERGED = f"{_PAGES}, k AS (SELECT pdf_id, page_no, page_no - row_number() OVER (PARTITION BY pdf_id ORDER BY page_no) AS run, o_orderkey FROM pg WHERE o_orderkey % 5 <> 0), merged AS (SELECT pdf_id, min(page_no)::INTEGER AS first_page, count(*) AS pages, string_agg('p' || o_orderkey, ' ' ORDER BY page_no) AS text FROM k GROUP BY pdf_id, run)"


def merged(spark, d):
    return layout.merge_pages(pages(spark, d).filter("o_orderkey % 5 <> 0").select("pdf_id", "page_no", F.concat(F.lit("p"), F.col("o_orderkey").cast("string")).alias("text")))


@query(f"WITH {_MERGED} SELECT * FROM merged")
def q_pdf_documents(spark, d):
    """Runs of surviving consecutive pages become documents; a gap starts a new one."""
    return merged(spark, d)


@query(f"WITH {_MERGED} SELECT c_nationkey % 6 AS lang_no, avg(pages)::DOUBLE AS mean_pages, count(*) AS docs FROM merged JOIN customer ON c_custkey = pdf_id GROUP BY ALL")
def q_pdf_pages_per_doc(spark, d):
    """Mean pages of a merged document per language."""
    lang = table(spark, d, "customer").select("c_custkey", (F.col("c_nationkey") % 6).alias("lang_no"))
    return merged(spark, d).join(lang, F.col("pdf_id") == F.col("c_custkey")).groupBy("lang_no").agg(F.avg("pages").alias("mean_pages"), F.count(F.lit(1)).alias("docs"))


_BOX = "bx AS (SELECT l_orderkey AS page_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate) AS box_id, (l_partkey % 500)::BIGINT AS x0, ((l_suppkey * 37) % 700)::BIGINT AS y0, (l_partkey % 500 + 20 + 4 * l_quantity)::BIGINT AS x1, ((l_suppkey * 37) % 700 + 15 + round(l_discount * 1000))::BIGINT AS y1 FROM lineitem)"


def boxes(spark, d):
    """Layout stand-in: a page per order, a box per line."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate")
    x, y = F.col("l_partkey") % 500, (F.col("l_suppkey") * 37) % 700
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("page_id"), F.row_number().over(w).alias("box_id"), x.alias("x0"), y.alias("y0"), (x + 20 + 4 * F.col("l_quantity")).cast("long").alias("x1"), (y + 15 + F.round(F.col("l_discount") * 1000)).cast("long").alias("y1"))


_INTER = "greatest(0, least(a.x1, b.x1) - greatest(a.x0, b.x0)) * greatest(0, least(a.y1, b.y1) - greatest(a.y0, b.y0))"
_AREA = "({b}.x1 - {b}.x0) * ({b}.y1 - {b}.y0)"


_FULL = _BOX + ", fb AS (SELECT *, (x1 - x0) * (y1 - y0) AS size, (x1 - x0) * (y1 - y0) * (95 - (page_id + box_id) % 40) // 100 AS inner_area, ((page_id * 7 + box_id * 13) % 100) / 100.0::DOUBLE AS conf FROM bx)"


def full_boxes(spark, d):
    """Boxes with the area of their paragraphs and the script confidence of their words."""
    size = F.expr("(x1 - x0) * (y1 - y0)")
    return boxes(spark, d).withColumn("inner", F.floor(size * (95 - (F.col("page_id") + F.col("box_id")) % 40) / 100)).withColumn("conf", (F.col("page_id") * 7 + F.col("box_id") * 13) % 100 / 100)


def box_pairs(b):
    """Overlapping pairs of a page: equi-join on the page, overlap as residual; pages are small."""
    o = b.select("page_id", *(F.col(c).alias(f"{c}_b") for c in ("box_id", "x0", "y0", "x1", "y1")))
    side = lambda lo, hi: F.greatest(F.lit(0), F.least(hi, f"{hi}_b") - F.greatest(lo, f"{lo}_b"))
    return b.join(o, "page_id").filter("box_id <> box_id_b").withColumn("inter", side("x0", "x1") * side("y0", "y1")).filter("inter > 0")


@query(f"WITH {_BOX} SELECT DISTINCT a.page_id, a.box_id::INTEGER AS box_id FROM bx a JOIN bx b ON a.page_id = b.page_id AND a.box_id <> b.box_id WHERE ({_AREA.format(b='a')} < {_AREA.format(b='b')} OR ({_AREA.format(b='a')} = {_AREA.format(b='b')} AND a.box_id > b.box_id)) AND ({_INTER}) * 10 > 7 * ({_AREA.format(b='a')})")
def q_box_suppress(spark, d):
    """Boxes that a larger one covers by more than 0.7; ties go by id."""
    p = box_pairs(boxes(spark, d))
    mine, other = F.expr("(x1 - x0) * (y1 - y0)"), F.expr("(x1_b - x0_b) * (y1_b - y0_b)")
    return p.filter(((mine < other) | ((mine == other) & (F.col("box_id") > F.col("box_id_b")))) & (F.col("inter") * 10 > 7 * mine)).select("page_id", "box_id").distinct()


@query(f"WITH {_BOX}, i AS (SELECT a.page_id, sum({_INTER}) / 2.0 AS inter FROM bx a JOIN bx b ON a.page_id = b.page_id AND a.box_id <> b.box_id GROUP BY 1), s AS (SELECT page_id, sum((x1 - x0) * (y1 - y0))::DOUBLE AS area FROM bx GROUP BY 1) SELECT page_id, round(inter / area, 6)::DOUBLE AS overlap FROM i JOIN s USING (page_id) WHERE inter / area > 0.1")
def q_page_overlap(spark, d):
    """Pages whose boxes overlap by more than a tenth of their area."""
    b = boxes(spark, d)
    i = box_pairs(b).groupBy("page_id").agg((F.sum("inter") / 2).alias("i"))
    s = b.groupBy("page_id").agg(F.sum(F.expr("(x1 - x0) * (y1 - y0)")).alias("s"))
    return i.join(s, "page_id").withColumn("o", F.col("i") / F.col("s")).filter("o > 0.1").select("page_id", F.round("o", 6).alias("overlap"))


def _sparse(axis: str, size: int):
    def run(spark, d):
        b = boxes(spark, d).select("page_id", "box_id", F.col(f"{axis}0").alias("a"), F.col(f"{axis}1").alias("b"))
        w = Window.partitionBy("page_id").orderBy("a", "b", "box_id").rowsBetween(Window.unboundedPreceding, -1)
        c = b.withColumn("reach", F.max("b").over(w)).withColumn("add", F.greatest(F.lit(0), F.col("b") - F.greatest(F.col("a"), F.coalesce("reach", "a"))))
        return c.groupBy("page_id").agg((F.sum("add") / size).alias("cover")).filter("cover < 0.3")

    run.__name__ = f"q_page_{'h' if axis == 'x' else 'v'}sparse"
    query(f"WITH {_BOX}, c AS (SELECT page_id, {axis}0 AS a, {axis}1 AS b, max({axis}1) OVER (PARTITION BY page_id ORDER BY {axis}0, {axis}1, box_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM bx) SELECT page_id, sum(greatest(0, b - greatest(a, coalesce(reach, a)))) / {size}::DOUBLE AS cover FROM c GROUP BY page_id HAVING sum(greatest(0, b - greatest(a, coalesce(reach, a)))) / {size}::DOUBLE < 0.3")(run)


_sparse("x", 600)
_sparse("y", 800)


_INTER_A = _INTER.replace("a.", "m.").replace("b.", "o.")
_LEFT = f"""left_over AS (SELECT * FROM fb m WHERE NOT EXISTS (SELECT 1 FROM fb o WHERE o.page_id = m.page_id AND o.box_id <> m.box_id AND (m.size < o.size OR (m.size = o.size AND m.box_id > o.box_id)) AND ({_INTER_A}) * 10 > 7 * m.size))"""
_COVERED = "SELECT page_id, sum(greatest(0, b - greatest(a, coalesce(reach, a)))) AS cover FROM (SELECT page_id, {k}0 AS a, {k}1 AS b, max({k}1) OVER (PARTITION BY page_id ORDER BY {k}0, {k}1, box_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM left_over) GROUP BY page_id"


@query(f"""WITH {_FULL}, {_LEFT}, cx AS ({_COVERED.format(k='x')}), cy AS ({_COVERED.format(k='y')}),
ov AS (SELECT m.page_id, sum({_INTER_A}) / 2.0 AS shared FROM left_over m JOIN left_over o ON m.page_id = o.page_id AND m.box_id <> o.box_id GROUP BY 1),
pg AS (SELECT page_id, count(*) AS n, sum(size) AS total, bool_or(size - inner_area > 0.3::DOUBLE * size) AS sparse, count(*) FILTER (conf < 0.2) AS doubtful FROM left_over GROUP BY 1)
SELECT pg.page_id, n::INTEGER AS n_boxes, array_to_string(list_filter([CASE WHEN cx.cover < 180 THEN 'h_sparse' END, CASE WHEN doubtful > 1 THEN 'low_confidence' END, CASE WHEN coalesce(shared, 0) > 0.1::DOUBLE * total THEN 'overlap' END, CASE WHEN sparse THEN 'sparse_block' END, CASE WHEN cy.cover < 240 THEN 'v_sparse' END], lambda x: x IS NOT NULL), ',') AS flags
FROM pg JOIN cx USING (page_id) JOIN cy USING (page_id) LEFT JOIN ov USING (page_id)""")
def q_page_filters(spark, d):
    """All page tests after suppression, with the reasons."""
    return layout.filter_pages(full_boxes(spark, d)).select("page_id", "n_boxes", F.array_join("flags", ",").alias("flags"))


@query()
def q_box_suppress_greedy(spark, d):
    """Variant: largest boxes first, and a suppressed box suppresses none (tested on hand-made pages)."""
    return layout.suppress_greedy(boxes(spark, d))


@query(f"WITH {_BOX} SELECT page_id, string_agg('w' || box_id, ' ' ORDER BY y0, x0, box_id) AS text FROM bx GROUP BY page_id")
def q_pdf_raw_text(spark, d):
    """Unfiltered text of a page in reading order."""
    return layout.raw_page_text(boxes(spark, d).withColumn("text", F.concat(F.lit("w"), F.col("box_id").cast("string"))))


# Typeset documents: 20 lines a page, a line is a block, a sentence a paragraph; a character is 6 wide, a line 15 high.
_SENT = r"list_filter(list_transform(string_split(regexp_replace({x}, '([.!?…।])\s+', '\1' || chr(10), 'g'), chr(10)), lambda s: trim(s)), lambda s: s <> '')"
_MIXED = "CASE WHEN doc_id % 23 = 0 THEN translate(text, 'aeiou', 'αειου') ELSE text END"
_SET = f"""ln AS (SELECT doc_id AS pdf_id, unnest(string_split({_MIXED}, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS no FROM documents WHERE doc_id % 3 = 1),
bl AS (SELECT pdf_id, no // 20 AS page_no, no % 20 AS block_id, 15 * (6 * length(line) + CASE WHEN {H.format(x="pdf_id || ':' || no")} % 9 = 0 THEN 600 ELSE 0 END) AS block_area, {_SENT.format(x='line')} AS ss FROM ln),
pa AS (SELECT pdf_id, page_no, block_id, block_area, unnest(ss) AS s, generate_subscripts(ss, 1) - 1 AS para_id FROM bl),
wd AS (SELECT pdf_id, page_no, block_id, para_id, unnest(list_filter(regexp_split_to_array(s, '\\s+'), lambda w: regexp_matches(w, '\\p{{L}}'))) AS w FROM pa)"""


def paragraphs(spark, d):
    docs = table(spark, d, "documents").filter("doc_id % 3 = 1")
    text = F.when(F.col("doc_id") % 23 == 0, F.translate("text", "aeiou", "αειου")).otherwise(F.col("text"))
    line = docs.select(F.col("doc_id").alias("pdf_id"), F.posexplode(F.split(text, "\n")).alias("no", "line"))
    margin = F.when(T.md5_int(F.concat_ws(":", "pdf_id", "no")) % 9 == 0, 600).otherwise(0)
    block = line.select("pdf_id", F.floor(F.col("no") / 20).alias("page_no"), (F.col("no") % 20).alias("block_id"), (15 * (6 * F.length("line") + margin)).alias("block_area"), F.posexplode(T.sentences(F.col("line"))).alias("para_id", "s"))
    return block.withColumn("area", 90 * F.length("s"))


def script_words(spark, d):
    """Words with the share of their letters that the language's script has."""
    words = paragraphs(spark, d).select("pdf_id", "page_no", "block_id", "para_id", F.posexplode(F.filter(T.words(F.col("s")), lambda w: w.rlike(r"\p{L}"))).alias("word_id", "text"))
    return words.withColumn("conf", F.length(F.regexp_replace("text", r"[^\p{IsLatin}]", "")) / F.length(F.regexp_replace("text", r"[^\p{L}]", "")))


@query(f"WITH {_SET}, b AS (SELECT pdf_id, page_no, block_id, max(block_area) AS block, sum(90 * length(s)) AS inner_area FROM pa GROUP BY ALL) SELECT pdf_id, page_no, count(*) AS blocks, count(*) FILTER (block - inner_area > block * 0.3::DOUBLE) AS sparse FROM b GROUP BY ALL")
def q_page_sparse_block(spark, d):
    """Blocks of a page whose paragraphs leave much of them empty."""
    return layout.sparse_blocks(paragraphs(spark, d))


@query(f"WITH {_SET}, p AS (SELECT pdf_id, page_no, block_id, para_id, avg(length(regexp_replace(w, '[^\\p{{Latin}}]', '', 'g')) / length(regexp_replace(w, '[^\\p{{L}}]', '', 'g'))::DOUBLE) AS conf FROM wd GROUP BY ALL) SELECT pdf_id, page_no, count(*) FILTER (conf < 0.8) AS doubtful FROM p GROUP BY ALL HAVING count(*) FILTER (conf < 0.8) > 1")
def q_page_script(spark, d):
    """Pages with more than one paragraph in doubtful script."""
    return layout.low_script_pages(script_words(spark, d), 0.8, 1)


def ocr_pages(spark, d):
    """A JSON result per page: blocks, paragraphs, words."""
    w = script_words(spark, d).join(paragraphs(spark, d).select("pdf_id", "page_no", "block_id", "para_id", "block_area", "area"), ["pdf_id", "page_no", "block_id", "para_id"])
    box = lambda area: F.array(F.lit(0), F.lit(0), (F.col(area) / 15).cast("int"), F.lit(15))
    kept = lambda *c: F.array_sort(F.collect_list(F.struct(*c)))
    p = w.groupBy("pdf_id", "page_no", "block_id", "block_area", "para_id", "area").agg(kept("word_id", "text", "conf").alias("words"))
    p = p.select("pdf_id", "page_no", "block_id", "block_area", "para_id", F.struct(box("area").alias("box"), F.transform("words", lambda x: F.struct(x["text"].alias("text"), x["conf"].alias("conf"))).alias("words")).alias("p"))
    b = p.groupBy("pdf_id", "page_no", "block_id", "block_area").agg(F.array_sort(F.collect_list(F.struct("para_id", "p"))).alias("ps"))
    b = b.select("pdf_id", "page_no", "block_id", F.struct(box("block_area").alias("box"), F.transform("ps", lambda x: x["p"]).alias("paragraphs")).alias("b"))
    pages = b.groupBy("pdf_id", "page_no").agg(F.array_sort(F.collect_list(F.struct("block_id", "b"))).alias("bs"))
    return pages.select("pdf_id", "page_no", F.to_json(F.struct(F.transform("bs", lambda x: x["b"]).alias("blocks"))).alias("json"))


@query(f"WITH {_SET} SELECT pdf_id, page_no, count(DISTINCT block_id) AS blocks, count(DISTINCT (block_id, para_id)) AS paragraphs, count(*) AS words, sum(length(w))::BIGINT AS chars FROM wd GROUP BY ALL")
def q_ocr_flatten(spark, d):
    """OCR results flattened to words, counted per page."""
    w = layout.flatten_ocr(ocr_pages(spark, d))
    return w.groupBy("pdf_id", "page_no").agg(F.count_distinct("block_id").alias("blocks"), F.count_distinct("block_id", "para_id").alias("paragraphs"), F.count("text").alias("words"), F.sum(F.length("text")).cast("long").alias("chars"))
