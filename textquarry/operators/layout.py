"""Scanned pages: selection of files, layout tests of pages, and documents from runs of pages.

A page's boxes are gathered once (a page has few boxes, whatever the corpus), so suppression and all page tests share one shuffle by page. Coordinates are integers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .. import config
from ..functions.text import let

WIDTH, HEIGHT = 600, 800
#: Share of a box that a larger one may cover; share of a page's width or height under which it is sparse; overlap; empty share of a
#: block; script confidence; paragraphs under that confidence that a page may have.
SUPPRESS, SPARSE, OVERLAP, EMPTY, CONFIDENCE, DOUBTFUL = 0.7, 0.3, 0.1, 0.3, 0.2, 1
_OCR = "struct<blocks:array<struct<box:array<int>,paragraphs:array<struct<box:array<int>,words:array<struct<text:string,conf:double>>>>>>>"


def selection_steps(supported: Column, readable: Column, pages: Column, ppi: Column) -> dict[str, Column]:
    """The rules of the selection of files, in order."""
    return {
        "supported": supported,
        "readable": readable,
        "not_long": pages <= config.PDF_MAX_PAGES,
        "not_short": pages >= config.PDF_MIN_PAGES,
        "sharp": ppi >= config.PDF_MIN_PPI,
    }


def surviving(files: DataFrame, steps: dict[str, Column]) -> DataFrame:
    """Files left after each step, in one pass: every step is a cumulative condition."""
    alive, out = F.lit(True), [F.count(F.lit(1)).alias("found")]
    for name, rule in steps.items():
        alive = alive & rule
        out.append(F.count_if(alive).alias(name))
    return files.agg(*out)


def image_gate(pages: DataFrame, run: int = config.PDF_RUN, max_area: float = config.PDF_MAX_AREA, min_brightness: float = config.PDF_MIN_BRIGHTNESS, mode: str = "first") -> DataFrame:
    """pdf_id, gate: mean image area and brightness of *run* consecutive pages; the first ones, or `any` full run of them."""
    if mode == "first":
        means = pages.filter(F.col("page_no") <= run).groupBy("pdf_id").agg(F.avg("area").alias("area"), F.avg("brightness").alias("brightness"))
        return means.withColumn("gate", (F.col("area") < max_area) & (F.col("brightness") > min_brightness))
    w = Window.partitionBy("pdf_id").orderBy("page_no").rowsBetween(0, run - 1)
    means = pages.select("pdf_id", F.avg("area").over(w).alias("area"), F.avg("brightness").over(w).alias("brightness"), F.count(F.lit(1)).over(w).alias("n"))
    return means.groupBy("pdf_id").agg(F.bool_or((F.col("n") == run) & (F.col("area") < max_area) & (F.col("brightness") > min_brightness)).alias("gate"))


def flatten_ocr(pages: DataFrame, json_col: str = "json") -> DataFrame:
    """One row per word of a page's OCR result: place of block, paragraph and word, the paragraph's box, text and confidence."""
    p = pages.withColumn("_j", F.from_json(json_col, _OCR))
    keep = [c for c in pages.columns if c != json_col]
    p = p.select(*keep, F.posexplode_outer("_j.blocks").alias("block_id", "_b"))
    p = p.select(*keep, "block_id", F.col("_b.box").alias("block_box"), F.posexplode_outer("_b.paragraphs").alias("para_id", "_p"))
    p = p.select(*keep, "block_id", "block_box", "para_id", F.col("_p.box").alias("box"), F.posexplode_outer("_p.words").alias("word_id", "_w"))
    return p.select(*keep, "block_id", "block_box", "para_id", "box", "word_id", F.col("_w.text").alias("text"), F.col("_w.conf").alias("conf"))


def _size(b: Column) -> Column:
    return (b["x1"] - b["x0"]) * (b["y1"] - b["y0"])


def _shared(a: Column, b: Column) -> Column:
    side = lambda lo, hi: F.greatest(F.lit(0), F.least(a[hi], b[hi]) - F.greatest(a[lo], b[lo]))
    return side("x0", "x1") * side("y0", "y1")


def _suppressed(a: Column, boxes: Column, tau: float) -> Column:
    smaller = lambda b: (_size(a) < _size(b)) | ((_size(a) == _size(b)) & (a["box_id"] > b["box_id"]))
    return F.exists(boxes, lambda b: (a["box_id"] != b["box_id"]) & smaller(b) & (_shared(a, b) * 10 > F.lit(int(tau * 10)) * _size(a)))


def _cover(boxes: Column, low: str, high: str) -> Column:
    """Length of the union of the boxes' intervals on one axis."""
    intervals = F.array_sort(F.transform(boxes, lambda b: F.struct(b[low].alias("a"), b[high].alias("b"))))
    start = F.struct(F.lit(None).cast("long").alias("reach"), F.lit(0).cast("long").alias("sum"))
    more = lambda acc, i: F.struct(
        F.greatest(acc["reach"], i["b"].cast("long")).alias("reach"),
        (acc["sum"] + F.greatest(F.lit(0).cast("long"), i["b"] - F.greatest(i["a"], F.coalesce(acc["reach"], i["a"].cast("long"))))).cast("long").alias("sum"),
    )
    return F.aggregate(intervals, start, more, lambda acc: acc["sum"])


def filter_pages(boxes: DataFrame, tau: float = SUPPRESS) -> DataFrame:
    """page_id, n_boxes (left after suppression), flags, keep. Small boxes go first, since they raise false flags.

    *boxes*: page_id, box_id, x0, y0, x1, y1, `inner` (area of the paragraphs in the block) and `conf` (mean script confidence of its words).
    """
    pages = boxes.groupBy("page_id").agg(F.collect_list(F.struct("box_id", "x0", "y0", "x1", "y1", "inner", "conf")).alias("all"))
    left = pages.select("page_id", let(F.col("all"), lambda bs: F.filter(bs, lambda a: ~_suppressed(a, bs, tau))).alias("b"))
    total = lambda f: F.aggregate("b", F.lit(0).cast("long"), lambda s, x: s + f(x).cast("long"))
    twice = let(F.col("b"), lambda bs: F.aggregate(bs, F.lit(0).cast("long"), lambda s, x: s + F.aggregate(bs, F.lit(0).cast("long"), lambda t, y: t + F.when(x["box_id"] != y["box_id"], _shared(x, y)).otherwise(F.lit(0)).cast("long"))))
    rules = {
        "h_sparse": _cover(F.col("b"), "x0", "x1") < F.lit(SPARSE * WIDTH),
        "low_confidence": F.size(F.filter("b", lambda x: x["conf"] < CONFIDENCE)) > DOUBTFUL,
        "overlap": twice / 2 > F.lit(OVERLAP) * total(_size),
        "sparse_block": F.exists("b", lambda x: (_size(x) - x["inner"]) > F.lit(EMPTY) * _size(x)),
        "v_sparse": _cover(F.col("b"), "y0", "y1") < F.lit(SPARSE * HEIGHT),
    }
    flags = F.array_compact(F.array(*(F.when(rule, F.lit(name)) for name, rule in rules.items())))
    return left.select("page_id", F.size("b").alias("n_boxes"), flags.alias("flags")).withColumn("keep", F.size("flags") == 0)


def suppress_greedy(boxes: DataFrame, tau: float = SUPPRESS) -> DataFrame:
    """page_id, box_id of suppressed boxes: largest first, and a suppressed box suppresses none."""
    box = F.struct("x0", "y0", "x1", "y1", "box_id")
    order = F.array_sort(F.collect_list(F.struct((-_size(box)).alias("size"), "box_id", box.alias("b"))))
    pages = boxes.groupBy("page_id").agg(F.transform(order, lambda x: x["b"]).alias("a"))
    none = F.slice("a", 1, 0)
    covered = lambda kept, b: F.exists(kept, lambda k: _shared(b, k) > F.lit(tau) * _size(b))
    step = lambda acc, b: F.when(covered(acc["kept"], b), F.struct(acc["kept"].alias("kept"), F.concat(acc["gone"], F.array(b)).alias("gone"))).otherwise(F.struct(F.concat(acc["kept"], F.array(b)).alias("kept"), acc["gone"].alias("gone")))
    gone = F.aggregate("a", F.struct(none.alias("kept"), none.alias("gone")), step, lambda acc: acc["gone"])
    return pages.select("page_id", F.explode(gone).alias("b")).select("page_id", "b.box_id")


def sparse_blocks(paragraphs: DataFrame, tau: float = EMPTY, relative: bool = True) -> DataFrame:
    """Pages with their blocks and how many of them are sparse: empty area over tau, as share of the block or in square points.

    *paragraphs*: pdf_id, page_no, block_id, block_area, area (of the paragraph).
    """
    block = paragraphs.groupBy("pdf_id", "page_no", "block_id").agg(F.max("block_area").alias("block"), F.sum("area").alias("inner"))
    empty = F.col("block") - F.col("inner")
    rule = empty > F.col("block") * F.lit(tau) if relative else empty > F.lit(tau)
    return block.groupBy("pdf_id", "page_no").agg(F.count(F.lit(1)).alias("blocks"), F.count_if(rule).alias("sparse"))


def low_script_pages(words: DataFrame, tau: float, limit: int) -> DataFrame:
    """Pages with more than *limit* paragraphs whose words' mean script confidence is under tau."""
    paragraph = words.groupBy("pdf_id", "page_no", "block_id", "para_id").agg(F.avg("conf").alias("conf"))
    return paragraph.groupBy("pdf_id", "page_no").agg(F.count_if(F.col("conf") < tau).alias("doubtful")).filter(F.col("doubtful") > limit)


def raw_page_text(boxes: DataFrame) -> DataFrame:
    """Text of all boxes in reading order, without any filter: the noisy baseline."""
    ordered = F.array_sort(F.collect_list(F.struct("y0", "x0", "box_id", "text")))
    return boxes.groupBy("page_id").agg(F.array_join(F.transform(ordered, lambda b: b["text"]), " ").alias("text"))


def merge_pages(pages: DataFrame) -> DataFrame:
    """pdf_id, first_page, pages, text: runs of consecutive pages; a gap starts a new document."""
    k = pages.withColumn("run", F.col("page_no") - F.row_number().over(Window.partitionBy("pdf_id").orderBy("page_no")))
    g = k.groupBy("pdf_id", "run").agg(F.min("page_no").alias("first_page"), F.count(F.lit(1)).alias("pages"), F.array_sort(F.collect_list(F.struct("page_no", "text"))).alias("a"))
    return g.select("pdf_id", "first_page", "pages", F.array_join(F.transform("a", lambda x: x["text"]), " ").alias("text"))

