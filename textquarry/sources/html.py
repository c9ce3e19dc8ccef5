"""Raw web pages: main content, plain tag strip as baseline, URLs and hosts."""

from __future__ import annotations

from collections.abc import Iterator
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ENTITIES = (("&nbsp;", " "), ("&copy;", "©"), ("&middot;", "·"), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"))


def decode(text: Column) -> Column:
    """Named entities; the ampersand last, so that nothing is decoded twice."""
    for a, b in ENTITIES:
        text = F.replace(text, F.lit(a), F.lit(b))
    return text


def extract_main(pages: DataFrame) -> DataFrame:
    """page_id, url, title, lang_hint, text by ordered expressions: no Python, one pass, pages of any size."""
    html = F.regexp_replace("html", r"(?s)<!--.*?-->", "")
    html = F.regexp_replace(html, r"(?s)<(script|style|nav|footer)\b[^>]*>.*?</(script|style|nav|footer)>", "")
    body = F.regexp_extract(html, r"(?s)<article[^>]*>(.*)</article>", 1)
    body = F.regexp_replace(body, r"(?s)<h1[^>]*>.*?</h1>", "")
    body = F.regexp_replace(body, r"<br\s*/?>|</p>", "\n")
    body = F.regexp_replace(body, r"<[^>]+>", "")
    return pages.select(
        "page_id", "url",
        decode(F.regexp_extract("html", r"(?s)<title>(.*?)</title>", 1)).alias("title"),
        F.regexp_extract("html", r'<html[^>]*lang="([a-z]+)"', 1).alias("lang_hint"),
        F.rtrim(decode(body), F.lit("\n")).alias("text"),
    )


class _Main(HTMLParser):
    SKIP = {"script", "style", "nav", "footer", "h1", "head"}

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.out: list[str] = []
        self.skip = self.inside = 0

    def handle_starttag(self, tag, attrs):
        if tag in self.SKIP:
            self.skip += 1
        elif tag == "article":
            self.inside += 1
        elif tag == "br" and self.inside and not self.skip:
            self.out.append("\n")

    def handle_endtag(self, tag):
        if tag in self.SKIP:
            self.skip = max(0, self.skip - 1)
        elif tag == "article":
            self.inside -= 1
        elif tag == "p" and self.inside and not self.skip:
            self.out.append("\n")

    def handle_data(self, data):
        if self.inside and not self.skip:
            self.out.append(data)


def extract_dom(pages: DataFrame) -> DataFrame:
    """page_id, text by a real parser: slower, for markup that the expressions can't follow."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for html in batch.column("html").to_pylist():
                parser = _Main()
                parser.feed(html or "")
                out.append("".join(parser.out).rstrip("\n"))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), pa.array(out, pa.string())], ["page_id", "text"])

    return pages.select("page_id", "html").mapInArrow(run, "page_id long, text string")


def strip_tags(html: Column) -> Column:
    """Baseline: only the tags go, so scripts, menus and footers stay."""
    return F.regexp_replace(html, r"<[^>]+>", " ")


def canonical_url(url: Column) -> Column:
    """Lower-case scheme-free host without www or m, path without file ending or final slash, no query or fragment."""
    bare = F.regexp_replace(F.regexp_replace(url, r"^https?://", ""), r"[?#].*$", "")
    host = F.regexp_replace(F.lower(F.regexp_extract(bare, r"^([^/]*)", 1)), r"^(www|m)\.", "")
    path = F.regexp_replace(F.regexp_replace(F.regexp_extract(bare, r"^[^/]*(.*)$", 1), r"\.html?$", ""), r"/+$", "")
    return F.concat(host, path)


def host(url: Column) -> Column:
    return F.regexp_extract(url, r"^https?://([^/?#]+)", 1)
