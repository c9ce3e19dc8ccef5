"""Secret scan with corpus-wide ownership frequency, with DataFrame functions only.

Per text, three plain patterns (assignment, access key, hex run) and one candidate pattern (long
mixed-case token) are marked in place by control characters, split, and turned into code-point spans by a
running sum over the pieces. Then every candidate value is hashed and aggregated over the corpus: in how
many repositories (different texts) and by how many owners (sources) it occurs. Copies of one text are one repository of one
owner, the least of its holders. A value that many owners write in texts of their own, or that every owner of the corpus
holds, is a widely copied example; any other is live-looking, in however many documents it stands. Live-looking candidates are added
to the plain spans.

Stepwise counts (hash and text, hash and owner, then hash) are combined before each shuffle, so a value that a third of
all rows hold costs one partial row per task; the join back is a plain equi-join that adaptive
execution splits. Texts are never shuffled by the scan.

Defined cases: null text counts as empty; empty text has no findings; the marks' own control characters in a text are
read as another control character of the same length, which no pattern accepts; repeated rows and copies of a text share
their findings and count as one repository; a null owner is an owner of its own; empty tables give empty
results; other columns are not read (`redact_live` carries them, whatever their names).

Tables written on the way hold spans and hashes of values, never a value.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace, unused

KINDS = ("assign", "access", "hex")

_ASSIGN = r"""((?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)"""
_ACCESS = r"(AKIA[A-Z0-9]{16,})"  # the run of key characters is maximal, so 20 characters in all
_HEX = r"([0-9a-f]{24,})"
_TOKEN = r"([A-Za-z0-9+/_=-]{20,})"
_ON, _MID, _OFF = "\x01", "\x02", "\x04"
_SAFE = "\x03\x03\x03"

#: A value is a widely copied example from so many owners with texts of their own on, or when all owners hold it and are so many.
MANY_OWNERS, ALL_OWNERS = 5, 3


#: Matches of one text beyond which spans are gathered in chunks of so many.
CHUNK = 512
_SPANS = "array<struct<start:int,end:int,value:string>>"


def _none(kind: str) -> Column:
    return F.array().cast(kind)


def _run(parts: Column, at: Column) -> Column:
    """struct(at, out): spans of the parts (head MID value OFF gap), the first of which stands at *at*, and where the last ends."""
    return F.aggregate(
        parts,
        F.struct(at.cast("int").alias("at"), _none(_SPANS).alias("out")),
        lambda acc, part: F.struct(
            (acc["at"] + F.length(part) - 2).alias("at"),
            F.concat(
                acc["out"],
                F.array(F.struct(acc["at"].alias("start"), (acc["at"] + F.instr(part, _OFF) - 2).cast("int").alias("end"), F.substring_index(F.substring_index(part, _OFF, 1), _MID, -1).alias("value"))),
            ),
        ),
    )


def _in_chunks(parts: Column, first: Column) -> Column:
    """The same spans from chunks, each counted from its own start and then moved, so that no array is grown match by match."""
    count = F.ceil(F.size(parts) / CHUNK).cast("int")
    chunks = F.transform(F.sequence(F.lit(0), count - 1), lambda c: _run(F.slice(parts, c * CHUNK + 1, F.lit(CHUNK)), F.lit(0)))
    starts = lambda c: F.aggregate(c, F.struct(first.alias("at"), _none("array<int>").alias("out")), lambda acc, x: F.struct((acc["at"] + x["at"]).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")), lambda acc: acc["out"])
    moved = lambda x, by: F.transform(x["out"], lambda s: F.struct((s["start"] + by).alias("start"), (s["end"] + by).alias("end"), s["value"].alias("value")))
    return F.element_at(F.transform(F.array(chunks), lambda c: F.flatten(F.zip_with(c, starts(c), moved))), 1)


def _pieces(text: Column, pattern: str, groups: int) -> Column:
    """Array of struct(start, end, value) of all matches; value is the last group."""
    mark = f"{_ON}$1{_MID}$2{_OFF}" if groups == 2 else f"{_ON}{_MID}$1{_OFF}"
    marked = F.split(F.regexp_replace(text, F.lit(pattern), F.lit(mark)), _ON, -1)

    def spans(parts: Column) -> Column:
        # All parts but the first begin with a match.
        rest, first = F.slice(parts, F.lit(2), F.greatest(F.size(parts) - 1, F.lit(0))), F.length(F.element_at(parts, 1))
        many = F.when(F.size(parts) <= CHUNK, _run(rest, first)["out"]).otherwise(F.element_at(F.transform(F.array(rest), lambda r: _in_chunks(r, first)), 1))
        return F.when(F.size(parts) > 1, many).otherwise(_none(_SPANS))

    return F.element_at(F.transform(F.array(marked), spans), 1)


def _kind(spans: Column, kind: str, order: int) -> Column:
    """Spans without their values: place, kind, length and hash of the value."""
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), F.lit(order).alias("rank"), F.lit(kind).alias("kind"), s["end"].alias("end"), F.length(s["value"]).alias("size"), F.xxhash64(s["value"]).alias("a"), F.xxhash64(F.lit(7), s["value"]).alias("b")))


def _mixed(value: Column) -> Column:
    """Looks random: upper and lower case, digits, many different characters."""
    return value.rlike("[A-Z]") & value.rlike("[a-z]") & value.rlike("[0-9].*[0-9]") & (F.size(F.array_distinct(F.split(value, ""))) >= 12)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source") -> DataFrame:
    """Per document: id, owner, text hash, `plain` spans and `extra` candidates outside them."""
    text = F.translate(F.coalesce(F.col(text_col), F.lit("")), _ON + _MID + _OFF, _SAFE)
    text = F.when(F.col(text_col).rlike(f"[{_ON}{_MID}{_OFF}]"), text).otherwise(F.coalesce(F.col(text_col), F.lit("")))
    df = docs.select(F.col(id_col).alias("doc_id"), F.col(owner_col).alias("owner"), F.xxhash64(F.col(text_col)).alias("th"), text.alias("t"))
    empty = F.array().cast("array<struct<start:int,end:int,value:string>>")
    assign = F.filter(_pieces(F.col("t"), _ASSIGN, 2), lambda s: F.length(s["value"]) >= 6)
    df = df.select(
        "doc_id", "owner", "th",
        assign.alias("assign"),
        F.when(F.col("t").contains("AKIA"), _pieces(F.col("t"), _ACCESS, 1)).otherwise(empty).alias("access"),
        _pieces(F.col("t"), _HEX, 1).alias("hex"),
        F.filter(_pieces(F.col("t"), _TOKEN, 1), lambda s: _mixed(s["value"])).alias("token"),
    )
    plain = F.concat(*(_kind(F.col(k), k, i) for i, k in enumerate(KINDS)))
    df = df.withColumn("plain", F.array_sort(plain))
    extra = F.filter("token", lambda s: ~F.exists("plain", lambda p: (p["start"] < s["end"]) & (s["start"] < p["end"])))
    return df.select("doc_id", "owner", "th", "plain", _kind(extra, "token", len(KINDS)).alias("extra"))


def value_ownership(found: DataFrame) -> DataFrame:
    """Per value hash: `owners`, `repos`, `live`."""
    owner = F.coalesce(F.col("owner"), F.lit(""))
    everyone = found.agg(F.count_distinct(owner)).first()[0]
    values = found.select("th", owner.alias("owner"), F.explode(F.array_distinct(F.transform(F.concat("plain", "extra"), lambda s: F.struct(s["a"].alias("a"), s["b"].alias("b"))))).alias("h"))
    held = values.groupBy("h.a", "h.b", "owner", "th").agg(F.count(F.lit(1)).alias("copies"))
    holders = held.groupBy("a", "b", "owner").agg(F.count(F.lit(1)).alias("texts")).groupBy("a", "b").agg(F.count(F.lit(1)).alias("holders"))
    by_text = held.groupBy("a", "b", "th").agg(F.min("owner").alias("owner"))
    by_owner = by_text.groupBy("a", "b", "owner").agg(F.count(F.lit(1)).alias("repos"))
    totals = by_owner.groupBy("a", "b").agg(F.count(F.lit(1)).alias("owners"), F.sum("repos").alias("repos")).join(holders, ["a", "b"])
    example = (F.col("owners") >= MANY_OWNERS) | ((F.col("holders") == everyone) & (F.col("holders") >= ALL_OWNERS))
    return totals.select("a", "b", "owners", "repos", (~example).alias("live"))


def secret_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source") -> DataFrame:
    """Per document: `doc_id`, `plain` spans, `added` live-looking spans, `live` (spans of either kind whose value is live-looking)."""
    found = Workspace(docs.sparkSession, "secrets").write(scan(docs, id_col, text_col, owner_col))
    owned = value_ownership(found)
    spans = found.select("doc_id", "th", F.explode(F.concat("plain", "extra")).alias("s")).select("doc_id", "th", "s", "s.a", "s.b")
    live = spans.join(owned.filter("live").select("a", "b"), ["a", "b"]).groupBy(F.col("doc_id").alias("_d"), F.col("th").alias("_t")).agg(F.array_sort(F.collect_set("s")).alias("live"))
    out = found.join(live.hint("shuffle_hash"), found["doc_id"].eqNullSafe(live["_d"]) & (found["th"] == live["_t"]), "left")
    none = F.array().cast(found.schema["plain"].dataType)
    out = out.withColumn("live", F.coalesce("live", none))
    return out.select("doc_id", "th", "plain", F.filter("live", lambda s: s["kind"] == "token").alias("added"), "live")


def secret_digest(docs: DataFrame) -> DataFrame:
    found = secret_scan(docs.select("doc_id", "text", "source"))
    said = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    count = lambda kind: F.size(F.filter("plain", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(
        "doc_id",
        *(count(k) for k in KINDS),
        F.sha2(F.array_join(F.transform("plain", said), ","), 256).alias("base_sha256"),
        F.array_join(F.transform(F.array_sort(F.concat("plain", "added")), said), ",").alias("spans"),
        F.size("added").cast("long").alias("n_added"),
        F.size("live").cast("long").alias("n_live"),
    )


def redact_live(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source") -> DataFrame:
    """The documents with live-looking values replaced by `<SECRET>`; examples that many owners copy stay.

    A value is replaced by its exact span; overlapping spans are replaced once.
    """
    found = secret_scan(docs, id_col, text_col, owner_col)
    doc, th, live, own = (unused(c, docs) for c in ("_doc", "_th", "_live", "_own_th"))
    hit = found.filter(F.size("live") > 0).select(F.col("doc_id").alias(doc), F.col("th").alias(th), F.col("live").alias(live)).dropDuplicates([doc, th])
    joined = docs.withColumn(own, F.xxhash64(F.col(text_col))).join(hit.hint("shuffle_hash"), F.col(id_col).eqNullSafe(F.col(doc)) & (F.col(own) == F.col(th)), "left")
    text = F.col(text_col)
    cut = F.aggregate(
        F.col(live),
        F.struct(F.lit(0).alias("at"), F.lit("").alias("out")),
        lambda acc, s: F.when(s["start"] < acc["at"], acc).otherwise(
            F.struct(s["end"].alias("at"), F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["end"] - s["size"] - acc["at"]), F.lit("<SECRET>")).alias("out"))
        ),
        lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))),
    )
    return joined.withColumn(text_col, F.when(F.col(live).isNotNull(), cut).otherwise(text)).drop(doc, th, live, own)
