"""Personal data in running text, with disguises undone and offsets kept.

Two passes over each whole text:

* the *plain* pass finds e-mail addresses, IPv4 addresses, card numbers and phone numbers as written;
* the *disguise* pass runs a chain of transducers over the text (look-alike characters, spelled
  digits, "at"/"dot" wording). Each transducer is a list of edits `(start, end, replacement)`;
  applying it also rewrites an array that holds, for each character of the new text, the source span
  it came from. Detectors run on the normal form, and the array maps what they find back to code
  points of the source. A finding that lies inside a plain one of its kind is left out; one that extends or crosses plain spans
  is added to them. Plain spans stay as they are; redaction merges what overlaps.

Defined cases: null text counts as empty; empty text has no findings; ties cannot arise (findings of a
kind and pass never overlap); repeated rows are scanned each on its own; other columns are not read. Work is map-only
and linear in the text, so it needs no shuffle and a lost executor only repeats its own splits.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import steps

KINDS = ("email", "ip", "card", "phone")

_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]*\Z")
# A run of digits is only tried from its first digit: a start further right fails where that one fails.
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")

# Digit words of the four languages of the corpus.
DIGIT_WORDS = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}
AT_WORDS = ("at", "arobase", "arroba", "ät", "klammeraffe")
DOT_WORDS = ("dot", "punkt", "punto", "point", "period")
PLUS_WORDS = ("plus", "más", "mas")
# Final labels that make a bare "name at host dot label" an address.
TOP_LABELS = "com org net edu gov mil int info biz io ai app dev co uk us ca au de at ch fr es it nl be eu pt se no fi dk pl cz ru jp cn in br mx ar example test local invalid".split()
# The other country labels, and further common ones.
TOP_LABELS += """ac ad ae af ag ai al am ao aq as aw ax az ba bb bd bf bg bh bi bj bm bn bo bs bt bw by bz cc cd cf cg ci ck cl cm co cr cu cv cw cx cy dj dm do dz ec ee eg er et
 fj fk fm fo ga gd ge gf gg gh gi gl gm gn gp gq gr gs gt gu gw gy hk hm hn hr ht hu id ie il im iq ir is je jm jo ke kg kh ki km kn kp kr kw ky kz la lb lc li lk lr ls lt lu lv ly
 ma mc md me mg mh mk ml mm mn mo mp mq mr ms mt mu mv mw my mz na nc ne nf ng ni np nr nu nz om pa pe pf pg ph pk pm pn pr ps pw py qa re ro rs rw sa sb sc sd sg sh si sk sl sm sn so
 sr ss st su sv sx sy sz tc td tf tg th tj tk tl tm tn to tr tt tv tw tz ua ug uy uz va vc ve vg vi vn vu wf ws ye yt za zm zw
 xyz online site shop store tech club pro name blog cloud agency email mobi museum coop aero jobs travel""".split()
TOP_LABELS = sorted(set(TOP_LABELS))
# Labels that are common words: "at some point so".
WORD_LABELS = frozenset("am as by do is me my so to la ne sa ma re si su va ve mu pro name site store shop club cloud travel jobs online email agency".split())
# Words before "at" that are no mailbox: "look at example.com".
NO_LOCAL = frozenset(
    """look looks looked looking us me him her them you it this that these those here there available found find finds visit visits visited hosted host live lives living sold sell
 sells buy buys bought shop work works worked working more online offline back site sites page pages website websites blog read reads see seen sign signup register registered be is
 are was were been meet meets met only directly details information published posted post located based start starts started up out in on off and or but not now then today free
 video videos article articles story document documents download downloads downloaded shown listed online order orders ordered check checks arrive arrived aim aimed pointed point
 points click available accessible viewed view stay stays stayed book books booked learn even still just also again all both especially particularly starting store stores stored
 everyone everything someone something people researcher researchers engineer engineers editor writer director manager developer developers team teams colleagues friends
 employees professor student students teacher""".split()
)
# Words that are no host name: "look at the dot com".
NO_HOST = frozenset("the a an this that each every one any all its his her my our your their le la les un une der die das ein eine el los las una".split())

# Letters of other scripts that look like ASCII ones.
_LOOKALIKE = dict(zip("АВЕКМНОРСТХЅІЈаеорсухіјѕһԁΑΒΕΖΗΙΚΜΝΟΡΤΥΧοɡı", "ABEKMHOPCTXSIJaeopcyxijshdABEZHIKMNOPTYXogi", strict=True))
_LOOKALIKE |= {"＠": "@", "﹫": "@", "．": ".", "。": ".", "․": ".", "·": ".", "•": ".", "＋": "+", "‐": "-", "‑": "-", "‒": "-", "–": "-", "—": "-", "−": "-", "－": "-", "＿": "_", "（": "(", "）": ")", " ": " ", " ": " ", " ": " ", " ": " ", "　": " "}
_LOOKALIKE |= dict.fromkeys("​‌‍⁠﻿­", "")

_LONG_DASHES = "\u2013\u2014"


def _more_lookalikes() -> dict[str, str]:
    """Decimal digits and compatibility letters of Unicode, by rule."""
    import unicodedata

    out = {}
    for code in range(0x80, 0x1FBFA):
        c = chr(code)
        if (d := unicodedata.decimal(c, None)) is not None:
            out[c] = str(d)
        elif unicodedata.category(c)[0] == "L":
            plain = unicodedata.normalize("NFKC", c)
            if len(plain) == 1 and plain.isascii() and plain.isalpha() and c not in "ªº":
                out[c] = plain
    return out


_tables: dict[str, object] = {}


def _lookalikes() -> tuple[dict[str, str], re.Pattern]:
    if not _tables:
        table = _more_lookalikes() | _LOOKALIKE
        _tables["map"] = table
        _tables["find"] = re.compile("[" + "".join(map(re.escape, table)) + "]")
    return _tables["map"], _tables["find"]


def _any(words) -> str:
    return "|".join(sorted(words, key=lambda w: (-len(w), w)))


_GAP = r"[ \t]{1,8}"
_SPELLED = re.compile(rf"(?i)\b(?:(?:{_any(DIGIT_WORDS)})\b[ \t]{{0,8}}[-.,]?[ \t]{{0,8}}){{4,}}")
_SPELLED_HINT = re.compile(rf"[\s,.+()-](?:{_any(DIGIT_WORDS)})[ \t,.()-]{{1,8}}(?:(?:{_any(DIGIT_WORDS)}|{_any(DOT_WORDS)})\b|[0-9])|[0-9][ \t,.()-]{{1,8}}(?:(?:{_any(DOT_WORDS)})[ \t]{{1,8}})?(?:{_any(DIGIT_WORDS)})\b")
_DOT_WORD = rf"{_GAP}(?:{_any(DOT_WORDS)}){_GAP}"
# Digits and digit words in a row, with separators or dot words between them, possessive so that no start is tried twice over.
_ITEM = rf"(?:[0-9]++|\b(?:{_any(DIGIT_WORDS)})\b)"
_NUMBER = re.compile(rf"(?i)(?<![\w]){_ITEM}(?:(?:{_DOT_WORD}|[ \t().,-]{{0,8}}){_ITEM})++")
_WORD_RUN = re.compile(rf"(?i)\b(?:{_any(DIGIT_WORDS)})\b(?:[ \t]{{0,8}}[-,]?[ \t]{{0,8}}\b(?:{_any(DIGIT_WORDS)})\b)*")
_ANY_DOT = re.compile(rf"(?i){_DOT_WORD}|\.")
# Digit words that are common words as well: alone beside a whole number they are read as such.
_OFTEN_WORDS = frozenset("one oh un neuf null uno dos".split())
_ONE_WORD = re.compile(rf"(?i)\b(?:{_any(DIGIT_WORDS)})\b")
_PLUS = re.compile(rf"(?i)\b(?:{_any(PLUS_WORDS)}){_GAP}(?=[0-9])")
_LETTER_DIGITS = re.compile(r"(?<=[0-9])(?:[ -]?[OolI|]){1,4}(?=[ .-]?[0-9])")
_BRACKET_AT = re.compile(rf"(?i)[ \t]{{0,8}}(?:[\[({{<][ \t]{{0,8}}(?:{_any(AT_WORDS)}|@)[ \t]{{0,8}}[\])}}>]|(?<=[a-z0-9])_at_(?=[a-z0-9]))[ \t]{{0,8}}")
_BRACKET_DOT = re.compile(rf"(?i)[ \t]{{0,8}}(?:[\[({{<][ \t]{{0,8}}(?:{_any(DOT_WORDS)}|\.)[ \t]{{0,8}}[\])}}>]|(?<=[a-z0-9])_dot_(?=[a-z0-9]))[ \t]{{0,8}}")
_HOST_AHEAD = rf"(?=[A-Za-z0-9-]{{1,63}}(?:[ \t]{{0,8}}\.[ \t]{{0,8}}|(?i:{_DOT_WORD}))[A-Za-z])"
_SPACED = re.compile(rf"(?<=[A-Za-z0-9])[ \t]{{0,8}}@{_GAP}{_HOST_AHEAD}|(?<=[A-Za-z0-9]){_GAP}@[ \t]{{0,8}}{_HOST_AHEAD}")
_WORDED = re.compile(
    rf"(?i)(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9_%+-]{{0,63}}(?:{_GAP}(?:{_any(DOT_WORDS)}){_GAP}[A-Za-z0-9_%+-]{{1,63}}|\.[A-Za-z0-9_%+-]{{1,63}}){{0,4}}"
    rf"(?P<at>{_GAP}(?:{_any(AT_WORDS)}){_GAP}|@)(?P<host>[A-Za-z0-9-]{{1,63}}(?:(?:{_GAP}(?:{_any(DOT_WORDS)}){_GAP}|\.)[A-Za-z0-9-]{{1,63}}){{0,4}}"
    rf"{_GAP}(?:{_any(DOT_WORDS)}){_GAP}(?:{_any(TOP_LABELS)})|[A-Za-z0-9-]{{1,63}}(?:\.[A-Za-z0-9-]{{1,63}}){{0,4}}\.(?:{_any(TOP_LABELS)}))\b"
)
_DIGIT_DOT = re.compile(rf"(?i)(?<=[0-9]){_DOT_WORD}(?=[0-9])")
_AT_HOST = re.compile(rf"(?i){_GAP}(?:{_any(AT_WORDS)}){_GAP}(?=[A-Za-z0-9-]{{1,63}}(?:\.[A-Za-z0-9-]{{1,63}}){{0,4}}\.(?:{_any(TOP_LABELS)})\b)")
_DOT_GAP = re.compile(rf"(?i){_GAP}(?:{_any(DOT_WORDS)}){_GAP}")
_SPACED_DOT = re.compile(rf"(?i)@[A-Za-z0-9-]{{1,63}}({_GAP}\.[ \t]{{0,8}}|[ \t]{{0,8}}\.{_GAP})(?=(?:{_any(TOP_LABELS)})\b)")
_DOT_HINTS = tuple(f"{a}{w}{b}" for w in DOT_WORDS for a in " \t" for b in " \t")
_DIGITISH = re.compile(r"[0-9](?:[ -]?[0-9OolI|]){8,}")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else (d * 2 - 9 if d > 4 else d * 2)
    return total % 10 == 0


def plain_spans(text: str, cards: re.Pattern = _CARD) -> dict[str, list[tuple[int, int]]]:
    """Findings of each kind as written: leftmost, not overlapping, failing ones dropped."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    if "@" in text:
        done = 0
        for m in _DOMAIN.finditer(text):
            # The local part is the run of its characters before the sign, as far as the last finding.
            start, step = m.start(), 128
            while True:
                low = max(done, m.start() - step)
                start = _LOCAL.search(text, low, m.start()).start()
                if start > low or low == done:
                    break
                step *= 4
            if start < m.start():
                out["email"].append((start, m.end()))
                done = m.end()
    if not _DIGIT.search(text):
        return out
    if "." in text:
        out["ip"] = [m.span() for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split("."))]
    for m in cards.finditer(text):
        if m.end() - m.start() >= 13:
            digits = m.group().replace(" ", "").replace("-", "")
            if 13 <= len(digits) <= 19 and luhn(digits):
                out["card"].append(m.span())
    if "+" in text:
        out["phone"] = [m.span() for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m.group()) <= 15]
    return out


class Aligned:
    """A text derived from a source, and the source span of each of its characters."""

    __slots__ = ("text", "start", "end")

    def __init__(self, text: str, start: list[int] | range, end: list[int] | range) -> None:
        self.text, self.start, self.end = text, start, end

    @classmethod
    def of(cls, text: str) -> Aligned:
        return cls(text, range(len(text)), range(1, len(text) + 1))

    def edited(self, edits: list[tuple[int, int, str]]) -> Aligned:
        """Apply edits that are in order and do not overlap; new characters carry the whole span they replace."""
        if not edits:
            return self
        text, start, end, at = [], [], [], 0
        for a, b, new in edits:
            text.append(self.text[at:a])
            start.extend(self.start[at:a])
            end.extend(self.end[at:a])
            text.append(new)
            if new and b > a:
                start.extend([self.start[a]] * len(new))
                end.extend([self.end[b - 1]] * len(new))
            at = b
        text.append(self.text[at:])
        start.extend(self.start[at:])
        end.extend(self.end[at:])
        return Aligned("".join(text), start, end)

    def source(self, a: int, b: int) -> tuple[int, int]:
        return self.start[a], self.end[b - 1]


def _undo_lookalikes(t: Aligned) -> Aligned:
    if t.text.isascii():
        return t
    table, find = _lookalikes()
    if table.keys().isdisjoint(set(t.text)):
        return t
    return t.edited([(m.start(), m.end(), table[m.group()]) for m in find.finditer(t.text)])


def _number_edits(text: str) -> list[tuple[int, int, str]]:
    """Digit words of numbers that are long enough for a detector, or have the dots of an address."""
    edits = []
    for m in _NUMBER.finditer(text):
        runs = list(_WORD_RUN.finditer(text, m.start(), m.end()))
        if not runs:
            continue
        words = [_ONE_WORD.findall(r.group()) for r in runs]
        digits = sum(map(str.isdigit, m.group())) + sum(map(len, words))
        if digits < 9 and (digits < 4 or len(_ANY_DOT.findall(m.group())) < 3):
            continue
        at = max(0, m.start() - 1)
        for r, ws in zip(runs, words, strict=True):
            edge = r.start() == m.start() or r.end() == m.end()
            if edge and len(ws) == 1 and ws[0].lower() in _OFTEN_WORDS and any(plain_spans(text[at : r.start()] if r.end() == m.end() else text[r.end() : m.end()]).values()):
                continue
            edits.append((*r.span(), "".join(DIGIT_WORDS[w.lower()] for w in ws)))
    return edits


def _undo_spelled_digits(t: Aligned) -> Aligned:
    low = t.text.lower()
    if _SPELLED_HINT.search(" " + low):
        t = t.edited(_number_edits(t.text))
        edits = []
        for m in _SPELLED.finditer(t.text):
            words = list(_ONE_WORD.finditer(t.text, m.start(), m.end()))
            edits.append((words[0].start(), words[-1].end(), "".join(DIGIT_WORDS[w.group().lower()] for w in words)))
        t = t.edited(edits)
    if any(w in low for w in PLUS_WORDS):
        t = t.edited([(m.start(), m.end(), "+") for m in _PLUS.finditer(t.text)])
    if _DIGITISH.search(t.text):
        t = t.edited([(m.start(), m.end(), re.sub("[Oo]", "0", re.sub("[lI|]", "1", m.group()))) for m in _LETTER_DIGITS.finditer(t.text)])
    return t


def _undo_at_and_dot(t: Aligned) -> Aligned:
    """Wording is undone where a dot is disguised as well, where brackets mark it, or between a word that may be a mailbox and a host."""
    if any(c in t.text for c in "[({<") or "_at_" in t.text.lower():
        t = t.edited([(m.start(), m.end(), "@") for m in _BRACKET_AT.finditer(t.text)])
        t = t.edited([(m.start(), m.end(), ".") for m in _BRACKET_DOT.finditer(t.text)])
    if "@ " in t.text or " @" in t.text or "@\t" in t.text or "\t@" in t.text:
        t = t.edited([(m.start(), m.end(), "@") for m in _SPACED.finditer(t.text)])
        t = t.edited([(m.start(1), m.end(1), ".") for m in _SPACED_DOT.finditer(t.text)])
    low = t.text.lower()
    if any(h in low for h in _DOT_HINTS):
        t = t.edited([(m.start(), m.end(), ".") for m in _DIGIT_DOT.finditer(t.text)])
        t = t.edited(_worded_edits(t))
    edits = []
    for m in _AT_HOST.finditer(t.text):
        local = _LOCAL.search(t.text, max(0, m.start() - 64), m.start()).group()
        if local.strip("._%+-") and local.lower() not in NO_LOCAL and local[-1] not in ".%":
            edits.append((m.start(), m.end(), "@"))
    return t.edited(edits)


def _worded_edits(t: Aligned) -> list[tuple[int, int, str]]:
    edits = []
    for m in _WORDED.finditer(t.text):
        host = m.group("host")
        if re.split(r"[ \t.]", host, maxsplit=1)[0].lower() in NO_HOST:
            continue
        sure = m.group("at").strip().lower() != "at"
        if not sure and host.lower().split()[-1] in WORD_LABELS and host.lower().split()[-2:-1] not in ([], ["dot"]):
            continue
        if m.group("at") == "@" or _DOT_GAP.search(host) or _DOT_GAP.search(t.text, m.start(), m.start("at")):
            edits += [(m.start() + g.start(), m.start() + g.end(), ".") for g in _DOT_GAP.finditer(m.group()[: m.start("at") - m.start()])]
            if m.group("at") != "@":
                edits.append((*m.span("at"), "@"))
            edits += [(m.start("host") + g.start(), m.start("host") + g.end(), ".") for g in _DOT_GAP.finditer(host)]
    return edits


TRANSDUCERS = (_undo_lookalikes, _undo_spelled_digits, _undo_at_and_dot)


def normal_form(text: str) -> Aligned:
    out = Aligned.of(text)
    for undo in TRANSDUCERS:
        out = undo(out)
    return out


def disguised_spans(text: str, plain: dict[str, list[tuple[int, int]]]) -> dict[str, list[tuple[int, int]]]:
    """Findings that only the normal form shows, in source offsets."""
    if any(c in text for c in _LONG_DASHES):  # beside an address they are punctuation, not hyphens
        beside = {i for a, b in plain["email"] for i in (a - 1, b) if 0 <= i < len(text) and text[i] in _LONG_DASHES}
        text = "".join("\n" if i in beside else c for i, c in enumerate(text)) if beside else text
    normal = normal_form(text)
    if normal.text == text:
        return {k: [] for k in KINDS}
    out = {}
    for kind, spans in plain_spans(normal.text).items():
        mapped = [normal.source(a, b) for a, b in spans]
        # Plain spans of a kind are in order and do not overlap: only the last that starts at or before a can hold (a, b).
        starts = [x for x, _ in plain[kind]]
        out[kind] = [(a, b) for a, b in mapped if not ((k := bisect_right(starts, a)) and b <= plain[kind][k - 1][1])]
    return out


def merged(spans: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """Overlapping spans as one, of the kind of the longest (the first of equals)."""
    out: list[tuple[int, int, str, int]] = []
    for a, b, kind in sorted(spans):
        if out and a < out[-1][1]:
            x, y, k, size = out[-1]
            out[-1] = (x, max(y, b), *((kind, b - a) if b - a > size else (k, size)))
        else:
            out.append((a, b, kind, b - a))
    return [s[:3] for s in out]


SCHEMA = "doc_id long, plain array<struct<kind:string,start:int,end:int>>, added array<struct<kind:string,start:int,end:int>>"


def find_pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its id, the plain spans and the spans that the disguise pass adds."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        rows = lambda found: [{"kind": k, "start": a, "end": b} for k in KINDS for a, b in sorted(found[k])]
        for part in steps(batches, "text"):
            plain, added = [], []
            for text in part.column("text").to_pylist():
                found = plain_spans(text or "")
                plain.append(rows(found))
                added.append(rows(disguised_spans(text or "", found)))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(plain, span), pa.array(added, span)], ["doc_id", "plain", "added"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(scan, SCHEMA)


def redact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents with every finding replaced by its kind in angle brackets; other columns stay."""
    schema = docs.schema

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, text_col):
            out = []
            for text in part.column(text_col).to_pylist():
                if text is None:
                    out.append(None)
                    continue
                plain = plain_spans(text)
                added = disguised_spans(text, plain)
                pieces, at = [], 0
                for a, b, kind in merged([(a, b, k) for k in KINDS for a, b in [*plain[k], *added[k]]]):
                    pieces += [text[at:a], f"<{kind.upper()}>"]
                    at = b
                out.append("".join([*pieces, text[at:]]))
            i = part.schema.get_field_index(text_col)
            yield part.set_column(i, part.schema.field(i), pa.array(out, part.schema.field(i).type))

    return docs.mapInArrow(scan, schema)


def pii_digest(docs: DataFrame) -> DataFrame:
    """The contract's columns: counts and digest of the plain spans, all spans, and how many were added."""
    found = find_pii(docs)
    text = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    count = lambda kind: F.size(F.filter("plain", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    of_kind = lambda kind: F.array_sort(F.filter(F.concat("plain", "added"), lambda s: s["kind"] == kind))
    both = F.flatten(F.array(*(of_kind(k) for k in KINDS)))
    return found.select(
        "doc_id",
        *(count(k) for k in KINDS),
        F.sha2(F.array_join(F.transform("plain", text), ","), 256).alias("base_sha256"),
        F.array_join(F.transform(both, text), ",").alias("spans"),
        F.size("added").cast("long").alias("n_added"),
    )
