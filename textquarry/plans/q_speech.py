"""Queries: subtitles, segments, transcripts, totals."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import speech
from ..registry import query, table

_CUES = "(SELECT conv_id, turn, CASE turn % 3 WHEN 0 THEN '[music] ' || t WHEN 1 THEN 'ANNA: ' || t ELSE t || '...' END AS line FROM (SELECT conv_id, turn, replace(text, chr(10), ' ') AS t FROM conversations))"
_STRIP = "trim(regexp_replace(regexp_replace(regexp_replace(line, '\\[[^\\]]*\\]|\\([^)]*\\)', '', 'g'), '^[A-Z]+: ', ''), '\\.\\.\\.', '', 'g'))"


def subtitle_files(spark, d):
    """A subtitle file per conversation: number, times and line of each cue."""
    c = table(spark, d, "conversations").withColumn("t", F.replace("text", F.lit("\n"), F.lit(" ")))
    line = F.when(F.col("turn") % 3 == 0, F.concat(F.lit("[music] "), "t")).when(F.col("turn") % 3 == 1, F.concat(F.lit("ANNA: "), "t")).otherwise(F.concat("t", F.lit("...")))
    cue = F.concat_ws("\n", (F.col("turn") + 1).cast("string"), F.lit("00:00:01,000 --> 00:00:02,000"), line)
    files = c.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", cue.alias("c")))), lambda x: x["c"]), "\n\n").alias("content"))
    return files.select(F.col("conv_id").alias("file_id"), "content")


@query(f"SELECT conv_id AS file_id, string_agg(line, chr(10) ORDER BY turn) AS text FROM {_CUES} GROUP BY conv_id")
def q_srt_text(spark, d):
    """Subtitle files without numbers and times."""
    return subtitle_files(spark, d).select("file_id", speech.srt_to_text(F.col("content")).alias("text"))


@query(f"SELECT conv_id, turn, {_STRIP} AS line FROM {_CUES}")
def q_srt_clean(spark, d):
    """Cue lines without sounds, speaker names and continuation marks."""
    t = F.replace("text", F.lit("\n"), F.lit(" "))
    line = F.when(F.col("turn") % 3 == 0, F.concat(F.lit("[music] "), t)).when(F.col("turn") % 3 == 1, F.concat(F.lit("ANNA: "), t)).otherwise(F.concat(t, F.lit("...")))
    return table(spark, d, "conversations").select("conv_id", "turn", speech.strip_cues(line).alias("line"))


@query(f"SELECT conv_id AS file_id, string_agg({_STRIP}, chr(10) ORDER BY turn) AS text FROM {_CUES} GROUP BY conv_id")
def q_srt_documents(spark, d):
    """One document per subtitle file."""
    return speech.srt_documents(subtitle_files(spark, d))


_GAP = 6 * 3600 * 1000
_SEGS = f"""f AS (SELECT user_id AS video_id, event_id AS frame_id, epoch_us(ts) // 1000 AS ms, event_type AS token FROM events),
s AS (SELECT *, CASE WHEN ms - lag(ms) OVER w > {_GAP} OR lag(ms) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM f WINDOW w AS (PARTITION BY video_id ORDER BY ms, frame_id)),
n AS (SELECT *, sum(b) OVER (PARTITION BY video_id ORDER BY ms, frame_id)::BIGINT AS seg FROM s),
t AS (SELECT video_id, seg, min(ms) AS start, max(ms) AS "end", string_agg(token, ' ' ORDER BY ms, frame_id) AS text FROM n GROUP BY ALL),
pu AS (SELECT video_id, seg, CASE WHEN coalesce(start - lag("end") OVER v >= {4 * _GAP}, true) THEN upper(substr(text, 1, 1)) || substr(text, 2) ELSE text END || CASE WHEN coalesce(lead(start) OVER v - "end" >= {4 * _GAP}, true) THEN '.' ELSE ',' END AS text FROM t WINDOW v AS (PARTITION BY video_id ORDER BY seg))"""


def segments(spark, d):
    ms = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1000)
    frames = table(spark, d, "events").select(F.col("user_id").alias("video_id"), F.col("event_id").alias("frame_id"), ms.alias("ms"), F.col("event_type").alias("token"))
    return speech.segment_by_silence(frames, _GAP)


@query(f'WITH {_SEGS} SELECT video_id, seg, count(*) AS frames, min(ms) AS start, max(ms) AS "end" FROM n GROUP BY ALL')
def q_asr_segments(spark, d):
    """Segments between silences."""
    return segments(spark, d).groupBy("video_id", "seg").agg(F.count(F.lit(1)).alias("frames"), F.min("ms").alias("start"), F.max("ms").alias("end"))


@query(f"WITH {_SEGS} SELECT video_id, seg, text FROM t")
def q_asr_transcripts(spark, d):
    return speech.transcribe(segments(spark, d)).select("video_id", "seg", "text")


@query(f"WITH {_SEGS} SELECT video_id, seg, text FROM pu")
def q_asr_punctuated(spark, d):
    """Marks and capitals by the length of pauses."""
    return speech.punctuate(speech.transcribe(segments(spark, d)), 4 * _GAP)


@query(f"WITH {_SEGS} SELECT video_id, string_agg(text, ' ' ORDER BY seg) AS text FROM pu GROUP BY video_id")
def q_asr_documents(spark, d):
    """Frames to segments, transcripts, punctuation, one document per video."""
    return speech.stitch(speech.punctuate(speech.transcribe(segments(spark, d)), 4 * _GAP))


_KIND = "CASE doc_id % 2 WHEN 0 THEN 'course' ELSE 'radio' END"


def _manual(spark, d):
    docs = table(spark, d, "documents").filter("doc_id % 3 = 2")
    return speech.manual_documents(docs.filter("doc_id % 2 = 0"), "course").unionByName(speech.manual_documents(docs.filter("doc_id % 2 = 1"), "radio"))


@query(f"SELECT doc_id, lang, text, 'speech' AS modality, {_KIND} AS kind FROM documents WHERE doc_id % 3 = 2 AND text <> ''")
def q_speech_manual(spark, d):
    """Transcripts by people (courses, radio talks) as documents."""
    return _manual(spark, d)


@query(f"""WITH a AS (SELECT {_KIND} AS kind, lang FROM documents WHERE doc_id % 3 = 2 AND text <> '' UNION ALL SELECT 'subtitles', 'en' FROM (SELECT DISTINCT conv_id FROM conversations) UNION ALL SELECT 'video', 'en' FROM (SELECT DISTINCT user_id FROM events))
SELECT coalesce(kind, 'all') AS kind, coalesce(lang, 'all') AS lang, count(*) AS instances FROM a GROUP BY ROLLUP (kind, lang)""")
def q_speech_totals(spark, d):
    """Instances of speech per source and language, with totals."""
    other = lambda name, key, kind: table(spark, d, name).select(key).distinct().select(F.lit(kind).alias("kind"), F.lit("en").alias("lang"))
    return speech.speech_totals(_manual(spark, d).select("kind", "lang").unionByName(other("conversations", "conv_id", "subtitles")).unionByName(other("events", "user_id", "video")))
