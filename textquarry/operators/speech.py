"""Speech: subtitle files, silence segments, pluggable transcription and punctuation, documents per recording."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def srt_lines(content: Column) -> Column:
    """Text lines of a subtitle file: no cue numbers, no times, no empty lines."""
    return F.filter(F.split(content, "\n"), lambda x: (x != "") & ~x.rlike(r"^\d+$") & ~x.contains(" --> "))


def srt_to_text(content: Column) -> Column:
    return F.array_join(srt_lines(content), "\n")


def strip_cues(line: Column) -> Column:
    """Without bracketed sounds, speaker names and continuation marks."""
    line = F.regexp_replace(F.regexp_replace(line, r"\[[^\]]*\]|\([^)]*\)", ""), "^[A-Z]+: ", "")
    return F.trim(F.regexp_replace(line, r"\.\.\.", ""))


def srt_documents(files: DataFrame) -> DataFrame:
    """One document per subtitle file (file_id, content)."""
    return files.select("file_id", F.array_join(F.transform(srt_lines(F.col("content")), strip_cues), "\n").alias("text"))


def segment_by_silence(frames: DataFrame, gap_ms: int) -> DataFrame:
    """Adds `seg`: a silence of more than *gap_ms* before a frame of a video starts a new one. A video is sorted in one task."""
    w = Window.partitionBy("video_id").orderBy("ms", "frame_id")
    pause = F.col("ms") - F.lag("ms").over(w)
    return frames.withColumn("_new", F.when(F.coalesce(pause > gap_ms, F.lit(True)), 1).otherwise(0)).withColumn("seg", F.sum("_new").over(w)).drop("_new")


def join_tokens(tokens: Column) -> Column:
    """Stub of a transcriber: the frames' tokens with blanks between."""
    return F.array_join(tokens, " ")


def transcribe(segmented: DataFrame, transcriber: Callable[[Column], Column] = join_tokens) -> DataFrame:
    """video_id, seg, start, end, text: the transcriber turns a segment's tokens in time order into text."""
    ordered = F.array_sort(F.collect_list(F.struct("ms", "frame_id", "token")))
    s = segmented.groupBy("video_id", "seg").agg(F.min("ms").alias("start"), F.max("ms").alias("end"), ordered.alias("f"))
    return s.select("video_id", "seg", "start", "end", transcriber(F.transform("f", lambda x: x["token"])).alias("text"))


def punctuate(segments: DataFrame, stop_ms: int) -> DataFrame:
    """Marks from pauses: a full stop before a long pause and at the end, else a comma; a capital letter after a full stop."""
    w = Window.partitionBy("video_id").orderBy("seg")
    stop = lambda pause: F.coalesce(pause >= stop_ms, F.lit(True))
    ends = stop(F.lead("start").over(w) - F.col("end"))
    begins = stop(F.col("start") - F.lag("end").over(w))
    first = F.when(begins, F.concat(F.upper(F.substring("text", 1, 1)), F.substring(F.col("text"), F.lit(2), F.length("text")))).otherwise(F.col("text"))
    return segments.select("video_id", "seg", F.concat(first, F.when(ends, ".").otherwise(",")).alias("text"))


def stitch(segments: DataFrame) -> DataFrame:
    """One document per video, its segments in time order."""
    a = segments.groupBy("video_id").agg(F.array_sort(F.collect_list(F.struct("seg", "text"))).alias("a"))
    return a.select("video_id", F.array_join(F.transform("a", lambda x: x["text"]), " ").alias("text"))


def manual_documents(transcripts: DataFrame, kind: str) -> DataFrame:
    """Transcripts written by people are documents as they are."""
    return transcripts.filter("text <> ''").select("doc_id", "lang", "text", F.lit("speech").alias("modality"), F.lit(kind).alias("kind"))


def speech_totals(instances: DataFrame) -> DataFrame:
    """Instances per kind and language with totals."""
    out = instances.rollup("kind", "lang").agg(F.count(F.lit(1)).alias("instances"))
    return out.select(F.coalesce("kind", F.lit("all")).alias("kind"), F.coalesce("lang", F.lit("all")).alias("lang"), "instances")
