"""Structured Streaming forms of the intake: windows with watermarks and exact duplicates within a watermark.

`AvailableNow` turns a stream into a finite run, so that each stream has a batch result to equal.
"""

from __future__ import annotations

import uuid
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shared import shared_folder


def run_available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now into files of the shared folder, and read them back."""
    spark: SparkSession = stream.sparkSession
    folder, epochs = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}", set()

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/epoch={epoch}")
        epochs.add(epoch)

    stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{folder}/state").foreachBatch(keep).start().awaitTermination()
    if not epochs:
        return spark.createDataFrame([], stream.schema)
    last = [max(epochs)] if mode == "complete" else sorted(epochs)  # each complete result holds those before it
    return spark.read.schema(stream.schema).parquet(*(f"{folder}/out/epoch={e}" for e in last))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a file stream; the table is one file or a folder of files, and the pattern matches both."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/{name}.parque[t]")


def tumbling(events: DataFrame, size: str, late: str = "3 days", slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, late: str = "3 days") -> DataFrame:
    """Sessions per user: silences of more than *gap* end one; state is the open session of each user."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    s = e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), "n")


def running_attrition(docs: DataFrame, alive: dict) -> DataFrame:
    """Documents that pass each rule so far, per language."""
    kept, out = F.lit(True), [F.count(F.lit(1)).alias("docs")]
    for name, rule in alive.items():
        kept = kept & rule
        out.append(F.count_if(kept).alias(name))
    return docs.groupBy("lang").agg(*out)


def near_copies_available(bands: DataFrame) -> DataFrame:
    """(doc_id, band, first) of a stream of (doc_id, band, h): documents whose bucket held an earlier one, of a batch before or with a smaller id.

    State is a table of the first id of each bucket, in files by epoch; a repeated epoch writes its own again. Nothing runs per bucket.
    """
    spark = bands.sparkSession
    folder, epochs = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}", set()
    key = ["band", "h"]

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.select("doc_id", *key).write.mode("overwrite").parquet(f"{folder}/bands/epoch={epoch}")
        held = spark.read.schema(batch.select("doc_id", *key).schema).parquet(f"{folder}/bands/epoch={epoch}")
        least = held.groupBy(*key).agg(F.min("doc_id").alias("least"))
        before = sorted(e for e in epochs if e < epoch)
        if before:
            known = spark.read.schema("band int, h long, first long").parquet(*(f"{folder}/first/epoch={e}" for e in before))
            least = least.join(known, key, "left")
        else:
            least = least.withColumn("first", F.lit(None).cast("long"))
        least.filter("first is null").select(*key, F.col("least").alias("first")).write.mode("overwrite").parquet(f"{folder}/first/epoch={epoch}")
        found = held.join(least.select(*key, F.coalesce("first", "least").alias("first")), key).filter(F.col("doc_id") != F.col("first"))
        found.select("doc_id", "band", "first").write.mode("overwrite").parquet(f"{folder}/out/epoch={epoch}")
        epochs.add(epoch)

    bands.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{folder}/state").foreachBatch(keep).start().awaitTermination()
    schema = "doc_id long, band int, first long"
    return spark.read.schema(schema).parquet(*(f"{folder}/out/epoch={e}" for e in sorted(epochs))) if epochs else spark.createDataFrame([], schema)
