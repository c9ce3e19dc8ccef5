"""Tables in other formats, and a table function, a scalar function and an aggregate that are not built in."""

from __future__ import annotations

import io
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf
from pyspark.sql.types import StructType

from ..shared import Workspace


def through(df: DataFrame, kind: str, **options: str) -> DataFrame:
    """Written as files of a format in the shared folder and read back with the same schema."""
    space = Workspace(df.sparkSession, kind)
    path = f"{space.root}/data"
    df.write.format(kind).options(**options).save(path)
    reader = df.sparkSession.read.format(kind).options(**options)
    return (reader if kind == "orc" else reader.schema(df.schema)).load(path)


def partitioned(df: DataFrame, by: str, rows_per_file: int = 1_000_000) -> DataFrame:
    """Sink: Parquet folders by a column of few values; rows are dealt by value and hash, so that a large value has many writers."""
    space = Workspace(df.sparkSession, "partitioned")
    path = f"{space.root}/data"
    df.write.partitionBy(by).option("maxRecordsPerFile", rows_per_file).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def binary_files(spark: SparkSession, path: str) -> DataFrame:
    """Scanned files as they lie: path, length, content."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")


class _Lines(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.folder = options["path"]

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(self.folder)
        return [InputPartition(f.path) for f in store.get_file_info(fs.FileSelector(path)) if f.is_file and f.base_name.startswith("part-") and f.size]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from pyarrow import fs

        store, _ = fs.FileSystem.from_uri(self.folder)
        with store.open_input_stream(partition.value) as stream:
            for raw in io.TextIOWrapper(stream, encoding="utf-8", newline="\n"):
                no, _, line = raw.removesuffix("\n").partition("\t")
                yield int(no), line


class NumberedLines(DataSource):
    """A source in Python: files of "number, tab, line", a task per file (a stand-in for a crawler's feed)."""

    @classmethod
    def name(cls) -> str:
        return "numbered_lines"

    def schema(self) -> str:
        return "no long, line string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Lines(self.options)


def feed(df: DataFrame) -> str:
    """Writes (no, line), lines without line breaks, as a feed into the shared folder, and returns where it is."""
    folder = f"{Workspace(df.sparkSession, 'feed').root}/data"
    df.select(F.concat(F.col("no").cast("string"), F.lit("\t"), F.coalesce("line", F.lit(""))).alias("value")).write.text(folder)
    return folder if "://" in folder else f"file://{folder}"


def register(spark: SparkSession) -> None:
    spark.dataSource.register(NumberedLines)


def _vowels(text: pd.Series) -> pd.Series:
    return text.fillna("").str.count("[aeiou]").astype("int64")


def vowels(text: Column) -> Column:
    """Scalar function over Arrow batches."""
    return F.pandas_udf(_vowels, "long")(text)


def _spread(values: pd.Series) -> float:
    return float(values.max() - values.min()) if len(values) else 0.0


def spread(values: Column) -> Column:
    """Aggregate function over Arrow groups."""
    return F.pandas_udf(_spread, "double")(values)


def split_lines_function():
    """Table function: (no, line) of a text."""

    @udtf(returnType="no: int, line: string")
    class SplitLines:
        def eval(self, text: str):
            for i, line in enumerate((text or "").split("\n")):
                yield i, line

    return SplitLines
