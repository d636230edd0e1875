"""Readers and writers around the record envelope: JSON lines, CSV, text, XML, ORC, Parquet, zip."""

from __future__ import annotations

import io
import uuid
import zipfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..plans.components import shared_base


def write_records(df: DataFrame, fmt: str, *partition_by: str) -> str:
    """Writes to a new path in the shared folder and returns it."""
    path = f"{shared_base(df.sparkSession)}/{uuid.uuid4().hex}"
    w = df.write.format(fmt)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)
    return path


def read_records(spark: SparkSession, path: str, fmt: str, schema: str, **options: str) -> DataFrame:
    """Reads with a stated schema; nothing is inferred from the data."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_text(spark: SparkSession, path: str, granularity: str = "line") -> DataFrame:
    """(path, pos, text) of text files: lines, paragraphs (blank lines between), or whole files."""
    whole = spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), F.col("value").alias("text"))
    if granularity == "file":
        return whole.select("path", F.lit(0).alias("pos"), "text")
    parts = F.split("text", "\n" if granularity == "line" else "\n[ \t]*\n+")
    return whole.select("path", F.posexplode(parts).alias("pos", "text")).filter(F.col("text") != "")


def read_html(spark: SparkSession, path: str) -> DataFrame:
    """(path, title, text) of HTML files, without markup."""
    from ..operators.clean import strip_markup

    page = spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), F.col("value").alias("html"))
    return page.select("path", F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1).alias("title"), strip_markup(F.col("html")).alias("text"))


def read_xml(spark: SparkSession, path: str, row_tag: str, schema: str) -> DataFrame:
    """Rows of XML files, one for each element `row_tag`."""
    return spark.read.format("xml").option("rowTag", row_tag).schema(schema).load(path)


def sections(texts: DataFrame, heading: str = r"(?m)^#+ ") -> DataFrame:
    """(path, pos, text): files of many articles (a book) cut where a heading stands."""
    parts = F.split(F.regexp_replace("text", heading, "\x1e$0"), "\x1e")
    return texts.select("path", F.posexplode(F.filter(parts, lambda x: F.trim(x) != "")).alias("pos", "text"))


def write_buckets(df: DataFrame, name: str, n: int, *by: str) -> str:
    """A table in the warehouse, dealt to n buckets and sorted by the columns, so that joins on them don't shuffle it."""
    df.write.bucketBy(n, *by).sortBy(*by).mode("overwrite").format("parquet").saveAsTable(name)
    return name


class ZippedLines(DataSource):
    """Source "zipped_lines": JSON lines of all members of zip archives; a task reads one member. Options: path (archives,
    separated by commas, that every executor can open). Schema: path, name, value."""

    @classmethod
    def name(cls) -> str:
        return "zipped_lines"

    def schema(self) -> str:
        return "path string, name string, value string"

    def reader(self, schema) -> DataSourceReader:
        return _ZippedReader(self.options["path"].split(","))


class _ZippedReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        out = []
        for p in self.paths:
            with zipfile.ZipFile(p) as z:
                out += [InputPartition((p, n)) for n in z.namelist()]
        return out

    def read(self, partition: InputPartition) -> Iterator[tuple[str, str, str]]:
        path, name = partition.value
        with zipfile.ZipFile(path) as z, z.open(name) as f:
            for line in io.TextIOWrapper(f, "utf-8", "replace"):
                if line.strip():
                    yield path, name, line.rstrip("\n")


def read_zip(spark: SparkSession, path: str) -> DataFrame:
    """(path, name, text) of the members of zip archives, read as binary files and unpacked in Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for p, data in zip(b.column("path").to_pylist(), b.column("content").to_pylist()):
                with zipfile.ZipFile(io.BytesIO(data)) as z:
                    for n in z.namelist():
                        yield pa.RecordBatch.from_arrays([pa.array([p]), pa.array([n]), pa.array([z.read(n).decode("utf-8", "replace")])], names=["path", "name", "text"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "path string, name string, text string")
