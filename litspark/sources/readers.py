"""Readers: pages as regions through the Python data source API, and plain text, CSV, JSON, ORC and binary files."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from litspark.operators.parse import REGION, regions


class PageFile(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class RegionReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self) -> list[PageFile]:
        import glob
        import os

        path = self.options["path"]
        return [PageFile(p) for p in sorted(glob.glob(os.path.join(path, "*.html")) if os.path.isdir(path) else glob.glob(path))]

    def read(self, partition: PageFile) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8", errors="replace") as file:
            page = file.read()
        for region in regions(page):
            yield (partition.path, *region)


class HtmlRegions(DataSource):
    """``spark.read.format("html_regions").load(folder)``: one row per region of each ``.html`` file on a mounted path."""

    @classmethod
    def name(cls) -> str:
        return "html_regions"

    def schema(self) -> str:
        return f"path string, {REGION}"

    def reader(self, schema) -> RegionReader:
        return RegionReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(HtmlRegions)


def binary_pages(spark: SparkSession, path: str, pattern: str = "*.html") -> DataFrame:
    """(page_id, url, html) of page files through Spark's binary reader, from any store."""
    from pyspark.sql import functions as F

    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path)
    return files.select(F.xxhash64("path").alias("page_id"), F.col("path").alias("url"), F.decode("content", "UTF-8").alias("html"))


FORMATS = ("json", "csv", "orc", "parquet", "text")


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write and read back with the same schema."""
    if kind not in FORMATS:
        raise ValueError(f"one of {FORMATS}")
    writer, reader = df.write.mode("overwrite").format(kind), df.sparkSession.read.format(kind)
    if kind == "csv":
        writer, reader = writer.options(header=True, escape='"', multiLine=True), reader.options(header=True, escape='"', multiLine=True)
    writer.save(path)
    return (reader if kind == "text" else reader.schema(df.schema)).load(path)
