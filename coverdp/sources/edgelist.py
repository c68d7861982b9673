"""Edge files: a reader for plain adjacency text as a Spark data source, and round trips through the built-in formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeListSource(DataSource):
    """format("edgelist").option("lines", "1 2;2 3"): edges from a short inline text, for fixtures and shells. Files go through read_edge_text."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return EdgeListReader(self.options)


class EdgeListReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.lines = [x.strip() for x in options.get("lines", "").split(";") if x.strip()]

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((i, i + 1000)) for i in range(0, len(self.lines), 1000)]

    def read(self, partition):
        a, z = partition.value
        for line in self.lines[a:z]:
            src, dst = line.split()[:2]
            yield min(int(src), int(dst)), max(int(src), int(dst))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeListSource)


def read_edge_text(spark: SparkSession, path: str) -> DataFrame:
    """src, dst from text files of two ids a line; lines that begin with # and lines without two numbers are left out."""
    parts = F.split(F.trim("value"), r"\s+")
    a, b = F.try_to_number(F.get(parts, F.lit(0)), F.lit("999999999999999999")).cast("long"), F.try_to_number(F.get(parts, F.lit(1)), F.lit("999999999999999999")).cast("long")
    return spark.read.text(path).where(~F.col("value").startswith("#")).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).where("src is not null and dst is not null and src <> dst").distinct()


def write_edges(edges: DataFrame, path: str, kind: str) -> None:
    """parquet, orc, csv, json or text (two ids a line)."""
    if kind == "text":
        edges.select(F.concat_ws(" ", "src", "dst").alias("value")).write.text(path)
    else:
        edges.write.format(kind).option("header", "true").save(path)


def read_edges(spark: SparkSession, path: str, kind: str) -> DataFrame:
    if kind == "text":
        return read_edge_text(spark, path)
    return spark.read.schema("src bigint, dst bigint").format(kind).option("header", "true").load(path)
