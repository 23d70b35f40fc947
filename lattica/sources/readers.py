"""Graphs from files."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model.graph import PropertyGraph

FORMATS = ("parquet", "orc", "json", "csv", "tsv")


def read_table(spark: SparkSession, path: str, format: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table; for text formats give the schema, so that nothing is inferred."""
    if format not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    reader = spark.read
    if schema:
        reader = reader.schema(schema)
    if format in ("csv", "tsv"):
        return reader.option("header", True).option("sep", "," if format == "csv" else "\t").csv(path)
    return reader.format(format).load(path)


def read_graph(spark: SparkSession, vertices: str, edges: str, format: str = "parquet", directed: bool = True, vertex_schema: str | None = None, edge_schema: str | None = "src bigint, dst bigint, elabel string") -> PropertyGraph:
    """From a table of vertices and one of edges (src, dst, elabel); folders partitioned by label are read by label."""
    return PropertyGraph.of(read_table(spark, vertices, format, vertex_schema), read_table(spark, edges, format, edge_schema if format in ("csv", "tsv", "json") else None), directed)


def read_edge_list(spark: SparkSession, path: str, label: str = "edge") -> DataFrame:
    """src, dst, elabel from text lines "src dst" parted by white space or commas; lines of other kinds (headers, comments) are left out."""
    ends = F.split(F.trim("value"), r"[\s,]+")
    rows = spark.read.text(path).where(F.col("value").rlike(r"^\s*\d+[\s,]+\d+\s*$"))
    return rows.select(F.get(ends, F.lit(0)).cast("bigint").alias("src"), F.get(ends, F.lit(1)).cast("bigint").alias("dst"), F.lit(label).alias("elabel"))


_LINE = re.compile(r"\s*(\d+)[\s,]+(\d+)\s*$")


@dataclass
class _Range(InputPartition):
    path: str
    start: int
    end: int


class EdgeListReader(DataSourceReader):
    """Byte ranges of a file; a line belongs to the range in which it begins."""

    def __init__(self, options):
        self.path, self.step = options["path"], int(options.get("bytes", 64 << 20))

    def partitions(self):
        import os

        size = os.path.getsize(self.path)
        return [_Range(self.path, a, min(a + self.step, size)) for a in range(0, size, self.step)] or [_Range(self.path, 0, 0)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        with open(partition.path, "rb") as f:
            if partition.start:
                f.seek(partition.start - 1)
                f.readline()
            while f.tell() < partition.end and (line := f.readline()):
                if m := _LINE.match(line.decode("utf-8", "replace")):
                    yield int(m[1]), int(m[2])


class EdgeListSource(DataSource):
    """spark.dataSource.register(EdgeListSource); spark.read.format("edge_list").load(path): for files that all executors see."""

    @classmethod
    def name(cls) -> str:
        return "edge_list"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> EdgeListReader:
        return EdgeListReader(self.options)


def register_udtf(spark: SparkSession) -> None:
    """SQL: SELECT t.* FROM lines, LATERAL parse_edge_line(value) t"""
    from pyspark.sql.functions import udtf

    @udtf(returnType="src bigint, dst bigint")
    class ParseEdgeLine:
        def eval(self, line: str):
            import re

            if line and (m := re.match(r"\s*(\d+)[\s,]+(\d+)\s*$", line)):
                yield int(m[1]), int(m[2])

    spark.udtf.register("parse_edge_line", ParseEdgeLine)
