"""Sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph


def write_violations(found: DataFrame, path: str) -> None:
    """rule_id and binding, a folder for each rule."""
    found.write.mode("overwrite").partitionBy("rule_id").parquet(path)


def write_report(report: DataFrame, path: str) -> None:
    report.write.mode("overwrite").option("header", True).csv(path)


def write_graph(graph: PropertyGraph, path: str) -> None:
    """Vertices by label and edges by label, so that a label's filter reads its folder only."""
    graph.vertices.write.mode("overwrite").partitionBy("vlabel").parquet(f"{path}/vertices")
    graph.edges.write.mode("overwrite").partitionBy("elabel").parquet(f"{path}/edges")


def write_bucketed(graph: PropertyGraph, table: str, buckets: int) -> None:
    """Edges as a table bucketed by src: joins on src need no shuffle of it."""
    graph.edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(table)


def flat_bindings(found: DataFrame) -> DataFrame:
    """rule_id and the binding as text, for sinks without nested types."""
    return found.select("rule_id", F.array_join(F.transform("binding", lambda b: F.concat(b["var"], F.lit("="), b["vid"].cast("string"))), ",").alias("binding"))


def discard(df: DataFrame) -> None:
    """Run a plan and keep nothing."""
    df.write.format("noop").mode("overwrite").save()
