"""Graphs written once to the shared folder: vertices in folders by label, arcs by kind (edge label and the labels of both ends).

A pattern edge then reads the folders of its kind only, and the labels of its ends need no join. Counts by kind and degree
classes are made while the graph is stored; planners read them from the driver, where they are as few as there are kinds.
"""

from __future__ import annotations

import hashlib
import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.store import exists, files_of, fresh_path
from .graph import Facts, PropertyGraph


def _balanced(df: DataFrame, *by: str) -> DataFrame:
    """Files by key without one task per key: small parts are joined and large ones split at run time."""
    return df.hint("rebalance", *[F.col(c) for c in by])


def stored(graph: PropertyGraph, version: str, path: str | None = None) -> PropertyGraph:
    """Write the graph below a path of the shared folder and return the graph that reads it. version names its contents."""
    spark = graph.vertices.sparkSession
    path = path or fresh_path(spark, "graph")
    _balanced(graph.vertices, "vlabel").write.mode("overwrite").partitionBy("vlabel").parquet(f"{path}/vertices")
    label = spark.read.schema(graph.vertices.schema).parquet(f"{path}/vertices").select("vid", "vlabel")
    arcs = graph.edges.join(label.select(F.col("vid").alias("src"), F.col("vlabel").alias("src_label")), "src", "left")
    arcs = arcs.join(label.select(F.col("vid").alias("dst"), F.col("vlabel").alias("dst_label")), "dst", "left")
    arcs = arcs.select("src", "dst", "elabel", "src_label", "dst_label")
    _balanced(arcs, "elabel", "src_label", "dst_label").write.mode("overwrite").partitionBy("elabel", "src_label", "dst_label").parquet(f"{path}/arcs")
    _write_facts(spark, path, _facts(spark, path, graph, version))
    return load(spark, path, version)


def _read(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    # folders' names give the labels; they are text whatever they look like
    inferred = spark.conf.get("spark.sql.sources.partitionColumnTypeInference.enabled")
    spark.conf.set("spark.sql.sources.partitionColumnTypeInference.enabled", "false")
    try:
        return spark.read.parquet(f"{path}/vertices"), spark.read.parquet(f"{path}/arcs") if exists(spark, f"{path}/arcs/_SUCCESS") and files_of(spark, f"{path}/arcs") else None
    finally:
        spark.conf.set("spark.sql.sources.partitionColumnTypeInference.enabled", inferred)


def _facts(spark: SparkSession, path: str, graph: PropertyGraph, version: str) -> dict:
    vertices, arcs = _read(spark, path)
    plain = [(n, t) for n, t in graph.catalog.items() if isinstance(t, T.AtomicType)]
    measures = [F.count(F.lit(1)).alias("n")]
    for i, (n, t) in enumerate(plain):
        measures += [F.count(n).alias(f"h{i}"), F.approx_count_distinct(n).alias(f"d{i}"), (F.count_if(F.col(n)) if isinstance(t, T.BooleanType) else F.lit(None).cast("bigint")).alias(f"t{i}")]
    rows = vertices.groupBy("vlabel").agg(*measures).collect()  # one row per label
    out = {"version": version, "directed": graph.directed, "vertices": [(r["vlabel"], r["n"]) for r in rows], "degrees": [], "several": False}
    out["values"] = [[r["vlabel"], n, r[f"h{i}"], r[f"d{i}"], r[f"t{i}"]] for r in rows for i, (n, _) in enumerate(plain)]
    if arcs is None:
        return out
    kind = ["elabel", "src_label", "dst_label"]
    step = F.when(F.col("d") < 64, F.col("d")).otherwise(F.pow(F.lit(2), F.floor(F.log2("d"))).cast("bigint"))
    rows = []
    for end, way in (("src", True), *((("dst", False),) if graph.directed else ())):
        degree = arcs.groupBy(end, *kind).agg(F.count(F.lit(1)).alias("d"))
        rows.append(degree.groupBy(*kind, step.alias("degree")).agg(F.count(F.lit(1)).alias("n"), F.sum("d").alias("arcs")).withColumn("out", F.lit(way)))
    classes = (rows[0].unionByName(rows[1]) if len(rows) > 1 else rows[0]).collect()  # at most about a hundred rows per kind
    several = len({r["elabel"] for r in classes}) > 1 and not graph.several_labels().isEmpty()
    return out | {"degrees": [[r["src_label"], r["elabel"], r["dst_label"], r["out"], r["degree"], r["n"], r["arcs"]] for r in classes], "several": several}


def _write_facts(spark: SparkSession, path: str, facts: dict) -> None:
    spark.range(1).select(F.lit(json.dumps(facts)).alias("value")).coalesce(1).write.mode("overwrite").text(f"{path}/facts")


def load(spark: SparkSession, path: str, version: str | None = None) -> PropertyGraph:
    """A stored graph; with a version, only if it is that one."""
    said = json.loads(spark.read.text(f"{path}/facts").first()["value"])
    if version is not None and said["version"] != version:
        raise ValueError("another version of the graph is stored there")
    arcs: dict = {}
    degrees: dict = {}
    for a, e, b, out, degree, n, total in said["degrees"]:
        if out:
            arcs[a, e, b] = arcs.get((a, e, b), 0) + total
        for way in (out,) if said["directed"] else (True, False):
            by = degrees.setdefault((a, e, b, way) if out else (b, e, a, way), {})
            by[degree] = by.get(degree, 0) + n
    facts = Facts(said["version"], dict(map(tuple, said["vertices"])), arcs, degrees, said["several"], {(label, n): (have, distinct, true) for label, n, have, distinct, true in said["values"]})
    vertices, kinds = _read(spark, path)
    if kinds is None:
        kinds = spark.createDataFrame([], "src bigint, dst bigint, elabel string, src_label string, dst_label string")
    first = ["vid", "vlabel"]
    return PropertyGraph(vertices.select(*first, *[c for c in vertices.columns if c not in first]), kinds.select("src", "dst", "elabel"), said["directed"], kinds, facts)


def table_version(spark: SparkSession, *paths: str) -> str:
    """A name for the contents of tables: their files' names, sizes and times."""
    return hashlib.sha256(repr([files_of(spark, p) for p in paths]).encode()).hexdigest()[:32]
