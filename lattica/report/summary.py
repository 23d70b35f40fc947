"""Reports over violations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph
from ..rules.ast import Rule


def culprits(found: DataFrame, rule: Rule, top: int | None = None) -> DataFrame:
    """vid, n: how many violations each vertex is in, most first; counted per variable before vertices meet."""
    per = [found.groupBy(F.col(v).alias("vid")).agg(F.count(F.lit(1)).alias("n")) for v in rule.pattern.variables]
    total = reduce(DataFrame.unionByName, per).groupBy("vid").agg(F.sum("n").alias("n"))
    return total.orderBy(F.desc("n"), "vid").limit(top) if top else total


def described(found: DataFrame, graph: PropertyGraph, var: str, *attrs: str) -> DataFrame:
    """The violations counted per value of a variable first, then with the vertex's attributes."""
    counted = found.groupBy(F.col(var).alias("vid")).agg(F.count(F.lit(1)).alias("n"))
    return counted.join(graph.vertices.select("vid", "vlabel", *attrs), "vid")


def rolled_up(found: DataFrame, graph: PropertyGraph, var: str, *attrs: str) -> DataFrame:
    return described(found, graph, var, *attrs).rollup(*attrs).agg(F.sum("n").alias("n"))


def cubed(found: DataFrame, graph: PropertyGraph, var: str, *attrs: str) -> DataFrame:
    return described(found, graph, var, *attrs).cube(*attrs).agg(F.sum("n").alias("n"))


def grouped_by_sets(found: DataFrame, graph: PropertyGraph, var: str, *sets: tuple[str, ...]) -> DataFrame:
    """Violations by several groupings at once; a column outside a row's grouping is null, and `grouping` tells which they are."""
    attrs = list(dict.fromkeys(a for s in sets for a in s))
    rows = described(found, graph, var, *attrs)
    return rows.groupingSets([[F.col(a) for a in s] for s in sets], *attrs).agg(F.sum("n").alias("n"), F.grouping_id().cast("bigint").alias("grouping"))


def ranked_in_label(found: DataFrame, graph: PropertyGraph, var: str, attr: str, top: int) -> DataFrame:
    """attr, vid, n, rank: the vertices with most violations within each attribute value."""
    order = Window.partitionBy(attr).orderBy(F.desc("n"), "vid")
    return described(found, graph, var, attr).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top).select(attr, "vid", "n", "rank")


def pivoted(times: DataFrame, queries: list[str]) -> DataFrame:
    """A strategy per row and a query per column, from (strategy, query, ms)."""
    return times.groupBy("strategy").pivot("query", queries).agg(F.first("ms"))
