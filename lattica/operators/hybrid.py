"""Hybrids: units of the balanced scheme over the index, and a parallel scheme of the index's own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph
from ..plans import steps
from ..plans.steps import Needs
from ..rules import shape
from ..rules.ast import Pattern
from . import balanced, pathindex
from .pathindex import Options


def match_balanced_indexed(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, options: Options = Options(), n: int = 4, method: str = "snake") -> DataFrame:
    """Pivots are the index's roots and are dealt to workers by the size of their balls."""
    parts = shape.components(pattern)
    pivots = balanced.pivots(graph, pattern)
    index = pathindex.build_index(graph, pattern, semantics, needs, options, {part: v for part, (v, _) in zip(parts, pivots, strict=True)})
    out = []
    for part, (pivot, radius) in zip(parts, pivots, strict=True):
        units = balanced.assign(balanced.ball_sizes(graph, pattern, pivot, radius), n, method).select(F.col("vid").alias(pivot), "worker")
        start = index.cands[pivot].join(units, pivot).repartition(n, "worker").drop("worker")
        out.append((part, pathindex.match_component(graph, index, part, semantics, needs, options, start)))
    return steps.combined(graph, pattern, out, semantics, needs)


def match_indexed_parallel(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, options: Options = Options(), n: int = 4, method: str = "snake") -> DataFrame:
    """Root candidates are dealt to workers by the number of tree matches that the index promises."""
    index = pathindex.build_index(graph, pattern, semantics, needs, options)
    out = []
    for part, root in index.roots.items():
        units = pathindex.root_weights(index, part).select(F.col(root).alias("vid"), F.col("weight").alias("cost"))
        dealt = balanced.assign(units, n, method).select(F.col("vid").alias(root), "worker")
        start = index.cands[root].join(dealt, root).repartition(n, "worker").drop("worker")
        out.append((part, pathindex.match_component(graph, index, part, semantics, needs, options, start)))
    return steps.combined(graph, pattern, out, semantics, needs)
