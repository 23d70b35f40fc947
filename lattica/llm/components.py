"""Connected components of a graph given as a table of edges, by repeated contraction.

In each round every node takes the least of itself and its neighbours as parent, and edges move to the parents; the
rounds end when no edge is left. With ids in random order (hashes) the graph shrinks by a constant factor a round. Only
tables move: nothing is collected but whether edges are left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import saved


def components(edges: DataFrame) -> DataFrame:
    """(node, label) for every node of edges (a, b): nodes have equal labels exactly if they are connected. Null ends and loops are left out."""
    edges = saved(edges.select("a", "b").where("a <> b").distinct(), "edges")
    labels = None
    while not edges.isEmpty():
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        parents = saved(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("parent")), "parents")
        if labels is None:
            labels = parents.select("node", F.col("parent").alias("label"))
        else:
            step = parents.select(F.col("node").alias("label"), "parent")
            labels = saved(labels.join(step, "label", "left").select("node", F.coalesce("parent", "label").alias("label")), "labels")
        a = parents.select(F.col("node").alias("a"), F.col("parent").alias("pa"))
        b = parents.select(F.col("node").alias("b"), F.col("parent").alias("pb"))
        moved = edges.join(a, "a").join(b, "b").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b"))
        edges = saved(moved.where("a <> b").distinct(), "edges")
    return labels if labels is not None else edges.select(F.col("a").alias("node"), F.col("b").alias("label"))
