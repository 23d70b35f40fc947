"""Statistics of label triples and what a match order is expected to cost."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph
from ..rules.ast import Edge, Pattern

Tree = list[tuple[str, str, Edge]]


def triples(graph: PropertyGraph) -> DataFrame:
    """src_label, elabel, dst_label, arcs, max_degree, sum_squares (of out-degrees): one row for each kind of arc."""
    if graph.kinds is not None:
        rows = graph.kinds
    else:
        label = graph.vertices.select("vid", "vlabel")
        rows = graph.edges.join(label.select(F.col("vid").alias("src"), F.col("vlabel").alias("src_label")), "src").join(label.select(F.col("vid").alias("dst"), F.col("vlabel").alias("dst_label")), "dst")
    degrees = rows.groupBy("src", "src_label", "elabel", "dst_label").agg(F.count(F.lit(1)).alias("d"))
    return degrees.groupBy("src_label", "elabel", "dst_label").agg(F.sum("d").alias("arcs"), F.max("d").alias("max_degree"), F.sum(F.col("d") * F.col("d")).alias("sum_squares"))


@dataclass(frozen=True)
class Statistics:
    """Vertices by label and arcs by (source label, edge label, target label): as many rows as there are kinds."""

    vertices: dict[str | None, int]
    arcs: dict[tuple[str | None, str, str | None], int]
    directed: bool = True

    @staticmethod
    def of(graph: PropertyGraph) -> Statistics:
        if graph.facts:
            return Statistics(graph.facts.vertices, graph.facts.arcs, graph.directed)
        arcs = {(r["src_label"], r["elabel"], r["dst_label"]): r["arcs"] for r in triples(graph).collect()}
        return Statistics({r["vlabel"]: r["n"] for r in graph.label_counts().collect()}, arcs, graph.directed)

    def candidates(self, label: str | None) -> int:
        return sum(n for k, n in self.vertices.items() if label in (None, k))

    def matching(self, pattern: Pattern, e: Edge) -> int:
        """Arcs that fit a pattern edge; both ways for an undirected one over a directed graph."""

        def kind(a: str | None, b: str | None) -> int:
            return sum(n for (s, lab, d), n in self.arcs.items() if a in (None, s) and e.label in (None, lab) and b in (None, d))

        a, b = pattern.label(e.src), pattern.label(e.dst)
        return kind(a, b) + (kind(b, a) if self.directed and not pattern.directed else 0)

    def fan_out(self, pattern: Pattern, parent: str, e: Edge) -> float:
        """Expected arcs of an edge at a vertex of the parent."""
        return self.matching(pattern, e) / max(1, self.candidates(pattern.label(parent)))

    def _steps(self, pattern: Pattern, order: tuple[str, ...], shares: dict[str, float]) -> Iterator[tuple[float, tuple[str, str, Edge] | None]]:
        """The size of the partial results after each variable's link, before its other edges are closed, and the link."""
        size, bound = float(self.candidates(pattern.label(order[0]))) * shares.get(order[0], 1.0), {order[0]}
        yield size, None
        for v in order[1:]:
            edges = [(e.src if e.dst == v else e.dst, e) for e in pattern.edges if v in (e.src, e.dst) and e.src != e.dst and ({e.src, e.dst} - {v}) <= bound]
            if not edges:
                yield float("inf"), None
                return
            edges.sort(key=lambda x: self.fan_out(pattern, *x))
            parent, link = edges[0]
            size *= self.fan_out(pattern, parent, link) * shares.get(v, 1.0)
            yield size, (parent, v, link)
            for other, e in edges[1:]:
                size *= min(1.0, self.fan_out(pattern, other, e) / max(1, self.candidates(pattern.label(v))))
            bound.add(v)

    def order_cost(self, pattern: Pattern, order: tuple[str, ...], shares: dict[str, float] | None = None) -> float:
        """Sum of the sizes of partial results: a link multiplies by its fan-out and the share that the filter keeps, a closing edge by its density."""
        return sum(size for size, _ in self._steps(pattern, order, shares or {}))

    def tree(self, pattern: Pattern, order: tuple[str, ...], shares: dict[str, float] | None = None) -> Tree:
        """Links of an order: each variable hangs on the bound one from which it has the least fan-out."""
        return [link for _, link in self._steps(pattern, order, shares or {}) if link]

    def best_order(self, pattern: Pattern, part: tuple[str, ...], shares: dict[str, float] | None = None, first: set[str] | None = None, exhaustive: int = 8) -> tuple[str, ...]:
        """The cheapest connected order with the variables of `first` (the core) before the others; ties by the pattern's own order.

        All orders are tried for parts of up to `exhaustive` variables; for larger ones the cheapest next variable is taken.
        """
        core = [v for v in part if v in (first or ())]
        rest = [v for v in part if v not in core]
        if len(part) <= exhaustive:
            return min(((*a, *b) for a in permutations(core) for b in permutations(rest)), key=lambda o: self.order_cost(pattern, o, shares))
        order: tuple[str, ...] = ()
        for group in (core, rest):
            left = list(group)
            while left:
                v = min(left, key=lambda v: (self.order_cost(pattern, (*order, v), shares), part.index(v)))
                order = (*order, v)
                left.remove(v)
        return order
