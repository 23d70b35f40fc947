"""Strategy `direct`: every pattern edge is one join over the whole graph, in declared order, without scheme or index."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame

from ..model.graph import PropertyGraph
from ..plans import steps
from ..plans.steps import Needs
from ..rules import shape
from ..rules.ast import Pattern


def match(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, hub_degree: int | None = None, hub_parts: int = 16, in_cells: bool = False, cell_arcs: int = steps.CELL_ARCS) -> DataFrame:
    """hub_degree: arcs of a vertex with more than so many are dealt to hub_parts parts, so that no task has all of them.

    in_cells: a variable that closes a cycle is joined and its edge closed at once, in cells of cell_arcs arcs between two blocks of vertices.
    """
    parts = []

    def blocks(edge):
        kind = pattern.label(edge.src), edge.label, pattern.label(edge.dst)
        n = graph.facts.matching(*kind) * (1 + (graph.directed and not pattern.directed)) if graph.facts else steps.arcs_of(graph, pattern, edge).count()
        return max(steps.LEAST_BLOCKS, math.ceil(math.sqrt(n / cell_arcs)))

    for part in shape.components(pattern):
        first, order = steps.declared_order(pattern, part)

        def link(parent, child, edge):
            pairs = steps.oriented(steps.arcs_of(graph, pattern, edge), edge, parent, child)
            return pairs if steps.free(graph, pattern, child, needs) else pairs.join(steps.candidates(graph, pattern, child, needs), child)

        parts.append(
            (part, steps.component_matches(pattern, part, steps.candidates(graph, pattern, first, needs), first, order, link, lambda e: steps.arcs_of(graph, pattern, e), steps.any_arc(graph, pattern), semantics, hubs=(hub_degree, hub_parts) if hub_degree else None, cells=blocks if in_cells else None, checks=needs.checks if needs else None))
        )
    return steps.combined(graph, pattern, parts, semantics, needs)
