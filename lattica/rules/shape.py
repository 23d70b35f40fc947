"""The shape of a pattern: hops, centres, spanning trees, cores, automorphisms. Patterns are tiny, so all is done on the driver."""

from __future__ import annotations

from collections import deque
from itertools import combinations, permutations

from .ast import Edge, Pattern


def hops_from(pattern: Pattern, start: str, within: set[str] | None = None) -> dict[str, int]:
    """Distances from a variable, whatever the direction of edges."""
    out, queue = {start: 0}, deque([start])
    while queue:
        v = queue.popleft()
        for w in sorted(pattern.neighbours(v), key=pattern.variables.index):
            if w not in out and (within is None or w in within):
                out[w] = out[v] + 1
                queue.append(w)
    return out


def components(pattern: Pattern) -> list[tuple[str, ...]]:
    out, left = [], list(pattern.variables)
    while left:
        reached = hops_from(pattern, left[0])
        out.append(tuple(v for v in pattern.variables if v in reached))
        left = [v for v in left if v not in reached]
    return out


def eccentricity(pattern: Pattern, var: str) -> int:
    return max(hops_from(pattern, var).values())


def pivot_vector(pattern: Pattern, label_counts: dict[str | None, int] | None = None) -> list[tuple[str, int]]:
    """(centre, radius) of each component: the least eccentricity, then the fewest candidates, then the first."""
    out = []
    for part in components(pattern):
        best = min(part, key=lambda v: (eccentricity(pattern, v), (label_counts or {}).get(pattern.label(v), 0), pattern.variables.index(v)))
        out.append((best, eccentricity(pattern, best)))
    return out


def spanning_tree(pattern: Pattern, root: str) -> list[tuple[str, str, Edge]]:
    """(parent, child, edge) in breadth-first order."""
    out, seen, queue = [], {root}, deque([root])
    while queue:
        v = queue.popleft()
        for e in pattern.edges:
            w = e.dst if e.src == v else e.src if e.dst == v else None
            if w is not None and w not in seen:
                seen.add(w)
                out.append((v, w, e))
                queue.append(w)
    return out


def non_tree_edges(pattern: Pattern, tree: list[tuple[str, str, Edge]], part: tuple[str, ...]) -> list[Edge]:
    """Edges of a component that its tree doesn't use, by place: of two equal edges one stays."""
    left = [e for e in pattern.edges if e.src in part]
    for _, _, e in tree:
        left.remove(e)
    return left


def two_core(pattern: Pattern, part: tuple[str, ...] | None = None) -> set[str]:
    """What is left of a component when variables with one neighbour are stripped again and again; empty without a cycle."""
    left = set(part or pattern.variables)
    while weak := {v for v in left if len((pattern.neighbours(v) & left) - {v}) < 2}:
        left -= weak
    return left


def shortest_cycle(pattern: Pattern, part: tuple[str, ...] | None = None) -> set[str]:
    """The variables of a shortest cycle of at least three, the first by order; empty without one."""
    chosen = [v for v in pattern.variables if v in (part or pattern.variables)]
    for k in range(3, len(chosen) + 1):
        for some in combinations(chosen, k):
            first, *rest = some
            for order in permutations(rest):
                ring = [first, *order, first]
                if all(b in pattern.neighbours(a) for a, b in zip(ring[:-1], ring[1:], strict=True)):
                    return set(some)
    return set()


def core_of(pattern: Pattern, root: str, mode: str = "two_core", part: tuple[str, ...] | None = None) -> set[str]:
    """The dense part that is matched first; the root alone if there is no cycle."""
    core = {"two_core": two_core, "shortest_cycle": shortest_cycle}[mode](pattern, part)
    return core or {root}


def automorphisms(pattern: Pattern) -> list[dict[str, str]]:
    """Renamings of the variables that leave labels and edges as they are, by backtracking: a variable only goes where label and
    edges to those before it agree."""
    names = pattern.variables

    def key(e: Edge, m: dict[str, str]) -> tuple:
        a, b = m[e.src], m[e.dst]
        return (a, b, e.label) if pattern.directed else (*sorted((a, b)), e.label)

    def among(chosen: tuple[str, ...], m: dict[str, str]) -> list[str]:
        return sorted(repr(key(e, m)) for e in pattern.edges if e.src in chosen and e.dst in chosen)

    same = dict(zip(names, names, strict=True))
    out: list[dict[str, str]] = []

    def extend(m: dict[str, str]) -> None:
        if len(m) == len(names):
            out.append(m)
            return
        v = names[len(m)]
        for w in names:
            if w in m.values() or pattern.label(v) != pattern.label(w):
                continue
            now = m | {v: w}
            if among(tuple(now), now) == among(tuple(now.values()), same):
                extend(now)

    extend({})
    return out
