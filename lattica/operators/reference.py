"""A plain backtracking search on the driver: ground truth for tests, and the local search of one worker for small balls."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from ..rules.ast import Pattern


def search(labels: dict[int, str], arcs: Iterable[tuple[int, int, str]], pattern: Pattern, semantics: str = "mono", allowed: dict[str, set[int]] | None = None) -> Iterator[dict[str, int]]:
    """All bindings of the pattern; allowed narrows the candidates of variables."""
    stored = set(arcs)
    if not pattern.directed:
        stored |= {(b, a, lab) for a, b, lab in stored}
    pairs = {(a, b) for a, b, _ in stored}
    joined = pattern.arcs()
    names = pattern.variables

    def fits(var: str, v: int, bound: dict[str, int]) -> bool:
        now = {**bound, var: v}
        if semantics != "homo" and v in bound.values():
            return False
        for e in pattern.edges:
            if var in (e.src, e.dst) and e.src in now and e.dst in now:
                a, b = now[e.src], now[e.dst]
                if (a, b) not in pairs if e.label is None else (a, b, e.label) not in stored:
                    return False
        if semantics == "induced":
            for w in now:
                if (var, w) not in joined and (v, now[w]) in pairs or (w, var) not in joined and (now[w], v) in pairs:
                    return False
        return True

    def extend(i: int, bound: dict[str, int]) -> Iterator[dict[str, int]]:
        if i == len(names):
            yield dict(bound)
            return
        var, label = names[i], pattern.label(names[i])
        for v in sorted(allowed[var] if allowed and var in allowed else labels):
            if (label is None or labels[v] == label) and fits(var, v, bound):
                yield from extend(i + 1, {**bound, var: v})

    yield from extend(0, {})
