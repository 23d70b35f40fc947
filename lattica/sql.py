"""Rules as SQL over the views of `PropertyGraph.register`: for users of SQL and for plan tests."""

from __future__ import annotations

import datetime

from .rules.ast import FALSE, Const, Literal, Rule


def _constant(v) -> str:
    if isinstance(v, bool):
        return str(v).lower()
    if isinstance(v, str):
        return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(v, datetime.datetime):
        return f"TIMESTAMP '{v}'"
    return f"DATE '{v}'" if isinstance(v, datetime.date) else str(v)


def _literal(x: Literal, absent: str) -> str:
    if isinstance(x, Const):
        return f"coalesce({x.var}.{x.attr} = {_constant(x.value)}, {absent})"
    if x.exists:
        return absent if absent == "true" else f"{x.left}.{x.left_attr} IS NOT NULL"
    return f"coalesce({x.left}.{x.left_attr} = {x.right}.{x.right_attr}, {absent})"


def rule_to_sql(rule: Rule, semantics: str = "mono", absent_in_x: str = "unsatisfied", prefix: str = "g") -> str:
    """One SELECT of the violating bindings."""
    p, names = rule.pattern, rule.pattern.variables
    source = [f"{prefix}_vertices {v}" for v in names]
    where = [f"{v.var}.vlabel = {_constant(v.label)}" for v in p.vertices if v.label is not None]
    for e in p.edges:
        label = "" if e.label is None else f" AND e.elabel = {_constant(e.label)}"
        ends = f"(e.src = {e.src}.vid AND e.dst = {e.dst}.vid)"
        if not p.directed:
            ends = f"({ends} OR (e.src = {e.dst}.vid AND e.dst = {e.src}.vid))"
        where.append(f"EXISTS (SELECT 1 FROM {prefix}_edges e WHERE {ends}{label})")
    if semantics != "homo":
        where += [f"{a}.vid <> {b}.vid" for i, a in enumerate(names) for b in names[i + 1 :]]
    if semantics == "induced":
        where += [f"NOT EXISTS (SELECT 1 FROM {prefix}_edges e WHERE e.src = {a}.vid AND e.dst = {b}.vid)" for a in names for b in names if (a, b) not in p.arcs()]
    where += [_literal(x, "true" if absent_in_x == "satisfied" else "false") for x in rule.when]
    if rule.then is not FALSE:
        then = " AND ".join(_literal(x, "false") for x in rule.then) or "true"
        where.append(f"NOT ({then})")
    return f"SELECT {', '.join(f'{v}.vid AS {v}' for v in names)} FROM {', '.join(source)} WHERE {' AND '.join(where) or 'true'}"
