"""The text form of rules.

    match (a:MAIN)-[co]-(b:MAIN), (b)-[co]-(c:MAIN) where a.dormant = true and c.dormant = true then b.tied = true

A label that is left out or `_` matches any label; `->` and `<-` make a pattern directed, `--` undirected (one kind for a
pattern); `then false` has no satisfying match, `then true` is the empty consequent. Strings stand in single quotes,
doubled inside; dates as date '2024-01-31'.
"""

from __future__ import annotations

import datetime
import decimal
import re

from .ast import FALSE, Const, Edge, Literal, Pattern, Rule, Same, Vertex


class RuleSyntaxError(ValueError):
    pass


_TOKEN = re.compile(r"\s*(?:(?P<string>'(?:[^']|'')*')|(?P<number>-?\d+(?:\.\d+)?(?:[eE][-+]?\d+)?m?)|(?P<name>[A-Za-z_]\w*)|(?P<mark><-\[|\]->|-\[|\]-|[(),:.=]))")


def _tokens(text: str) -> list[tuple[str, str]]:
    out, at = [], 0
    text = text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise RuleSyntaxError(f"at {at}: {text[at : at + 20]!r}")
        out.append((m.lastgroup or "", m[m.lastgroup or 0]))
        at = m.end()
    return out


class _Reader:
    def __init__(self, text: str):
        self.tokens, self.at = _tokens(text), 0

    def peek(self) -> str:
        return self.tokens[self.at][1] if self.at < len(self.tokens) else ""

    def take(self, *wanted: str) -> str:
        value = self.peek()
        if not value or wanted and value not in wanted:
            raise RuleSyntaxError(f"expected {' or '.join(wanted) or 'more'}, got {value or 'the end'}")
        self.at += 1
        return value

    def name(self) -> str:
        if self.at >= len(self.tokens) or self.tokens[self.at][0] != "name":
            raise RuleSyntaxError(f"expected a name, got {self.peek() or 'the end'}")
        return self.take()

    def label(self) -> str | None:
        kind, value = self.tokens[self.at] if self.at < len(self.tokens) else ("", "")
        if kind not in ("name", "string"):
            raise RuleSyntaxError(f"expected a label, got {value or 'the end'}")
        self.at += 1
        return None if value == "_" else value[1:-1].replace("''", "'") if kind == "string" else value


def parse_rule(text: str, rule_id: str = "rule") -> Rule:
    r = _Reader(text)
    r.take("match")
    labels: dict[str, str | None] = {}
    edges: list[tuple[Edge, bool]] = []

    def node() -> str:
        r.take("(")
        var = r.name()
        if r.peek() == ":":
            r.take()
            label = r.label()
            if labels.get(var) is not None and labels[var] != label:
                raise RuleSyntaxError(f"two labels for {var}")
            labels[var] = label if labels.get(var) is None else labels[var]
        labels.setdefault(var, None)
        r.take(")")
        return var

    while True:
        left = node()
        while r.peek() in ("-[", "<-["):
            back = r.take() == "<-["
            label = r.label()
            close = r.take("]-", "]->")
            right = node()
            if back and close == "]->":
                raise RuleSyntaxError("an edge has one direction")
            edges.append((Edge(right, left, label) if back else Edge(left, right, label), back or close == "]->"))
            left = right
        if r.peek() != ",":
            break
        r.take()
    if len({d for _, d in edges}) > 1:
        raise RuleSyntaxError("a pattern is either directed or undirected")
    pattern = Pattern(tuple(Vertex(v, lab) for v, lab in labels.items()), tuple(e for e, _ in edges), not edges or edges[0][1])

    def value():
        kind, raw = r.tokens[r.at] if r.at < len(r.tokens) else ("", "")
        if kind == "string":
            r.take()
            return raw[1:-1].replace("''", "'")
        if kind == "number":
            r.take()
            return decimal.Decimal(raw[:-1]) if raw.endswith("m") else float(raw) if re.search("[.eE]", raw) else int(raw)
        if raw in ("true", "false"):
            r.take()
            return raw == "true"
        if raw in ("date", "timestamp") and r.at + 1 < len(r.tokens) and r.tokens[r.at + 1][0] == "string":
            r.take()
            kind_of = datetime.date if raw == "date" else datetime.datetime
            return kind_of.fromisoformat(r.take()[1:-1])
        raise RuleSyntaxError(f"expected a value, got {raw or 'the end'}")

    def literal() -> Literal:
        var = r.name()
        r.take(".")
        attr = r.name()
        r.take("=")
        if r.at + 1 < len(r.tokens) and r.tokens[r.at][0] == "name" and r.tokens[r.at + 1][1] == ".":
            other = r.name()
            r.take(".")
            return Same(var, attr, other, r.name())
        return Const(var, attr, value())

    def conjunction() -> tuple[Literal, ...]:
        out = [literal()]
        while r.peek() == "and":
            r.take()
            out.append(literal())
        return tuple(out)

    when: tuple[Literal, ...] = ()
    if r.peek() == "where":
        r.take()
        when = conjunction()
    r.take("then")
    then: tuple[Literal, ...] | object
    if r.peek() in ("true", "false"):
        then = () if r.take() == "true" else FALSE
    else:
        then = conjunction()
    if r.peek():
        raise RuleSyntaxError(f"unexpected {r.peek()}")
    return Rule(rule_id, pattern, when, then)  # type: ignore[arg-type]


def _quoted(label: str | None) -> str:
    return "_" if label is None else label if re.fullmatch(r"[A-Za-z]\w*", label) else "'" + label.replace("'", "''") + "'"


def _value(v) -> str:
    if isinstance(v, bool):
        return "true" if v else "false"
    if isinstance(v, str):
        return "'" + v.replace("'", "''") + "'"
    if isinstance(v, datetime.datetime):
        return f"timestamp '{v.isoformat()}'"
    if isinstance(v, datetime.date):
        return f"date '{v.isoformat()}'"
    return f"{v}m" if isinstance(v, decimal.Decimal) else repr(v)


def to_text(rule: Rule) -> str:
    p, close = rule.pattern, "]->" if rule.pattern.directed else "]-"
    nodes = [f"({v.var}:{_quoted(v.label)})" for v in p.vertices]
    links = [f"({e.src})-[{_quoted(e.label)}{close}({e.dst})" for e in p.edges]

    def conjunction(literals) -> str:
        return " and ".join(f"{x.var}.{x.attr} = {_value(x.value)}" if isinstance(x, Const) else f"{x.left}.{x.left_attr} = {x.right}.{x.right_attr}" for x in literals)

    where = f" where {conjunction(rule.when)}" if rule.when else ""
    then = "false" if rule.then is FALSE else conjunction(rule.then) if rule.then else "true"
    return f"match {', '.join(nodes + links)}{where} then {then}"
