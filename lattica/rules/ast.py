"""Patterns, literals and rules: small immutable objects on the driver."""

from __future__ import annotations

import datetime
import decimal
import json
from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame

Scalar = bool | int | float | str | decimal.Decimal | datetime.date | datetime.datetime


@dataclass(frozen=True)
class Vertex:
    """A variable; label None matches any label."""

    var: str
    label: str | None = None


@dataclass(frozen=True)
class Edge:
    """From src to dst; label None matches any label."""

    src: str
    dst: str
    label: str | None = None


@dataclass(frozen=True)
class Pattern:
    vertices: tuple[Vertex, ...]
    edges: tuple[Edge, ...] = ()
    directed: bool = True

    @staticmethod
    def of(vertices: Iterable[Vertex | tuple | str], edges: Iterable[Edge | tuple] = (), directed: bool = True) -> Pattern:
        vs = tuple(v if isinstance(v, Vertex) else Vertex(v) if isinstance(v, str) else Vertex(*v) for v in vertices)
        return Pattern(vs, tuple(e if isinstance(e, Edge) else Edge(*e) for e in edges), directed)

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(v.var for v in self.vertices)

    def label(self, var: str) -> str | None:
        return next(v.label for v in self.vertices if v.var == var)

    def neighbours(self, var: str) -> set[str]:
        return {e.dst if e.src == var else e.src for e in self.edges if var in (e.src, e.dst)}

    def arcs(self) -> set[tuple[str, str]]:
        """Ordered pairs that some pattern edge joins; an undirected edge joins both."""
        out = {(e.src, e.dst) for e in self.edges}
        return out if self.directed else out | {(b, a) for a, b in out}


@dataclass(frozen=True)
class Const:
    """var.attr = value"""

    var: str
    attr: str
    value: Scalar

    @property
    def uses(self) -> tuple[tuple[str, str], ...]:
        return ((self.var, self.attr),)


@dataclass(frozen=True)
class Same:
    """left.left_attr = right.right_attr; of an attribute with itself: it exists"""

    left: str
    left_attr: str
    right: str
    right_attr: str

    @property
    def exists(self) -> bool:
        return (self.left, self.left_attr) == (self.right, self.right_attr)

    @property
    def uses(self) -> tuple[tuple[str, str], ...]:
        return ((self.left, self.left_attr), (self.right, self.right_attr))


Literal = Const | Same


class _False:
    def __repr__(self) -> str:
        return "FALSE"


#: The consequent that no match satisfies.
FALSE = _False()


@dataclass(frozen=True)
class Rule:
    rule_id: str
    pattern: Pattern
    when: tuple[Literal, ...] = ()
    then: tuple[Literal, ...] | _False = ()

    @property
    def literals(self) -> tuple[Literal, ...]:
        return self.when + (() if self.then is FALSE else self.then)

    def attributes(self, var: str, literals: Iterable[Literal] | None = None) -> list[str]:
        """Attributes of a variable that the literals use."""
        return sorted({a for x in (self.literals if literals is None else literals) for v, a in x.uses if v == var})


@dataclass(frozen=True)
class RuleSet:
    rules: tuple[Rule, ...]

    @staticmethod
    def of(rules: Iterable[Rule]) -> RuleSet:
        return RuleSet(tuple(rules))

    def __iter__(self):
        return iter(self.rules)

    def to_json(self) -> str:
        from .parser import to_text

        return json.dumps([{"rule_id": r.rule_id, "text": to_text(r)} for r in self.rules])

    @staticmethod
    def from_json(text: str) -> RuleSet:
        from .parser import parse_rule

        return RuleSet(tuple(parse_rule(x["text"], x["rule_id"]) for x in json.loads(text)))

    @staticmethod
    def from_df(table: DataFrame) -> RuleSet:
        """From rows (rule_id, text): rules are few, so they are collected."""
        from .parser import parse_rule

        return RuleSet(tuple(parse_rule(r["text"], r["rule_id"]) for r in table.select("rule_id", "text").orderBy("rule_id").collect()))
