"""Rule analysis before planning."""

from __future__ import annotations

import datetime
import decimal
from dataclasses import dataclass

from pyspark.sql import types as T

from .ast import FALSE, Const, Rule, Same


class RuleError(ValueError):
    pass


class RuleTypeError(RuleError):
    pass


def _class_of_type(t: T.DataType) -> str:
    if isinstance(t, T.NumericType):
        return "numeric"
    if isinstance(t, T.StringType):
        return "string"
    if isinstance(t, T.BooleanType):
        return "boolean"
    if isinstance(t, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return "temporal"
    return t.simpleString()


def _class_of_value(v) -> str:
    if isinstance(v, bool):
        return "boolean"
    if isinstance(v, (int, float, decimal.Decimal)):
        return "numeric"
    return "temporal" if isinstance(v, (datetime.date, datetime.datetime)) else "string"


@dataclass(frozen=True)
class Findings:
    """never_when: X can't hold; trivial: Y holds whenever X does."""

    never_when: bool = False
    trivial: bool = False


def analyze(rule: Rule, catalog: dict[str, T.DataType]) -> Findings:
    names = rule.pattern.variables
    if not names or len(set(names)) != len(names):
        raise RuleError(f"{rule.rule_id}: variables must be there and differ")
    for e in rule.pattern.edges:
        if not {e.src, e.dst} <= set(names):
            raise RuleError(f"{rule.rule_id}: an edge uses an unknown variable")
    for x in rule.literals:
        if not {v for v, _ in x.uses} <= set(names):
            raise RuleError(f"{rule.rule_id}: a literal uses an unknown variable")
        if isinstance(x, Const):
            kinds = {_class_of_value(x.value)} | {_class_of_type(catalog[a]) for _, a in x.uses if a in catalog}
        else:
            kinds = {_class_of_type(catalog[a]) for _, a in x.uses if a in catalog}
        if len(kinds) > 1:
            raise RuleTypeError(f"{rule.rule_id}: {x} compares {' with '.join(sorted(kinds))}")
    fixed: dict[tuple[str, str], set] = {}
    for x in rule.when:
        if isinstance(x, Const):
            fixed.setdefault((x.var, x.attr), set()).add(x.value)
    trivial = rule.then is not FALSE and all(x in rule.when or isinstance(x, Same) and Same(x.right, x.right_attr, x.left, x.left_attr) in rule.when for x in rule.then)
    return Findings(any(len(v) > 1 for v in fixed.values()), trivial)
