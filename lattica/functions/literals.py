"""Literals as columns. Attributes of a bound variable stand in columns named by `attr_column`."""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce
from operator import and_

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..rules.ast import FALSE, Const, Literal, Rule

ABSENT_MODES = ("unsatisfied", "satisfied")


def attr_column(var: str, attr: str) -> str:
    return f"{var}__{attr}"


def literal_column(literal: Literal, absent: bool = False) -> Column:
    """Whether the literal holds, never null; absent: what it is where an attribute is missing.

    `x.A = x.A` says that A exists. It is kept as a null test, which the optimizer can't fold to true.
    """
    if isinstance(literal, Const):
        value = F.col(attr_column(literal.var, literal.attr)) == F.lit(literal.value)
    elif literal.exists:
        return F.lit(True) if absent else F.col(attr_column(literal.left, literal.left_attr)).isNotNull()
    else:
        value = F.col(attr_column(literal.left, literal.left_attr)) == F.col(attr_column(literal.right, literal.right_attr))
    return F.coalesce(value, F.lit(absent))


def conjunction(literals: Iterable[Literal], absent: bool = False) -> Column:
    return reduce(and_, (literal_column(x, absent) for x in literals), F.lit(True))


def when_column(rule: Rule, absent_in_x: str = "unsatisfied") -> Column:
    """X of a rule. A missing attribute makes a literal of X false ("unsatisfied") or true ("satisfied")."""
    if absent_in_x not in ABSENT_MODES:
        raise ValueError(f"absent_in_x is one of {ABSENT_MODES}")
    return conjunction(rule.when, absent_in_x == "satisfied")


def then_column(rule: Rule) -> Column:
    """Y of a rule: a missing attribute makes it false."""
    return F.lit(False) if rule.then is FALSE else conjunction(rule.then)


def falling_factorial(n: Column, k: int) -> Column:
    """n (n - 1) ... (n - k + 1), 0 where n < k."""
    out = F.lit(1).cast("bigint")
    for i in range(k):
        out = out * F.greatest(n - i, F.lit(0)).cast("bigint")
    return out
