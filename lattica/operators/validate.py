"""Validation: every match that satisfies X but not Y of its rule.

Rewrites above Catalyst (each can be switched off): literals of X about one variable, and Y where it is about one, become
filters on candidates; equalities of X between components become join conditions; rules that can't be broken have an empty
plan; rules of one pattern share its matches; where a pattern has symmetries that the rule keeps, one match of each orbit is
checked and the others are made from it.
"""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.literals import attr_column, conjunction, falling_factorial, literal_column, then_column, when_column
from ..model.graph import PropertyGraph
from ..plans import steps
from ..plans.cost import Statistics
from ..plans.steps import Needs
from ..rules import shape
from ..rules.ast import FALSE, Const, Pattern, Rule, Same
from ..rules.check import analyze
from . import balanced, direct, hybrid, pathindex

STRATEGIES = ("direct", "balanced", "indexed", "balanced_indexed", "indexed_parallel", "auto")


def choose(pattern: Pattern, graph: PropertyGraph | None = None, needs: Needs | None = None, least_gain: float = 0.2) -> str:
    """Strategy `auto`. On a stored graph the index is taken where its order of steps is expected to cost so much less than the
    declared one, by the graph's counts; elsewhere by shape: cycles and larger patterns profit from it, single vertices need no search."""
    if not pattern.edges:
        return "direct"
    parts = shape.components(pattern)
    if graph is None or not graph.facts:
        return "indexed" if any(shape.two_core(pattern, part) for part in parts) or len(pattern.vertices) > 3 else "direct"
    statistics, shares, declared, best = Statistics.of(graph), pathindex.shares_of(graph, pattern, needs), 0.0, 0.0
    for part in parts:
        first, order = steps.declared_order(pattern, part)
        declared += statistics.order_cost(pattern, (first, *(c for _, c, _ in order)), shares)
        best += statistics.order_cost(pattern, statistics.best_order(pattern, part, shares), shares)
    return "indexed" if best < (1 - least_gain) * declared else "direct"


def match(graph: PropertyGraph, pattern: Pattern, strategy: str = "direct", semantics: str = "mono", needs: Needs | None = None, distinct_subgraphs: bool = False, **options) -> DataFrame:
    """Bindings: a column for each variable, and those of needs. distinct_subgraphs keeps one of the bindings that automorphisms make of each other."""
    if strategy == "auto":
        strategy = choose(pattern, graph, needs)
    run = {
        "direct": direct.match,
        "balanced": balanced.match,
        "indexed": pathindex.match,
        "balanced_indexed": hybrid.match_balanced_indexed,
        "indexed_parallel": hybrid.match_indexed_parallel,
    }[strategy]
    df = run(graph, pattern, semantics, needs, **options)
    extra = [attr_column(v, a) for v in pattern.variables for a in (needs.attrs.get(v, []) if needs else [])]
    df = df.select(*pattern.variables, *extra)
    return df.where(_canonical(pattern, shape.automorphisms(pattern))) if distinct_subgraphs else df


def _canonical(pattern: Pattern, renamings: list[dict[str, str]]):
    """The binding is the least of its orbit. Only variables that a renaming moves are compared, so bindings can be dropped before the others are bound."""

    def least(pairs):
        (v, w), *rest = pairs
        return (F.col(v) < F.col(w)) | (F.col(v) == F.col(w)) & least(rest) if rest else F.col(v) <= F.col(w)

    moved = [[(v, m[v]) for v in pattern.variables if m[v] != v] for m in renamings]
    return reduce(and_, (least(pairs) for pairs in moved if pairs), F.lit(True))


def _orbit(df: DataFrame, pattern: Pattern, renamings: list[dict[str, str]]) -> DataFrame:
    """All bindings that the renamings make of each."""

    def renamed(v):
        targets = list(dict.fromkeys(m[v] for m in renamings))
        out = F.col(targets[0])
        for w in targets[1:]:
            out = F.when(F.col("_m").isin([i for i, m in enumerate(renamings) if m[v] == w]), F.col(w)).otherwise(out)
        return out.alias(v)

    return df.withColumn("_m", F.explode(F.array(*[F.lit(i) for i in range(len(renamings))]))).select(*[renamed(v) for v in pattern.variables])


def _kept_by(rule: Rule, m: dict[str, str]) -> bool:
    """The rule says the same after renaming."""

    def renamed(literals):
        out = set()
        for x in literals:
            if isinstance(x, Const):
                out.add((m[x.var], x.attr, repr(x.value)))
            else:
                out.add(frozenset([(m[x.left], x.left_attr), (m[x.right], x.right_attr)]))
        return out

    same = {v: v for v in m}
    plain = []
    for literals in (rule.when, () if rule.then is FALSE else rule.then):
        now, then = renamed(literals), set()
        for x in literals:
            then.add((x.var, x.attr, repr(x.value)) if isinstance(x, Const) else frozenset([(x.left, x.left_attr), (x.right, x.right_attr)]))
        plain.append(now == then)
    return all(plain) and bool(same)


def needs_of(rule: Rule, absent_in_x: str, pushdown: bool, push_then: bool = True) -> Needs:
    needs = Needs({v: rule.attributes(v) for v in rule.pattern.variables if rule.attributes(v)})
    absent = absent_in_x == "satisfied"
    if not pushdown:
        return needs
    for v in rule.pattern.variables:
        own = [x for x in rule.when if {u for u, _ in x.uses} == {v}]
        if own:
            needs.filters[v] = conjunction(own, absent)
            needs.said[v] = [(tuple(own), False)]
    if push_then and rule.then is not FALSE and rule.then and len({u for x in rule.then for u, _ in x.uses}) == 1:
        v = rule.then[0].uses[0][0]
        broken = ~conjunction(rule.then)
        needs.filters[v] = needs.filters[v] & broken if v in needs.filters else broken
        needs.said.setdefault(v, []).append((tuple(rule.then), True))
    if not absent:
        needs.joins = [x for x in rule.when if isinstance(x, Same) and x.left != x.right]
    return needs


def _empty(graph: PropertyGraph, variables: Iterable[str]) -> DataFrame:
    return graph.vertices.sparkSession.createDataFrame([], T.StructType([T.StructField(v, T.LongType()) for v in variables]))


def violations(graph: PropertyGraph, rule: Rule, strategy: str = "direct", semantics: str = "mono", absent_in_x: str = "unsatisfied", pushdown: bool = True, symmetry: bool = False, **options) -> DataFrame:
    """The bindings that break the rule, a column for each variable."""
    found = analyze(rule, graph.catalog)
    if rule.then == () or absent_in_x == "unsatisfied" and (found.never_when or found.trivial):
        return _empty(graph, rule.pattern.variables)
    renamings = [m for m in shape.automorphisms(rule.pattern) if _kept_by(rule, m)] if symmetry and semantics != "homo" else []
    needs, broken = needs_of(rule, absent_in_x, pushdown), when_column(rule, absent_in_x) & ~then_column(rule)
    checks = [(frozenset(v for v in rule.pattern.variables if rule.attributes(v)), broken)]
    if len(renamings) > 1:
        checks.append((frozenset(v for m in renamings for v in m if m[v] != v), _canonical(rule.pattern, renamings)))
    needs.checks = checks if pushdown else []
    df = match(graph, rule.pattern, strategy, semantics, needs, **options)
    df = reduce(DataFrame.where, (c for _, c in checks), df).select(*rule.pattern.variables)
    if len(renamings) > 1:
        df = _orbit(df, rule.pattern, renamings)
    return df


def as_bindings(df: DataFrame, rule: Rule) -> DataFrame:
    """rule_id, binding array<struct<var, vid>>."""
    pairs = F.array(*[F.struct(F.lit(v).alias("var"), F.col(v).alias("vid")) for v in rule.pattern.variables])
    return df.select(F.lit(rule.rule_id).alias("rule_id"), pairs.alias("binding"))


def validate(graph: PropertyGraph, rules: Iterable[Rule], strategy: str = "direct", semantics: str = "mono", absent_in_x: str = "unsatisfied", share: bool = True, **options) -> DataFrame:
    """rule_id and binding of all violations of a set of rules; rules of one pattern are checked on one set of matches."""
    groups: dict[Pattern, list[Rule]] = {}
    for r in rules:
        analyze(r, graph.catalog)
        groups.setdefault(r.pattern, []).append(r)
    out = []
    for pattern, some in groups.items():
        if len(some) == 1 or not share:
            out += [as_bindings(violations(graph, r, strategy, semantics, absent_in_x, **options), r) for r in some]
            continue
        needs = Needs({v: sorted({a for r in some for a in r.attributes(v)}) for v in pattern.variables})
        df = match(graph, pattern, strategy, semantics, needs, **options)
        broken = F.array_compact(F.array(*[F.when(when_column(r, absent_in_x) & ~then_column(r) & F.lit(r.then != ()), F.lit(r.rule_id)) for r in some]))
        pairs = F.array(*[F.struct(F.lit(v).alias("var"), F.col(v).alias("vid")) for v in pattern.variables])
        out.append(df.select(F.explode(broken).alias("rule_id"), pairs.alias("binding")))
    return reduce(DataFrame.unionByName, out)


def satisfies(graph: PropertyGraph, rules: Iterable[Rule], **options) -> DataFrame:
    """rule_id, holds: each rule's search may stop at its first violation."""
    rows = []
    for r in rules:
        one = violations(graph, r, **options).limit(1).agg(F.count(F.lit(1)).alias("n"))
        rows.append(one.select(F.lit(r.rule_id).alias("rule_id"), (F.col("n") == 0).alias("holds")))
    return reduce(DataFrame.unionByName, rows)


def counts(graph: PropertyGraph, rule: Rule, strategy: str = "direct", semantics: str = "mono", absent_in_x: str = "unsatisfied", leaves: str = "expand", **options) -> DataFrame:
    """rule_id, matches, support (X holds), violations, confidence (1 - violations / support, null without support).

    leaves="count": for a star whose rule speaks of its centre only, from degrees, without making a match.
    """
    x, y = when_column(rule, absent_in_x), then_column(rule) if rule.then != () else F.lit(True)
    if leaves == "count":
        df, times = _centres(graph, rule, semantics)
        row = df.agg(*[F.coalesce(F.sum(F.when(c, times)), F.lit(0)).cast("bigint").alias(n) for n, c in (("matches", F.lit(True)), ("support", x), ("violations", x & ~y))])
    else:
        df = match(graph, rule.pattern, strategy, semantics, needs_of(rule, absent_in_x, False), **options)
        row = df.agg(F.count(F.lit(1)).alias("matches"), F.count_if(x).alias("support"), F.count_if(x & ~y).alias("violations"))
    return row.select(F.lit(rule.rule_id).alias("rule_id"), "matches", "support", "violations", (1 - F.col("violations") / F.nullif("support", F.lit(0))).alias("confidence"))


def _about_centre(rule: Rule, semantics: str) -> bool:
    star = star_of(rule.pattern)
    return semantics == "mono" and star is not None and not any(rule.attributes(v) for v in star[1])


def _centres(graph: PropertyGraph, rule: Rule, semantics: str):
    """The possible centres of a star with the attributes that the rule asks for, and the number of matches of each."""
    if not _about_centre(rule, semantics):
        raise ValueError("leaves are only counted for stars of like leaves, under mono, with a rule about the centre")
    centre, leaves = star_of(rule.pattern)
    degrees = star_degrees(graph, rule.pattern).withColumnRenamed("centre", centre)
    df = degrees.join(steps.candidates(graph, rule.pattern, centre, Needs({centre: rule.attributes(centre)})), centre)
    return df, falling_factorial(F.col("d"), len(leaves))


def witnesses(graph: PropertyGraph, rule: Rule, semantics: str = "mono", absent_in_x: str = "unsatisfied", **options) -> DataFrame:
    """The distinct values of the variables that X and Y speak of, in violations.

    For a star whose rule speaks of its centre only, centres with enough leaves are witnesses, and no match is made.
    """
    used = [v for v in rule.pattern.variables if rule.attributes(v)] or list(rule.pattern.variables)
    if _about_centre(rule, semantics) and used == [star_of(rule.pattern)[0]] and rule.then != ():
        df, times = _centres(graph, rule, semantics)
        return df.where((times > 0) & when_column(rule, absent_in_x) & ~then_column(rule)).select(*used)
    return violations(graph, rule, semantics=semantics, absent_in_x=absent_in_x, **options).select(*used).distinct()


def star_of(pattern: Pattern) -> tuple[str, list[str]] | None:
    """(centre, leaves) of a star whose leaves and edges are alike, without other edges."""
    if len(pattern.vertices) < 2 or len(pattern.edges) != len(pattern.vertices) - 1:
        return None
    for c in pattern.variables:
        leaves = [v for v in pattern.variables if v != c]
        kinds = {(e.src == c, e.label) if pattern.directed else e.label for e in pattern.edges}
        if pattern.neighbours(c) == set(leaves) and len(kinds) == 1 and len({pattern.label(v) for v in leaves}) == 1:
            return c, leaves
    return None


def star_degrees(graph: PropertyGraph, pattern: Pattern) -> DataFrame:
    """centre, d: distinct possible leaves of each possible centre of a star; no match is enumerated."""
    centre, leaves = star_of(pattern) or (None, None)
    if centre is None:
        raise ValueError("not a star of like leaves")
    edge = pattern.edges[0]
    pairs = steps.oriented(steps.arcs_of(graph, pattern, edge), edge, centre, edge.dst if edge.src == centre else edge.src)
    leaf = next(c for c in pairs.columns if c != centre)
    pairs = pairs.where(F.col(centre) != F.col(leaf))
    if graph.kinds is None:
        pairs = pairs.join(steps.candidates(graph, pattern, leaf), leaf, "left_semi")
    return pairs.groupBy(centre).agg(F.count(F.lit(1)).alias("d")).join(steps.candidates(graph, pattern, centre), centre, "left_semi").withColumnRenamed(centre, "centre")


def explained(graph: PropertyGraph, rule: Rule, strategy: str = "direct", semantics: str = "mono", absent_in_x: str = "unsatisfied", **options) -> DataFrame:
    """The violations with `failing`: the literals of Y that do not hold, joined by '; '."""
    needs = needs_of(rule, absent_in_x, True)
    df = match(graph, rule.pattern, strategy, semantics, needs, **options).where(when_column(rule, absent_in_x) & ~then_column(rule))
    names = [F.lit("false")] if rule.then is FALSE else [F.when(~literal_column(x), F.lit(_said(x))) for x in rule.then]
    return df.select(*rule.pattern.variables, F.array_join(F.array_compact(F.array(*names)), "; ").alias("failing"))


def _said(x) -> str:
    return f"{x.var}.{x.attr} = {x.value}" if isinstance(x, Const) else f"{x.left}.{x.left_attr} = {x.right}.{x.right_attr}"


def fd_rule(rule_id: str, label: str | None, lhs: list[str], rhs: list[str]) -> Rule:
    """A functional dependency of a table as a rule of two unconnected vertices."""
    return Rule(rule_id, Pattern.of([("x", label), ("y", label)]), tuple(Same("x", a, "y", a) for a in lhs), tuple(Same("x", a, "y", a) for a in rhs))


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """side, binding columns: rows of one set of violations that the other lacks, copies counted."""
    only = [x.exceptAll(y.select(*x.columns)).select(F.lit(s).alias("side"), *a.columns) for s, x, y in (("left", a, b), ("right", b, a))]
    return only[0].unionByName(only[1])
