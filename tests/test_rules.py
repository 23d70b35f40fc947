"""Rule language, analysis and pattern shapes."""

import datetime
import decimal

import pytest
from pyspark.sql import types as T

from lattica import workloads
from lattica.operators.balanced import greedy_split
from lattica.rules import shape
from lattica.rules.ast import FALSE, Const, Pattern, Rule, RuleSet, Same
from lattica.rules.check import RuleError, RuleTypeError, analyze
from lattica.rules.parser import RuleSyntaxError, parse_rule, to_text


@pytest.mark.parametrize("name", sorted(workloads.TEXTS))
def test_text_round_trip(name):
    rule = workloads.rule(name)
    assert parse_rule(to_text(rule), name) == rule


def test_values_and_labels():
    rule = parse_rule("match (x:'Pa rt')-[_]->(y:_) where x.a = 'it''s' and x.b = -1.5 and x.c = 2m and x.d = date '2024-01-31' then false")
    assert rule.pattern.label("x") == "Pa rt" and rule.pattern.edges[0].label is None and rule.then is FALSE
    assert [c.value for c in rule.when] == ["it's", -1.5, decimal.Decimal(2), datetime.date(2024, 1, 31)]
    assert parse_rule(to_text(rule)) == rule
    assert parse_rule("match (x)<-[a]-(y) then true").pattern.edges[0].src == "y"


@pytest.mark.parametrize("text", ["match (x", "match (x)-[a]-(y)-[b]->(z) then true", "match (x) then x.a =", "match (x) then x.a = 1 extra", "match (x)<-[a]->(y) then true"])
def test_syntax_errors(text):
    with pytest.raises(RuleSyntaxError):
        parse_rule(text)


def test_json_round_trip():
    rules = RuleSet.of([workloads.rule("star3"), workloads.rule("never_both")])
    assert RuleSet.from_json(rules.to_json()) == rules


def test_rules_from_table(spark):
    table = spark.createDataFrame([("b", to_text(workloads.rule("star3"))), ("a", to_text(workloads.rule("opening")))], "rule_id string, text string")
    assert [r.rule_id for r in RuleSet.from_df(table)] == ["a", "b"]


def test_analysis():
    catalog = {"a": T.IntegerType(), "s": T.StringType()}
    one = Pattern.of([("x", None), ("y", None)])
    with pytest.raises(RuleTypeError):
        analyze(Rule("r", one, (), (Const("x", "s", 1),)), catalog)
    with pytest.raises(RuleTypeError):
        analyze(Rule("r", one, (), (Same("x", "s", "y", "a"),)), catalog)
    with pytest.raises(RuleError):
        analyze(Rule("r", one, (), (Const("z", "a", 1),)), catalog)
    with pytest.raises(RuleError):
        analyze(Rule("r", Pattern.of(["x", "x"]), (), ()), catalog)
    assert analyze(Rule("r", one, (Const("x", "a", 1), Const("x", "a", 2)), FALSE), catalog).never_when
    assert analyze(Rule("r", one, (Same("x", "a", "y", "a"),), (Same("y", "a", "x", "a"),)), catalog).trivial
    assert not analyze(Rule("r", one, (), (Const("x", "unknown", 1),)), catalog).trivial


def _undirected(n, edges):
    names = [f"v{i}" for i in range(n)]
    return Pattern.of(names, [(f"v{a}", f"v{b}") for a, b in edges], directed=False)


def test_centres():
    assert shape.pivot_vector(_undirected(5, [(0, 1), (1, 2), (2, 3), (3, 4)])) == [("v2", 2)]
    assert shape.pivot_vector(_undirected(4, [(0, 1), (1, 2), (2, 3)])) == [("v1", 2)]
    assert shape.pivot_vector(_undirected(4, [(0, 1), (0, 2), (0, 3)])) == [("v0", 1)]
    assert shape.pivot_vector(_undirected(3, [(0, 1), (1, 2), (0, 2)])) == [("v0", 1)]
    assert len(shape.pivot_vector(_undirected(4, [(0, 1), (2, 3)]))) == 2


def test_cores_trees_automorphisms():
    kite = _undirected(4, [(0, 1), (1, 2), (0, 2), (2, 3)])
    assert shape.two_core(kite) == {"v0", "v1", "v2"}
    chorded = _undirected(4, [(0, 1), (1, 2), (2, 3), (3, 0), (0, 2)])
    assert shape.two_core(chorded) == {"v0", "v1", "v2", "v3"} and len(shape.shortest_cycle(chorded)) == 3
    assert shape.core_of(_undirected(3, [(0, 1), (1, 2)]), "v1") == {"v1"}
    tree = shape.spanning_tree(kite, "v0")
    assert [(p, c) for p, c, _ in tree] == [("v0", "v1"), ("v0", "v2"), ("v2", "v3")]
    assert len(shape.non_tree_edges(kite, tree, kite.variables)) == 1
    assert len(shape.automorphisms(_undirected(4, [(0, 1), (0, 2), (0, 3)]))) == 6
    assert len(shape.automorphisms(Pattern.of(["a", "b"], [("a", "b")]))) == 1


def test_greedy_split():
    costs = list(enumerate([9, 7, 6, 5, 5, 4]))
    given = greedy_split(costs, 3)
    loads = [sum(c for i, c in costs if given[i] == w) for w in range(3)]
    assert sorted(loads) == [11, 12, 13]
