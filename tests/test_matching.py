"""Worked graphs, semantics, and every strategy against exhaustive search."""

import random

import pytest
from pyspark.sql import functions as F

from lattica.model import stored
from lattica.model.graph import PropertyGraph
from lattica.operators import balanced, pathindex, validate
from lattica.operators.pathindex import CandidateIndex, Options
from lattica.operators.reference import search
from lattica.plans.ranks import ranked
from lattica.plans.steps import Needs
from lattica.rules import shape
from lattica.rules.ast import FALSE, Const, Pattern, Rule, Same
from lattica.rules.parser import parse_rule
from lattica.sql import rule_to_sql
from lattica.streaming import incremental

ATTRS = "vid bigint, vlabel string, name string, a int, b int"


def make(spark, vertices, edges, directed=True):
    rows = [(v, lab, at.get("name"), at.get("a"), at.get("b")) for v, lab, at in vertices]
    return PropertyGraph.of(spark.createDataFrame(rows, ATTRS), spark.createDataFrame(edges, "src bigint, dst bigint, elabel string"), directed)


def plain(n, label="P"):
    return [(i, label, {}) for i in range(1, n + 1)]


def bindings(df):
    return sorted(tuple(r) for r in df.collect())


def n_matches(g, pattern, semantics, strategy="direct"):
    return validate.match(g, pattern, strategy, semantics).count()


def test_two_places(spark):
    g = make(spark, [(1, "town", {}), (2, "country", {"name": "B"}), (3, "state", {"name": "C"}), (4, "region", {"name": "D"})], [(1, i, "located") for i in (2, 3, 4)])
    rule = parse_rule("match (x:town)-[located]->(y:_), (x)-[located]->(z:_) then y.name = z.name")
    assert n_matches(g, rule.pattern, "mono") == 6 and validate.violations(g, rule).count() == 6
    row = validate.counts(g, rule).first()
    assert (row["matches"], row["support"], row["violations"], row["confidence"]) == (6, 6, 6, 0.0)
    same = make(spark, [(1, "town", {}), (2, "c", {"name": "B"}), (3, "s", {"name": "C"}), (4, "r", {"name": "B"})], [(1, i, "located") for i in (2, 3, 4)])
    assert validate.violations(same, rule).count() == 4


def test_never_together(spark):
    g = make(spark, [(1, "film", {}), (2, "award", {"name": "A"}), (3, "award", {"name": "B"}), (4, "film", {})], [(1, 2, "won"), (1, 3, "won"), (4, 2, "won")])
    rule = parse_rule("match (x:film)-[won]->(y:award), (x)-[won]->(z:award) where y.name = 'A' and z.name = 'B' then false")
    assert bindings(validate.violations(g, rule)) == [(1, 2, 3)]


def test_existence_and_absence(spark):
    g = make(spark, [(1, "P", {"a": 1}), (2, "P", {"a": 2}), (3, "P", {})], [])
    assert bindings(validate.violations(g, parse_rule("match (x:P) then x.a = x.a"))) == [(3,)]
    assert bindings(validate.violations(g, parse_rule("match (x:P) then x.nowhere = 1"))) == [(1,), (2,), (3,)]
    four = make(spark, [(1, "P", {"a": 1, "b": 2}), (2, "P", {"a": 1}), (3, "P", {"b": 3}), (4, "P", {"a": 2, "b": 3})], [])
    rule = parse_rule("match (x:P) where x.a = 1 then x.b = 2")
    assert bindings(validate.violations(four, rule)) == [(2,)]
    assert bindings(validate.violations(four, rule, absent_in_x="satisfied")) == [(2,), (3,)]
    pair = make(spark, plain(2), [(1, 2, "e")])
    assert validate.violations(pair, parse_rule("match (x:P)-[e]->(y:P) then x.a = y.a")).count() == 1


def test_path_on_a_triangle(spark):
    g = make(spark, plain(3), [(1, 2, "e"), (2, 3, "e"), (1, 3, "e")], directed=False)
    p = Pattern.of([("a", "P"), ("b", "P"), ("c", "P")], [("a", "b", "e"), ("b", "c", "e")], directed=False)
    assert [n_matches(g, p, s) for s in ("mono", "induced", "homo")] == [6, 0, 12]
    assert validate.violations(g, Rule("r", p, (), ())).count() == 0
    assert validate.violations(g, Rule("r", p, (), FALSE)).count() == 6


def test_wildcards_loops_and_opposite_arcs(spark):
    g = make(spark, plain(2), [(1, 2, "a"), (1, 2, "b")])
    assert n_matches(g, Pattern.of(["x", "y"], [("x", "y")]), "mono") == 1
    assert n_matches(g, Pattern.of(["x", "y"], [("x", "y", "a")]), "mono") == 1
    assert g.several_labels().count() == 1
    loop = make(spark, plain(2), [(1, 1, "e"), (1, 2, "e")])
    arc, own, lone = Pattern.of(["x", "y"], [("x", "y")]), Pattern.of(["x"], [("x", "x")]), Pattern.of(["x"])
    assert [bindings(validate.match(loop, arc, semantics=s)) for s in ("mono", "induced", "homo")] == [[(1, 2)], [], [(1, 1), (1, 2)]]
    assert [bindings(validate.match(loop, own, semantics=s)) for s in ("mono", "induced", "homo")] == [[(1,)]] * 3
    assert [bindings(validate.match(loop, lone, semantics=s)) for s in ("mono", "induced")] == [[(1,), (2,)], [(2,)]]
    two = make(spark, plain(3), [(1, 2, "e"), (2, 1, "e"), (1, 3, "e")])
    assert [n_matches(two, arc, s) for s in ("mono", "induced", "homo")] == [3, 1, 3]
    both = Pattern.of(["x", "y"], [("x", "y"), ("y", "x")])
    assert [n_matches(two, both, s) for s in ("mono", "induced", "homo")] == [2, 2, 2]


def test_disconnected(spark):
    g = make(spark, [(1, "P", {"name": "n", "a": 1}), (2, "P", {"name": "n", "a": 2}), (3, "P", {"name": "m", "a": 1})], [])
    rule = validate.fd_rule("fd", "P", ["name"], ["a"])
    assert n_matches(g, rule.pattern, "mono") == 6 and n_matches(g, rule.pattern, "homo") == 9
    row = validate.counts(g, rule).first()
    assert (row["support"], row["violations"]) == (2, 2)
    assert validate.counts(g, rule, semantics="homo").first()["support"] == 5
    assert "Cartesian" not in validate.violations(g, rule)._jdf.queryExecution().executedPlan().toString()


def test_kite_star_and_squares(spark):
    g = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (1, 3, "e"), (3, 4, "e")], directed=False)
    kite = Pattern.of(["a", "b", "c", "d"], [("a", "b"), ("b", "c"), ("a", "c"), ("c", "d")], directed=False)
    star = Pattern.of(["a", "b", "c", "d"], [("a", "b"), ("a", "c"), ("a", "d")], directed=False)
    for strategy in ("direct", "indexed"):
        assert [n_matches(g, kite, s, strategy) for s in ("mono", "induced", "homo")] == [2, 2, 14]
        assert [n_matches(g, star, s, strategy) for s in ("mono", "induced", "homo")] == [6, 0, 44]
    square = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (3, 4, "e"), (4, 1, "e"), (1, 3, "e")], directed=False)
    ring = Pattern.of(["a", "b", "c", "d"], [("a", "b"), ("b", "c"), ("c", "d"), ("d", "a")], directed=False)
    assert [n_matches(square, ring, s) for s in ("mono", "induced", "homo")] == [8, 0, 50]
    assert validate.match(square, ring, distinct_subgraphs=True).count() == 1


def test_dead_ends(spark):
    g = make(spark, [(1, "X", {}), (2, "Y", {}), (3, "Z", {}), (4, "Y", {})], [(1, 2, "e"), (1, 4, "e"), (2, 3, "e")])
    p = Pattern.of([("x", "X"), ("y", "Y"), ("z", "Z")], [("x", "y"), ("y", "z")])
    index = pathindex.build_index(g, p, options=Options(degree_filter=False))
    assert bindings(index.stages["y", "label"]) == [(2,), (4,)] and bindings(index.cands["y"]) == [(2,)]
    assert bindings(pathindex.match(g, p, index=index).select("x", "y", "z")) == [(1, 2, 3)]


def test_kept_index(spark, tmp_path):
    raw = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (1, 3, "e"), (3, 4, "e")], directed=False)
    g = stored.stored(raw, "one")
    p = Pattern.of(["a", "b", "c"], [("a", "b"), ("b", "c"), ("a", "c")], directed=False)
    path = str(tmp_path / "index")
    kept = pathindex.build_index(g, p).persist(path)
    assert pathindex.match(g, p, index=kept).count() == 6 and kept.size(spark, path)["bytes"] > 0
    with pytest.raises(ValueError, match="stored graph"):
        pathindex.build_index(raw, p).persist(path)
    filtered = Needs({"a": ["a"]}, {"a": F.col("a__a") == 1})
    other = stored.stored(raw, "two")
    for wrong, word in (
        (pathindex.fingerprint(g, Pattern.of(["a", "b"], [("a", "b")])), "pattern"),
        (pathindex.fingerprint(other, p), "graph"),
        (pathindex.fingerprint(g, p, "homo"), "semantics"),
        (pathindex.fingerprint(g, p, needs=filtered), "filters"),
        (pathindex.fingerprint(g, p, options=Options(passes=1)), "options"),
    ):
        with pytest.raises(ValueError, match=word):
            CandidateIndex.load(spark, path, p, wrong)


def test_stored_graph(spark, tmp_path):
    vertices, edges = [(1, "P", {"a": 1}), (2, "P", {"a": 2}), (3, "7", {}), (4, "Q", {"a": 1})], [(1, 2, "e"), (1, 2, "f"), (2, 3, "e"), (3, 4, "0"), (4, 4, "e")]
    raw = make(spark, vertices, edges)
    path = str(tmp_path / "g")
    g = stored.stored(raw, "v", path)
    assert sorted(map(tuple, g.edges.collect())) == sorted(edges) and g.catalog == raw.catalog
    assert g.facts.vertices == {"P": 2, "7": 1, "Q": 1} and g.facts.arcs["P", "e", "P"] == 1 and g.facts.several
    assert g.facts.share_where("P", [Const("x", "a", 1)]) == 0.5 and g.facts.weight_with(1, "P", "e", "P", True) == 1
    assert sorted(map(tuple, g.arcs("e", src_label="P", dst_label="7").collect())) == [(2, 3)]
    assert bindings(g.arcs(None)) == [(1, 2), (2, 3), (3, 4), (4, 4)]
    with pytest.raises(ValueError):
        stored.load(spark, path, "w")
    none = stored.stored(make(spark, plain(2), []), "v")
    assert n_matches(none, Pattern.of(["x", "y"], [("x", "y")]), "mono", "indexed") == 0 and n_matches(none, Pattern.of(["x"]), "mono") == 2


def test_refusals(spark):
    g = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e")])
    p = Pattern.of(["a", "b"], [("a", "b")])
    for wrong in ({"placement": "somewhere"}, {"method": "none"}):
        with pytest.raises(ValueError):
            balanced.match(g, p, **wrong)
    assert balanced.placed(g, p, "auto", 1) == "joined" and balanced.placed(g, p, "auto") == "replicated"
    with pytest.raises(ValueError, match="bytes"):
        balanced.placed(g, p, "replicated", 1)
    ranges = balanced.candidate_ranges(g, Rule("r", Pattern.of(["a", "b"])), 2)
    assert balanced.messages(ranges, 2).count() == 4
    with pytest.raises(ValueError, match="messages"):
        balanced.messages(ranges, 2, most=3)


def test_ranks_split_ties(spark):
    rows = spark.createDataFrame([(i % 2, i) for i in range(500)] + [(None, 1000)], "c int, vid int")
    for descending in (False, True):
        got = [(r["c"], r["vid"]) for r in sorted(ranked(rows, ["c", "vid"], descending).collect(), key=lambda r: r["nth"])]
        some = sorted(((i % 2, i) for i in range(500)), key=lambda r: (-r[0] if descending else r[0], r[1]))
        assert got == ([*some, (None, 1000)] if descending else [(None, 1000), *some])


def test_automorphisms_of_larger_patterns():
    ring = Pattern.of([f"v{i}" for i in range(10)], [(f"v{i}", f"v{(i + 1) % 10}") for i in range(10)], directed=False)
    assert len(shape.automorphisms(ring)) == 20
    assert len(shape.automorphisms(Pattern.of([f"v{i}" for i in range(10)], [(f"v{i}", f"v{(i + 1) % 10}") for i in range(10)]))) == 10


def test_hubs_are_split(spark):
    g = make(spark, plain(12), [(1, i, "e") for i in range(2, 10)] + [(10, 11, "e"), (2, 12, "e")])
    p = Pattern.of(["x", "y", "z"], [("x", "y"), ("x", "z")])
    assert bindings(validate.match(g, p, hub_degree=3, hub_parts=4)) == bindings(validate.match(g, p))


def test_ended_by_new_arcs(spark):
    old = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (3, 4, "e")], directed=False)
    new = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (3, 4, "e"), (1, 3, "e")], directed=False)
    rule = parse_rule("match (a:P)-[e]-(b:P), (b)-[e]-(c:P) then false")
    before, after = (validate.violations(x, rule, semantics="induced") for x in (old, new))
    gone = incremental.ended(before, new, rule)
    assert bindings(gone) == sorted(set(bindings(before)) - set(bindings(after))) and gone.count() > 0


def test_factorised_leaves(spark):
    g = make(spark, [(i, "P", {"a": i % 2}) for i in range(1, 8)], [(1, i, "e") for i in range(2, 7)] + [(2, 3, "e"), (2, 4, "e"), (7, 1, "e")], directed=False)
    rule = parse_rule("match (a:P)-[e]-(b:P), (a)-[e]-(c:P), (a)-[e]-(d:P) where a.a = 1 then false")
    assert validate.counts(g, rule, leaves="count").first() == validate.counts(g, rule).first()
    assert bindings(validate.witnesses(g, rule)) == bindings(validate.violations(g, rule).select("a").distinct())
    with pytest.raises(ValueError):
        validate.counts(g, parse_rule("match (a:P)-[e]-(b:P), (a)-[e]-(c:P) then b.a = 1"), leaves="count")


def random_case(seed):
    rng = random.Random(seed)
    n, directed = rng.randint(3, 9), rng.random() < 0.5
    vertices = [(i, rng.choice("PQ"), {k: rng.randint(1, 2) for k in "ab" if rng.random() < 0.7}) for i in range(1, n + 1)]
    edges = sorted({(rng.randint(1, n), rng.randint(1, n), rng.choice("ef")) for _ in range(rng.randint(2, 18))})
    k = rng.randint(1, 4)
    names = "wxyz"[:k]
    pattern = Pattern.of([(v, rng.choice(["P", "Q", None])) for v in names], {(rng.choice(names), rng.choice(names), rng.choice(["e", "f", None])) for _ in range(rng.randint(0, 4))}, directed)
    pattern = Pattern(pattern.vertices, tuple(sorted(pattern.edges, key=repr)), directed)

    def literal():
        return Const(rng.choice(names), rng.choice("ab"), rng.randint(1, 2)) if rng.random() < 0.5 else Same(rng.choice(names), rng.choice("ab"), rng.choice(names), rng.choice("ab"))

    when = tuple(literal() for _ in range(rng.randint(0, 2)))
    then = FALSE if rng.random() < 0.3 else tuple(literal() for _ in range(rng.randint(1, 2)))
    return vertices, edges, directed, Rule("r", pattern, when, then)


def expected(vertices, edges, rule, semantics, absent):
    values = {v: at for v, _, at in vertices}

    def holds(x, m, missing):
        got = [values[m[v]].get(a) for v, a in x.uses]
        if None in got:
            return missing
        return got[0] == x.value if isinstance(x, Const) else got[0] == got[1]

    out = []
    for m in search({v: lab for v, lab, _ in vertices}, edges, rule.pattern, semantics):
        x = all(holds(lit, m, absent == "satisfied") for lit in rule.when)
        y = rule.then is not FALSE and all(holds(lit, m, False) for lit in rule.then)
        if x and not y:
            out.append(tuple(m[v] for v in rule.pattern.variables))
    return sorted(out)


@pytest.mark.parametrize("seed", [0, 1, 2, 3, 5, 7, 8, 10, 11, 13])
def test_strategies_against_search(spark, seed):
    vertices, edges, directed, rule = random_case(seed)
    g = make(spark, vertices, edges, directed)
    semantics, absent = random.Random(seed).choice([("mono", "unsatisfied"), ("induced", "unsatisfied"), ("homo", "satisfied"), ("mono", "satisfied")])
    want = expected(vertices, edges, rule, semantics, absent)
    if seed % 2:  # every other case on a graph stored by kind
        g = stored.stored(g, str(seed))
    cases = [("direct", {"hub_degree": 2, "hub_parts": 3}), ("indexed", {}), ("indexed", {"options": pathindex.FULL}), ("balanced", {"n": 2, "method": "greedy", "ranges": 2}), ("direct", {"pushdown": False, "symmetry": True}), ("auto", {})]
    for strategy, options in cases:
        assert bindings(validate.violations(g, rule, strategy, semantics, absent, **options)) == want, (strategy, options)


@pytest.mark.parametrize("seed", range(100, 104))
def test_other_strategies_against_search(spark, seed):
    vertices, edges, directed, rule = random_case(seed)
    g = make(spark, vertices, edges, directed)
    want = expected(vertices, edges, rule, "mono", "unsatisfied")
    cases = [("balanced", {"placement": "shipped", "n": 2}), ("balanced", {"local_matcher": "search", "n": 2}), ("balanced_indexed", {"n": 2}), ("indexed_parallel", {"n": 2})]
    cases += [("indexed", {"options": Options(core="shortest_cycle", passes=0)}), ("indexed", {"options": Options(use_index=False)})]
    for strategy, options in cases:
        assert bindings(validate.violations(g, rule, strategy, **options)) == want, (strategy, options)


@pytest.mark.parametrize("seed", range(200, 205))
def test_sql_form(spark, seed):
    vertices, edges, directed, rule = random_case(seed)
    g = make(spark, vertices, edges, directed)
    g.register("g")
    for semantics in ("mono", "induced", "homo"):
        assert bindings(spark.sql(rule_to_sql(rule, semantics))) == expected(vertices, edges, rule, semantics, "unsatisfied")


def test_shared_patterns(spark):
    g = make(spark, [(1, "P", {"a": 1}), (2, "P", {"a": 2, "b": 1}), (3, "P", {"b": 1})], [(1, 2, "e"), (2, 3, "e")])
    rules = [parse_rule(f"match (x:P)-[e]->(y:P) then {t}", f"r{i}") for i, t in enumerate(("x.a = y.a", "y.b = 1", "false", "true"))]
    def rows(share):
        return sorted((r["rule_id"], tuple((b["var"], b["vid"]) for b in r["binding"])) for r in validate.validate(g, rules, share=share).collect())

    assert rows(True) == rows(False) and len(rows(True)) == 4
    assert {r["rule_id"]: r["holds"] for r in validate.satisfies(g, rules).collect()} == {"r0": False, "r1": True, "r2": False, "r3": True}


def test_units_are_disjoint_and_cover(spark):
    g = make(spark, plain(6), [(i, i + 1, "e") for i in range(1, 6)], directed=False)
    units = balanced.ball_sizes(g, Pattern.of([("x", "P"), ("y", "P")], [("x", "y")], directed=False), "x", 1)
    for method in ("snake", "greedy", "hash"):
        rows = balanced.assign(units, 2, method).collect()
        assert sorted(r["vid"] for r in rows) == [1, 2, 3, 4, 5, 6] and {r["worker"] for r in rows} <= {0, 1}
    assert {r["vid"]: r["cost"] for r in units.collect()} == {1: 2, 2: 3, 3: 3, 4: 3, 5: 3, 6: 2}


def test_range_methods(spark):
    g = make(spark, [(i, "P", {"a": i % 5}) for i in range(1, 101)], [])
    rule = parse_rule("match (x:P) then x.a = x.a")
    exact = balanced.candidate_ranges(g, rule, 4).collect()
    assert sorted(r["cnt"] for r in exact) == [25] * 4
    assert sum(r["cnt"] for r in balanced.candidate_ranges(g, rule, 4, "a", "approx").collect()) == 100


def test_star_degrees_and_weights(spark):
    g = make(spark, plain(5), [(1, i, "e") for i in range(2, 6)] + [(2, 3, "e")], directed=False)
    star = Pattern.of(["a", "b", "c", "d"], [("a", "b"), ("a", "c"), ("a", "d")], directed=False)
    want = n_matches(g, star, "mono")
    assert sum(d * (d - 1) * (d - 2) for _, d in validate.star_degrees(g, star).select("centre", "d").collect()) == want
    index = pathindex.build_index(g, star, "homo")
    assert pathindex.root_weights(index, star.variables).agg(F.sum("weight")).first()[0] == n_matches(g, star, "homo")


def test_changes(spark):
    g = make(spark, plain(4), [(1, 2, "e"), (2, 3, "e"), (1, 3, "e"), (3, 4, "e")], directed=False)
    rule = parse_rule("match (a:P)-[e]-(b:P), (b)-[e]-(c:P), (a)-[e]-(c) then false")
    assert bindings(incremental.replayed(g, rule, 3)) == bindings(validate.violations(g, rule))
    found = validate.violations(g, rule)
    less = PropertyGraph(g.vertices, g.edges.where("NOT (src IN (1, 2) AND dst IN (1, 2))"), False)
    assert incremental.retracted(found, less, rule).count() == 6
    assert incremental.recheck(g, rule, spark.createDataFrame([(4,)], "vid bigint")).count() == 0


def test_stream_of_edges(spark, tmp_path):
    vertices = make(spark, plain(4), []).vertices
    rule = parse_rule("match (a:P)-[e]-(b:P), (b)-[e]-(c:P), (a)-[e]-(c) then false")
    source = tmp_path / "in"
    for i, edge in enumerate([(1, 2, "e"), (2, 3, "e"), (1, 3, "e"), (3, 4, "e")]):
        spark.createDataFrame([edge], "src bigint, dst bigint, elabel string").coalesce(1).write.mode("append").parquet(str(source))
    arcs = spark.readStream.schema("src bigint, dst bigint, elabel string").option("maxFilesPerTrigger", 1).parquet(str(source))
    paths = [str(tmp_path / n) for n in ("edges", "found", "checkpoint")]
    query = incremental.validate_stream(vertices, arcs, rule, *paths, directed=False).trigger(availableNow=True).start()
    query.awaitTermination(120)
    assert spark.read.parquet(paths[1]).count() == 6


def test_shape_of_results_without_rows(spark):
    g = make(spark, plain(1), [])
    rule = parse_rule("match (x:P)-[e]->(y:Q) then true")
    assert validate.violations(g, rule).columns == ["x", "y"] and validate.violations(g, rule).count() == 0
    assert len(shape.components(rule.pattern)) == 1


def test_pivots_with_their_candidates(spark):
    g = make(spark, [(1, "P", {}), (2, "P", {}), (5, "Q", {})], [(1, 5, "e"), (2, 5, "e")])
    rules = [parse_rule("match (a:P)-[e]->(b:Q) then false", "pair"), parse_rule("match (a:P), (b:_) then false", "two"), parse_rule("match (a:R) then false", "none")]
    want = {("pair", 0, "b", 1, 1, 5, 5), ("two", 0, "a", 0, 2, 1, 2), ("two", 1, "b", 0, 3, 1, 5), ("none", 0, "a", 0, 0, None, None)}
    assert set(map(tuple, balanced.pivot_table(g, rules).collect())) == want


def _with_copies(spark):
    """A random graph in which some arcs are there several times, with a hub and arcs to nothing."""
    import random

    rng = random.Random(3)
    arcs = [(rng.randrange(40), rng.randrange(40)) for _ in range(500)] + [(0, i) for i in range(40)] + [(7, None), (None, 7)]
    vertices = spark.createDataFrame([(i, "P", i % 3) for i in range(40)], "vid bigint, vlabel string, kind int")
    return PropertyGraph(vertices, spark.createDataFrame([(a, b, "e") for a, b in arcs], "src bigint, dst bigint, elabel string"))


@pytest.mark.parametrize("semantics", ["mono", "induced", "homo"])
def test_paths_closed_in_cells(spark, semantics):
    graph = _with_copies(spark)
    for text in ("match (a:P)-[e]->(b:P)-[e]->(c:P), (a)-[e]->(c)", "match (a:_)-[e]->(b:_)-[e]->(c:_)-[e]->(a), (c)-[e]->(d:_), (b)-[e]->(d), (d)-[e]->(a)"):
        rule = parse_rule(f"{text} then a.kind = b.kind", "r")
        want = sorted(map(tuple, validate.violations(graph, rule, semantics=semantics).collect()))
        assert want or semantics == "induced"
        for cell_arcs in (1 << 20, 20):
            assert sorted(map(tuple, validate.violations(graph, rule, semantics=semantics, in_cells=True, cell_arcs=cell_arcs).collect())) == want


def test_lists_of_a_cell_meet_a_few_at_a_time(spark):
    import pyarrow as pa

    from lattica.plans.steps import _cell_matches

    rows = [(-1, None, None, 1, 2), (-1, None, None, 1, 2), (-1, None, None, 3, 2), (-1, None, None, 9, 2), (1, 2, [5, 6, 7], None, None), (2, 2, [8], None, None), (0, 1, [4, 6, 7, 8], None, None), (0, 3, [5], None, None)]
    batch = pa.RecordBatch.from_pylist([dict(zip(("_role", "_end", "_list", "a", "b"), r, strict=True)) for r in rows], pa.schema([("_role", pa.int32()), ("_end", pa.int64()), ("_list", pa.list_(pa.int64())), ("a", pa.int64()), ("b", pa.int64())]))
    for marks, at_once in ((1, 1), (10, 3), (1 << 20, 1 << 20)):
        found = [tuple(r.values()) for out in _cell_matches(["a", "b"], "b", "c", "a", marks, at_once)(iter([batch])) for r in out.to_pylist()]
        assert sorted(found) == sorted([(1, 2, c) for c in (6, 7, 8, 8)] * 2 + [(3, 2, 5)])
