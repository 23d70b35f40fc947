"""Statistics and match orders."""

from lattica.model.graph import PropertyGraph
from lattica.plans.cost import Statistics
from lattica.rules.ast import Pattern


def test_order_starts_where_few_vertices_are(spark):
    vertices = spark.createDataFrame([(i, "A" if i < 3 else "B") for i in range(60)], "vid bigint, vlabel string")
    edges = spark.createDataFrame([(i % 3, i, "e") for i in range(3, 60)], "src bigint, dst bigint, elabel string")
    stats = Statistics.of(PropertyGraph.of(vertices, edges))
    pattern = Pattern.of([("x", "B"), ("y", "A")], [("y", "x", "e")])
    assert stats.matching(pattern, pattern.edges[0]) == 57
    assert stats.best_order(pattern, ("x", "y"))[0] == "y"
    assert [c for _, c, _ in stats.tree(pattern, ("y", "x"))] == ["x"] and stats.best_order(pattern, ("x", "y"), exhaustive=1) == ("y", "x")
    path = Pattern.of(["a", "b", "c"], [("a", "b"), ("b", "c")])
    assert stats.order_cost(path, ("a", "c", "b")) == float("inf")
