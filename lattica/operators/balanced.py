"""Strategy `balanced`: pivots are dealt to workers as units of near-equal total cost, and each worker matches from its pivots.

The coordinator's part (pivots, ranges, messages) is tables of a few rows; units, costs and the split are distributed.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable
from functools import reduce
from itertools import product
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph
from ..plans import steps
from ..plans.ranks import ranked
from ..plans.steps import Needs
from ..rules import shape
from ..rules.ast import Pattern, Rule
from ..sources.store import saved, ship
from . import reference

#: Bytes of arcs (24 each) that `placement="replicated"` may copy to every worker.
REPLICATED_BYTES = 64 << 20
#: Units that the greedy split may bring to the driver, and messages that it may make there: more is an error.
GREEDY_UNITS, MOST_MESSAGES = 1_000_000, 1_000_000


def _label_counts(graph: PropertyGraph) -> dict[str | None, int]:
    counts: dict[str | None, int] = dict(graph.facts.vertices) if graph.facts else {r["vlabel"]: r["n"] for r in graph.label_counts().collect()}  # one row per label
    counts[None] = sum(counts.values())
    return counts


def pivots(graph: PropertyGraph, pattern: Pattern) -> list[tuple[str, int]]:
    """(variable, radius) per component; label counts break ties."""
    tied = any(len([v for v in part if shape.eccentricity(pattern, v) == min(shape.eccentricity(pattern, w) for w in part)]) > 1 and len({pattern.label(v) for v in part}) > 1 for part in shape.components(pattern))
    return shape.pivot_vector(pattern, _label_counts(graph) if tied else None)


def pivot_table(graph: PropertyGraph, rules: Iterable[Rule]) -> DataFrame:
    """rule_id, component, var, radius, and of the pivot's candidates their number, least and greatest vid, from one pass over the vertices."""
    rows = [(r.rule_id, i, v, k, r.pattern.label(v)) for r in rules for i, (v, k) in enumerate(pivots(graph, r.pattern))]
    chosen = graph.vertices.sparkSession.createDataFrame(rows, "rule_id string, component int, var string, radius int, label string")
    found = graph.vertices.groupBy("vlabel").agg(F.count(F.lit(1)).alias("n"), F.min("vid").alias("lo"), F.max("vid").alias("hi"))  # one row per label
    met = F.broadcast(chosen).join(found, F.col("label").isNull() | (F.col("label") == F.col("vlabel")), "left")
    return met.groupBy("rule_id", "component", "var", "radius").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("candidates"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))


def pivot_candidates(graph: PropertyGraph, rule: Rule, range_attr: str = "vid") -> DataFrame:
    """rule_id, component, var, vid, attr_value of all candidates of the rule's pivots."""
    out = []
    for i, (var, _) in enumerate(pivots(graph, rule.pattern)):
        value = F.col(range_attr) if range_attr == "vid" else graph.attribute(range_attr)
        out.append(graph.labelled(rule.pattern.label(var)).select(F.lit(rule.rule_id).alias("rule_id"), F.lit(i).alias("component"), F.lit(var).alias("var"), "vid", value.alias("attr_value")))
    return reduce(DataFrame.unionByName, out)


def candidate_histogram(graph: PropertyGraph, rules: Iterable[Rule], range_attr: str = "vid") -> DataFrame:
    """rule_id, var, attr_value, cnt: how often each attribute value occurs among the candidates."""
    rows = [pivot_candidates(graph, r, range_attr).groupBy("rule_id", "var", "attr_value").agg(F.count(F.lit(1)).alias("cnt")) for r in rules]
    return reduce(DataFrame.unionByName, rows)


def ranged_candidates(graph: PropertyGraph, rule: Rule, m: int, range_attr: str = "vid", method: str = "exact") -> DataFrame:
    """The pivots' candidates (rule_id, component, var, vid, attr_value) with range_id: m ranges (from 0) with as many candidates each.

    Exact: candidates are ranked by attribute and id. Approx: bounds from approximate quantiles, in one pass; equal values share a
    range. Candidates without the attribute come first.
    """
    out = []
    rows = pivot_candidates(graph, rule, range_attr)
    for i, _ in enumerate(pivots(graph, rule.pattern)):
        own = rows.where(F.col("component") == i)
        if method == "approx":
            cuts = own.agg(F.percentile_approx("attr_value", [k / m for k in range(1, m)], 10_000)).first()[0] if m > 1 else []
            cuts = sorted(set(cuts or []))
            number = reduce(lambda acc, c: acc + (F.col("attr_value") > F.lit(c)).cast("int"), cuts, F.lit(0))
            out.append(own.withColumn("range_id", F.coalesce(number, F.lit(0))))
        else:
            out.append(ranked(own, ["attr_value", "vid"]).withColumn("range_id", F.floor((F.col("nth") - 1) * m / F.col("total")).cast("int")).drop("nth", "total"))
    return reduce(DataFrame.unionByName, out)


def candidate_ranges(graph: PropertyGraph, rule: Rule, m: int, range_attr: str = "vid", method: str = "exact") -> DataFrame:
    """rule_id, component, var, range_id, lo, hi, cnt of the ranges."""
    dealt = ranged_candidates(graph, rule, m, range_attr, method)
    return dealt.groupBy("rule_id", "component", "var", "range_id").agg(F.min("attr_value").alias("lo"), F.max("attr_value").alias("hi"), F.count(F.lit(1)).alias("cnt"))


def messages(ranges: DataFrame, n: int, most: int = MOST_MESSAGES) -> DataFrame:
    """msg_id, rule_id, ranges (component:range, ...), worker: a message for each tuple of ranges, one range per component, dealt in turn.

    Ranges are few (m per component), and their product is made on the driver; more than `most` messages are an error.
    """
    rows = [(k, rule_id, ",".join(f"{c}:{x}" for c, x in combo), k % n) for k, (rule_id, combo) in enumerate(_tuples(ranges, most))]
    return ranges.sparkSession.createDataFrame(rows, "msg_id int, rule_id string, ranges string, worker int")


def _tuples(ranges: DataFrame, most: int) -> list[tuple[str, tuple[tuple[int, int], ...]]]:
    """(rule_id, ((component, range), ...)) of all messages."""
    by: dict[str, dict[int, list[int]]] = {}
    for r in ranges.select("rule_id", "component", "range_id").collect():
        by.setdefault(r["rule_id"], {}).setdefault(r["component"], []).append(r["range_id"])
    if sum(prod(map(len, parts.values())) for parts in by.values()) > most:
        raise ValueError(f"more than {most} messages: ask for fewer ranges")
    return [(rule_id, combo) for rule_id in sorted(by) for combo in product(*[[(c, x) for x in sorted(by[rule_id][c])] for c in sorted(by[rule_id])])]


def ball_sizes(graph: PropertyGraph, pattern: Pattern, var: str, radius: int) -> DataFrame:
    """vid and cost of each candidate: the vertices within the radius, itself included."""
    seeds = graph.labelled(pattern.label(var)).select("vid")
    return graph.ball(seeds, radius).groupBy(F.col("centre").alias("vid")).agg(F.count(F.lit(1)).alias("cost"))


def work_units(graph: PropertyGraph, rules: Iterable[Rule]) -> DataFrame:
    """rule_id, component, var, vid, cost: a unit for each candidate of each pivot.

    A rule with several components has tuples of pivots as units, with the sum of their balls as cost. Tuples are never
    made one by one: a message stands for all tuples of its ranges, and `message_costs` adds their costs up.
    """
    out = []
    for r in rules:
        for i, (var, radius) in enumerate(pivots(graph, r.pattern)):
            out.append(ball_sizes(graph, r.pattern, var, radius).select(F.lit(r.rule_id).alias("rule_id"), F.lit(i).alias("component"), F.lit(var).alias("var"), "vid", "cost"))
    return reduce(DataFrame.unionByName, out)


def workload(units: DataFrame) -> DataFrame:
    """rule_id, var, units, total_cost, max_cost."""
    return units.groupBy("rule_id", "var").agg(F.count(F.lit(1)).alias("units"), F.sum("cost").cast("bigint").alias("total_cost"), F.max("cost").alias("max_cost"))


def greedy_split(costs: list[tuple[int, int]], n: int) -> dict[int, int]:
    """Worker of each unit id: the dearest unit next, always to the worker with the least load (then the lowest number)."""
    heap = [(0, w) for w in range(n)]
    out = {}
    for unit, cost in sorted(costs, key=lambda x: (-x[1], x[0])):
        load, w = heapq.heappop(heap)
        out[unit] = w
        heapq.heappush(heap, (load + cost, w))
    return out


def assign(units: DataFrame, n: int, method: str = "snake") -> DataFrame:
    """Adds worker to units (vid, cost). snake: rank by cost, deal to and fro; greedy: on the driver, for few units; hash: no balance."""
    if method == "hash":
        return units.withColumn("worker", F.pmod(F.xxhash64("vid"), F.lit(n)).cast("int"))
    if method not in ("snake", "greedy"):
        raise ValueError("method is one of snake, greedy, hash")
    if method == "greedy":
        if units.count() > GREEDY_UNITS:
            raise ValueError(f"the greedy split works on the driver, for up to {GREEDY_UNITS} units: use snake")
        given = greedy_split([(r["vid"], r["cost"]) for r in units.select("vid", "cost").collect()], n)
        table = units.sparkSession.createDataFrame(list(given.items()) or [], "vid bigint, worker int")
        return units.join(table, "vid")
    turn = F.pmod(F.col("nth") - 1, F.lit(2 * n))
    return ranked(units, ["cost", "vid"], descending=True).withColumn("worker", F.when(turn < n, turn).otherwise(2 * n - 1 - turn).cast("int")).drop("nth", "total")


def balance(assigned: DataFrame) -> DataFrame:
    """worker, units, load."""
    return assigned.groupBy("worker").agg(F.count(F.lit(1)).alias("units"), F.sum("cost").cast("bigint").alias("load"))


def _bfs_order(pattern: Pattern, root: str):
    return shape.spanning_tree(pattern, root)


PLACEMENTS = ("auto", "replicated", "joined", "shipped")


def arcs_bytes(graph: PropertyGraph, pattern: Pattern) -> int:
    """Bytes of the arcs that the pattern's edges read, 24 each."""
    kinds = {(pattern.label(e.src), e.label, pattern.label(e.dst)) for e in pattern.edges}
    if graph.facts:
        return 24 * sum(graph.facts.matching(*k) + (graph.facts.matching(*k[::-1]) if graph.directed and not pattern.directed else 0) for k in kinds)
    return 24 * len(kinds) * graph.edges.count()


def placed(graph: PropertyGraph, pattern: Pattern, placement: str, most: int = REPLICATED_BYTES) -> str:
    """The placement to use: auto is replicated where the arcs fit, else joined; replicated is refused where they don't."""
    if placement not in PLACEMENTS:
        raise ValueError(f"placement is one of {PLACEMENTS}")
    if placement not in ("auto", "replicated"):
        return placement
    size = arcs_bytes(graph, pattern)
    if size > most and placement == "replicated":
        raise ValueError(f"{size} bytes of arcs are too many to copy to every worker: use joined, shipped or auto")
    return "replicated" if size <= most else "joined"


def match_units(graph: PropertyGraph, pattern: Pattern, assigned: DataFrame, part: tuple[str, ...], pivot: str, radius: int, n: int, semantics: str = "mono", needs: Needs | None = None, placement: str = "auto", local_matcher: str = "joins", replicated_bytes: int = REPLICATED_BYTES) -> DataFrame:
    """Bindings of a component from the pivots (vid, worker, other columns are kept) of all workers, each binding by the worker of its pivot.

    replicated: every worker sees the whole graph, as copies of the arcs; joined: arcs stay where they are and are met by
    shuffles; shipped: each worker gets the balls of its pivots.
    """
    seeds = assigned.withColumnRenamed("vid", pivot)
    order = _bfs_order(pattern, pivot)
    if local_matcher == "search":
        return _searched(graph, pattern, seeds, part, pivot, radius, semantics, needs)
    placement = placed(graph, pattern, placement, replicated_bytes)
    if placement == "shipped":
        own = _shipped(graph, pattern, seeds, pivot, radius)

        def arcs(e):
            return own if e.label is None else own.where(F.array_contains("labels", e.label))

        def pairs(e):
            return arcs(e).select("worker", "src", "dst")

        def shipped_link(p, c, e):
            found = steps.oriented(pairs(e), e, p, c)
            return found.join(steps.candidates(graph, pattern, c, needs), c) if pattern.label(c) is not None or not steps.free(graph, pattern, c, needs) else found

        start = seeds.join(steps.candidates(graph, pattern, pivot, needs), pivot)
        return steps.component_matches(pattern, part, start, pivot, order, shipped_link, pairs, lambda u, v: own.select("worker", "src", "dst"), semantics, ("worker",)).drop("worker")
    copy = F.broadcast if placement == "replicated" else (lambda df: df)

    def link(p, c, e):
        return copy(steps.oriented(steps.arcs_of(graph, pattern, e), e, p, c))

    def dress(df, c):
        return df if steps.free(graph, pattern, c, needs) else df.join(steps.candidates(graph, pattern, c, needs), c)

    start = steps.candidates(graph, pattern, pivot, needs).join(seeds, pivot).repartition(n, "worker").drop("worker")
    return steps.component_matches(pattern, part, start, pivot, order, link, lambda e: copy(steps.arcs_of(graph, pattern, e)), steps.any_arc(graph, pattern), semantics, (), dress)


def _shipped(graph: PropertyGraph, pattern: Pattern, seeds: DataFrame, pivot: str, radius: int) -> DataFrame:
    """worker, src, dst, labels: for each worker all arcs between vertices of its pivots' balls."""
    reached = seeds.select("worker", F.col(pivot).alias("vid"))
    frontier, around = reached, graph.arcs(None, closed=True)
    for _ in range(radius):
        frontier = frontier.join(around, F.col("vid") == F.col("src")).select("worker", F.col("dst").alias("vid")).distinct()
        reached = reached.union(frontier).distinct()
    rows = graph.edges
    if not pattern.directed and graph.directed:
        rows = rows.union(rows.select("dst", "src", "elabel")).distinct()
    arcs = rows.groupBy("src", "dst").agg(F.collect_set("elabel").alias("labels"))
    from_ = arcs.join(reached.withColumnRenamed("vid", "src"), "src")
    return from_.join(reached.withColumnRenamed("vid", "dst"), ["worker", "dst"], "left_semi").select("worker", "src", "dst", "labels")


def _searched(graph, pattern, seeds, part, pivot, radius, semantics, needs) -> DataFrame:
    """The search routine itself, over the arcs and vertices of one pivot's ball at a time: for comparison only, as each ball is searched in Python."""
    import pandas as pd

    seeds = seeds.withColumn("worker", F.col(pivot))

    ship(graph.vertices.sparkSession)
    inner = Pattern(tuple(v for v in pattern.vertices if v.var in part), tuple(e for e in pattern.edges if e.src in part), pattern.directed)
    own = _shipped(graph, pattern, seeds, pivot, radius).select("worker", "src", "dst", F.explode("labels").alias("elabel"))
    loose = seeds.select("worker", F.col(pivot).alias("src"), F.lit(None).cast("bigint").alias("dst"), F.lit(None).cast("string").alias("elabel"))
    rows = own.unionByName(loose)
    # labels come with both ends
    label = graph.vertices.select("vid", "vlabel")
    rows = rows.join(label.select(F.col("vid").alias("src"), F.col("vlabel").alias("src_label")), "src").join(label.select(F.col("vid").alias("dst"), F.col("vlabel").alias("dst_label")), "dst", "left")
    # pandas would turn missing ends into floats
    rows = rows.withColumn("dst", F.coalesce("dst", F.lit(-1)))
    names = list(part)

    def run(pdf):
        labels = dict(zip(pdf["src"], pdf["src_label"], strict=True))
        real = pdf[pdf["dst"] >= 0]
        labels |= dict(zip(real["dst"], real["dst_label"], strict=True))
        mine = set(pdf.loc[pdf["dst"] < 0, "src"])
        found = reference.search({int(k): v for k, v in labels.items()}, {(int(a), int(b), e) for a, b, e in zip(real["src"], real["dst"], real["elabel"], strict=True)}, inner, semantics, {pivot: {int(v) for v in mine}})
        return pd.DataFrame(list(found), columns=names, dtype="int64")

    df = rows.groupBy("worker").applyInPandas(run, ", ".join(f"{v} bigint" for v in names))
    for v in names:
        if needs and (needs.attrs.get(v) or v in needs.filters):
            df = df.join(steps.candidates(graph, pattern, v, needs), v)
    return df


def dealt_units(graph: PropertyGraph, rule: Rule, n: int, ranges: int, range_attr: str = "vid", method: str = "snake") -> DataFrame:
    """The coordinator's part for a connected pattern: ranges, messages, the units that each message brings (vid, msg_id, cost), and their split (worker)."""
    (var, radius), *_ = pivots(graph, rule.pattern)
    found = saved(ranged_candidates(graph, rule, ranges, range_attr), "ranged")
    told = messages(found.select("rule_id", "component", "range_id").distinct(), n).select(F.split("ranges", ":")[1].cast("int").alias("range_id"), "msg_id")
    costs = ball_sizes(graph, rule.pattern, var, radius)
    return assign(found.join(F.broadcast(told), "range_id").join(costs, "vid").select("vid", "msg_id", "cost"), n, method)


def message_costs(graph: PropertyGraph, rule: Rule, found: DataFrame, most: int = MOST_MESSAGES) -> list[tuple[int, dict[int, int], int]]:
    """msg_id, range of each component, and the sum of the costs of all tuples of pivots in them. found: `ranged_candidates`."""
    facts = []
    for i, (var, radius) in enumerate(pivots(graph, rule.pattern)):
        rows = found.where(F.col("component") == i).join(ball_sizes(graph, rule.pattern, var, radius), "vid")
        facts.append({r["range_id"]: (r["n"], r["cost"]) for r in rows.groupBy("range_id").agg(F.count(F.lit(1)).alias("n"), F.sum("cost").alias("cost")).collect()})  # one row per range
    if not all(facts):  # a component without candidates: no tuple of pivots
        return []
    out = []
    for k, (_, combo) in enumerate(_tuples(found.select("rule_id", "component", "range_id").distinct(), most)):
        chosen = [facts[c][x] for c, x in combo]
        pairs = prod(m for m, _ in chosen)
        out.append((k, dict(combo), sum(cost * pairs // m for m, cost in chosen)))
    return out


def match(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, n: int = 4, method: str = "snake", placement: str = "auto", local_matcher: str = "joins", ranges: int = 8, range_attr: str = "vid") -> DataFrame:
    """The whole scheme: candidates in even ranges, a message per tuple of ranges, the units of each message with their costs,
    a split of near-equal cost, and each worker's search from its pivots.

    With several components the messages themselves are split, by the cost of all tuples of pivots in them (greedy, on the
    driver, where they were made), and bindings of the components meet within a message.
    """
    rule, parts, centres = Rule("scheme", pattern), shape.components(pattern), pivots(graph, pattern)
    if len(parts) == 1:
        (pivot, radius), part = centres[0], parts[0]
        units = dealt_units(graph, rule, n, ranges, range_attr, method).select("vid", "worker")
        return steps.combined(graph, pattern, [(part, match_units(graph, pattern, units, part, pivot, radius, n, semantics, needs, placement, local_matcher))], semantics, needs)
    found = saved(ranged_candidates(graph, rule, ranges, range_attr), "ranged")
    told = message_costs(graph, rule, found)
    workers = greedy_split([(k, cost) for k, _, cost in told], n)
    spark, out = graph.vertices.sparkSession, []
    for i, (part, (pivot, radius)) in enumerate(zip(parts, centres, strict=True)):
        dealt = spark.createDataFrame([(k, by[i], workers[k]) for k, by, _ in told], "_msg int, range_id int, worker int")
        own = found.where(F.col("component") == i).select("vid", "range_id")
        once = match_units(graph, pattern, own.withColumn("worker", F.col("range_id")), part, pivot, radius, n, semantics, needs, "shipped" if placement == "shipped" else placement, local_matcher)
        if "range_id" not in once.columns:
            once = once.join(own.withColumnRenamed("vid", pivot), pivot)
        out.append((part, once.join(F.broadcast(dealt), "range_id").drop("range_id", "worker")))
    return steps.combined(graph, pattern, out, semantics, needs, "_msg").drop("_msg")
