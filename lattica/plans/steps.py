"""The join plan of a component: link a new variable, close an edge between two bound ones, keep variables apart, forbid arcs.

Everything is one lazy DataFrame; Catalyst picks the joins. The order of the steps is ours, and a step closes every
pattern edge as soon as both its ends are bound, so that open wedges don't pile up.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import reduce
from itertools import permutations
from operator import and_

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.literals import attr_column
from ..model.graph import PropertyGraph
from ..rules.ast import Edge, Pattern, Same

SEMANTICS = ("mono", "induced", "homo")


@dataclass
class Needs:
    """Attributes that a caller wants with each variable, and filters on candidates; said: the literals of a filter, negated or not."""

    attrs: dict[str, list[str]] = field(default_factory=dict)
    filters: dict[str, Column] = field(default_factory=dict)
    joins: list[Same] = field(default_factory=list)
    said: dict[str, list[tuple[tuple, bool]]] = field(default_factory=dict)
    #: Conditions that the caller puts on bindings, with their variables: a plan that Spark can't push filters through has them early.
    checks: list[tuple[frozenset[str], Column]] = field(default_factory=list)


def candidates(graph: PropertyGraph, pattern: Pattern, var: str, needs: Needs | None = None) -> DataFrame:
    """[var, attributes] of the vertices with the variable's label that pass its filter."""
    attrs = (needs.attrs if needs else {}).get(var, [])
    rows = graph.labelled(pattern.label(var)).select(F.col("vid").alias(var), *[_typed(graph, a).alias(attr_column(var, a)) for a in attrs])
    return rows.where(needs.filters[var]) if needs and var in needs.filters else rows


def _typed(graph: PropertyGraph, attr: str) -> Column:
    return graph.attribute(attr)


def free(graph: PropertyGraph, pattern: Pattern, var: str, needs: Needs | None) -> bool:
    """No candidate table has to be joined to arcs of the variable: any vertex will do, or the arcs' kinds settle the label."""
    return (pattern.label(var) is None or graph.kinds is not None) and not (needs and (needs.attrs.get(var) or var in needs.filters))


def arcs_of(graph: PropertyGraph, pattern: Pattern, edge: Edge) -> DataFrame:
    """(src, dst) that match a pattern edge; an undirected one over a directed graph takes both directions."""
    return graph.arcs(edge.label, not pattern.directed, pattern.label(edge.src), pattern.label(edge.dst))


def any_arc(graph: PropertyGraph, pattern: Pattern) -> Callable[[str, str], DataFrame]:
    """Arcs of any label between two variables' vertices, for what must not be there."""
    return lambda u, v: graph.arcs(None, not pattern.directed, pattern.label(u), pattern.label(v))


def oriented(arcs: DataFrame, edge: Edge, parent: str, child: str) -> DataFrame:
    a, b = ("src", "dst") if edge.src == parent else ("dst", "src")
    return arcs.select(*[c for c in arcs.columns if c not in ("src", "dst")], F.col(a).alias(parent), F.col(b).alias(child))


def split_hubs(df: DataFrame, pairs: DataFrame, parent: str, child: str, hub_degree: int, salts: int) -> DataFrame:
    """df joined with pairs (parent, child) on the parent, arcs of hubs being dealt to `salts` parts.

    A hub has more than hub_degree pairs, so there are at most pairs / hub_degree hubs. Rows of df at a hub go to all its parts,
    each of its arcs to one, so every match is made once and no task has all arcs of a hub.
    """
    hubs = pairs.groupBy(parent).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > hub_degree).select(F.col(parent).alias("_hub"))
    heavy = F.col("_hub").isNotNull()
    dealt = pairs.join(hubs, F.col(parent) == F.col("_hub"), "left").withColumn("_salt", F.when(heavy, F.pmod(F.xxhash64(child), F.lit(salts))).otherwise(0).cast("int")).drop("_hub")
    ways = F.when(heavy, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    spread = df.join(hubs, F.col(parent) == F.col("_hub"), "left").withColumn("_salt", F.explode(ways)).drop("_hub")
    return spread.join(dealt, [parent, "_salt"]).drop("_salt")


#: Arcs between two blocks of vertices at most, blocks at least, and tasks at most, where paths are closed in cells.
CELL_ARCS, LEAST_BLOCKS, MOST_TASKS = 1 << 20, 3, 4096


def closed_in_cells(df: DataFrame, pairs: DataFrame, closing: DataFrame, parent: str, child: str, other: str, blocks: int) -> DataFrame:
    """df joined with pairs (parent, child) on the parent, where closing has (other, child) too; open paths are neither shuffled nor sorted.

    Vertices are dealt to blocks by hash. A cell is a block of others, one of parents and one of children, and gets the arcs between
    them as lists of children; rows of df go to a cell for each block of children. An arc goes to as many cells as there are
    blocks, so with sqrt(arcs / CELL_ARCS) blocks all that is shuffled are arcs^1.5 / sqrt(CELL_ARCS) arcs.
    """

    def block(v: str) -> Column:
        return F.pmod(F.xxhash64(v), F.lit(blocks)).cast("int")

    def cell(o: Column, p: Column, c: Column) -> Column:
        return ((o * blocks + p) * blocks + c).alias("_cell")

    def lists(arcs: DataFrame, end: str) -> DataFrame:
        """_end, _c (block of children), _list; an arc that is there n times is in lists of _n, of which there are n."""
        arcs = arcs.select(F.col(end).alias("_end"), F.col(child).alias("_child"), block(child).alias("_c")).where("_end is not null and _child is not null")
        once = arcs.repartition("_end", "_c").groupBy("_end", "_c", "_child").agg(F.count(F.lit(1)).cast("int").alias("_n"))
        return once.groupBy("_end", "_c", "_n").agg(F.sort_array(F.collect_list("_child")).alias("_list"))

    def laid(rows: DataFrame, roles: list[Column]) -> DataFrame:
        """A list of a role (_n: parents' lists, 0: others') goes to the cells of all blocks of the third kind."""
        rows = rows.withColumn("_role", F.explode(F.array(*roles))).withColumn("_p", every)
        place = F.when(F.col("_role") > 0, cell(F.col("_p"), block("_end"), F.col("_c"))).otherwise(cell(block("_end"), F.col("_p"), F.col("_c")))
        return rows.select(place.alias("_cell"), "_role", "_end", "_list", *none)

    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    none = [F.lit(None).cast(f.dataType).alias(f.name) for f in df.schema]
    near, ends = lists(pairs, parent), lists(closing, other)
    # the arcs of both may be the same, as in an undirected graph: then lists are made once
    held = laid(near, [F.col("_n"), F.lit(0)]) if near.sameSemantics(ends) else laid(near, [F.col("_n")]).union(laid(ends, [F.lit(0)]))
    spread = df.where(F.col(parent).isNotNull() & F.col(other).isNotNull()).withColumn("_c", every)
    spread = spread.select(cell(block(other), block(parent), F.col("_c")), F.lit(-1).alias("_role"), F.lit(None).cast("bigint").alias("_end"), F.array().cast("array<bigint>").alias("_list"), *df.columns)  # Arrow's writer goes over null lists again and again
    schema = T.StructType([*(T.StructField(f.name, f.dataType) for f in df.schema), T.StructField(child, T.LongType())])
    rows = spread.union(held).repartition(min(2 * blocks**3, MOST_TASKS), "_cell")
    return rows.groupBy("_cell").applyInArrow(_cell_matches(df.columns, parent, child, other), schema)


def _cell_matches(columns: list[str], parent: str, child: str, other: str, marks: int = 1 << 24, paths_at_once: int = 1 << 19):
    """The rows of a cell (_role -1) with each child that is in a list of their parent (_role n, n times) and in one of their other
    end (_role 0), as a function of its Arrow batches: some of the other ends at a time have their children marked in a table of
    `marks` bytes, where the rows' paths are looked up.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import pyarrow.compute as pc

        def pieces(sizes, most):
            """Bounds of runs of items whose sizes add up to so much at most, or of one larger item."""
            total, at = np.concatenate([[0], np.cumsum(sizes)]), 0
            while at < len(sizes):
                to = max(at + 1, int(np.searchsorted(total, total[at] + most, "right")) - 1)
                yield at, to
                at = to

        def places(first, sizes):
            """The places of all items of ranges, one range after the other."""
            return np.repeat(first - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())

        rows, near, ends = [], [], []
        for b in batches:
            role = b.column(b.schema.get_field_index("_role"))
            for out, chosen, names in ((rows, pc.equal(role, -1), columns), (near, pc.greater(role, 0), ["_end", "_list", "_role"]), (ends, pc.equal(role, 0), ["_end", "_list"])):
                out.append(pa.Table.from_batches([b.select(names).filter(chosen)]))
        rows, near, ends = (pa.concat_tables(x).combine_chunks() for x in (rows, near, ends))
        if not (len(rows) and len(near) and len(ends)):
            return

        def flat(lists):
            """Ends, their lists' sizes, and all children, by end."""
            at = pc.sort_indices(lists["_end"])
            lists = lists.take(at)
            return lists["_end"].to_numpy(), pc.list_value_length(lists["_list"]).to_numpy().astype(np.int64), pc.list_flatten(lists["_list"]).to_numpy()

        of_other, n_other, closing = flat(ends)
        children = np.unique(closing)
        closing = np.searchsorted(children, closing)
        times = near["_role"].to_numpy()
        near = pa.concat_tables([near, *[near.filter(pa.array(times > k)) for k in range(1, times.max())]])
        of_parent, n_parent, found = flat(near)
        place = np.minimum(np.searchsorted(children, found), len(children) - 1)
        good = children[place] == found  # other children close no path here
        total = np.concatenate([[0], np.cumsum(good)])
        upto = np.cumsum(n_parent)
        n_parent, found = total[upto] - total[upto - n_parent], place[good]
        # an end's lists lie side by side
        first_parent, first_other = np.concatenate([[0], np.cumsum(n_parent)]), np.concatenate([[0], np.cumsum(n_other)])
        others = np.unique(of_other)
        low, high = first_other[np.searchsorted(of_other, others)], first_other[np.searchsorted(of_other, others, "right")]

        a, b = rows[other].to_numpy(), rows[parent].to_numpy()
        own = np.minimum(np.searchsorted(others, a), len(others) - 1)
        begin = first_parent[np.searchsorted(of_parent, b)]
        paths = first_parent[np.searchsorted(of_parent, b, "right")] - begin
        order = np.flatnonzero((others[own] == a) & (paths > 0))
        order = order[np.argsort(own[order], kind="stable")]
        own, begin, paths = own[order], begin[order], paths[order]
        wide = len(children)
        table = np.zeros(max(wide, marks), dtype=bool)
        at_once = len(table) // wide
        for lo in range(0, len(others), at_once):
            hi = min(lo + at_once, len(others))
            x, y = np.searchsorted(own, [lo, hi])
            if x == y:
                continue
            sizes = high[lo:hi] - low[lo:hi]
            marked = np.repeat(np.arange(hi - lo) * wide, sizes) + closing[low[lo] : high[hi - 1]]
            table[marked] = True
            for i, j in pieces(paths[x:y], paths_at_once):
                n = paths[x + i : x + j]
                c = found[places(begin[x + i : x + j], n)]
                met = np.flatnonzero(table[np.repeat((own[x + i : x + j] - lo) * wide, n) + c])
                if len(met):
                    which = order[x + i : x + j][np.searchsorted(np.cumsum(n), met, "right")]
                    taken = rows.take(pa.array(which)).append_column(child, pa.array(children[c[met]]))
                    yield from taken.combine_chunks().to_batches()
            table[marked] = False

    return run


def apart(var: str, others: list[str]) -> Column:
    return reduce(and_, (F.col(var) != F.col(o) for o in others), F.lit(True))


def declared_order(pattern: Pattern, part: tuple[str, ...]) -> tuple[str, list[tuple[str, str, Edge]]]:
    """Start and links in the order of the pattern's edges, each taken as soon as it touches what is bound."""
    bound, links, left = {part[0]}, [], [e for e in pattern.edges if e.src in part]
    if left:
        bound = {left[0].src}
    start = next(iter(bound))
    while True:
        e = next((e for e in left if (e.src in bound) != (e.dst in bound)), None)
        if e is None:
            return start, links
        parent, child = (e.src, e.dst) if e.src in bound else (e.dst, e.src)
        links.append((parent, child, e))
        bound.add(child)
        left.remove(e)


def component_matches(
    pattern: Pattern,
    part: tuple[str, ...],
    start: DataFrame,
    first: str,
    order: list[tuple[str, str, Edge]],
    link: Callable[[str, str, Edge], DataFrame],
    arcs: Callable[[Edge], DataFrame],
    every_arc: Callable[[str, str], DataFrame],
    semantics: str,
    keys: tuple[str, ...] = (),
    dress: Callable[[DataFrame, str], DataFrame] | None = None,
    hubs: tuple[int, int] | None = None,
    cells: Callable[[Edge], int] | None = None,
    checks: list[tuple[frozenset[str], Column]] | None = None,
) -> DataFrame:
    """Bindings of one component. link gives (parent, child and its attributes); keys are extra columns that all joins share; dress joins what links don't bring of a new variable; hubs: (degree, parts) from which a vertex's arcs are split; cells: the blocks of vertices by which a new variable without attributes is linked and an edge of it closed at once, after those of checks that can be made."""
    if semantics not in SEMANTICS:
        raise ValueError(f"semantics is one of {SEMANTICS}")
    df, bound, left = start, [first], [e for e in pattern.edges if e.src in part]

    def closed(df: DataFrame) -> DataFrame:
        for e in [e for e in left if e.src in bound and e.dst in bound]:
            left.remove(e)
            if e.src == e.dst:
                loops = arcs(e).where("src = dst").select(*keys, F.col("src").alias(e.src))
                df = df.join(loops, [*keys, e.src], "left_semi")
            else:
                df = df.join(arcs(e).select(*keys, F.col("src").alias(e.src), F.col("dst").alias(e.dst)), [*keys, e.src, e.dst], "left_semi")
        return df

    df = closed(df)
    for parent, child, edge in order:
        left.remove(edge)
        pairs = link(parent, child, edge)
        closer = next((e for e in left if child in (e.src, e.dst) and {e.src, e.dst} - {child} <= set(bound) - {parent} and e.src != e.dst), None)
        if cells and closer and not keys and set(pairs.columns) == {parent, child}:
            left.remove(closer)
            other = closer.src if closer.dst == child else closer.dst
            df = reduce(DataFrame.where, (c for used, c in checks or () if used <= set(bound)), df)
            df = closed_in_cells(df, pairs, oriented(arcs(closer), closer, other, child), parent, child, other, max(cells(edge), cells(closer)))
        else:
            df = split_hubs(df, pairs, parent, child, *hubs) if hubs else df.join(pairs, [*keys, parent])
        if semantics != "homo":
            df = df.where(apart(child, bound))
        if dress:
            df = dress(df, child)
        bound.append(child)
        df = closed(df)
    if semantics == "induced":
        joined = pattern.arcs()
        symmetric = not pattern.directed
        for u, v in [*permutations(part, 2), *((v, v) for v in part)]:
            if (u, v) in joined or symmetric and u > v:
                continue
            pairs = every_arc(u, v)
            if u == v:
                pairs = pairs.where("src = dst").select(*keys, F.col("src").alias(u))
            else:
                pairs = pairs.select(*keys, F.col("src").alias(u), F.col("dst").alias(v))
            df = df.join(pairs, [*keys, *dict.fromkeys((u, v))], "left_anti")
    return df


def combined(graph: PropertyGraph, pattern: Pattern, parts: list[tuple[tuple[str, ...], DataFrame]], semantics: str, needs: Needs | None = None, key: str | None = None) -> DataFrame:
    """Join the components' bindings: on equalities between them (and a key that all bring) where there are any, else every pair."""
    (done, df), *rest = parts
    done = list(done)
    for part, other in rest:
        on = []
        if key:
            other = other.withColumnRenamed(key, f"{key}_other")
            on.append(F.col(key) == F.col(f"{key}_other"))
        for s in needs.joins if needs else []:
            if {s.left, s.right} <= set(done) | set(part) and (s.left in done) != (s.right in done):
                on.append(F.col(attr_column(s.left, s.left_attr)) == F.col(attr_column(s.right, s.right_attr)))
        if semantics != "homo":
            on += [F.col(a) != F.col(b) for a in done for b in part]
        df = df.join(other, reduce(and_, on)) if on else df.crossJoin(other)  # a pattern of unrelated parts has every pair as a match
        df = df.drop(f"{key}_other") if key else df
        if semantics == "induced":
            for a in done:
                for b in part:
                    for u, v in ((a, b), (b, a)):
                        df = df.join(any_arc(graph, pattern)(u, v).select(F.col("src").alias(u), F.col("dst").alias(v)), [u, v], "left_anti")
        done += part
    return df
