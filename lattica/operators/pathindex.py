"""Strategy `indexed`: candidates and links along a spanning tree, pruned, then the cyclic core first and the forest after it.

An index has, for each component of the pattern, a root, a table of candidates for every variable and a table
(parent, child) for every tree edge. Whatever is read more than once is written to the shared folder, for patterns of any
size, so plans don't nest; `persist` keeps a whole index for later runs of the same pattern on the same graph.

On a stored graph, counts by kind tell beforehand how much a step can prune: with "auto" a degree filter or a removal of dead
ends is left out where it is expected to keep more than 1 - least_gain of the candidates, and links go in the order of their
expected fan-out. Leaving a step out changes no result: an index only ever narrows.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace
from functools import reduce
from operator import mul

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.graph import PropertyGraph
from ..plans import steps
from ..plans.cost import Statistics
from ..plans.steps import Needs
from ..rules import shape
from ..rules.ast import Edge, Pattern
from ..sources.store import saved


@dataclass(frozen=True)
class Options:
    """Switches for ablation. degree_filter: True, False or "auto". passes: 1 removes dead ends from the leaves up and from the
    root down, which on a tree leaves none; 0 keeps them; "auto" asks the graph's counts (1 where there are none).
    root: "cost" takes root and tree from the cheapest order by the graph's counts ("rarest" where there are none), "rarest",
    "max_degree" and "first" see `choose_root`. settle: write tables that are read more than once. exhaustive: up to so many
    variables all orders are weighed, beyond it the cheapest next one is taken."""

    use_index: bool = True
    degree_filter: bool | str = "auto"
    per_label: bool = True
    passes: int | str = "auto"
    core_first: bool = True
    core: str = "two_core"
    root: str = "cost"
    least_gain: float = 0.2
    settle: bool = True
    exhaustive: int = 8


#: Everything on, whatever the counts say.
FULL = Options(degree_filter=True, passes=1)


@dataclass
class CandidateIndex:
    pattern: Pattern
    roots: dict[tuple[str, ...], str]
    trees: dict[tuple[str, ...], list[tuple[str, str, Edge]]]
    cands: dict[str, DataFrame]
    links: dict[tuple[str, str], DataFrame]
    stages: dict[tuple[str, str], DataFrame] = field(default_factory=dict)
    #: Links after the way up alone: enough to match from the root, where a parent that is bound was left over.
    grown: dict[tuple[str, str], DataFrame] = field(default_factory=dict)
    #: What the index was made for: pattern, graph version, semantics, filters and options.
    made_for: dict[str, str] = field(default_factory=dict)
    #: Candidate tables that narrow more than the label does, so that matching has to look at them.
    narrowed: set[str] = field(default_factory=set)

    def stats(self) -> DataFrame:
        """query_vertex, stage, candidates: how far each stage prunes."""
        rows = [df.agg(F.count(F.lit(1)).alias("candidates")).select(F.lit(v).alias("query_vertex"), F.lit(stage).alias("stage"), "candidates") for (v, stage), df in self.stages.items()]
        return reduce(DataFrame.unionByName, rows)

    def link_stats(self) -> DataFrame:
        """parent, child, links of each tree edge."""
        rows = [df.agg(F.count(F.lit(1)).alias("links")).select(F.lit(p).alias("parent"), F.lit(c).alias("child"), "links") for (p, c), df in self.links.items()]
        return reduce(DataFrame.unionByName, rows)

    def persist(self, path: str) -> CandidateIndex:
        """Write the tables below a path and return the index that reads them."""
        spark = next(iter(self.cands.values())).sparkSession
        if not self.made_for.get("graph"):
            raise ValueError("only an index of a stored graph can be kept: other graphs have no version to check it by")
        for v, df in self.cands.items():
            df.write.mode("overwrite").parquet(f"{path}/candidates-{v}")
        for (p, c), df in self.links.items():
            df.write.mode("overwrite").parquet(f"{path}/links-{p}-{c}")
        facts = {"made_for": self.made_for, "roots": list(self.roots.values()), "trees": [[(p, c, self.pattern.edges.index(e)) for p, c, e in tree] for tree in self.trees.values()]}
        spark.range(1).select(F.lit(json.dumps(facts)).alias("value")).coalesce(1).write.mode("overwrite").text(f"{path}/facts")
        return CandidateIndex.load(spark, path, self.pattern, self.made_for)

    @staticmethod
    def load(spark: SparkSession, path: str, pattern: Pattern, made_for: dict[str, str]) -> CandidateIndex:
        """The index, if it was made for the same (see `fingerprint`); else ValueError."""
        facts = json.loads(spark.read.text(f"{path}/facts").first()["value"])
        if wrong := [k for k in {*made_for, *facts["made_for"]} if made_for.get(k) != facts["made_for"].get(k)]:
            raise ValueError(f"the index was made for another {', '.join(sorted(wrong))}")
        parts = shape.components(pattern)
        roots = dict(zip(parts, facts["roots"], strict=True))
        trees = {part: [(p, c, pattern.edges[i]) for p, c, i in tree] for part, tree in zip(parts, facts["trees"], strict=True)}
        cands = {v: spark.read.parquet(f"{path}/candidates-{v}") for v in pattern.variables}
        links = {(p, c): spark.read.parquet(f"{path}/links-{p}-{c}") for t in trees.values() for p, c, _ in t}
        return CandidateIndex(pattern, roots, trees, cands, links, made_for=facts["made_for"], narrowed=set(pattern.variables))

    def size(self, spark: SparkSession, path: str) -> dict[str, int]:
        """Files and bytes of a kept index."""
        from ..sources.store import files_of

        files = files_of(spark, path)
        return {"files": len(files), "bytes": sum(n for _, n, _ in files)}


def fingerprint(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, options: Options = Options()) -> dict[str, str]:
    """What an index depends on. It may be used again only where all of it is the same."""
    filters = {v: str(c._jc) for v, c in sorted(needs.filters.items())} if needs else {}
    return {"pattern": repr(pattern), "graph": graph.facts.version if graph.facts else "", "semantics": semantics, "filters": json.dumps(filters), "options": repr(options)}


def required_degrees(pattern: Pattern, var: str, per_label: bool = True) -> list[tuple[str | None, str | None, bool, int]]:
    """(edge label, neighbour label, outgoing, distinct neighbours) that a match of a variable needs; loops need none."""
    groups: dict[tuple, set[str]] = {}
    for e in pattern.edges:
        for me, other, out in ((e.src, e.dst, True), (e.dst, e.src, False)):
            if me == var and other != var:
                key = (e.label if per_label else None, pattern.label(other) if per_label else None, True if not pattern.directed else out)
                groups.setdefault(key, set()).add(other)
    if not per_label:
        return [(None, None, True, len(pattern.neighbours(var) - {var}))] if pattern.neighbours(var) - {var} else []
    return [(*key, len(others)) for key, others in groups.items()]


def degree_filter(graph: PropertyGraph, pattern: Pattern, var: str, cands: DataFrame, per_label: bool = True, wanted: list | None = None) -> DataFrame:
    """Drop candidates with fewer distinct neighbours than the variable has. Unsound where two variables may share a vertex."""
    for edge_label, label, out, least in required_degrees(pattern, var, per_label) if wanted is None else wanted:
        own = pattern.label(var)
        arcs = graph.arcs(edge_label, not pattern.directed or not per_label, *((own, label) if out else (label, own)))
        me, other = ("src", "dst") if out else ("dst", "src")
        pairs = arcs.where("src <> dst").select(F.col(me).alias(var), F.col(other).alias("_other"))
        if label is not None and graph.kinds is None:
            pairs = pairs.join(graph.labelled(label).select(F.col("vid").alias("_other")), "_other", "left_semi")
        if least == 1:
            enough = pairs.select(var)
        else:
            enough = pairs.groupBy(var).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= least)
        cands = cands.join(enough.select(var), var, "left_semi")
    return cands


def choose_root(graph: PropertyGraph, pattern: Pattern, part: tuple[str, ...], policy: str = "rarest", core: str = "two_core") -> str:
    """The root: within the core if there is one; by policy the fewest candidates a neighbour, the greatest degree, or the first."""
    pool = sorted(shape.core_of(pattern, part[0], core, part), key=pattern.variables.index)
    if len(pool) == 1:
        pool = list(part)
    if policy == "first" or len({(pattern.label(v), len(pattern.neighbours(v))) for v in pool}) == 1:
        return pool[0]
    degree = {v: max(1, len(pattern.neighbours(v) - {v})) for v in pool}
    if policy == "max_degree" or len({pattern.label(v) for v in pool}) == 1:
        return max(pool, key=lambda v: (degree[v], -pattern.variables.index(v)))
    counts = graph.facts.vertices if graph.facts else {r["vlabel"]: r["n"] for r in graph.label_counts().collect()}  # one row per label
    total = sum(counts.values())
    return min(pool, key=lambda v: ((total if pattern.label(v) is None else counts.get(pattern.label(v), 0)) / degree[v], pattern.variables.index(v)))


def shares_of(graph: PropertyGraph, pattern: Pattern, needs: Needs | None) -> dict[str, float]:
    """The share of its label's vertices that each filtered variable's filter is expected to keep."""
    if not graph.facts or not needs:
        return {}
    return {v: reduce(mul, (graph.facts.share_where(pattern.label(v), literals, negated) for literals, negated in said), 1.0) for v, said in needs.said.items()}


def build_index(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, options: Options = Options(), roots: dict[tuple[str, ...], str] | None = None) -> CandidateIndex:
    """needs' filters narrow the candidates from the start; attributes are not part of an index."""
    index = CandidateIndex(pattern, {}, {}, {}, {}, made_for=fingerprint(graph, pattern, semantics, needs, options))
    facts, shares = graph.facts, shares_of(graph, pattern, needs)
    settled = (lambda df, label: saved(df, f"index-{label}")) if options.settle else (lambda df, label: df)
    alike: dict[tuple, DataFrame] = {}  # variables of one label, without filters and with the same needs of neighbours

    def requirements(var: str) -> list:
        if semantics == "homo" or not options.degree_filter:
            return []
        wanted = required_degrees(pattern, var, options.per_label)
        if options.degree_filter is True or not facts:
            return wanted
        return [r for r in wanted if facts.weight_with(r[3], pattern.label(var), r[0], r[1], r[2]) < 1 - options.least_gain]

    def narrowed(var: str) -> DataFrame:
        filtered = bool(needs and var in needs.filters)
        rows = steps.candidates(graph, pattern, var, Needs(needs.attrs, needs.filters)).select(var) if filtered else steps.candidates(graph, pattern, var)
        index.stages[var, "label"] = rows
        wanted = requirements(var)
        if wanted:
            index.narrowed.add(var)
            key = (pattern.label(var), tuple(wanted))
            if not filtered and key in alike:
                like = alike[key]
                rows = like.select(F.col(like.columns[0]).alias(var))
            else:
                rows = settled(degree_filter(graph, pattern, var, rows, options.per_label, wanted), "candidates")
                if not filtered:
                    alike[key] = rows
        index.stages[var, "degree"] = rows
        return rows

    def worth(part: tuple[str, ...], tree: list) -> bool:
        """Whether much is expected to be bound in vain: at parents whose other children, linked later, are missing."""
        if options.passes != "auto" or not facts:
            return bool(options.passes)
        alive, in_vain, met = dict.fromkeys(part, 1.0), 0.0, set()
        for p, c, e in reversed(tree):
            dead = facts.weight_dead(min(1.0, shares.get(c, 1.0) * alive[c]), pattern.label(p), e.label, pattern.label(c), e.src == p or not pattern.directed)
            alive[p] *= 1 - dead
            if p in met or p != tree[0][0]:  # not the first child: it is linked before anything else can be bound
                in_vain = max(in_vain, dead)
            met.add(p)
        return in_vain > options.least_gain

    for part in shape.components(pattern):
        if facts and options.root == "cost" and not (roots or {}).get(part):
            core = shape.core_of(pattern, part[0], options.core, part) if options.core_first else set()
            statistics = Statistics.of(graph)
            order = statistics.best_order(pattern, part, shares, core if len(core) > 1 else set(), options.exhaustive)
            root, tree = order[0], statistics.tree(pattern, order, shares)
        else:
            root = (roots or {}).get(part) or choose_root(graph, pattern, part, options.root, options.core)
            tree = shape.spanning_tree(pattern, root)
        index.roots[part], index.trees[part] = root, tree
        cands = {v: narrowed(v) for v in part}
        passes = worth(part, tree)
        grown: dict[tuple[str, str], DataFrame] = {}
        for p, c, e in reversed(tree):  # from the leaves: a link needs a child that can go on, a parent a link to each child
            pairs = steps.oriented(steps.arcs_of(graph, pattern, e), e, p, c)
            for v in (p, c) if passes else (c,):  # without passes a parent is bound, and filters wait for the attributes
                if passes or v in index.narrowed or graph.kinds is None and pattern.label(v) is not None:
                    pairs = pairs.join(cands[v], v, "left_semi")
            grown[p, c] = settled(pairs, "links") if passes else pairs
            if passes:
                cands[p] = cands[p].join(grown[p, c].select(p), p, "left_semi")
                index.narrowed.add(p)
        index.cands[root] = index.stages[root, "dead_ends"] = settled(cands[root], "candidates") if passes else cands[root]
        for p, c, _ in tree:  # from the root: a child needs a parent that is left
            index.links[p, c] = grown[p, c].join(index.cands[p], p, "left_semi") if passes else grown[p, c]
            index.cands[c] = cands[c].join(index.links[p, c].select(c), c, "left_semi") if passes else cands[c]
            index.stages[c, "dead_ends"] = index.cands[c]
        index.grown |= grown
    return index


def ordered(index: CandidateIndex, part: tuple[str, ...], options: Options) -> list[tuple[str, str, Edge]]:
    """Tree edges with those inside the core first, then the forest outwards, else in the tree's own order."""
    tree = index.trees[part]
    if not options.core_first:
        return tree
    core = shape.core_of(index.pattern, index.roots[part], options.core, part)
    bound, left, out = {index.roots[part]}, list(tree), []
    while left:
        step = next((s for s in left if s[0] in bound and s[0] in core and s[1] in core), None) or next(s for s in left if s[0] in bound)
        out.append(step)
        bound.add(step[1])
        left.remove(step)
    return out


def match_component(graph: PropertyGraph, index: CandidateIndex, part: tuple[str, ...], semantics: str, needs: Needs | None, options: Options, start: DataFrame | None = None, keys: tuple[str, ...] = (), until: set[str] | None = None) -> DataFrame:
    """Bindings of a component from the index; start replaces the root's candidates; until stops when these are bound."""
    pattern, root = index.pattern, index.roots[part]

    def dressed(df: DataFrame, var: str) -> DataFrame:
        attrs = needs.attrs.get(var) if needs else None
        return df.join(steps.candidates(graph, pattern, var, needs), var) if attrs else df

    def link(p, c, e):
        return dressed((index.grown or index.links)[p, c], c)

    order = ordered(index, part, options)
    chosen = part
    if until is not None:
        order = [s for s in order if s[1] in until]
        chosen = tuple(v for v in part if v in until)
        inner = Pattern(tuple(v for v in pattern.vertices if v.var in until), tuple(e for e in pattern.edges if {e.src, e.dst} <= until), pattern.directed)
    else:
        inner = pattern
    return steps.component_matches(inner, chosen, dressed(index.cands[root] if start is None else start, root), root, order, link, lambda e: steps.arcs_of(graph, pattern, e), steps.any_arc(graph, pattern), semantics, keys)


def match_core(graph: PropertyGraph, index: CandidateIndex, part: tuple[str, ...], semantics: str = "mono", options: Options = Options()) -> DataFrame:
    """Bindings of the core alone."""
    return match_component(graph, index, part, semantics, None, options, until=shape.core_of(index.pattern, index.roots[part], options.core, part))


def match(graph: PropertyGraph, pattern: Pattern, semantics: str = "mono", needs: Needs | None = None, options: Options = Options(), index: CandidateIndex | None = None) -> DataFrame:
    if not options.use_index:
        options = replace(options, degree_filter=False, passes=0)
    index = index or build_index(graph, pattern, semantics, needs, options)
    parts = [(part, match_component(graph, index, part, semantics, needs, options)) for part in index.roots]
    return steps.combined(graph, pattern, parts, semantics, needs)


def root_weights(index: CandidateIndex, part: tuple[str, ...]) -> DataFrame:
    """(root, weight): homomorphic matches of the tree from each root; an upper bound for the pattern's."""
    weights = {v: index.cands[v].withColumn("_w", F.lit(1).cast("double")) for v in part}
    for p, c, _ in reversed(index.trees[part]):
        sums = index.links[p, c].join(weights[c].withColumnRenamed("_w", "_wc"), c).groupBy(p).agg(F.sum("_wc").alias("_s"))
        weights[p] = weights[p].join(sums, p).select(p, (F.col("_w") * F.col("_s")).alias("_w"))
    root = index.roots[part]
    return weights[root].select(root, F.col("_w").alias("weight"))
