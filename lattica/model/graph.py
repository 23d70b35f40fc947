"""Property graphs over two DataFrames.

vertices: vid bigint, vlabel string, and typed nullable attribute columns (null: the vertex has no such attribute).
edges: src bigint, dst bigint, elabel string, distinct. An undirected graph stores both arcs of each edge.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

KINDS = ("region", "nation", "customer", "supplier", "part", "order", "user", "event", "doc", "page", "host", "target", "vector", "turn")
_FIXED = ("vid", "vlabel")


def vertex_id(kind: str, key: Column) -> Column:
    """Ids of all kinds in one space: the kind's number times 10^14, plus the key."""
    return F.lit((KINDS.index(kind) + 1) * 10**14).cast("bigint") + key.cast("bigint")


def both_arcs(edges: DataFrame) -> DataFrame:
    return edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel")).distinct()


@dataclass(frozen=True)
class Facts:
    """What a stored graph knows of itself: as many entries as there are kinds of vertices and arcs, times a few degree classes.

    degrees: (label, edge label, neighbour's label, outgoing) -> {neighbours: vertices with as many}; from 64 on by powers of two.
    """

    version: str
    vertices: dict[str | None, int]
    arcs: dict[tuple[str | None, str, str | None], int]
    degrees: dict[tuple[str | None, str, str | None, bool], dict[int, int]]
    several: bool
    #: (label, attribute) -> vertices that have it, distinct values (about), and of a boolean one how many are true.
    values: dict[tuple[str | None, str], tuple[int, int, int | None]]

    def count(self, label: str | None) -> int:
        return sum(n for k, n in self.vertices.items() if label in (None, k))

    def matching(self, a: str | None, label: str | None, b: str | None) -> int:
        return sum(n for (s, e, d), n in self.arcs.items() if a in (None, s) and label in (None, e) and b in (None, d))

    def share_where(self, label: str | None, literals: Iterable, negated: bool = False) -> float:
        """The share of a label's vertices of which literals about one variable are expected to hold (or, negated, not all to hold)."""
        share, total = 1.0, max(1, self.count(label))
        for x in literals:
            known = [self.values[k] for k in self.values if label in (None, k[0]) and k[1] == x.uses[0][1]]
            have = sum(n for n, _, _ in known)
            if hasattr(x, "value"):
                if isinstance(x.value, bool) and all(t is not None for _, _, t in known):
                    true = sum(t for _, _, t in known)
                    have = true if x.value else have - true
                else:
                    have /= max(1, max((d for _, d, _ in known), default=1))
            share *= min(1.0, have / total)
        return 1 - share if negated else share

    def _classes(self, a: str | None, label: str | None, b: str | None, out: bool) -> list[tuple[int, int]]:
        return [(k, n) for (s, e, d, o), by in self.degrees.items() if o == out and a in (None, s) and label in (None, e) and b in (None, d) for k, n in by.items()]

    def weight_with(self, least: int, a: str | None, label: str | None, b: str | None, out: bool) -> float:
        """The share of a kind's arcs that lie at vertices with so many neighbours of the kind: what a degree filter leaves to do."""
        classes = self._classes(a, label, b, out)
        return sum(k * n for k, n in classes if k >= least) / max(1, sum(k * n for k, n in classes))

    def weight_dead(self, share: float, a: str | None, label: str | None, b: str | None, out: bool) -> float:
        """The share of a kind's arcs at vertices none of whose neighbours passes a filter that keeps a share of them."""
        classes = self._classes(a, label, b, out)
        return sum(k * n * (1 - share) ** k for k, n in classes) / max(1, sum(k * n for k, n in classes))


@dataclass(frozen=True)
class PropertyGraph:
    vertices: DataFrame
    edges: DataFrame
    directed: bool = True
    #: Of a stored graph: its arcs with src_label and dst_label, in folders by kind, and its facts.
    kinds: DataFrame | None = field(default=None, compare=False)
    facts: Facts | None = field(default=None, compare=False)

    @staticmethod
    def of(vertices: DataFrame, edges: DataFrame, directed: bool = True) -> PropertyGraph:
        """From raw tables: edges become distinct, and both arcs of undirected ones are stored."""
        edges = edges.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"), F.col("elabel").cast("string").alias("elabel"))
        return PropertyGraph(vertices, edges.distinct() if directed else both_arcs(edges), directed)

    @property
    def catalog(self) -> dict[str, T.DataType]:
        """Attribute names and types."""
        return {f.name: f.dataType for f in self.vertices.schema if f.name not in _FIXED}

    def attribute(self, name: str) -> Column:
        """The attribute's column; one unknown to the catalog is absent everywhere."""
        return F.col(name) if name in self.catalog else F.lit(None)

    def arcs(self, label: str | None, closed: bool = False, src_label: str | None = None, dst_label: str | None = None) -> DataFrame:
        """Distinct (src, dst) of a label, of any label for None; closed: in both directions.

        A stored graph reads only the kinds with the labels of the ends; of others the caller checks the ends' labels.
        """

        def of(a: str | None, b: str | None) -> DataFrame:
            rows = self.edges if self.kinds is None else self.kinds
            for name, value in (("elabel", label), *((("src_label", a), ("dst_label", b)) if self.kinds is not None else ())):
                if value is not None:
                    rows = rows.where(F.col(name) == value)
            return rows.select("src", "dst")

        pairs = of(src_label, dst_label)
        if closed and self.directed:
            return pairs.union(of(dst_label, src_label).select("dst", "src")).distinct()
        return pairs if label is not None or self.facts is not None and not self.facts.several else pairs.distinct()

    def labelled(self, label: str | None) -> DataFrame:
        return self.vertices if label is None else self.vertices.where(F.col("vlabel") == label)

    def filter_vertices(self, condition: Column) -> PropertyGraph:
        return self.induced(self.vertices.where(condition).select("vid"))

    def filter_edges(self, condition: Column) -> PropertyGraph:
        return PropertyGraph(self.vertices, self.edges.where(condition), self.directed)

    def select_attrs(self, *names: str) -> PropertyGraph:
        return PropertyGraph(self.vertices.select(*_FIXED, *names), self.edges, self.directed)

    def with_attrs_from_map(self, column: str, types: dict[str, str]) -> PropertyGraph:
        """Project attributes from a map column on demand; a missing key or a value that isn't of the type is absent."""
        values = {n: F.get(F.array(F.col(column)[n]), F.lit(0)).try_cast(t) if hasattr(Column, "try_cast") else F.expr(f"try_cast({column}['{n}'] AS {t})") for n, t in types.items()}
        return PropertyGraph(self.vertices.withColumns(values).drop(column), self.edges, self.directed)

    def induced(self, vids: DataFrame) -> PropertyGraph:
        """The vertices of a table (vid) and all edges between them."""
        chosen = vids.select(F.col("vid").alias("_v")).distinct()
        edges = self.edges.join(chosen, F.col("src") == F.col("_v"), "left_semi").join(chosen, F.col("dst") == F.col("_v"), "left_semi")
        return PropertyGraph(self.vertices.join(chosen, F.col("vid") == F.col("_v"), "left_semi"), edges, self.directed)

    def first_n(self, n: int) -> PropertyGraph:
        """The n smallest vertex ids and the edges between them."""
        return self.induced(self.vertices.select("vid").orderBy("vid").limit(n))

    def ball(self, seeds: DataFrame, radius: int) -> DataFrame:
        """(centre, vid) of all vertices within so many hops of each seed (vid), in any direction."""
        reached = seeds.select(F.col("vid").alias("centre"), F.col("vid"))
        frontier, steps = reached, self.arcs(None, closed=True)
        for _ in range(radius):
            frontier = frontier.join(steps, F.col("vid") == F.col("src")).select("centre", F.col("dst").alias("vid")).distinct()
            reached = reached.union(frontier).distinct()
        return reached

    def ball_sql(self, seeds: DataFrame, radius: int) -> DataFrame:
        """The same as `ball`, by a recursive query: a step has each vertex once, however many ways lead there, and LIMIT ALL
        lifts Spark's bound of a million rows.
        """
        spark = self.vertices.sparkSession
        seeds.select("vid").createOrReplaceTempView("_ball_seeds")
        self.arcs(None, closed=True).createOrReplaceTempView("_ball_arcs")
        return spark.sql(f"""WITH RECURSIVE r(centre, vid, hops) MAX RECURSION LEVEL {int(radius) + 1} AS (SELECT vid, vid, 0 FROM _ball_seeds
            UNION ALL SELECT DISTINCT r.centre, a.dst, r.hops + 1 FROM r JOIN _ball_arcs a ON a.src = r.vid WHERE r.hops < {int(radius)})
            SELECT DISTINCT centre, vid FROM (SELECT * FROM r LIMIT ALL)""")

    def sample_vertices(self, share: float, seed: int = 0) -> PropertyGraph:
        """A seeded sample of the vertices, by their ids alone, and the edges between them."""
        place = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}/"), F.col("vid").cast("string"))), 1, 8), 16, 10).cast("bigint")
        return self.induced(self.vertices.where(place < F.lit(int(share * 2**32))).select("vid"))

    def degrees_about(self, rsd: float = 0.02) -> DataFrame:
        """vid and about how many distinct neighbours: a sketch per vertex, so a hub's arcs need no exact distinct.

        A sketch holds 1 / rsd^2 hashes of 63 bits, or the next power of two, and counts exactly until it is full.
        """
        arcs = self.edges if not self.directed else self.edges.select("src", "dst").union(self.edges.select("dst", "src"))
        size = min(26, max(4, math.ceil(-2 * math.log2(rsd))))
        return arcs.groupBy(F.col("src").alias("vid")).agg(F.theta_sketch_estimate(F.theta_sketch_agg("dst", size)).alias("degree"))

    def degrees(self) -> DataFrame:
        """vid and the number of distinct neighbours (the vertex itself included if it has a loop), by out-arcs of the closure."""
        return self.arcs(None, closed=True).groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("degree"))

    def label_counts(self) -> DataFrame:
        return self.vertices.groupBy("vlabel").agg(F.count(F.lit(1)).alias("n"))

    def statistics(self) -> DataFrame:
        """One row: vertices, arcs, labels, greatest degree, sum of squared degrees."""
        degrees = self.degrees().agg(F.coalesce(F.max("degree"), F.lit(0)).alias("max_degree"), F.coalesce(F.sum(F.col("degree") * F.col("degree")), F.lit(0)).alias("sum_squares"))
        return self.vertices.agg(F.count(F.lit(1)).alias("n_vertices"), F.countDistinct("vlabel").alias("n_labels")).crossJoin(self.edges.agg(F.count(F.lit(1)).alias("n_arcs"))).crossJoin(degrees)

    def degree_histogram(self) -> DataFrame:
        return self.degrees().groupBy("degree").agg(F.count(F.lit(1)).alias("n"))

    def clashes(self) -> DataFrame:
        """Vertex ids that occur more than once: empty for a sound graph (hash-made ids could collide)."""
        return self.vertices.groupBy("vid").agg(F.count(F.lit(1)).alias("n")).where("n > 1")

    def several_labels(self) -> DataFrame:
        """Ordered pairs with more than one edge label."""
        return self.edges.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n_labels")).where("n_labels > 1")

    def common_neighbours(self, pairs: DataFrame) -> DataFrame:
        """a, b and the number of common neighbours of given pairs (a, b)."""
        steps = self.arcs(None, closed=True)
        left = pairs.join(steps.select(F.col("src").alias("a"), F.col("dst").alias("m")), "a")
        return left.join(steps.select(F.col("src").alias("b"), F.col("dst").alias("m")), ["b", "m"]).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n_common"))

    def top_neighbours(self, k: int, score: str) -> DataFrame:
        """src, rank, dst: the k neighbours of each vertex with the greatest attribute, ties by id."""
        from pyspark.sql import Window

        value = self.vertices.select(F.col("vid").alias("dst"), F.col(score).alias("score"))
        order = Window.partitionBy("src").orderBy(F.desc_nulls_last("score"), "dst")
        return self.arcs(None).join(value, "dst").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("src", "rank", "dst", "score")

    def register(self, prefix: str = "g") -> None:
        """Temporary views for SQL users: <prefix>_vertices and <prefix>_edges."""
        self.vertices.createOrReplaceTempView(f"{prefix}_vertices")
        self.edges.createOrReplaceTempView(f"{prefix}_edges")
