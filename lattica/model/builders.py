"""Graphs made from the given tables."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.ranks import ranked
from .graph import PropertyGraph, vertex_id

#: The base tables of each graph.
TABLES = {
    "copurchase": ("part", "lineitem"),
    "trade": ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"),
    "docs": ("documents", "labels"),
    "sessions": ("events",),
    "dialogue": ("conversations",),
    "web": ("pages",),
    "similar": ("embeddings",),
}
MAIN_TYPES = ("STANDARD", "ECONOMY", "MEDIUM", "PROMO")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _part_vertices(part: DataFrame) -> DataFrame:
    return part.select(
        vertex_id("part", F.col("p_partkey")).alias("vid"),
        F.when(F.col("p_type").isin(*MAIN_TYPES), F.lit("MAIN")).otherwise("SIDE").alias("vlabel"),
        F.col("p_name").alias("name"),
        F.col("p_brand").alias("brand"),
        F.col("p_type").alias("ptype"),
        F.col("p_size").alias("size"),
        F.col("p_retailprice").alias("price"),
        (F.col("p_size") >= 40).alias("dormant"),
        (F.col("p_size") >= 35).alias("tied"),
        (F.col("p_size") >= 45).alias("size_ge45"),
    )


def _together(lines: DataFrame) -> DataFrame:
    """Ordered pairs of different parts in one order: both arcs come from the self-join."""
    items = lines.select("l_orderkey", vertex_id("part", F.col("l_partkey")).alias("p")).distinct()
    pairs = items.select("l_orderkey", F.col("p").alias("src")).join(items.select("l_orderkey", F.col("p").alias("dst")), "l_orderkey")
    return pairs.where("src <> dst").select("src", "dst", F.lit("co").alias("elabel")).distinct()


def copurchase(spark: SparkSession, sf_dir: str, full: bool = False) -> PropertyGraph:
    """Parts that meet in an order, by default on lines that both came back: the stand-in for a social graph."""
    lines = load(spark, sf_dir, "lineitem")
    lines = lines if full else lines.where(F.col("l_returnflag") == "R")
    return PropertyGraph(_part_vertices(load(spark, sf_dir, "part")), _together(lines), directed=False)


def _vertices(rows: DataFrame, kind: Column | str, /, **columns) -> DataFrame:
    return rows.select(columns.pop("vid").alias("vid"), (F.lit(kind) if isinstance(kind, str) else kind).alias("vlabel"), *[c.alias(n) for n, c in columns.items()])


def _arcs(rows: DataFrame, src: Column, dst: Column, label: str) -> DataFrame:
    return rows.select(src.alias("src"), dst.alias("dst"), F.lit(label).alias("elabel")).where("src IS NOT NULL AND dst IS NOT NULL").distinct()


def trade(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """The star schema as a knowledge graph."""
    region, nation, customer, supplier, part, orders, lines = (load(spark, sf_dir, t) for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"))
    c = F.col
    vertices = [
        _vertices(region, "region", vid=vertex_id("region", c("r_regionkey")), name=c("r_name")),
        _vertices(nation, "nation", vid=vertex_id("nation", c("n_nationkey")), name=c("n_name")),
        _vertices(customer, "customer", vid=vertex_id("customer", c("c_custkey")), name=c("c_name"), nation=c("c_nationkey").cast("int"), balance=c("c_acctbal"), segment=c("c_mktsegment")),
        _vertices(supplier, "supplier", vid=vertex_id("supplier", c("s_suppkey")), name=c("s_name"), nation=c("s_nationkey").cast("int"), balance=c("s_acctbal")),
        _vertices(part, "part", vid=vertex_id("part", c("p_partkey")), name=c("p_name"), brand=c("p_brand"), ptype=c("p_type")),
        _vertices(orders, "order", vid=vertex_id("order", c("o_orderkey")), status=c("o_orderstatus"), priority=c("o_orderpriority"), total=c("o_totalprice")),
    ]
    both = lines.join(orders, c("l_orderkey") == c("o_orderkey"))
    edges = [
        _arcs(nation, vertex_id("nation", c("n_nationkey")), vertex_id("region", c("n_regionkey")), "in_region"),
        _arcs(customer, vertex_id("customer", c("c_custkey")), vertex_id("nation", c("c_nationkey")), "based_in"),
        _arcs(supplier, vertex_id("supplier", c("s_suppkey")), vertex_id("nation", c("s_nationkey")), "based_in"),
        _arcs(orders, vertex_id("customer", c("o_custkey")), vertex_id("order", c("o_orderkey")), "placed"),
        _arcs(lines, vertex_id("order", c("l_orderkey")), vertex_id("part", c("l_partkey")), "contains"),
        _arcs(lines, vertex_id("order", c("l_orderkey")), vertex_id("supplier", c("l_suppkey")), "shipped_by"),
        _arcs(lines, vertex_id("supplier", c("l_suppkey")), vertex_id("part", c("l_partkey")), "sources"),
        _arcs(both, vertex_id("customer", c("o_custkey")), vertex_id("supplier", c("l_suppkey")), "buys_from"),
    ]
    return PropertyGraph(_stacked(vertices), _stacked(edges))


def _stacked(tables: list[DataFrame]) -> DataFrame:
    out = tables[0]
    for t in tables[1:]:
        out = out.unionByName(t, allowMissingColumns=True)
    return out


def docs(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Documents with the labels that some have; edges join equal texts."""
    rows = load(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("digest"), "lang", "source", "n_chars")
    labelled = rows.join(load(spark, sf_dir, "labels"), "doc_id", "left")
    vertices = _vertices(labelled, F.col("lang"), vid=vertex_id("doc", F.col("doc_id")), quality=F.col("quality"), toxic=F.col("toxic"), source=F.col("source"), n_chars=F.col("n_chars"))
    keyed = rows.select("digest", vertex_id("doc", F.col("doc_id")).alias("v"))
    pairs = keyed.select("digest", F.col("v").alias("src")).join(keyed.select("digest", F.col("v").alias("dst")), "digest").where("src <> dst")
    return PropertyGraph(vertices, pairs.select("src", "dst", F.lit("same_text").alias("elabel")).distinct(), directed=False)


def sessions(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Events, each followed by its user's next one, and users."""
    events = load(spark, sf_dir, "events").withColumn("vid", vertex_id("event", F.col("event_id")))
    nodes = _vertices(events, F.col("event_type"), vid=F.col("vid"), value=F.col("value"), k=F.get_json_object("props", "$.k").cast("int"), user=F.col("user_id"), ts=F.col("ts"), day=F.to_date("ts"))
    users = _vertices(events.select("user_id").distinct(), "user", vid=vertex_id("user", F.col("user_id")), user=F.col("user_id"))
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    follow = events.withColumn("dst", F.lead("vid").over(order))
    edges = [_arcs(follow, F.col("vid"), F.col("dst"), "next"), _arcs(events, F.col("vid"), vertex_id("user", F.col("user_id")), "by")]
    return PropertyGraph(_stacked([nodes, users]), _stacked(edges))


def dialogue(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turns of conversations in their order."""
    turns = load(spark, sf_dir, "conversations").withColumn("vid", vertex_id("turn", F.col("conv_id") * 10_000 + F.col("turn")))
    follow = turns.withColumn("dst", F.lead("vid").over(Window.partitionBy("conv_id").orderBy("turn")))
    return PropertyGraph(_vertices(turns, F.col("role"), vid=F.col("vid"), role=F.col("role"), conv=F.col("conv_id"), turn=F.col("turn")), _arcs(follow, F.col("vid"), F.col("dst"), "next"))


def _named_ids(kind: str, names: DataFrame, exact: bool) -> DataFrame:
    """name and vid of distinct names: dense ranks (made range by range), or hashes (47 bits; `PropertyGraph.clashes` finds collisions)."""
    names = names.distinct()
    if exact:
        return ranked(names, ["name"]).select("name", vertex_id(kind, F.col("nth")).alias("vid"))
    return names.withColumn("vid", vertex_id(kind, F.pmod(F.xxhash64("name"), F.lit(10**14))))


def web(spark: SparkSession, sf_dir: str, exact: bool = True) -> PropertyGraph:
    """Pages, their hosts and the targets of their links."""
    pages = load(spark, sf_dir, "pages").select("page_id", "url", "html", vertex_id("page", F.col("page_id")).alias("page"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    nodes = _vertices(pages, "page", vid=F.col("page"), lang=F.nullif(F.regexp_extract("html", '<html[^>]* lang="([^"]*)"', 1), F.lit("")), path=F.regexp_extract("url", "^[a-z]+://[^/]+(.*)$", 1))
    hosts = _named_ids("host", pages.select(F.col("host").alias("name")), exact)
    links = pages.select("page", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("name"))
    targets = _named_ids("target", links.select("name"), exact)
    vertices = [nodes, _vertices(hosts, "host", vid=F.col("vid"), path=F.col("name")), _vertices(targets, "target", vid=F.col("vid"), path=F.col("name"))]
    edges = [
        _arcs(pages.join(hosts, F.col("host") == F.col("name")), F.col("page"), F.col("vid"), "on_host"),
        _arcs(links.join(targets, "name"), F.col("page"), F.col("vid"), "links_to"),
    ]
    return PropertyGraph(_stacked(vertices), _stacked(edges))


def dot(a: Column, b: Column) -> Column:
    """Inner product of two array columns in double precision, summed in their order, by built-in functions."""
    return F.aggregate(F.zip_with(a, b, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)


def cosine(a: Column, b: Column, squares: tuple[Column, Column] | None = None) -> Column:
    """Cosine of two array columns, whose inner products with themselves may be given; NaN, as IEEE 754 and SQL have it, where a vector is zero."""
    x, y = squares or (dot(a, a), dot(b, b))
    norm = F.sqrt(x * y)
    return F.when(norm == 0, F.lit(float("nan"))).otherwise(dot(a, b) / norm)


def cosine_udf():
    """The same cosine as a vectorised Python function: for cross-checks only."""

    @F.arrow_udf("double")  # a pandas one would turn NaN into null
    def run(a: pa.Array, b: pa.Array) -> pa.Array:
        import numpy as np

        x, y = (c.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(max(1, len(c)), -1) for c in (a, b))
        with np.errstate(all="ignore"):
            return pa.array(((x * y).sum(1) / np.sqrt((x * x).sum(1) * (y * y).sum(1)))[: len(a)])

    return run


def event_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, k: a value out of the events' JSON, read as a variant."""
    return load(spark, sf_dir, "events").select("event_id", F.try_variant_get(F.try_parse_json("props"), "$.k", "int").alias("k"))


def _near_pairs(least: float, rows_at_once: int = 1024, pairs_at_once: int = 1 << 18):
    """Both arcs of the pairs of a block pair (vid, own, lo, hi, embedding) whose cosine is high enough, as a function of its Arrow batches.

    A product of matrices in single precision leaves out pairs that are below the bound by more than its rounding can be.
    The others' cosine is made in double precision, with the sums in the vectors' order, as `cosine` makes it. Vectors whose
    squared length is zero, not finite or so far from one that it would round away are compared with all others in that way.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        table = pa.Table.from_batches(list(batches)).combine_chunks()
        vid, own, lo, hi = (table[c].to_numpy() for c in ("vid", "own", "lo", "hi"))
        flat = table["embedding"].combine_chunks().flatten().to_numpy(zero_copy_only=False)
        v = np.ascontiguousarray(flat.astype(np.float64).reshape(len(vid), -1).T)  # a row for each component

        def dots(i, j):
            out = np.zeros(len(i))
            for x in v:
                out += x[i] * x[j]
            return out

        def exact(i, j):
            keep = (vid[i] != vid[j]) & ~(dots(i, j) / np.sqrt(square[i] * square[j]) < least)  # a cosine that is NaN is above all others
            i, j = vid[i[keep]], vid[j[keep]]
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([i, j])), pa.array(np.concatenate([j, i]))], ["src", "dst"])

        with np.errstate(all="ignore"):
            every = np.arange(len(vid))
            square = dots(every, every)
            odd = ~((square > 1e-100) & (square < 1e100))
            unit = np.ascontiguousarray(np.where(odd, 0, v / np.sqrt(square)).T.astype(np.float32))
            bound = least - (len(v) + 8) * 2.0**-23
            left, right = every[own == lo[0]], every[own == hi[0]]
            for a in range(0, len(left), rows_at_once):
                rows = left[a : a + rows_at_once]
                others = right[a + 1 :] if lo[0] == hi[0] else right
                hit = (unit[rows] @ unit[others].T >= bound) | odd[rows][:, None] | odd[others][None, :]
                if lo[0] == hi[0]:
                    hit = np.triu(hit)  # the first row's first other one is the second row
                found = np.flatnonzero(hit)
                for x in range(0, len(found), pairs_at_once):
                    i, j = np.divmod(found[x : x + pairs_at_once], max(1, len(others)))
                    yield exact(rows[i], others[j])

    return run


#: Vectors of a block at most: a pair of blocks is one task's, with both blocks in memory.
BLOCK_ROWS = 8192


def similar(spark: SparkSession, sf_dir: str, least: float = 0.35, blocks: int = 8) -> PropertyGraph:
    """Vectors joined where their cosine is high enough: exact, each of at least so many blocks against each by products of matrices.

    Vectors that are null, empty or hold a null have no cosine, nor have two of unequal length; a zero vector's is NaN, which is above all numbers.
    """
    rows = load(spark, sf_dir, "embeddings").select(vertex_id("vector", F.col("vec_id")).alias("vid"), "embedding", "label")
    nodes = _vertices(rows, (F.col("label") % 2).cast("string"), vid=F.col("vid"), label=F.col("label"))
    blocks = max(blocks, -(-rows.count() // BLOCK_ROWS))
    keyed = rows.where(F.col("vid").isNotNull() & F.forall("embedding", F.isnotnull) & (F.size("embedding") > 0)).select("vid", "embedding", F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int").alias("own"))
    dealt = keyed.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    dealt = dealt.select("vid", "embedding", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), F.size("embedding").alias("dims"))
    near = dealt.groupBy("lo", "hi", "dims").applyInArrow(_near_pairs(least), "src bigint, dst bigint")
    return PropertyGraph(nodes, near.select("src", "dst", F.lit("near").alias("elabel")), directed=False)
