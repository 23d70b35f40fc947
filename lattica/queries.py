"""Queries of the graph engine by name, and their DuckDB oracles on the base tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads
from .functions.literals import falling_factorial
from .model import builders, stored
from .model.graph import PropertyGraph, vertex_id
from .operators import balanced, pathindex, validate
from .operators.pathindex import Options
from .plans import cost
from .report import summary
from .sources.store import exists, fresh_path, shared_root
from .streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]


_STORED: dict[tuple[str, ...], tuple[str, PropertyGraph]] = {}


def raw_graph(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    """A graph as plans over the base tables."""
    return getattr(builders, name)(spark, sf_dir)


def graph(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    """The graph stored by kind, once for an application and a state of its tables."""
    version = f"{name}-{stored.table_version(spark, *[f'{sf_dir}/{t}.parquet' for t in builders.TABLES[name]])}"
    key = (spark.sparkContext.applicationId, shared_root(spark), version)
    if key not in _STORED or not exists(spark, _STORED[key][0]):
        path = fresh_path(spark, f"graph-{name}")
        _STORED[key] = path, stored.stored(raw_graph(spark, sf_dir, name), version, path)
    return _STORED[key][1]


def _violations(name: str, **options) -> Query:
    return lambda spark, d: validate.violations(graph(spark, d, workloads.graph_name(name)), workloads.rule(name), **options)


def _count(name: str, strategy: str, semantics: str) -> Query:
    def run(spark, d):
        found = validate.match(graph(spark, d, workloads.graph_name(name)), workloads.rule(name).pattern, strategy, semantics)
        return found.agg(F.count(F.lit(1)).alias("n"))

    return run


def _copurchase(f: Callable[[PropertyGraph], DataFrame]) -> Query:
    return lambda spark, d: f(graph(spark, d, "copurchase"))


# ---- fixed SQL pieces on base tables; ids are the kind's number times 10^14 plus the key

PARTS = """pv AS (SELECT 500000000000000 + p_partkey AS vid, CASE WHEN p_type IN ('STANDARD', 'ECONOMY', 'MEDIUM', 'PROMO') THEN 'MAIN' ELSE 'SIDE' END AS vlabel,
  p_name AS name, p_brand AS brand, p_type AS ptype, p_size AS size, p_retailprice AS price, p_size >= 40 AS dormant, p_size >= 35 AS tied FROM part)"""
CO = """items AS (SELECT DISTINCT l_orderkey AS o, 500000000000000 + l_partkey AS p FROM lineitem WHERE l_returnflag = 'R'),
co AS (SELECT DISTINCT x.p AS src, y.p AS dst FROM items x JOIN items y ON x.o = y.o AND x.p <> y.p)"""
MAIN = f"""{PARTS}, {CO}, m AS (SELECT * FROM pv WHERE vlabel = 'MAIN'), s AS (SELECT * FROM pv WHERE vlabel = 'SIDE'),
mm AS (SELECT src, dst FROM co WHERE src IN (SELECT vid FROM m) AND dst IN (SELECT vid FROM m)),
ss AS (SELECT src, dst FROM co WHERE src IN (SELECT vid FROM s) AND dst IN (SELECT vid FROM s))"""
PATH_ROWS = "SELECT e.src AS a, e.dst AS b, f.dst AS c FROM mm e JOIN mm f ON e.dst = f.src"
STAR_ROWS = "SELECT e.src AS a, e.dst AS b, f.dst AS c, g.dst AS d FROM ss e JOIN ss f ON e.src = f.src JOIN ss g ON e.src = g.src"
TRIANGLE_ROWS = "SELECT e.src AS a, e.dst AS b, f.dst AS c FROM mm e JOIN mm f ON e.dst = f.src JOIN mm g ON g.src = e.src AND g.dst = f.dst"
STAR_APART = "b <> c AND b <> d AND c <> d"
NO = "NOT EXISTS (SELECT 1 FROM co z WHERE z.src = {0} AND z.dst = {1})"
TRADE = """place AS (SELECT DISTINCT 600000000000000 + l_orderkey AS o, 400000000000000 + l_suppkey AS s FROM lineitem),
sup AS (SELECT 400000000000000 + s_suppkey AS s, s_nationkey AS nation FROM supplier),
inside AS (SELECT DISTINCT 600000000000000 + l_orderkey AS o, 500000000000000 + l_partkey AS p FROM lineitem)"""
DOCS = """dv AS (SELECT 900000000000000 + d.doc_id AS vid, md5(d.text) AS h, l.quality FROM documents d LEFT JOIN labels l USING (doc_id))"""
TURNS = """tv AS (SELECT 1400000000000000 + conv_id * 10000 + turn AS vid, conv_id, turn, role FROM conversations),
nx AS (SELECT vid AS x, role AS xr, lead(vid) OVER w AS y, lead(role) OVER w AS yr FROM tv WINDOW w AS (PARTITION BY conv_id ORDER BY turn))"""
WEB = """pg AS (SELECT 1000000000000000 + page_id AS vid, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, nullif(regexp_extract(html, '<html[^>]* lang="([^"]*)"', 1), '') AS lang, html FROM pages),
hs AS (SELECT host, 1100000000000000 + row_number() OVER (ORDER BY host) AS vid FROM (SELECT DISTINCT host FROM pg)),
lk AS (SELECT DISTINCT vid AS page, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pg),
tg AS (SELECT target, 1200000000000000 + row_number() OVER (ORDER BY target) AS vid FROM (SELECT DISTINCT target FROM lk))"""
SIMILAR = """ev AS MATERIALIZED (SELECT 1300000000000000 + vec_id AS vid, embedding::DOUBLE[64] AS v, array_inner_product(embedding::DOUBLE[64], embedding::DOUBLE[64]) AS norm, label FROM embeddings),
half AS MATERIALIZED (SELECT x.vid AS src, y.vid AS dst, x.label AS ls, y.label AS ld FROM ev x JOIN ev y ON x.vid < y.vid WHERE array_inner_product(x.v, y.v) / sqrt(x.norm * y.norm) >= 0.35),
near AS MATERIALIZED (SELECT * FROM half UNION ALL SELECT dst, src, ld, ls FROM half)"""
HOME = f"""WITH {TRADE} SELECT 300000000000000 + o_custkey AS c, p.o AS o, p.s AS s, 200000000000000 + c_nationkey AS n{{cols}}
FROM orders JOIN customer ON o_custkey = c_custkey JOIN place p ON p.o = 600000000000000 + o_orderkey JOIN sup ON sup.s = p.s AND sup.nation = c_nationkey{{tail}}"""
DOR = "{0} IN (SELECT vid FROM pv WHERE dormant)"

VIOLATIONS: dict[str, str] = {
    "path3": f"WITH {MAIN}, r AS ({PATH_ROWS}) SELECT a, b, c FROM r WHERE a <> c AND {DOR.format('a')} AND {DOR.format('b')} AND {DOR.format('c')} AND b NOT IN (SELECT vid FROM pv WHERE size >= 35)",
    "path3_strict": f"WITH {MAIN}, r AS ({PATH_ROWS}) SELECT a, b, c FROM r WHERE a <> c AND {DOR.format('a')} AND {DOR.format('b')} AND {DOR.format('c')} AND b NOT IN (SELECT vid FROM pv WHERE size >= 45)",
    "star3": f"WITH {MAIN}, r AS ({STAR_ROWS}) SELECT a, b, c, d FROM r WHERE {STAR_APART} AND {DOR.format('a')}",
    "star3_holds": f"WITH {MAIN}, r AS ({STAR_ROWS}) SELECT a, b, c, d FROM r WHERE {STAR_APART} AND a IN (SELECT vid FROM pv WHERE size IS NULL)",
    "triangle": f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT a, b, c FROM r WHERE {DOR.format('a')} AND {DOR.format('b')} AND NOT {DOR.format('c')}",
    "kite": f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT a, b, c, t.dst AS d FROM r JOIN mm t ON t.src = a WHERE t.dst <> b AND t.dst <> c AND {DOR.format('a')} AND {DOR.format('b')} AND NOT {DOR.format('c')}",
    "two_places": f"WITH {TRADE} SELECT p.o AS x, p.s AS y, q.s AS z FROM place p JOIN place q ON p.o = q.o AND p.s <> q.s JOIN sup u ON u.s = p.s JOIN sup v ON v.s = q.s WHERE u.nation <> v.nation",
    "never_both": f"WITH {PARTS}, {TRADE} SELECT p.o AS x, p.p AS y, q.p AS z FROM inside p JOIN inside q ON p.o = q.o AND p.p <> q.p JOIN pv u ON u.vid = p.p JOIN pv v ON v.vid = q.p WHERE u.brand = 'Brand#1' AND v.brand = 'Brand#2'",
    "home_cycle": HOME.format(cols="", tail=""),
    "home_cycle_tail": HOME.format(cols=", i.p AS p", tail=" JOIN inside i ON i.o = p.o"),
    "typing_doc": f"WITH {DOCS} SELECT vid AS x FROM dv WHERE quality IS NULL",
    "dup_label": f"WITH {DOCS} SELECT a.vid AS x, b.vid AS y FROM dv a JOIN dv b ON a.h = b.h AND a.vid <> b.vid WHERE NOT coalesce(a.quality = b.quality, false)",
    "dup_label_x": f"WITH {DOCS} SELECT a.vid AS x, b.vid AS y FROM dv a JOIN dv b ON a.h = b.h AND a.vid <> b.vid WHERE coalesce(a.quality = 1, false) AND NOT coalesce(b.quality = 1, false)",
    "fd_part": f"WITH {PARTS} SELECT a.vid AS x, b.vid AS y FROM pv a JOIN pv b ON a.name = b.name AND a.brand = b.brand AND a.vid <> b.vid WHERE a.ptype <> b.ptype",
    "chain3": """WITH n AS (SELECT 800000000000000 + event_id AS a, event_type AS t1, 800000000000000 + lead(event_id) OVER w AS b, lead(event_type) OVER w AS t2, 800000000000000 + lead(event_id, 2) OVER w AS c, lead(event_type, 2) OVER w AS t3
        FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT a, b, c FROM n WHERE t1 = 'signup' AND t2 = 'error' AND t3 = 'purchase'""",
    "turn_taking": f"WITH {TURNS} SELECT x, y FROM nx WHERE xr = 'assistant' AND y IS NOT NULL AND yr <> 'user'",
    "opening": f"WITH {TURNS} SELECT x, y FROM nx WHERE xr = 'system' AND y IS NOT NULL AND yr <> 'user'",
    "host_lang": f"WITH {WEB} SELECT a.vid AS x, h.vid AS h, b.vid AS y FROM pg a JOIN pg b ON a.host = b.host AND a.vid <> b.vid JOIN hs h ON h.host = a.host WHERE NOT coalesce(a.lang = b.lang, false)",
    "similar_triangle": f"WITH {SIMILAR} SELECT e.src AS a, e.dst AS b, f.dst AS c FROM near e JOIN near f ON e.dst = f.src JOIN near g ON g.src = e.src AND g.dst = f.dst WHERE e.ls <> e.ld",
}
VIOLATIONS["two_places_wild"] = VIOLATIONS["two_places"]
VIOLATIONS["tail_kite"] = VIOLATIONS["kite"]
VIOLATIONS["turn_broken"] = f"WITH {TURNS} SELECT x, y FROM nx WHERE xr = 'assistant' AND y IS NOT NULL AND yr <> 'assistant'"
VIOLATIONS["opening_broken"] = f"WITH {TURNS} SELECT x, y FROM nx WHERE xr = 'system' AND y IS NOT NULL AND yr <> 'assistant'"
INDUCED = {
    "path3_strict": f"{VIOLATIONS['path3_strict']} AND {NO.format('a', 'c')}",
    "star3": f"{VIOLATIONS['star3']} AND {NO.format('b', 'c')} AND {NO.format('b', 'd')} AND {NO.format('c', 'd')}",
    "kite": f"SELECT * FROM ({VIOLATIONS['kite']}) WHERE (b, d) NOT IN (SELECT (src, dst) FROM co2) AND (c, d) NOT IN (SELECT (src, dst) FROM co2)",
}
INDUCED["kite"] = f"WITH {CO}, co2 AS (SELECT * FROM co) {INDUCED['kite']}"
SATISFIED_X = f"WITH {DOCS} SELECT a.vid AS x, b.vid AS y FROM dv a JOIN dv b ON a.h = b.h AND a.vid <> b.vid WHERE coalesce(a.quality = 1, true) AND NOT coalesce(b.quality = 1, false)"
MATCHES = {
    "path3": {
        "mono": f"WITH {MAIN}, r AS ({PATH_ROWS}) SELECT count(*) AS n FROM r WHERE a <> c",
        "induced": f"WITH {MAIN}, r AS ({PATH_ROWS}) SELECT count(*) AS n FROM r WHERE a <> c AND {NO.format('a', 'c')}",
        "homo": f"WITH {MAIN}, r AS ({PATH_ROWS}) SELECT count(*) AS n FROM r",
    },
    "star3": {
        "mono": f"WITH {MAIN}, r AS ({STAR_ROWS}) SELECT count(*) AS n FROM r WHERE {STAR_APART}",
        "induced": f"WITH {MAIN}, r AS ({STAR_ROWS}) SELECT count(*) AS n FROM r WHERE {STAR_APART} AND {NO.format('b', 'c')} AND {NO.format('b', 'd')} AND {NO.format('c', 'd')}",
        "homo": f"WITH {MAIN}, r AS ({STAR_ROWS}) SELECT count(*) AS n FROM r",
    },
    "triangle": dict.fromkeys(("mono", "induced", "homo"), f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT count(*) AS n FROM r"),
}


def _stats(g: PropertyGraph) -> DataFrame:
    return g.statistics()


def _units(rules: list[str]) -> Query:
    return _copurchase(lambda g: balanced.work_units(g, [workloads.rule(r) for r in rules]).select("rule_id", "var", "vid", "cost"))


def _snake(g: PropertyGraph) -> DataFrame:
    return balanced.assign(balanced.ball_sizes(g, workloads.rule("path3").pattern, "b", 1), 4, "snake")


def _index(g: PropertyGraph, name: str) -> pathindex.CandidateIndex:
    return pathindex.build_index(g, workloads.rule(name).pattern, options=replace(pathindex.FULL, root="rarest"))


def _stacked_candidates(g: PropertyGraph, stage: str) -> DataFrame:
    index = _index(g, "triangle")
    out = None
    for v in index.pattern.variables:
        rows = index.stages[v, stage].select(F.lit(v).alias("var"), F.col(v).alias("vid"))
        out = rows if out is None else out.unionByName(rows)
    return out


def _star_count(g: PropertyGraph) -> DataFrame:
    """All matches of the star from degrees alone, nothing enumerated."""
    rows = validate.star_degrees(g, workloads.rule("star3").pattern)
    return rows.agg(F.coalesce(F.sum(falling_factorial(F.col("d"), 3)), F.lit(0)).cast("bigint").alias("n"))


def _parts(found: DataFrame, g: PropertyGraph) -> DataFrame:
    return summary.cubed(found, g, "a", "brand", "ptype")


def _tagged(found: DataFrame) -> DataFrame:
    """Bindings without arrays, for comparing: rule_id, var, vid, n."""
    return found.select("rule_id", F.explode("binding").alias("b")).groupBy("rule_id", F.col("b.var").alias("var"), F.col("b.vid").alias("vid")).agg(F.count(F.lit(1)).alias("n"))


def _message_costs(g: PropertyGraph) -> DataFrame:
    rule = workloads.rule("path3")
    rows = [(k, by[0], cost) for k, by, cost in balanced.message_costs(g, rule, balanced.ranged_candidates(g, rule, 8))]
    return g.vertices.sparkSession.createDataFrame(rows, "msg_id int, range_id int, cost bigint")


def _planted(g: PropertyGraph) -> DataFrame:
    """Pairs that are joined under two labels: every third part's arcs upwards have a second one."""
    up = g.edges.where("src < dst AND src % 3 = 0").withColumn("elabel", F.lit("up"))
    return PropertyGraph(g.vertices, g.edges.unionByName(up)).several_labels()


def _similar_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The edges of near vectors on which the vectorised Python cosine agrees with the built-in one."""
    c = F.col
    v = builders.load(spark, sf_dir, "embeddings").select(vertex_id("vector", c("vec_id")).alias("vid"), "embedding", builders.dot(c("embedding"), c("embedding")).alias("square"))
    ends = [v.withColumnsRenamed({"vid": end, "embedding": x, "square": f"{x}{x}"}) for end, x in (("src", "a"), ("dst", "b"))]
    near = graph(spark, sf_dir, "similar").edges.where("src < dst").join(ends[0], "src").join(ends[1], "dst")  # a cosine is that of both arcs
    both = near.select("src", "dst", "elabel", builders.cosine_udf()("a", "b").alias("x"), builders.cosine(c("a"), c("b"), (c("aa"), c("bb"))).alias("y"))
    agree = both.where((F.abs(c("x") - c("y")) < 1e-9) | F.isnan("x") & F.isnan("y"))
    return agree.select(F.inline(F.array(F.struct("src", "dst"), F.struct(c("dst").alias("src"), c("src").alias("dst")))), "elabel")


def _ended(g: PropertyGraph) -> DataFrame:
    """Star violations under `induced` that are none any more once every tenth edge has come."""
    late = (F.least("src", "dst") * 31 + F.greatest("src", "dst")) % 10 == 0
    old = PropertyGraph(g.vertices, g.edges.where(~late), g.directed)
    return incremental.ended(validate.violations(old, workloads.rule("star3"), semantics="induced"), g, workloads.rule("star3"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    edges = {"copurchase": "copurchase", "trade": "trade", "docs": "docs", "sessions": "sessions", "dialogue": "dialogue", "web": "web", "similar": "similar"}
    for short, name in edges.items():
        out[f"g_{short}_edges"] = lambda spark, d, name=name: raw_graph(spark, d, name).edges
    out["g_copurchase_vertices"] = _copurchase(lambda g: g.vertices.select("vid", "vlabel", "name", "brand", "ptype", "size", "price", "dormant", "tied"))
    out["g_first_n_edges"] = _copurchase(lambda g: g.first_n(1000).edges)
    out["g_stats"] = _copurchase(_stats)
    out["g_degree_hist"] = _copurchase(lambda g: g.degree_histogram())
    out["g_label_counts"] = lambda spark, d: graph(spark, d, "trade").label_counts()
    out["g_multilabel_pairs"] = lambda spark, d: graph(spark, d, "trade").several_labels()
    out["g_ball2"] = _copurchase(lambda g: g.ball(g.labelled("SIDE").where("size = 50").select("vid"), 2).groupBy("centre").agg(F.count(F.lit(1)).alias("n")))
    out["g_ball2_recursive"] = _copurchase(lambda g: g.ball_sql(g.labelled("SIDE").where("size = 50").select("vid"), 2).groupBy("centre").agg(F.count(F.lit(1)).alias("n")))
    out["g_sample_edges"] = _copurchase(lambda g: g.sample_vertices(0.3).edges)
    out["g_multilabel_planted"] = _copurchase(_planted)
    out["g_degrees_about"] = _copurchase(lambda g: g.degrees_about().join(g.degrees().withColumnRenamed("degree", "exact"), "vid").where(F.abs(F.col("degree") - F.col("exact")) <= 0.2 * F.col("exact")).select("vid"))
    out["g_event_values"] = builders.event_values
    out["g_similar_udf"] = _similar_udf
    out["g_kinds"] = lambda spark, d: cost.triples(graph(spark, d, "trade"))
    out["g_top_neighbours"] = _copurchase(lambda g: g.top_neighbours(2, "price").select("src", "rank", "dst"))
    for name, by in MATCHES.items():
        for semantics in by:
            out[f"m_{name}_direct_count{'' if semantics == 'mono' else '_' + semantics}"] = _count(name, "direct", semantics)
    for name in VIOLATIONS:
        if name not in ("dup_label_x",):
            out[f"v_{name}"] = _violations(name)
    out["v_similar_triangle"] = _violations("similar_triangle", symmetry=True, in_cells=True)  # a and b change places: half of the open paths, none of which is shuffled
    out["v_dup_label_x_unsatisfied"] = _violations("dup_label_x")
    out["v_dup_label_x_satisfied"] = _violations("dup_label_x", absent_in_x="satisfied")
    main = ("path3_strict", "star3", "triangle", "kite")
    for name in main:
        out[f"v_{name}_balanced"] = _violations(name, strategy="balanced")
        out[f"v_{name}_indexed"] = _violations(name, strategy="indexed")
        out[f"v_{name}_balanced_indexed"] = _violations(name, strategy="balanced_indexed")
        out[f"v_{name}_indexed_parallel"] = _violations(name, strategy="indexed_parallel")
    for name in INDUCED:
        for s in ("", "_balanced", "_indexed", "_balanced_indexed", "_indexed_parallel"):
            out[f"v_{name}_induced{s}"] = _violations(name, strategy=s[1:] or "direct", semantics="induced")
    out["v_tail_kite_indexed"] = _violations("tail_kite", strategy="indexed")
    out["v_home_cycle_auto"] = _violations("home_cycle", strategy="auto")
    out["v_host_lang_hubs"] = _violations("host_lang", hub_degree=20)
    out["v_path3_strict_shipped"] = _violations("path3_strict", strategy="balanced", placement="shipped")
    out["v_triangle_shipped"] = _violations("triangle", strategy="balanced", placement="shipped")
    out["v_triangle_searched"] = _violations("triangle", strategy="balanced", local_matcher="search")
    out["v_triangle_greedy"] = _violations("triangle", strategy="balanced", method="greedy")
    out["v_kite_indexed_core_cycle"] = _violations("kite", strategy="indexed", options=Options(core="shortest_cycle"))
    out["v_kite_indexed_plain"] = _violations("kite", strategy="indexed", options=Options(core_first=False, degree_filter=False, passes=0))
    out["v_home_cycle_indexed"] = _violations("home_cycle", strategy="indexed")
    out["v_home_cycle_tail_indexed"] = _violations("home_cycle_tail", strategy="indexed")
    out["v_two_places_indexed"] = _violations("two_places", strategy="indexed")
    out["v_fd_part_balanced"] = _violations("fd_part", strategy="balanced")
    out["v_dup_label_indexed"] = _violations("dup_label", strategy="indexed")
    out["v_triangle_auto"] = _violations("triangle", strategy="auto")
    out["v_triangle_symmetry"] = _violations("triangle", symmetry=True)
    out["v_star3_symmetry"] = _violations("star3", symmetry=True)
    out["v_triangle_no_pushdown"] = _violations("triangle", pushdown=False)
    out["b_pivots"] = lambda spark, d: balanced.pivot_table(raw_graph(spark, d, "copurchase"), [workloads.rule(r) for r in ("path3", "star3", "triangle", "fd_part")])
    out["b_candidate_hist"] = _copurchase(lambda g: balanced.candidate_histogram(g, [workloads.rule("path3"), workloads.rule("star3")], "size"))
    out["b_ranges"] = _copurchase(lambda g: balanced.candidate_ranges(g, workloads.rule("path3"), 8).select("rule_id", "var", "range_id", "lo", "hi", "cnt"))
    out["b_messages"] = _copurchase(lambda g: balanced.messages(balanced.candidate_ranges(g, workloads.rule("path3"), 8), 4))
    out["b_messages_fd"] = _copurchase(lambda g: balanced.messages(balanced.candidate_ranges(g, workloads.rule("fd_part"), 3), 4))
    out["b_message_costs"] = _copurchase(_message_costs)
    out["b_message_units"] = _copurchase(lambda g: balanced.dealt_units(g, workloads.rule("path3"), 4, 8).select("vid", "msg_id", "cost", "worker"))
    out["b_units_path3"] = _units(["path3"])
    out["b_workload"] = _copurchase(lambda g: balanced.workload(balanced.work_units(g, [workloads.rule("path3"), workloads.rule("star3")])))
    out["b_assign_snake"] = _copurchase(lambda g: _snake(g).select("vid", "cost", "worker"))
    out["b_balance"] = _copurchase(lambda g: balanced.balance(_snake(g)))
    out["i_root_candidates"] = _copurchase(lambda g: _index(g, "triangle").stages["a", "label"].select(F.col("a").alias("vid")))
    out["i_degree_filtered"] = _copurchase(lambda g: _index(g, "star3").stages["a", "degree"].select(F.col("a").alias("vid")))
    out["i_pruned_candidates"] = _copurchase(lambda g: _stacked_candidates(g, "dead_ends"))
    out["i_links"] = _copurchase(lambda g: _index(g, "triangle").links["a", "b"])
    out["i_stats"] = _copurchase(lambda g: _index(g, "triangle").stats())
    out["i_core_matches"] = _copurchase(lambda g: pathindex.match_core(g, _index(g, "kite"), ("a", "b", "c", "d")))
    out["i_non_tree_check"] = _copurchase(lambda g: validate.match(g, workloads.rule("triangle").pattern, "indexed"))
    out["i_tree_weights"] = _copurchase(lambda g: pathindex.root_weights(_index_homo(g), ("a", "b", "c")).agg(F.sum("weight").cast("bigint").alias("n")))
    out["r_satisfies"] = _copurchase(lambda g: validate.satisfies(g, [workloads.rule(r) for r in ("path3", "star3", "star3_holds", "triangle")]))
    out["r_counts"] = _copurchase(lambda g: validate.counts(g, workloads.rule("path3_strict")).withColumn("confidence", F.round("confidence", 6)))
    out["r_witness_star3"] = _copurchase(lambda g: validate.witnesses(g, workloads.rule("star3")))
    out["r_culprits_topk"] = _copurchase(lambda g: summary.culprits(validate.violations(g, workloads.rule("triangle")), workloads.rule("triangle"), 10))
    out["r_by_brand_rollup"] = _copurchase(lambda g: summary.rolled_up(validate.violations(g, workloads.rule("star3")), g, "a", "brand", "ptype"))
    out["r_by_type_cube"] = _copurchase(lambda g: _parts(validate.violations(g, workloads.rule("star3")), g))
    out["r_rank_in_label"] = _copurchase(lambda g: summary.ranked_in_label(validate.violations(g, workloads.rule("triangle")), g, "c", "brand", 2))
    out["r_explain"] = lambda spark, d: validate.explained(graph(spark, d, "docs"), workloads.rule("dup_label_x"))
    out["r_distinct_triangles"] = _copurchase(lambda g: validate.match(g, workloads.rule("triangle").pattern, distinct_subgraphs=True))
    out["r_star_count_factorised"] = _copurchase(_star_count)
    out["r_rule_set"] = _copurchase(lambda g: _tagged(validate.validate(g, [workloads.rule(r) for r in ("path3_strict", "path3", "triangle")])))
    out["r_difference"] = _copurchase(lambda g: validate.difference(validate.violations(g, workloads.rule("star3")), validate.violations(g, workloads.rule("star3"), "indexed", "induced")))
    out["r_counts_factorised"] = _copurchase(lambda g: validate.counts(g, workloads.rule("star3"), leaves="count").withColumn("confidence", F.round("confidence", 6)))
    out["r_grouping_sets"] = _copurchase(lambda g: summary.grouped_by_sets(validate.violations(g, workloads.rule("star3")), g, "a", ("brand",), ("ptype",), ()).select("brand", "ptype", "n"))
    out["s_ended_induced"] = _copurchase(_ended)
    out["s_sliding_windows"] = lambda spark, d: incremental.sliding_counts(builders.load(spark, d, "events"))
    out["s_incremental_triangle"] = _copurchase(lambda g: incremental.replayed(g, workloads.rule("triangle"), 3))
    out["s_active_windows"] = lambda spark, d: incremental.windowed_counts(builders.load(spark, d, "events"))
    out["t_within_hours"] = lambda spark, d: incremental.temporal_edges(builders.load(spark, d, "events"), 3600 * 6)
    out["t_asof"] = lambda spark, d: incremental.asof_link(builders.load(spark, d, "events"), "error", "signup")
    return out


def _index_homo(g: PropertyGraph) -> pathindex.CandidateIndex:
    return pathindex.build_index(g, workloads.rule("path3").pattern, "homo", options=pathindex.FULL)


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {f"v_{n}": sql for n, sql in VIOLATIONS.items() if n != "dup_label_x"}
    out["v_dup_label_x_unsatisfied"] = VIOLATIONS["dup_label_x"]
    out["v_dup_label_x_satisfied"] = SATISFIED_X
    for name in queries():
        if "_induced" in name and name.startswith("v_"):
            out[name] = next(sql for n, sql in INDUCED.items() if name.startswith(f"v_{n}_induced"))
        elif name.startswith("v_") and name not in out:
            base = next(n for n in sorted(VIOLATIONS, key=len, reverse=True) if name.startswith(f"v_{n}"))
            out[name] = VIOLATIONS[base]
    for name, by in MATCHES.items():
        for semantics, sql in by.items():
            out[f"m_{name}_direct_count{'' if semantics == 'mono' else '_' + semantics}"] = sql
    degree = "SELECT src AS vid, count(*) AS degree FROM co GROUP BY src"
    ranges = f"""WITH {MAIN}, k AS (SELECT vid, row_number() OVER (ORDER BY vid) - 1 AS nth, count(*) OVER () AS total FROM m)
        SELECT 'path3' AS rule_id, 'b' AS var, (nth * 8 // total)::INT AS range_id, min(vid) AS lo, max(vid) AS hi, count(*) AS cnt FROM k GROUP BY ALL"""

    def balls(var: str, label: str) -> str:
        return f"SELECT p.vid, 1 + count(DISTINCT co.dst) FILTER (WHERE co.dst <> p.vid) AS cost FROM {label} p LEFT JOIN co ON co.src = p.vid GROUP BY p.vid"

    snake = f"""WITH {MAIN}, u AS ({balls('b', 'm')}), k AS (SELECT *, (row_number() OVER (ORDER BY cost DESC, vid) - 1) % 8 AS t FROM u),
        w AS (SELECT vid, cost, (CASE WHEN t < 4 THEN t ELSE 7 - t END)::INT AS worker FROM k)"""
    deg2 = "d AS (SELECT src AS vid FROM mm GROUP BY src HAVING count(*) >= 2)"
    pruned = f"""{deg2}, root AS (SELECT DISTINCT src AS vid FROM mm WHERE src IN (SELECT vid FROM d) AND dst IN (SELECT vid FROM d)),
        leaf AS (SELECT DISTINCT dst AS vid FROM mm WHERE src IN (SELECT vid FROM root) AND dst IN (SELECT vid FROM d))"""
    star = VIOLATIONS["star3"]
    tri = VIOLATIONS["triangle"]
    counted = f"SELECT a AS vid, count(*) AS n FROM ({star}) GROUP BY a"
    rules = {n: VIOLATIONS[n] for n in ("path3_strict", "path3", "triangle")}
    out |= {
        "g_copurchase_edges": f"WITH {CO} SELECT src, dst, 'co' AS elabel FROM co",
        "g_copurchase_vertices": f"WITH {PARTS} SELECT * FROM pv",
        "g_trade_edges": """WITH l AS (SELECT * FROM lineitem) SELECT 200000000000000 + n_nationkey AS src, 100000000000000 + n_regionkey AS dst, 'in_region' AS elabel FROM nation
            UNION SELECT 300000000000000 + c_custkey, 200000000000000 + c_nationkey, 'based_in' FROM customer UNION SELECT 400000000000000 + s_suppkey, 200000000000000 + s_nationkey, 'based_in' FROM supplier
            UNION SELECT 300000000000000 + o_custkey, 600000000000000 + o_orderkey, 'placed' FROM orders UNION SELECT 600000000000000 + l_orderkey, 500000000000000 + l_partkey, 'contains' FROM l
            UNION SELECT 600000000000000 + l_orderkey, 400000000000000 + l_suppkey, 'shipped_by' FROM l UNION SELECT 400000000000000 + l_suppkey, 500000000000000 + l_partkey, 'sources' FROM l
            UNION SELECT 300000000000000 + o_custkey, 400000000000000 + l_suppkey, 'buys_from' FROM l JOIN orders ON l_orderkey = o_orderkey""",
        "g_docs_edges": f"WITH {DOCS} SELECT a.vid AS src, b.vid AS dst, 'same_text' AS elabel FROM dv a JOIN dv b ON a.h = b.h AND a.vid <> b.vid",
        "g_sessions_edges": """WITH n AS (SELECT 800000000000000 + event_id AS src, 800000000000000 + lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events)
            SELECT src, dst, 'next' AS elabel FROM n WHERE dst IS NOT NULL UNION SELECT 800000000000000 + event_id, 700000000000000 + user_id, 'by' FROM events""",
        "g_dialogue_edges": f"WITH {TURNS} SELECT x AS src, y AS dst, 'next' AS elabel FROM nx WHERE y IS NOT NULL",
        "g_web_edges": f"WITH {WEB} SELECT pg.vid AS src, hs.vid AS dst, 'on_host' AS elabel FROM pg JOIN hs USING (host) UNION SELECT page, tg.vid, 'links_to' FROM lk JOIN tg USING (target)",
        "g_similar_edges": f"WITH {SIMILAR} SELECT src, dst, 'near' AS elabel FROM near",
        "g_first_n_edges": f"WITH {PARTS}, {CO}, f AS (SELECT vid FROM pv ORDER BY vid LIMIT 1000) SELECT src, dst, 'co' AS elabel FROM co WHERE src IN (SELECT vid FROM f) AND dst IN (SELECT vid FROM f)",
        "g_stats": f"WITH {PARTS}, {CO}, g AS ({degree}) SELECT (SELECT count(*) FROM pv) AS n_vertices, (SELECT count(DISTINCT vlabel) FROM pv) AS n_labels, (SELECT count(*) FROM co) AS n_arcs, max(degree) AS max_degree, sum(degree * degree)::BIGINT AS sum_squares FROM g",
        "g_degree_hist": f"WITH {CO}, g AS ({degree}) SELECT degree, count(*) AS n FROM g GROUP BY degree",
        "g_label_counts": "SELECT 'region' AS vlabel, count(*) AS n FROM region UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT 'customer', count(*) FROM customer UNION ALL SELECT 'supplier', count(*) FROM supplier UNION ALL SELECT 'part', count(*) FROM part UNION ALL SELECT 'order', count(*) FROM orders",
        "g_multilabel_pairs": "SELECT 1::BIGINT AS src, 1::BIGINT AS dst, 1::BIGINT AS n_labels WHERE false",
        "g_sample_edges": f"""WITH {PARTS}, {CO}, f AS (SELECT vid FROM pv WHERE ('0x' || substr(md5('0/' || vid::VARCHAR), 1, 8))::BIGINT < floor(0.3 * 4294967296))
            SELECT src, dst, 'co' AS elabel FROM co WHERE src IN (SELECT vid FROM f) AND dst IN (SELECT vid FROM f)""",
        "g_multilabel_planted": f"WITH {CO} SELECT src, dst, 2::BIGINT AS n_labels FROM co WHERE src < dst AND src % 3 = 0",
        "g_degrees_about": f"WITH {CO} SELECT DISTINCT src AS vid FROM co",
        "g_event_values": "SELECT event_id, json_extract(props, '$.k')::INT AS k FROM events",
        "g_similar_udf": f"WITH {SIMILAR} SELECT src, dst, 'near' AS elabel FROM near",
        "g_kinds": """WITH e AS (SELECT DISTINCT 'customer' AS src_label, 'placed' AS elabel, 'order' AS dst_label, o_custkey AS s, o_orderkey AS d FROM orders
            UNION SELECT 'nation', 'in_region', 'region', n_nationkey, n_regionkey FROM nation UNION SELECT 'customer', 'based_in', 'nation', c_custkey, c_nationkey FROM customer
            UNION SELECT 'supplier', 'based_in', 'nation', s_suppkey, s_nationkey FROM supplier UNION SELECT 'order', 'contains', 'part', l_orderkey, l_partkey FROM lineitem
            UNION SELECT 'order', 'shipped_by', 'supplier', l_orderkey, l_suppkey FROM lineitem UNION SELECT 'supplier', 'sources', 'part', l_suppkey, l_partkey FROM lineitem
            UNION SELECT 'customer', 'buys_from', 'supplier', o_custkey, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
            k AS (SELECT src_label, elabel, dst_label, s, count(*) AS n FROM e GROUP BY ALL)
            SELECT src_label, elabel, dst_label, sum(n)::BIGINT AS arcs, max(n) AS max_degree, sum(n * n)::BIGINT AS sum_squares FROM k GROUP BY ALL""",
        "g_ball2": f"""WITH {PARTS}, {CO}, c AS (SELECT vid FROM pv WHERE vlabel = 'SIDE' AND size = 50),
            r AS (SELECT vid AS centre, vid FROM c UNION SELECT vid, dst FROM c JOIN co ON src = vid UNION SELECT c.vid, y.dst FROM c JOIN co x ON x.src = c.vid JOIN co y ON y.src = x.dst) SELECT centre, count(*) AS n FROM r GROUP BY centre""",
        "g_top_neighbours": f"WITH {PARTS}, {CO}, k AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY price DESC, dst)::INT AS rank FROM co JOIN pv ON vid = dst) SELECT src, rank, dst FROM k WHERE rank <= 2",
        "b_pivots": f"""WITH {PARTS}, t AS (SELECT * FROM (VALUES ('path3', 0, 'b', 1, 'MAIN'), ('star3', 0, 'a', 1, 'SIDE'), ('triangle', 0, 'a', 1, 'MAIN'), ('fd_part', 0, 'x', 0, NULL), ('fd_part', 1, 'y', 0, NULL)) AS t(rule_id, component, var, radius, label))
            SELECT rule_id, component, var, radius, count(vid) AS candidates, min(vid) AS lo, max(vid) AS hi FROM t LEFT JOIN pv ON label IS NULL OR label = vlabel GROUP BY ALL""",
        "b_candidate_hist": f"WITH {PARTS} SELECT 'path3' AS rule_id, 'b' AS var, size AS attr_value, count(*) AS cnt FROM pv WHERE vlabel = 'MAIN' GROUP BY size UNION ALL SELECT 'star3', 'a', size, count(*) FROM pv WHERE vlabel = 'SIDE' GROUP BY size",
        "b_ranges": ranges,
        "b_messages": "SELECT i::INT AS msg_id, 'path3' AS rule_id, '0:' || i AS ranges, (i % 4)::INT AS worker FROM range(8) AS t(i)",
        "b_messages_fd": "SELECT (3 * i + j)::INT AS msg_id, 'fd_part' AS rule_id, '0:' || i || ',1:' || j AS ranges, ((3 * i + j) % 4)::INT AS worker FROM range(3) AS t(i), range(3) AS u(j)",
        "b_message_costs": f"""WITH {MAIN}, u AS ({balls('b', 'm')}), k AS (SELECT *, ((row_number() OVER (ORDER BY vid) - 1) * 8 // count(*) OVER ())::INT AS r FROM u)
            SELECT r AS msg_id, r AS range_id, sum(cost)::BIGINT AS cost FROM k GROUP BY r""",
        "b_message_units": f"""WITH {MAIN}, u AS ({balls('b', 'm')}), k AS (SELECT *, ((row_number() OVER (ORDER BY vid) - 1) * 8 // count(*) OVER ())::INT AS msg_id, (row_number() OVER (ORDER BY cost DESC, vid) - 1) % 8 AS t FROM u)
            SELECT vid, msg_id, cost, (CASE WHEN t < 4 THEN t ELSE 7 - t END)::INT AS worker FROM k""",
        "b_units_path3": f"WITH {MAIN}, u AS ({balls('b', 'm')}) SELECT 'path3' AS rule_id, 'b' AS var, vid, cost FROM u",
        "b_workload": f"WITH {MAIN}, x AS ({balls('b', 'm')}), y AS ({balls('a', 's')}) SELECT 'path3' AS rule_id, 'b' AS var, count(*) AS units, sum(cost)::BIGINT AS total_cost, max(cost) AS max_cost FROM x UNION ALL SELECT 'star3', 'a', count(*), sum(cost)::BIGINT, max(cost) FROM y",
        "b_assign_snake": f"{snake} SELECT * FROM w",
        "b_balance": f"{snake} SELECT worker, count(*) AS units, sum(cost)::BIGINT AS load FROM w GROUP BY worker",
        "i_root_candidates": f"WITH {MAIN} SELECT vid FROM m",
        "i_degree_filtered": f"WITH {MAIN} SELECT src AS vid FROM ss GROUP BY src HAVING count(*) >= 3",
        "i_pruned_candidates": f"WITH {MAIN}, {pruned} SELECT 'a' AS var, vid FROM root UNION ALL SELECT 'b', vid FROM leaf UNION ALL SELECT 'c', vid FROM leaf",
        "i_links": f"WITH {MAIN}, {pruned} SELECT src AS a, dst AS b FROM mm WHERE src IN (SELECT vid FROM root) AND dst IN (SELECT vid FROM d)",
        "i_stats": f"""WITH {MAIN}, {pruned}, v AS (SELECT unnest(['a', 'b', 'c']) AS query_vertex) SELECT query_vertex, 'label' AS stage, (SELECT count(*) FROM m) AS candidates FROM v
            UNION ALL SELECT query_vertex, 'degree', (SELECT count(*) FROM d) FROM v UNION ALL SELECT query_vertex, 'dead_ends', CASE WHEN query_vertex = 'a' THEN (SELECT count(*) FROM root) ELSE (SELECT count(*) FROM leaf) END FROM v""",
        # the index keeps only core matches whose variable a can still get its tail: a third neighbour
        "i_core_matches": f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT a, b, c FROM r WHERE (SELECT count(*) FROM mm WHERE src = a) >= 3",
        "i_non_tree_check": f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT a, b, c FROM r",
        "i_tree_weights": MATCHES["path3"]["homo"],
        "r_satisfies": " UNION ALL ".join(f"SELECT '{n}' AS rule_id, count(*) = 0 AS holds FROM ({VIOLATIONS[n]})" for n in ("path3", "star3", "star3_holds", "triangle")),
        "r_counts": f"""WITH {MAIN}, r AS ({PATH_ROWS}), k AS (SELECT {DOR.format('a')} AND {DOR.format('b')} AND {DOR.format('c')} AS x, b IN (SELECT vid FROM pv WHERE size >= 45) AS y FROM r WHERE a <> c)
            SELECT 'path3_strict' AS rule_id, count(*) AS matches, count(*) FILTER (WHERE x) AS support, count(*) FILTER (WHERE x AND NOT y) AS violations, round(1 - count(*) FILTER (WHERE x AND NOT y) / count(*) FILTER (WHERE x), 6) AS confidence FROM k""",
        "r_witness_star3": f"SELECT DISTINCT a FROM ({star})",
        "r_culprits_topk": f"WITH v AS ({tri}) SELECT vid, count(*) AS n FROM (SELECT a AS vid FROM v UNION ALL SELECT b FROM v UNION ALL SELECT c FROM v) GROUP BY vid ORDER BY n DESC, vid LIMIT 10",
        "r_by_brand_rollup": f"WITH c AS ({counted}), {PARTS} SELECT brand, ptype, sum(n)::BIGINT AS n FROM c JOIN pv USING (vid) GROUP BY ROLLUP (brand, ptype)",
        "r_by_type_cube": f"WITH c AS ({counted}), {PARTS} SELECT brand, ptype, sum(n)::BIGINT AS n FROM c JOIN pv USING (vid) GROUP BY CUBE (brand, ptype)",
        "r_rank_in_label": f"WITH c AS (SELECT c AS vid, count(*) AS n FROM ({tri}) GROUP BY c), {PARTS}, k AS (SELECT brand, vid, n, row_number() OVER (PARTITION BY brand ORDER BY n DESC, vid)::INT AS rank FROM c JOIN pv USING (vid)) SELECT * FROM k WHERE rank <= 2",
        "r_explain": f"SELECT *, 'y.quality = 1' AS failing FROM ({VIOLATIONS['dup_label_x']})",
        "r_distinct_triangles": f"WITH {MAIN}, r AS ({TRIANGLE_ROWS}) SELECT a, b, c FROM r WHERE a < b AND b < c",
        "r_star_count_factorised": MATCHES["star3"]["mono"],
        "r_rule_set": " UNION ALL ".join(f"SELECT '{n}' AS rule_id, var, vid, count(*) AS n FROM (SELECT 'a' AS var, a AS vid FROM ({sql}) UNION ALL SELECT 'b', b FROM ({sql}) UNION ALL SELECT 'c', c FROM ({sql})) GROUP BY ALL" for n, sql in rules.items()),
        "r_difference": f"WITH l AS ({star}), r AS ({INDUCED['star3']}) SELECT 'left' AS side, * FROM (SELECT * FROM l EXCEPT ALL SELECT * FROM r) UNION ALL SELECT 'right', * FROM (SELECT * FROM r EXCEPT ALL SELECT * FROM l)",
        "r_counts_factorised": f"""WITH {MAIN}, r AS ({STAR_ROWS}), k AS (SELECT {DOR.format('a')} AS bad FROM r WHERE {STAR_APART})
            SELECT 'star3' AS rule_id, count(*) AS matches, count(*) AS support, count(*) FILTER (WHERE bad) AS violations, round(1 - count(*) FILTER (WHERE bad) / count(*), 6) AS confidence FROM k""",
        "r_grouping_sets": f"WITH c AS ({counted}), {PARTS} SELECT brand, ptype, sum(n)::BIGINT AS n FROM c JOIN pv USING (vid) GROUP BY GROUPING SETS ((brand), (ptype), ())",
        "s_ended_induced": f"""WITH {PARTS}, {CO}, s AS (SELECT * FROM pv WHERE vlabel = 'SIDE'), old AS (SELECT * FROM co WHERE (least(src, dst) * 31 + greatest(src, dst)) % 10 <> 0),
            ss AS (SELECT src, dst FROM old WHERE src IN (SELECT vid FROM s) AND dst IN (SELECT vid FROM s)), r AS ({STAR_ROWS}),
            f AS (SELECT a, b, c, d FROM r WHERE {STAR_APART} AND {DOR.format('a')} AND NOT EXISTS (SELECT 1 FROM old z WHERE (z.src, z.dst) IN ((b, c), (b, d), (c, d))))
            SELECT DISTINCT f.* FROM f JOIN co z ON (z.src = b AND z.dst = c) OR (z.src = b AND z.dst = d) OR (z.src = c AND z.dst = d)""",
        "s_sliding_windows": """WITH w AS (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY])::TIMESTAMP AS begin, event_type FROM events)
            SELECT begin, event_type, count(*) AS n FROM w GROUP BY ALL""",
        "s_incremental_triangle": tri,
        "s_active_windows": "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL",
        "t_within_hours": """SELECT 800000000000000 + a.event_id AS src, 800000000000000 + b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id
            AND (b.ts > a.ts OR b.ts = a.ts AND b.event_id > a.event_id) AND epoch_us(b.ts) - epoch_us(a.ts) <= 21600000000""",
        "t_asof": """SELECT 800000000000000 + e.event_id AS src, 800000000000000 + (SELECT arg_max(s.event_id, (s.ts, s.event_id)) FROM events s WHERE s.user_id = e.user_id AND s.event_type = 'signup' AND (s.ts, s.event_id) < (e.ts, e.event_id)) AS dst
            FROM events e WHERE e.event_type = 'error'""",
    }
    out["g_ball2_recursive"] = out["g_ball2"]
    return out
