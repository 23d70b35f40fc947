"""Readers, sinks, streams of events and plan shapes."""

from pyspark.sql import functions as F

from lattica import workloads
from lattica.model import builders
from lattica.operators import validate
from lattica.report import measures, summary
from lattica.sources import readers, writers
from lattica.streaming import incremental

SF = "/root/testdata/sf0.001"


def test_edge_lists(spark, tmp_path):
    text = tmp_path / "edges.txt"
    text.write_text("# comment\nsrc dst\n1 2\n 2,3\n4\t5\nx y\n")
    want = [(1, 2), (2, 3), (4, 5)]
    assert sorted(tuple(r)[:2] for r in readers.read_edge_list(spark, str(text)).collect()) == want
    spark.dataSource.register(readers.EdgeListSource)
    for step in (3, 7, 1000):
        rows = spark.read.format("edge_list").option("bytes", step).load(str(text)).collect()
        assert sorted(map(tuple, rows)) == want
    readers.register_udtf(spark)
    spark.read.text(str(text)).createOrReplaceTempView("lines")
    assert sorted(map(tuple, spark.sql("SELECT t.* FROM lines, LATERAL parse_edge_line(value) t").collect())) == want


def test_graph_round_trip(spark, tmp_path):
    g = builders.copurchase(spark, SF)
    writers.write_graph(g, str(tmp_path / "g"))
    back = readers.read_graph(spark, str(tmp_path / "g/vertices"), str(tmp_path / "g/edges"), directed=False)
    rule = workloads.rule("triangle")
    assert validate.violations(back, rule).count() == validate.violations(g, rule).count() == 52
    found = validate.validate(g, [rule])
    writers.write_violations(found, str(tmp_path / "v"))
    writers.write_report(writers.flat_bindings(found), str(tmp_path / "r"))
    assert spark.read.parquet(str(tmp_path / "v")).where("rule_id = 'triangle'").count() == 52
    writers.write_bucketed(g, "bucketed_edges", 4)
    assert spark.table("bucketed_edges").count() == g.edges.count()


def test_golden_counts(spark):
    g = builders.copurchase(spark, SF)
    for name, n in (("path3", 10172), ("star3", 5376), ("triangle", 1668), ("kite", 15644)):
        assert validate.match(g, workloads.rule(name).pattern).count() == n
    assert validate.violations(g, workloads.rule("star3")).count() == 1842


def test_plans(spark):
    g = builders.copurchase(spark, SF)
    for name in ("triangle", "star3", "path3"):
        profile = measures.plan_profile(validate.violations(g, workloads.rule(name)))
        assert profile["python"] == 0 and profile["cartesian"] == 0 and profile["exchanges"] <= 24, (name, profile)


def test_measures(spark):
    times = spark.createDataFrame([("direct", "q", 40.0), ("indexed", "q", 10.0)], "strategy string, query string, ms double")
    assert {r["strategy"]: r["speedup"] for r in measures.speedups(times, "direct").collect()} == {"direct": 1.0, "indexed": 4.0}
    assert summary.pivoted(times, ["q"]).count() == 2
    assert measures.peak_memory(spark).peak_virtual > 0 and measures.time_run(lambda: spark.range(3), 1, 0) > 0
    even = spark.createDataFrame([(1, 2), (2, 2)], "vid int, degree long")
    assert abs(measures.degree_gini(even).first()[0]) < 1e-9
    assert measures.memory_ratio({"a": 5, "b": 1}, "b")["a"] == 5 and measures.phase_share(99, 100) == 0.99


def test_event_streams(spark, tmp_path):
    events = builders.load(spark, SF, "events")
    days = tmp_path / "days"
    events.withColumn("ts", F.col("ts").cast("timestamp")).repartition(3).write.parquet(str(days))
    stream = incremental.watermarked(spark.readStream.schema("event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string").parquet(str(days)))
    counts = incremental.windowed_counts(stream)
    query = counts.writeStream.format("memory").queryName("windows").outputMode("complete").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination(120)
    assert spark.table("windows").agg(F.sum("n")).first()[0] == events.count()
    assert incremental.session_counts(events).agg(F.sum("n")).first()[0] == events.count()
    chain = incremental.typed_chain(events, events, "signup", "purchase", "5 days")
    assert chain.where("b_ts <= a_ts").count() == 0 and chain.count() > 0


def test_stream_of_next_events(spark, tmp_path):
    events = builders.load(spark, SF, "events").where("user_id < 20").withColumn("ts", F.col("ts").cast("timestamp"))
    days = tmp_path / "days"
    cut = events.selectExpr("percentile_approx(ts, 0.5)").first()[0]
    for part in (events.where(F.col("ts") <= cut), events.where(F.col("ts") > cut)):  # in order within a user
        part.coalesce(1).write.mode("append").parquet(str(days))
    kept = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(days))
        query = incremental.next_edges_stream(stream).writeStream.format("memory").queryName("nexts").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "n")).start()
        assert query.awaitTermination(180)
        got = sorted(map(tuple, spark.table("nexts").collect()))
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", kept)
    whole = builders.sessions(spark, SF)
    ids = events.select((F.col("event_id") + 8 * 10**14).alias("src"))
    assert got == sorted(map(tuple, whole.edges.where("elabel = 'next'").select("src", "dst").join(ids, "src", "left_semi").collect())) and got


def test_streams_of_typed_chains_and_sliding_windows(spark, tmp_path):
    events = builders.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    days = tmp_path / "days"
    events.repartition(2).write.parquet(str(days))

    def source():
        return spark.readStream.schema(events.schema).parquet(str(days)).withWatermark("ts", "1 hour")

    chain = incremental.typed_chain(source(), source(), "signup", "purchase", "5 days").select("src", "dst")
    query = chain.writeStream.format("memory").queryName("chains").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    assert query.awaitTermination(180)
    want = incremental.typed_chain(events, events, "signup", "purchase", "5 days").select("src", "dst")
    assert sorted(map(tuple, spark.table("chains").collect())) == sorted(map(tuple, want.collect()))
    query = incremental.sliding_counts(source()).writeStream.format("memory").queryName("sliding").outputMode("complete").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "s")).start()
    assert query.awaitTermination(180)
    assert spark.table("sliding").agg(F.sum("n")).first()[0] == 2 * events.count()


def test_sets_samples_and_sketches(spark):
    g = builders.copurchase(spark, SF)
    found = validate.violations(g, workloads.rule("triangle"))
    rows = summary.grouped_by_sets(found, g, "a", ("brand",), ("ptype",), ()).collect()
    assert sum(r["n"] for r in rows) == 3 * 52 and len({r["grouping"] for r in rows}) == 3
    kept = g.sample_vertices(0.5, seed=3).vertices.count()
    assert 50 < kept < 150 and g.sample_vertices(1.0).edges.count() == g.edges.count()
    about = g.degrees_about().join(g.degrees().withColumnRenamed("degree", "exact"), "vid")
    assert about.where(F.abs(F.col("degree") - F.col("exact")) > 0.2 * F.col("exact")).count() == 0
    seeds = g.labelled("SIDE").select("vid").limit(5)
    assert sorted(map(tuple, g.ball_sql(seeds, 2).collect())) == sorted(map(tuple, g.ball(seeds, 2).collect()))


def _odd_vectors(folder):
    """Embeddings of many lengths with equal ones, a zero one, one with a NaN and one id twice; and as many again with nulls."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.parquet as pq

    rng = np.random.default_rng(5)
    v = (rng.normal(size=(300, 64)) * 10.0 ** rng.integers(-18, 18, (300, 1))).astype(np.float32)
    v[7] = v[8] = v[9]
    v[20], v[21, 3], v[22, 5] = 0, np.nan, np.inf
    ids, rows, label = [*range(299), 5], v.tolist(), [i % 3 for i in range(300)]
    schema = pa.schema([("vec_id", pa.int64()), ("embedding", pa.list_(pa.float32())), ("label", pa.int32())])
    for name, more in (("whole", []), ("nulls", [(900, None), (901, [None, *rows[0][1:]]), (902, rows[7][:63]), (None, rows[7]), (903, [])])):
        (folder / name).mkdir()
        table = pa.table([ids + [i for i, _ in more], rows + [x for _, x in more], label + [0] * len(more)], schema=schema)
        pq.write_table(table, folder / name / "embeddings.parquet")
    return str(folder / "whole"), str(folder / "nulls")


def _by_sql(name, folder):
    import duckdb

    from lattica import queries

    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{folder}/embeddings.parquet'")
    return sorted(con.sql(queries.oracle_sql()[name]).fetchall())


def test_similar_vectors_of_any_kind(spark, tmp_path):
    whole, nulls = _odd_vectors(tmp_path)
    want = _by_sql("g_similar_edges", whole)
    assert len(want) > 2 * 2 * 296
    for blocks in (1, 3, 8):
        assert sorted(map(tuple, builders.similar(spark, whole, blocks=blocks).edges.collect())) == want
    assert sorted(map(tuple, builders.similar(spark, nulls).edges.collect())) == want


def test_similar_vectors_meet_in_products_of_matrices(spark):
    plan = builders.similar(spark, SF).edges._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "Join" not in plan


def _each_id_once(folder, whole):
    import pyarrow.parquet as pq

    (folder / "once").mkdir()
    pq.write_table(pq.read_table(f"{whole}/embeddings.parquet").slice(0, 299), folder / "once/embeddings.parquet")
    return str(folder / "once")


def test_cosines_agree_on_vectors_of_any_kind(spark, tmp_path):
    from lattica import queries

    whole, _ = _odd_vectors(tmp_path)
    once = _each_id_once(tmp_path, whole)
    assert sorted(map(tuple, queries.queries()["g_similar_udf"](spark, once).collect())) == _by_sql("g_similar_udf", once)


def test_recursive_balls_of_more_than_a_million_rows(spark):
    from lattica.model.graph import PropertyGraph

    n = 1100  # a star: from each leaf, all leaves are two steps away
    vertices = spark.range(n).select(F.col("id").alias("vid"), F.lit("P").alias("vlabel"))
    g = PropertyGraph.of(vertices, vertices.where("vid > 0").select(F.lit(0).alias("src"), F.col("vid").alias("dst"), F.lit("e").alias("elabel")), directed=False)
    rows = g.ball_sql(vertices.select("vid"), 2).groupBy("centre").agg(F.count(F.lit(1)).alias("n"))
    assert [tuple(r) for r in rows.groupBy("n").count().collect()] == [(n, n)]


def test_recursive_balls_far_out(spark):
    from lattica.model.graph import PropertyGraph

    vertices = spark.range(130).select(F.col("id").alias("vid"), F.lit("P").alias("vlabel"))
    g = PropertyGraph.of(vertices, vertices.where("vid > 0").select((F.col("vid") - 1).alias("src"), F.col("vid").alias("dst"), F.lit("e").alias("elabel")))
    assert g.ball_sql(vertices.where("vid = 0").select("vid"), 120).count() == 121


def test_sketched_degrees_are_exact_while_small(spark):
    from lattica.model.graph import PropertyGraph

    arcs = spark.range(20_000).select(F.col("id").alias("src"), F.explode(F.sequence(F.lit(1), F.lit(4))).alias("k"))
    hub = spark.range(100_000).select(F.lit(-1).alias("src"), (F.col("id") + 10**9).alias("dst"), F.lit("e").alias("elabel"))
    edges = arcs.select("src", (F.col("src") * 4 + F.col("k") + 10**6).alias("dst"), F.lit("e").alias("elabel")).union(hub)
    found = {r["degree"] for r in PropertyGraph(spark.range(20_000).select(F.col("id").alias("vid")), edges, directed=False).degrees_about().where("vid >= 0").select("degree").distinct().collect()}
    assert found == {4}
    about = PropertyGraph(spark.range(1).select(F.col("id").alias("vid")), hub, directed=False).degrees_about().first()["degree"]
    assert abs(about - 100_000) < 10_000


def test_triangles_of_vectors_of_any_kind(spark, tmp_path):
    from lattica import queries

    whole, _ = _odd_vectors(tmp_path)
    once = _each_id_once(tmp_path, whole)
    assert sorted(map(tuple, queries.queries()["v_similar_triangle"](spark, once).collect())) == _by_sql("v_similar_triangle", once)


def test_open_paths_of_near_vectors_are_not_shuffled(spark):
    from lattica import queries

    plan = queries.queries()["v_similar_triangle"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow [_cell" in plan and "LeftSemi" not in plan
