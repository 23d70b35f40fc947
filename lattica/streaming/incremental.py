"""Changing graphs: incremental validation, time-bounded edges, and streams.

New matches touch at least one new arc. For pattern edge i the delta takes edge i from the new arcs, edges before it from the
old ones and edges after it from both, so each new match is found once. Under `induced` a new arc can also end matches.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import permutations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.literals import then_column, when_column
from ..model.graph import PropertyGraph, both_arcs, vertex_id
from ..operators import validate
from ..plans import steps
from ..rules import shape
from ..rules.ast import Pattern, Rule


def delta_matches(old: PropertyGraph, new_edges: DataFrame, pattern: Pattern, semantics: str = "mono", needs=None) -> DataFrame:
    """Bindings of a connected pattern that the new edges make; edges that were there already count as old."""
    if len(shape.components(pattern)) > 1 or not pattern.edges:
        raise ValueError("a connected pattern with edges is asked for")
    fresh = new_edges if old.directed else both_arcs(new_edges)
    fresh = fresh.join(old.edges, ["src", "dst", "elabel"], "left_anti").distinct()
    graphs = {"old": old, "new": PropertyGraph(old.vertices, fresh, old.directed)}
    graphs["all"] = PropertyGraph(old.vertices, old.edges.unionByName(fresh), old.directed)
    part, out = pattern.variables, []
    for i, pivot in enumerate(pattern.edges):
        source = {k: "new" if k == i else "old" if k < i else "all" for k in range(len(pattern.edges))}
        # start from the new edge, then breadth-first
        order, bound = [], {pivot.src}
        left = [pivot, *(e for k, e in enumerate(pattern.edges) if k != i)]
        number = {id(e): k for k, e in enumerate(pattern.edges)}
        while step := next((e for e in left if (e.src in bound) != (e.dst in bound)), None):
            p, c = (step.src, step.dst) if step.src in bound else (step.dst, step.src)
            order.append((p, c, step))
            bound.add(c)
            left.remove(step)

        def arcs(e, number=number, source=source):
            rows = steps.arcs_of(graphs[source[number[id(e)]]], pattern, e)
            if e.label is None and source[number[id(e)]] == "new":  # a pair that was joined before isn't new to a wildcard
                rows = rows.join(steps.arcs_of(old, pattern, e), ["src", "dst"], "left_anti")
            return rows

        def link(p, c, e, arcs=arcs):
            pairs = steps.oriented(arcs(e), e, p, c)
            return pairs if steps.free(old, pattern, c, needs) else pairs.join(steps.candidates(old, pattern, c, needs), c)

        start = steps.candidates(old, pattern, pivot.src, needs)
        df = steps.component_matches(pattern, part, start, pivot.src, order, link, arcs, steps.any_arc(graphs["all"], pattern), semantics)
        out.append(df.select(*part, *[c for c in df.columns if c not in part]))
    return reduce(DataFrame.unionByName, out)


def delta_violations(old: PropertyGraph, new_edges: DataFrame, rule: Rule, semantics: str = "mono", absent_in_x: str = "unsatisfied") -> DataFrame:
    needs = validate.needs_of(rule, absent_in_x, True)
    df = delta_matches(old, new_edges, rule.pattern, semantics, needs)
    return df.where(when_column(rule, absent_in_x) & ~then_column(rule)).select(*rule.pattern.variables)


def retracted(found: DataFrame, graph: PropertyGraph, rule: Rule) -> DataFrame:
    """Violations of which an arc is gone from the graph."""
    kept = found
    for e in rule.pattern.edges:
        arcs = steps.arcs_of(graph, rule.pattern, e).select(F.col("src").alias(e.src), F.col("dst").alias(e.dst)) if e.src != e.dst else graph.arcs(e.label).where("src = dst").select(F.col("src").alias(e.src))
        kept = kept.join(arcs, list(dict.fromkeys((e.src, e.dst))), "left_semi")
    return found.join(kept, list(rule.pattern.variables), "left_anti")


def ended(found: DataFrame, graph: PropertyGraph, rule: Rule) -> DataFrame:
    """Violations found under `induced` that are none in a graph with more arcs: an arc joins two of their vertices that the pattern leaves apart."""
    joined, hits = rule.pattern.arcs(), []
    for u, v in [*permutations(rule.pattern.variables, 2), *((v, v) for v in rule.pattern.variables)]:
        if (u, v) in joined or not rule.pattern.directed and u > v:
            continue
        arcs = steps.any_arc(graph, rule.pattern)(u, v)
        arcs = arcs.where("src = dst").select(F.col("src").alias(u)) if u == v else arcs.select(F.col("src").alias(u), F.col("dst").alias(v))
        hits.append(found.join(arcs, list(dict.fromkeys((u, v))), "left_semi").select(*found.columns))
    return reduce(DataFrame.unionByName, hits).distinct() if hits else found.limit(0)


def recheck(graph: PropertyGraph, rule: Rule, changed: DataFrame, **options) -> DataFrame:
    """Violations that contain a vertex (vid) whose attributes changed."""
    found = validate.violations(graph, rule, **options)
    hits = [found.join(changed.select(F.col("vid").alias(v)), v, "left_semi") for v in rule.pattern.variables]
    return reduce(DataFrame.unionByName, hits).distinct()


def replayed(graph: PropertyGraph, rule: Rule, batches: int) -> DataFrame:
    """All violations, found by adding the edges in batches (a hash of their ends): equals the one-shot result."""
    ends = [F.least("src", "dst"), F.greatest("src", "dst")] if not graph.directed else ["src", "dst"]
    dealt = graph.edges.withColumn("_b", F.pmod(F.xxhash64(*ends), F.lit(batches)))
    out = []
    for b in range(batches):
        old = PropertyGraph(graph.vertices, dealt.where(F.col("_b") < b).drop("_b"), graph.directed)
        out.append(delta_violations(old, dealt.where(F.col("_b") == b).drop("_b"), rule))
    return reduce(DataFrame.unionByName, out)


def validate_stream(vertices: DataFrame, arcs: DataFrame, rule: Rule, edges_path: str, sink_path: str, checkpoint: str, directed: bool = True, semantics: str = "mono"):
    """A writer of violations as a stream of edges (src, dst, elabel) comes in.

    Each batch is matched against the edges of earlier batches, its violations and its edges are written below folders of the
    batch's number, which a replayed batch overwrites; so every violation is written once.
    """
    spark = vertices.sparkSession

    def handle(batch: DataFrame, number: int) -> None:
        schema = "src bigint, dst bigint, elabel string, batch bigint"
        stored = spark.read.schema(schema).parquet(edges_path) if number and _exists(spark, edges_path) else spark.createDataFrame([], schema)
        old = PropertyGraph(vertices, stored.where(F.col("batch") < number).drop("batch").distinct(), directed)
        fresh = batch.select("src", "dst", "elabel").distinct()
        delta_violations(old, fresh, rule, semantics).write.mode("overwrite").parquet(f"{sink_path}/batch={number}")
        (fresh if directed else both_arcs(fresh)).write.mode("overwrite").parquet(f"{edges_path}/batch={number}")

    return arcs.writeStream.foreachBatch(handle).option("checkpointLocation", checkpoint)


def _exists(spark, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def windowed_counts(events: DataFrame, window: str = "1 day") -> DataFrame:
    """day, event_type, n: works on streams too (with a watermark on ts)."""
    rows = events.withColumn("_ts", F.col("ts").cast("timestamp"))
    return rows.groupBy(F.window("_ts", window).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "n")


def sliding_counts(events: DataFrame, window: str = "2 days", slide: str = "1 day") -> DataFrame:
    """begin, event_type, n of windows that overlap: an event counts in each window that it lies in."""
    rows = events.withColumn("_ts", F.col("ts").cast("timestamp"))
    return rows.groupBy(F.window("_ts", window, slide).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("begin"), "event_type", "n")


def watermarked(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events with an event time that streams accept, late ones bounded, repeated ids dropped once within the bound."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return rows.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else rows.dropDuplicates(["event_id"])


def session_counts(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, begin, end, n of sessions with pauses shorter than the gap."""
    rows = events.withColumn("_ts", F.col("ts").cast("timestamp")) if not events.isStreaming else events.withColumn("_ts", F.col("ts"))
    return rows.groupBy(F.session_window("_ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "n")


def typed_chain(left: DataFrame, right: DataFrame, first: str, second: str, within: str = "1 day") -> DataFrame:
    """src, dst of a user's event of one type followed by one of another within a time: an inner join of two streams with bounds."""
    a = left.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"))
    b = right.where(F.col("event_type") == second).select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"))
    on = (F.col("user_id") == F.col("b_user")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {within}"))
    return a.join(b, on).select(vertex_id("event", F.col("a_id")).alias("src"), vertex_id("event", F.col("b_id")).alias("dst"), "a_ts", "b_ts")


def temporal_edges(events: DataFrame, within: int) -> DataFrame:
    """src, dst of events of one user at most `within` seconds apart: a range join through buckets of that width."""
    base = events.select("user_id", "event_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    width = within * 1_000_000
    left = base.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.floor(F.col("us") / width), F.floor(F.col("us") / width) + 1)).alias("bucket"))
    right = base.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), F.floor(F.col("us") / width).alias("bucket"))
    after = (F.col("ub") > F.col("ua")) | (F.col("ub") == F.col("ua")) & (F.col("b") > F.col("a"))
    near = left.join(right, ["user_id", "bucket"]).where(after & (F.col("ub") - F.col("ua") <= width))
    return near.select(vertex_id("event", F.col("a")).alias("src"), vertex_id("event", F.col("b")).alias("dst"))


def asof_link(events: DataFrame, later: str, earlier: str) -> DataFrame:
    """src, dst: each event of one type with its user's last one of another type before it (null without)."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = events.where(F.col("event_type").isin(later, earlier))
    rows = rows.withColumn("prev", F.last(F.when(F.col("event_type") == earlier, F.col("event_id")), ignorenulls=True).over(order))
    return rows.where(F.col("event_type") == later).select(vertex_id("event", F.col("event_id")).alias("src"), vertex_id("event", F.col("prev")).alias("dst"))


def next_edges_stream(events: DataFrame):
    """src, dst of each user's consecutive events, from state per user: events have to come in order within a user.

    Needs the RocksDB state store provider (spark.sql.streaming.stateStore.providerClass).
    """
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Last(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.last = handle.getValueState("last", "event_id bigint")

        def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
            pdf = pd.concat(list(rows)).sort_values(["ts", "event_id"])
            before = [self.last.get()[0]] if self.last.exists() else []
            ids = [*before, *pdf["event_id"].tolist()]
            self.last.update((int(ids[-1]),))
            base = 8 * 10**14
            yield pd.DataFrame({"src": [base + int(a) for a in ids[:-1]], "dst": [base + int(b) for b in ids[1:]]}, dtype="int64")

        def close(self) -> None:
            pass

    return events.select("user_id", "event_id", "ts").groupBy("user_id").transformWithStateInPandas(statefulProcessor=Last(), outputStructType="src bigint, dst bigint", outputMode="Append", timeMode="None")
