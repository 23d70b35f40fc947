"""Measures: run time, memory, speed-ups, shares, plan profile."""

from __future__ import annotations

import re
import statistics
import time
from collections.abc import Callable
from dataclasses import dataclass
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Memory:
    """kB of the JVM: greatest virtual and resident size so far."""

    peak_virtual: int
    peak_resident: int


def time_run(make: Callable[[], DataFrame], runs: int = 3, warm_up: int = 1) -> float:
    """Median milliseconds of making and running a plan, index and all; results go nowhere."""
    took = []
    for i in range(warm_up + runs):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if i >= warm_up:
            took.append(1000 * (time.perf_counter() - began))
    return statistics.median(took)


def peak_memory(spark: SparkSession) -> Memory:
    """From /proc of the JVM. On a cluster this is the driver's; executors report theirs as task metrics."""
    pid = spark.sparkContext._jvm.java.lang.ProcessHandle.current().pid()
    text = Path(f"/proc/{pid}/status").read_text()
    return Memory(*(int(re.search(rf"{k}:\s+(\d+)", text)[1]) for k in ("VmPeak", "VmHWM")))


def speedups(times: DataFrame, base: str) -> DataFrame:
    """strategy, query, speedup over the base strategy, from (strategy, query, ms)."""
    other = times.where(F.col("strategy") == base).select("query", F.col("ms").alias("base_ms"))
    return times.join(other, "query").select("strategy", "query", (F.col("base_ms") / F.col("ms")).alias("speedup"))


def mean_speedups(times: DataFrame, base: str) -> DataFrame:
    return speedups(times, base).groupBy("strategy").agg(F.avg("speedup").alias("mean_speedup"))


def phase_share(match_ms: float, total_ms: float) -> float:
    """The share of the run time that matching takes, from a run without and one with the check."""
    return min(1.0, match_ms / total_ms)


def memory_ratio(peaks: dict[str, int], base: str) -> dict[str, float]:
    return {k: v / peaks[base] for k, v in peaks.items()}


def plan_profile(df: DataFrame) -> dict[str, int]:
    """Counts of exchanges, joins by kind, Python nodes and Cartesian products in the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    names = {"exchanges": r"\bExchange\b", "broadcasts": r"BroadcastExchange", "sort_merge": r"SortMergeJoin", "hash": r"(?:Broadcast|Shuffled)Hash ?Join", "cartesian": r"CartesianProduct|BroadcastNestedLoopJoin", "python": r"Python|Pandas|Arrow"}
    return {k: len(re.findall(p, text)) for k, p in names.items()}


def degree_gini(degrees: DataFrame) -> DataFrame:
    """gini of the degree distribution (0: all equal), from counts per degree; the histogram is small."""
    hist = degrees.groupBy("degree").agg(F.count(F.lit(1)).alias("n")).withColumn("_all", F.lit("all"))

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values("degree")
        n, mass = pdf["n"].cumsum(), (pdf["n"] * pdf["degree"]).cumsum()
        total = mass.iloc[-1] if len(mass) else 0
        if not total:
            return pd.DataFrame({"gini": [0.0]})
        area = ((mass + mass.shift(fill_value=0)) / total * pdf["n"] / n.iloc[-1]).sum() / 2
        return pd.DataFrame({"gini": [1 - 2 * area]})

    return hist.groupBy("_all").applyInPandas(run, "gini double")
