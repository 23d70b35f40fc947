"""Places in an order of all rows, without a window over all of them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.store import saved


def ranked(rows: DataFrame, by: list[str], descending: bool = False) -> DataFrame:
    """Adds nth (from 1, by the ordering; the first column descending if asked for) and total.

    The rows are sorted into ranges of all ordering columns together, so ties of the first are split too; each range is
    numbered by itself, and prefix sums over the ranges, as many as there are partitions, give the places.
    """
    order = [F.desc_nulls_last(by[0]) if descending else F.asc_nulls_first(by[0]), *(F.asc_nulls_first(c) for c in by[1:])]
    place = F.monotonically_increasing_id()
    rows = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    rows = saved(rows.withColumns({"_part": F.shiftright(place, 33), "_k": place.bitwiseAND(F.lit((1 << 33) - 1))}), "ranked")
    counts, base, bases = sorted(map(tuple, rows.groupBy("_part").agg(F.count(F.lit(1)).alias("n")).collect())), 0, []  # one row per partition
    for part, n in counts:
        bases.append((part, base))
        base += n
    table = F.broadcast(rows.sparkSession.createDataFrame(bases, "_part bigint, _base bigint"))
    return rows.join(table, "_part").withColumns({"nth": F.col("_base") + F.col("_k") + 1, "total": F.lit(base).cast("bigint")}).drop("_part", "_k", "_base")
