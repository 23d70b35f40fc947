"""Chat formatting: collapse cumulative snapshots, then render.

A logged conversation that another one continues (it is a proper prefix of it, turn by turn) or repeats is redundant.
The key of a prefix of n turns is n and two 64-bit hashes: exclusive ors over its turns of a hash of place, role and text.
Running keys need no text to move, only built-in functions, and are made in two steps, per chunk of turns and then over
the chunks, so that a conversation of any length is spread over tasks. An anti-join against the keys of proper prefixes,
made distinct before it, leaves maximal conversations; of equal ones that with the smallest id stays.

Defined results: turns are ordered by turn, null first, then role and text; null roles or texts are values of their own and
are rendered as empty; repeated rows are turns of their own; turns with a null conversation id form one conversation;
an empty table gives an empty table; other columns are not used. Two different prefixes of the same length count as
equal only if both 64-bit hashes agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import saved

CHUNK_TURNS = 256
OPEN, CLOSE = "<|{role}|>\n", "\n<|end|>\n"


def _keyed(turns: DataFrame) -> DataFrame:
    """conv_id, place (from 1), role, text, and the running keys h1 and h2."""
    # the chunk comes from a turn's value, so that its place in the order needs no window over a whole conversation
    rows = turns.withColumn("chunk", F.floor(F.col("turn") / CHUNK_TURNS))
    inner = Window.partitionBy("conv_id", "chunk").orderBy("turn", "role", "text")
    rows = rows.withColumn("k", F.row_number().over(inner))
    before = Window.partitionBy("conv_id").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    counts = rows.groupBy("conv_id", "chunk").agg(F.count(F.lit(1)).alias("n"))
    counts = counts.select("conv_id", "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    rows = _same(rows, counts, ["conv_id", "chunk"]).withColumn("place", F.col("base") + F.col("k"))
    content = [F.col("place"), F.col("role").isNull(), F.col("role"), F.col("text").isNull(), F.col("text")]
    rows = rows.withColumns({"e1": F.xxhash64(F.lit(1), *content), "e2": F.xxhash64(F.lit(2), F.lit("turn"), *content)})
    run = inner.rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumns({"r1": F.bit_xor("e1").over(run), "r2": F.bit_xor("e2").over(run)})
    sums = rows.groupBy("conv_id", "chunk").agg(F.bit_xor("e1").alias("c1"), F.bit_xor("e2").alias("c2"))
    sums = sums.select("conv_id", "chunk", *[F.coalesce(F.bit_xor(c).over(before), F.lit(0)).alias(b) for c, b in (("c1", "b1"), ("c2", "b2"))])
    rows = _same(rows, sums, ["conv_id", "chunk"])
    return rows.select("conv_id", "place", "role", "text", F.col("r1").bitwiseXOR(F.col("b1")).alias("h1"), F.col("r2").bitwiseXOR(F.col("b2")).alias("h2"))


def _same(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """Inner join where null keys are equal."""
    renamed = right.select(*[F.col(k).alias(f"_{k}") for k in keys], *[c for c in right.columns if c not in keys])
    on = F.lit(True)
    for k in keys:
        on &= F.col(k).eqNullSafe(F.col(f"_{k}"))
    return left.join(renamed, on).drop(*[f"_{k}" for k in keys])


def keyed(turns: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    return _keyed(turns.select(F.col(conv_id).alias("conv_id"), F.col(turn).alias("turn"), F.col(role).alias("role"), F.col(text).alias("text")))


def maximal(keys: DataFrame) -> DataFrame:
    """conv_id, n_turns, n_copies (conversations that equal it, itself included) of the conversations that stay."""
    lengths = keys.groupBy("conv_id").agg(F.max(F.struct("place", "h1", "h2")).alias("last"))
    whole = lengths.groupBy(F.col("last.place").alias("n_turns"), F.col("last.h1").alias("h1"), F.col("last.h2").alias("h2"))
    whole = whole.agg(F.min("conv_id").alias("conv_id"), F.count(F.lit(1)).alias("n_copies"))
    tagged = _same(keys.select("conv_id", "place", "h1", "h2"), lengths.select("conv_id", F.col("last.place").alias("n_turns")), ["conv_id"])
    prefixes = tagged.where("place < n_turns").groupBy(F.col("place").alias("n_turns"), "h1", "h2").agg(F.count(F.lit(1)).alias("n")).drop("n")
    return whole.join(prefixes, ["n_turns", "h1", "h2"], "left_anti").select("conv_id", "n_turns", "n_copies")


def rendered_turn(role: Column, text: Column) -> Column:
    head, tail = OPEN.split("{role}")
    return F.concat(F.lit(head), F.coalesce(role, F.lit("")), F.lit(tail), F.coalesce(text, F.lit("")), F.lit(CLOSE))


def formatted(turns: DataFrame, **names) -> DataFrame:
    """conv_id, n_turns, n_copies and the rendered text of each maximal conversation."""
    keys = saved(keyed(turns, **names), "chat-keys")
    rows = _same(keys.select("conv_id", "place", rendered_turn(F.col("role"), F.col("text")).alias("part")), maximal(keys), ["conv_id"])
    # the rendered conversation is one value, so its turns meet in one row whatever the plan
    return rows.groupBy("conv_id", "n_turns", "n_copies").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("place", "part"))), lambda t: t["part"]), "").alias("rendered"))
