"""Mix sources to target weights.

The words of a source, document after document, form a stream that is packed into blocks of fixed length. The output is
made of shards of `shard_slots` slots, a block each. How many slots of a shard every source fills is drawn from a
multinomial over what the sources still owe their targets, so the draws decide what is taken, and a source that came short in one
shard is drawn more often in those after it; the last shards get smaller, down to a few slots, so that totals end near
the targets, off by what the last draw adds. Slot j of a source maps to a block through a keyed permutation of the block numbers, a new one for each pass
over the source; slots and blocks are joined by number. No source is passed over more often than `cap` times.

Draws are made on the driver for up to `draws` groups of shards (and a few small ones at the end); each group's task deals
its counts to its shards by multivariate hypergeometric draws, which is what a multinomial is within a given sum. So the
driver's work is bounded however many shards there are.

The stream's places are prefix sums in two steps (per salted bucket of a source, then within the bucket), so that a
source with a third of all rows is spread over many tasks. What the driver sees is one row per source, and group counts.

Defined results: a null or empty text has no words and nothing is taken from it; a null source is a source of its own and the
last; null or repeated document ids and repeated rows are rows of their own (equal ones are told apart by a number); an empty table gives an empty table; a source
without words has the target 0. Long texts span many blocks. Only the named columns are used.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import saved, ship

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS, CAP, BLOCK_WORDS, SHARD_SLOTS, DRAWS, LAST, SEED = (5, 2, 1), 3, 64, 8192, 4096, 32, 20240901
BUCKET_ROWS = 4096


@dataclass(frozen=True)
class Plan:
    """What a source has and owes, in words and in blocks (the stream's last block may be short)."""

    source: str | None
    size: int
    target: float
    blocks: int

    @property
    def owed(self) -> float:
        """Slots that bring the target: a slot brings size / blocks words on average."""
        return self.target * self.blocks / self.size if self.size else 0.0


def weights_of(sources: list[str | None], weights: tuple[int, ...] = WEIGHTS) -> dict[str | None, int]:
    """Weights in turn, by code point, null last."""
    ordered = sorted(sources, key=lambda s: (s is None, s or ""))
    return {s: weights[i % len(weights)] for i, s in enumerate(ordered)}


def targets_of(sizes: dict[str | None, int], weights: dict[str | None, int], cap: int = CAP) -> dict[str | None, float]:
    """Shares of the whole by weight; what a source can't give (above cap times its size) is shared by the others."""
    left, rest, out = Fraction(sum(sizes.values())), sum(weights.values()), {}
    for s in sorted(sizes, key=lambda s: Fraction(cap * sizes[s], weights[s])):
        most = cap * sizes[s]
        share = left * weights[s] / rest
        if share <= most:
            break
        out[s] = Fraction(most)
        left, rest = left - most, rest - weights[s]
    return {s: float(out[s] if s in out else left * weights[s] / rest) for s in sizes}


def _keys(source: str | None, turn: int, seed: int) -> list[int]:
    raw = hashlib.sha256(f"{seed}/{turn}/{'-' if source is None else '+' + source}".encode()).digest()
    return [int.from_bytes(raw[i : i + 8], "little") | 1 for i in range(0, 32, 8)]


def _scrambled(right: np.ndarray, key: int, mask: np.uint64) -> np.ndarray:
    f = right * np.uint64(0x9E3779B97F4A7C15) + np.uint64(key)
    f ^= f >> np.uint64(29)
    f *= np.uint64(0xBF58476D1CE4E5B9)
    return (f ^ (f >> np.uint64(32))) & mask


def permuted(j: np.ndarray, n: int, keys: list[int], back: bool = False) -> np.ndarray:
    """Images of numbers below n under a keyed permutation, or their originals: a Feistel network on the next even power of two, walked until the image is below n."""
    half = np.uint64(max(1, (max(n - 1, 1).bit_length() + 1) // 2))
    mask = (np.uint64(1) << half) - np.uint64(1)

    def once(x: np.ndarray) -> np.ndarray:
        left, right = x >> half, x & mask
        for k in reversed(keys) if back else keys:
            left, right = (right ^ _scrambled(left, k, mask), left) if back else (right, left ^ _scrambled(right, k, mask))
        return (left << half) | right

    out = once(np.asarray(j, np.uint64))
    while (far := out >= np.uint64(n)).any():
        out[far] = once(out[far])
    return out.astype(np.int64)


def group_sizes(total: int, shard_slots: int, draws: int) -> list[int]:
    """Slots of the groups of shards: whole shards, at most about `draws` groups, and a tail of halves down to LAST slots, whose
    draw is as far as totals stray from the targets."""
    group = shard_slots * max(1, -(-total // (shard_slots * draws)))
    whole, rest = divmod(total, group)
    sizes, tail = [group] * max(0, whole - 1), rest + (group if whole else 0)
    while tail > 0:
        sizes.append(tail if tail <= LAST else tail // 2)
        tail -= sizes[-1]
    return sizes


def drawn_counts(owed: list[float], most: list[int], sizes: list[int], seed: int) -> np.ndarray:
    """Slots of each source in each group: multinomial draws over what is still owed; none gets more than `most` in all."""
    rng, owed_now, room = np.random.default_rng(seed), np.array(owed, np.float64), np.array(most, np.int64)
    rows = []
    for size in sizes:
        row, left = np.zeros(len(room), np.int64), min(size, int(room.sum()))
        while left > 0:
            weight = np.where(room > row, np.maximum(owed_now - row, 0.0), 0.0)
            if not weight.sum():  # all have what they are owed: who has room
                weight = (room - row).astype(np.float64)
            row += np.minimum(rng.multinomial(left, weight / weight.sum()), room - row)
            left = min(size, int(room.sum())) - int(row.sum())
        rows.append(row)
        owed_now, room = owed_now - row, room - row
    return np.array(rows, np.int64).reshape(len(sizes), len(room))


def shards_of(counts: np.ndarray, shard_slots: int, seed: list[int]) -> np.ndarray:
    """A group's counts dealt to its shards: without replacement, so they add up."""
    rng, left, rows = np.random.default_rng(seed), np.array(counts, np.int64), []
    while (total := int(left.sum())) > shard_slots:
        # draws by marginals have no bound on the number of slots
        row, rest, room = np.zeros_like(left), total, shard_slots
        for i, n in enumerate(left.tolist()):
            if room and n:
                row[i] = room if rest == n else rng.hypergeometric(n, rest - n, room)
                room -= int(row[i])
            rest -= n
        rows.append(row)
        left = left - row
    return np.array([*rows, left])


def laid_out(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", block: int = BLOCK_WORDS, cap: int = CAP, weights: tuple[int, ...] = WEIGHTS, seed: int = SEED) -> tuple[DataFrame, list[Plan]]:
    """doc_id, source, text_key, copy, size and begin (the place of the document's first word in its source's stream), and the plans."""
    whole = F.coalesce(F.col(text), F.lit(""))
    rows = saved(
        docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), F.xxhash64(whole).alias("text_key"), F.regexp_count(whole, F.lit(WORD)).cast("bigint").alias("size")),
        "mix-sizes",
    )
    totals = rows.groupBy("source").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")).collect()
    sizes = {r["source"]: r["size"] for r in totals}
    targets = targets_of(sizes, weights_of(list(sizes), weights), cap) if sizes else {}
    plans = [Plan(s, sizes[s], targets[s], -(-sizes[s] // block)) for s in sorted(sizes, key=lambda s: (s is None, s or ""))]
    buckets = max(64, -(-sum(r["n"] for r in totals) // BUCKET_ROWS))
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "text_key"), F.lit(buckets)))
    inner = Window.partitionBy("source", "bucket").orderBy("doc_id", "text_key", "size").rowsBetween(Window.unboundedPreceding, 0)
    alike = Window.partitionBy("source", "bucket", "doc_id", "text_key", "size").orderBy("begin")
    bases = rows.groupBy("source", "bucket").agg(F.sum("size").alias("total"))
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = bases.select("source", "bucket", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"))
    out = rows.withColumn("begin", F.sum("size").over(inner) - F.col("size")).alias("r").join(bases.alias("b"), F.col("r.source").eqNullSafe(F.col("b.source")) & (F.col("r.bucket") == F.col("b.bucket")))
    out = out.select("r.doc_id", "r.source", "r.bucket", "r.text_key", "r.size", (F.col("begin") + F.col("base")).alias("begin"))
    return out.withColumn("copy", F.row_number().over(alike)).drop("bucket"), plans


def _slots(docs: DataFrame, plans: list[Plan], seed: int, shard_slots: int, draws: int, cap: int) -> DataFrame:
    """shard (group and number in it), source, slot, pass, block: the slots of all shards and the blocks that they take."""
    spark, schema = docs.sparkSession, "group bigint, shard bigint, source string, slot bigint, pass int, block bigint"
    owed = [p.owed for p in plans]
    sizes = group_sizes(round(sum(owed)), shard_slots, draws)
    if not sizes:
        return spark.createDataFrame([], schema)
    counts = drawn_counts(owed, [cap * p.blocks for p in plans], sizes, seed)
    first = np.vstack([np.zeros((1, len(plans)), np.int64), np.cumsum(counts, axis=0)])
    facts = [(p.source, p.blocks) for p in plans]

    def run(batches):
        for batch in batches:
            for group, begins, some in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at = list(begins)
                for shard, row in enumerate(shards_of(np.array(some), shard_slots, [seed, group])):
                    for i, n in enumerate(row.tolist()):
                        if not n:
                            continue
                        source, blocks = facts[i]
                        slot = np.arange(at[i], at[i] + n)
                        at[i] += n
                        turn, block = slot // blocks, np.empty(n, np.int64)
                        for t in np.unique(turn):
                            own = turn == t
                            block[own] = permuted(slot[own] % blocks, blocks, _keys(source, int(t), seed))
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(np.full(n, group)), pa.array(np.full(n, shard)), pa.array([source] * n, pa.string()), pa.array(slot), pa.array(turn.astype(np.int32)), pa.array(block)],
                            ["group", "shard", "source", "slot", "pass", "block"],
                        )

    rows = [(k, first[k].tolist(), counts[k].tolist()) for k in range(len(sizes))]
    table = spark.createDataFrame(rows, "group bigint, begins array<bigint>, counts array<bigint>")
    return table.repartition(max(1, min(len(rows), int(spark.conf.get("spark.sql.shuffle.partitions"))))).mapInArrow(run, schema)


def segments(layout: DataFrame, plans: list[Plan], block: int = BLOCK_WORDS, seed: int = SEED, shard_slots: int = SHARD_SLOTS, draws: int = DRAWS, cap: int = CAP) -> DataFrame:
    """The mix: one row for each piece of a document in a slot of a shard.

    group and shard, place (the slot's order in the shard), pass, slot, then the document's columns of `laid_out`, and first_word and n_words.
    """
    pieces = layout.where("size > 0").withColumn("block", F.explode(F.sequence(F.floor(F.col("begin") / block), F.floor((F.col("begin") + F.col("size") - 1) / block))))
    edge = F.col("block") * block
    pieces = pieces.withColumns({"from": F.greatest(F.col("begin"), edge), "to": F.least(F.col("begin") + F.col("size"), edge + block)})
    # the planner sees the few rows that slots are made of, not the slots: a broadcast would grow with the words
    slots = _slots(layout, plans, seed, shard_slots, draws, cap).hint("merge")
    joined = pieces.alias("p").join(slots.alias("s"), F.col("p.source").eqNullSafe(F.col("s.source")) & (F.col("p.block") == F.col("s.block")))
    return joined.select(
        "group",
        "shard",
        F.xxhash64(F.lit(seed), F.col("s.source"), F.col("slot")).alias("place"),
        "pass",
        "slot",
        "doc_id",
        F.col("p.source").alias("source"),
        "text_key",
        "copy",
        "size",
        "begin",
        (F.col("from") - F.col("begin")).alias("first_word"),
        (F.col("to") - F.col("from")).alias("n_words"),
    )


_MIX = ("block", "seed", "shard_slots", "draws", "cap")


def _mix(docs: DataFrame, options: dict, **columns) -> tuple[DataFrame, DataFrame, list[Plan]]:
    """The layout, the mix and the plans."""
    ship(docs.sparkSession)
    layout, plans = laid_out(docs, **columns, **{k: v for k, v in options.items() if k not in ("shard_slots", "draws")})
    layout = saved(layout, "mix-layout")
    return layout, segments(layout, plans, **{k: v for k, v in options.items() if k in _MIX}), plans


def taken(docs: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target and taken."""
    layout, mix, plans = _mix(docs, options)
    sums = mix.groupBy("source", "begin").agg(F.sum("n_words").alias("taken"))
    facts = docs.sparkSession.createDataFrame([(p.source, p.size, p.target) for p in plans], "source string, source_size bigint, target double")
    out = layout.alias("l").join(sums.alias("t"), F.col("l.source").eqNullSafe(F.col("t.source")) & (F.col("l.begin") == F.col("t.begin")) & (F.col("l.size") > 0), "left")
    out = out.select("l.doc_id", F.col("l.source").alias("source"), "l.size", F.coalesce("t.taken", F.lit(0)).cast("bigint").alias("taken")).alias("o")
    # one row for each source: a small table by the plan's own bound
    return out.join(facts.alias("f"), F.col("o.source").eqNullSafe(F.col("f.source"))).select("doc_id", "o.source", "size", "source_size", "target", "taken")


_WORDS = re.compile(WORD)


def _cut(text: str, pieces: list[tuple[int, int]], size: int) -> str:
    """The words of the pieces; whole texts stay as they are."""
    merged: list[list[int]] = []
    for a, n in sorted(pieces):
        if merged and merged[-1][1] == a:
            merged[-1][1] = a + n
        else:
            merged.append([a, a + n])
    if merged == [[0, size]]:
        return text
    at = [m.span() for m in _WORDS.finditer(text)]
    return "\n".join(text[at[a][0] : at[b - 1][1]] for a, b in merged)


def _with_rows(docs: DataFrame, parts: DataFrame, doc_id: str, text: str, source: str, *more: str) -> DataFrame:
    """The rows of docs (a struct `row`) with the columns `more` of parts, by id, source, text and the number among equal ones."""
    rows = docs.select(F.struct(*[docs[c].alias(f"c{i}") for i, c in enumerate(docs.columns)]).alias("row"), F.col(doc_id).alias("k_id"), F.col(source).alias("k_source"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("k_text"))
    rows = rows.withColumn("k_copy", F.row_number().over(Window.partitionBy("k_id", "k_source", "k_text").orderBy(F.lit(0))))
    on = F.col("k_id").eqNullSafe(F.col("doc_id")) & F.col("k_source").eqNullSafe(F.col("source")) & (F.col("k_text") == F.col("text_key")) & (F.col("k_copy") == F.col("copy"))
    return rows.join(parts, on).select("row", *more)


def packed(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", **options) -> DataFrame:
    """The output shards themselves: group, shard, place, source, n_words and text of each slot, the words of a block joined by spaces."""
    _, mix, _ = _mix(docs, options, doc_id=doc_id, text=text, source=source)
    names, at = docs.columns, docs.columns.index(text)
    keys = ["doc_id", "source", "text_key", "copy"]
    parts = mix.groupBy(*keys).agg(F.collect_list(F.struct("group", "shard", "place", "slot", "begin", "first_word", "n_words")).alias("parts"))  # a document's own slots
    joined = _with_rows(docs, parts, doc_id, text, source, "parts").select(F.col("row")[f"c{at}"].alias("text"), F.col("row")[f"c{names.index(source)}"].alias("source"), "parts")
    words = F.array_remove(F.split(F.coalesce(F.col("text"), F.lit("")), r"[\x20\x09-\x0D]+"), "")
    pieces = joined.withColumn("words", words).select("source", "words", F.inline("parts"))
    pieces = pieces.select("group", "shard", "place", "source", "slot", (F.col("begin") + F.col("first_word")).alias("at"), "n_words", F.array_join(F.slice("words", F.col("first_word").cast("int") + 1, F.col("n_words").cast("int")), " ").alias("piece"))
    slots = pieces.groupBy("group", "shard", "place", "source", "slot").agg(F.sum("n_words").alias("n_words"), F.sort_array(F.collect_list(F.struct("at", "piece"))).alias("pieces"))  # a block's own pieces
    return slots.select("group", "shard", "place", "source", "n_words", F.array_join(F.transform("pieces", lambda p: p["piece"]), " ").alias("text"))


def write_shards(docs: DataFrame, path: str, **options) -> None:
    """The output shards as folders by group; a shard's slots stand together, in their order."""
    out = packed(docs, **options)
    out.repartition("group", "shard").sortWithinPartitions("group", "shard", "place").write.mode("overwrite").partitionBy("group").parquet(path)


def mixed_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", n_chars: str = "n_chars", **options) -> DataFrame:
    """The mix as documents: a row for each pass that takes words of a document, with the words that it takes.

    A document that is taken more than once (its source is short of its target) has a row for each time; one of which
    nothing is taken has none. Whole documents keep their text; of others the taken words stay, a new line between parts.
    Text lengths in n_chars follow. Rows with equal ids are mixed one by one. The columns are those of docs.
    """
    _, mix, _ = _mix(docs, options, doc_id=doc_id, text=text, source=source)
    parts = mix.groupBy("doc_id", "source", "text_key", "copy", "pass", "size").agg(F.collect_list(F.struct("first_word", "n_words")).alias("parts"))
    names = docs.columns
    joined = _with_rows(docs, parts, doc_id, text, source, "parts", "size")
    flat = joined.select(*[F.col("row")[f"c{i}"].alias(f"c{i}") for i in range(len(names))], "parts", "size")
    at_text, at_chars = names.index(text), names.index(n_chars) if n_chars in names else None

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                rows = batch.slice(a, 512)
                parts, sizes = rows.column(len(names)).to_pylist(), rows.column(len(names) + 1).to_pylist()
                texts = [_cut(t or "", [(p["first_word"], p["n_words"]) for p in ps], n) for t, ps, n in zip(rows.column(at_text).to_pylist(), parts, sizes, strict=True)]
                columns = [rows.column(i) for i in range(len(names))]
                columns[at_text] = pa.array(texts, pa.string())
                if at_chars is not None:
                    columns[at_chars] = pa.array([len(t) for t in texts], columns[at_chars].type)
                yield pa.RecordBatch.from_arrays(columns, [f"c{i}" for i in range(len(names))])

    schema = T.StructType([T.StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema)])
    return flat.mapInArrow(run, schema).toDF(*names)
