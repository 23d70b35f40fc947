"""N-gram Jaccard join: a MinHash LSH forest, then exact verification.

The set of a text is that of its five-word shingles (words as they stand between white space; a text of one to four words
has one shingle, all of them). Texts with equal sets form a class, found by a 128-bit key; classes, not copies, go on.

Each class has a signature in each tree: `deepest` minima of six bits, packed into one 64-bit number with the first
minimum on top. So a tree is a trie of 64 branches, its sorted signatures are its leaves, a prefix is a shift, and classes
meet at the longest prefix that they share. The join begins at long prefixes and shortens them level by level. After a
level, exact similarities of the verified pairs tell how likely each was to be met (1 - (1 - s^depth)^trees), and so how many
pairs there must be; it stops once the pairs found are the target share of that, and a pair at the threshold itself would
be met with the least certainty `floor`. Each level verifies only pairs that no longer prefix joined.

Classes that meet at a level, directly or through others, form a group, which is cut into blocks of `block` classes that are
compared two by two. A group of more than `connected` classes falls apart into the nodes of the tries, cut into blocks in
the same way, and a pair of it is verified at the first tree that joins it: there work goes by the pairs that meet, not by the square of
what is connected. Both ways give the same links.
A task gives one row per class and block pair: how many documents it links to, and the least key that verified
links reach in the block pair. Components over these rows are the near-duplicate classes.

Nothing is collected but one histogram of similarities. A hot text, prefix or group is spread: copies are counted before the
shuffle, no bucket is capped and no pair of a group is emitted as a row.

Defined results: a text without words (null, empty, white space) links to nothing and has its own id as class; a class's
id is the least document id in it (null only if all are null); repeated rows are copies of each other; an empty table
gives an empty table; other columns are not used, whatever their names. `kept` decides by row: of a class one row stays, the others go, whether or not
they share its id, and rows that share an id but no class don't touch each other.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import saved, ship
from .components import components
from .wordcache import slices

WORDS, THRESHOLD = 5, 0.8
_U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


#: Bits of a minimum in a signature.
BITS = 6
#: Classes of similarities from the threshold to 1, for the recall that a level reaches.
STEPS = 50


@dataclass(frozen=True)
class Forest:
    """Parameters: trees, the longest prefix, the share of all pairs to be found, and how certainly a pair at the threshold is."""

    trees: int = 24
    deepest: int = 10
    recall: float = 0.999
    floor: float = 0.99
    threshold: float = THRESHOLD
    block: int = 256
    connected: int = 1 << 15
    seed: int = 7

    def __post_init__(self) -> None:
        if not 1 <= self.deepest * BITS <= 63:
            raise ValueError("a signature has to fit into 63 bits")

    def recall_at(self, depth: int, similarity: float | np.ndarray | None = None):
        s = self.threshold if similarity is None else similarity
        return 1 - (1 - s**depth) ** self.trees

    @property
    def first(self) -> int:
        """The longest prefix at which a pair at the threshold is met with the certainty asked for: the first level."""
        return next((d for d in range(self.deepest, 1, -1) if self.recall_at(d) >= self.floor), 1)

    def reached(self, depth: int, histogram: np.ndarray) -> float:
        """The share of all pairs that is found after the level, by the similarities of those found (the lower ends of their classes)."""
        low = self.threshold + (1 - self.threshold) * np.arange(STEPS) / STEPS
        total = float((histogram / self.recall_at(depth, low)).sum())
        return float(histogram.sum()) / total if total else 1.0

    def shift(self, depth: int) -> int:
        return BITS * (self.deepest - depth)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def shingle_sets(texts: list[str]) -> list[np.ndarray]:
    """The sorted 64-bit hashes of each text's distinct shingles."""
    raw = [t.encode() for t in texts]
    data = np.frombuffer(b"\n".join(raw) + b"\n", np.uint8)
    inside = ~_SPACE[data]
    begins = np.flatnonzero(inside & np.concatenate([[True], ~inside[:-1]]))
    if not len(begins):
        return [np.zeros(0, _U) for _ in texts]
    size = np.flatnonzero(~inside & np.concatenate([[False], inside[:-1]])) - begins
    first = np.concatenate([[0], np.cumsum(size)[:-1]])
    place = np.arange(int(size.sum())) - np.repeat(first, size)
    powers = np.ones(int(size.max()), _U)
    powers[1:] = _U(0x9E3779B97F4A7C15)
    powers = np.multiply.accumulate(powers)
    word = mixed(np.add.reduceat((data[inside].astype(_U) + _U(1)) * powers[place], first) + size.astype(_U))
    ends = np.cumsum([len(r) + 1 for r in raw])
    bounds = np.concatenate([[0], np.searchsorted(begins, ends)])
    n = len(word)
    full = np.zeros(max(n - WORDS + 1, 0), _U)
    for k in range(WORDS):
        full = (full + word[k : k + len(full)]) * _U(0xD6E8FEB86659FD93)
    full = mixed(full)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= WORDS:
            out.append(np.unique(full[a : b - WORDS + 1]))
        elif b > a:
            h = _U(b - a)
            with np.errstate(over="ignore"):
                for w in word[a:b]:
                    h = (h + w) * _U(0xC2B2AE3D27D4EB4F)
            out.append(mixed(np.array([h], _U)))
        else:
            out.append(np.zeros(0, _U))
    return out


def set_key(shingles: np.ndarray) -> bytes | None:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest() if len(shingles) else None


def signatures(sets: list[np.ndarray], forest: Forest) -> np.ndarray:
    """One number per set and tree: the set's minima in the tree, BITS bits of each, the first on top. Sets are not empty."""
    rng = np.random.default_rng(forest.seed)
    a = rng.integers(0, 1 << 32, forest.trees * forest.deepest, dtype=np.uint32) | np.uint32(1)
    b = rng.integers(0, 1 << 32, forest.trees * forest.deepest, dtype=np.uint32)
    flat = (np.concatenate(sets) >> _U(32)).astype(np.uint32)
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    out = np.zeros((len(sets), forest.trees), _U)
    for tree in range(forest.trees):
        for k in range(forest.deepest):
            i = tree * forest.deepest + k
            least = np.minimum.reduceat(flat * a[i] + b[i], starts).astype(_U)
            # a minimum is small where a set is large, so its bits are mixed before some are taken
            out[:, tree] = (out[:, tree] << _U(BITS)) | (mixed(least * _U(0x9E3779B97F4A7C15)) >> _U(64 - BITS))
    return out


def _mark(text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))


def signed(docs: DataFrame, forest: Forest, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, key (null without words), mark (a hash of the text) and the signatures in all trees."""

    def run(batches):
        for batch in batches:
            for rows, texts in slices(batch, "text"):
                sets = shingle_sets(texts)
                some = [i for i, s in enumerate(sets) if len(s)]
                found = signatures([sets[i] for i in some], forest).view(np.int64) if some else np.zeros((0, forest.trees), np.int64)
                offsets = np.zeros(len(texts) + 1, np.int32)
                offsets[np.array(some, np.int64) + 1] = forest.trees
                column = pa.ListArray.from_arrays(pa.array(np.cumsum(offsets).astype(np.int32)), pa.array(found.ravel()))
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([set_key(s) for s in sets], pa.binary()), rows.column(2), column], ["doc_id", "key", "mark", "trees"])

    return docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).alias("text"), _mark(text).alias("mark")).mapInArrow(run, "doc_id bigint, key binary, mark bigint, trees array<bigint>")


def _common(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Shared shingles of the pairs (left[i], right[i])."""
    sizes = np.array([len(s) for s in sets])
    everything = np.concatenate(sets)
    values, number, count = np.unique(everything, return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(len(sets)), sizes)
    shared = count[number] > 1
    column = (np.cumsum(count > 1) - 1)[number[shared]]
    owner, width = owner[shared], int((count > 1).sum())
    step = 2048
    if len(left) * 20_000 < (width // step + 1) * (len(sets) ** 2) * 25:  # few pairs: one by one (nanoseconds, roughly)
        return np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(left.tolist(), right.tolist(), strict=True)], np.int64)
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    total = np.zeros((len(sets), len(sets)), np.float32)
    for a in range(0, width, step):
        x, y = np.searchsorted(column, [a, a + step])
        block = np.zeros((len(sets), step), np.float32)
        block[owner[x:y], column[x:y] - a] = 1
        total += block @ block.T
    return total[left, right].astype(np.int64)


def _meeting(trees: np.ndarray, shift: int, only: int = -1) -> np.ndarray:
    """Which pairs share a prefix in some tree; with `only`, in that tree and in none before it."""
    node = trees >> shift
    out = np.zeros((len(trees), len(trees)), bool)
    for t in range(node.shape[1] if only < 0 else only):
        out |= node[:, t][:, None] == node[:, t][None, :]
    return out if only < 0 else (node[:, only][:, None] == node[:, only][None, :]) & ~out


def _linked(keys: list[bytes], weight: np.ndarray, trees: np.ndarray, side: np.ndarray, only: int, texts: list[str], shifts: tuple[int, int | None], threshold: float) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """For each class of a block pair: documents linked to, and the least key that verified links reach; then how many pairs
    have which similarity. side: 1 first block, 2 second, 3 both. shifts: of this level, and of the one before."""
    m = len(keys)
    pairs = _meeting(trees, shifts[0], only)
    if shifts[1] is not None:
        pairs &= ~_meeting(trees, shifts[1])
    cross = ((side[:, None] & 1) > 0) & ((side[None, :] & 2) > 0)
    left, right = np.nonzero(np.triu(pairs & (cross | cross.T), 1))
    links, label, histogram = np.zeros(m, np.int64), np.arange(m), np.zeros(STEPS, np.int64)
    if len(left):
        sets = shingle_sets(texts)
        sizes = np.array([len(s) for s in sets])
        common = _common(sets, left, right)
        union = sizes[left] + sizes[right] - common
        good = common >= threshold * union - 1e-9
        left, right, similarity = left[good], right[good], (common / union)[good]
        place = np.clip((similarity - threshold) / max(1 - threshold, 1e-9) * STEPS, 0, STEPS - 1).astype(np.int64)
        histogram = np.bincount(place, minlength=STEPS)
        np.add.at(links, left, weight[right])
        np.add.at(links, right, weight[left])
        while len(left):  # least labels along links until they stand
            before = label.copy()
            least = np.minimum(label[left], label[right])
            np.minimum.at(label, left, least)
            np.minimum.at(label, right, least)
            label = label[label]
            if (label == before).all():
                break
    return links, [keys[i] for i in label], histogram


def _compared(rows: DataFrame, forest: Forest, shifts: tuple[int, int | None]) -> DataFrame:
    """key, least, links of each class and block pair that has links, and the similarities of a block pair's links at one of
    its rows. rows are sorted within partitions by group, i, j and key."""

    def run(batches):
        held: list[dict] = []
        group = None

        def flush():
            links, least, histogram = _linked(
                [r["key"] for r in held],
                np.array([r["n"] for r in held]),
                np.array([r["trees"] for r in held], np.int64),
                np.array([r["side"] for r in held]),
                held[0]["tree"],
                [r["text"] or "" for r in held],
                shifts,
                forest.threshold,
            )
            at = np.flatnonzero(links).tolist()
            if not at:
                return None
            seen = [histogram.tolist(), *([None] * (len(at) - 1))]
            return pa.RecordBatch.from_arrays([pa.array([held[i]["key"] for i in at], pa.binary()), pa.array([least[i] for i in at], pa.binary()), pa.array(links[at]), pa.array(seen, pa.list_(pa.int64()))], ["key", "least", "links", "similar"])

        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                for row in batch.slice(a, 256).to_pylist():
                    now = (row["place"], row["tree"], row["i"], row["j"])
                    if now != group:
                        if held and (out := flush()) is not None:
                            yield out
                        held, group = [], now
                    held.append(row)
        if held and (out := flush()) is not None:
            yield out

    return rows.mapInArrow(run, "key binary, least binary, links bigint, similar array<bigint>")


def _blocks(grouped: DataFrame, block: int) -> DataFrame:
    """key, place, tree, i, j and side of each class in each block pair of its group (place, tree)."""
    by = ["place", "tree"]
    sizes = grouped.groupBy(*by).agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    placed = grouped.join(sizes, by).withColumn("own", F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    side = F.when(F.col("own") == F.col("other"), 3).when(F.col("own") < F.col("other"), 1).otherwise(2)
    return placed.select("key", *by, F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), side.alias("side"))


def _level(docs: DataFrame, classes: DataFrame, forest: Forest, depth: int, before: int | None) -> DataFrame | None:
    """What `_compared` finds of pairs that share a prefix of this depth and none of the level before; None if nothing meets."""
    shift = forest.shift(depth)
    nodes = classes.select("key", F.posexplode("trees").alias("tree", "signature"))
    nodes = nodes.withColumn("node", F.shiftright("signature", shift))
    longer = F.shiftright("signature", forest.shift(before)) if before else F.col("key")
    # a node below which all share a longer prefix brings no new pair
    shared = nodes.groupBy("tree", "node").agg(F.min("key").alias("leader"), F.min(longer).alias("low"), F.max(longer).alias("high")).where("low <> high").select("tree", "node", "leader")
    met = saved(nodes.join(shared, ["tree", "node"]).select("key", "tree", "node", "leader"), "near-met")
    groups = components(met.select(F.col("key").alias("a"), F.col("leader").alias("b")))
    groups = groups.select(F.col("node").alias("key"), F.col("label").alias("comp"))
    sizes = groups.groupBy("comp").agg(F.count(F.lit(1)).alias("m"))
    groups = saved(groups.join(sizes, "comp").withColumn("whole", F.col("m") <= forest.connected), "near-groups")
    small = groups.where("whole").select("key", F.xxhash64("comp").alias("place"), F.lit(-1).alias("tree"))
    large = met.join(groups.where("NOT whole").select("key"), "key").select("key", F.xxhash64("tree", "node").alias("place"), "tree")
    placed = _blocks(small.unionByName(large), forest.block)
    placed = placed.join(classes.select("key", "rep_id", "rep_mark", "n", "trees"), "key")
    source = _source(docs).join(placed.select("rep_id", "rep_mark").distinct(), F.col("doc_id").eqNullSafe(F.col("rep_id")) & (F.col("mark") == F.col("rep_mark")), "left_semi")
    one = source.groupBy("doc_id", "mark").agg(F.first("text").alias("text"))  # rows with the same id and text are one
    texts = placed.join(one, (F.col("rep_mark") == F.col("mark")) & F.col("rep_id").eqNullSafe(F.col("doc_id"))).select("place", "tree", "i", "j", "side", "key", "n", "trees", "text")
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    by = ["place", "tree", "i", "j"]
    return saved(_compared(texts.repartition(parts, *by).sortWithinPartitions(*by, "key"), forest, (shift, forest.shift(before) if before else None)), "near-checked")


def _source(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "mark", "text")


def _labelled(docs: DataFrame, forest: Forest, doc_id: str, text: str) -> tuple[DataFrame, DataFrame]:
    """The signed rows, and for each key its label (equal for near duplicates), the least row with it (rep_id, rep_mark; null ids last), n copies and links."""
    ship(docs.sparkSession)
    rows = saved(signed(docs, forest, doc_id, text), "near-signed")
    classes = saved(rows.where("key is not null").groupBy("key").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")).alias("rep"), F.count(F.lit(1)).alias("n"), F.first("trees").alias("trees")).select("key", F.col("rep.doc_id").alias("rep_id"), F.col("rep.mark").alias("rep_mark"), "n", "trees"), "near-classes")
    source = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).alias("text"), _mark(text).alias("mark"))
    checked, before, histogram = None, None, np.zeros(STEPS, np.int64)
    for depth in range(forest.first, 0, -1):
        found = _level(source, classes, forest, depth, before)
        checked, before = found if checked is None else checked.unionByName(found), depth
        seen = found.where("similar is not null").select(F.posexplode("similar").alias("step", "n")).groupBy("step").agg(F.sum("n").alias("n")).collect()  # STEPS rows
        for r in seen:
            histogram[r["step"]] += r["n"]
        if forest.reached(depth, histogram) >= forest.recall:
            break
    found = components(checked.select(F.col("key").alias("a"), F.col("least").alias("b"))).withColumnRenamed("node", "key")
    links = checked.groupBy("key").agg(F.sum("links").alias("links"))
    facts = classes.select("key", "rep_id", "rep_mark", "n").join(links, "key", "left").join(found, "key", "left").withColumn("label", F.coalesce("label", "key"))
    return rows, saved(facts, "near-facts")


def joined(docs: DataFrame, forest: Forest = Forest(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: doc_id, class_id and n_links (documents with a similarity of the threshold or more to it)."""
    rows, facts = _labelled(docs, forest, doc_id, text)
    ids = facts.groupBy("label").agg(F.min("rep_id").alias("class_id"))
    facts = facts.join(ids, "label").select("key", "class_id", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))
    out = rows.select("doc_id", "key").join(facts, "key", "left")
    return out.select("doc_id", F.when(F.col("key").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0).cast("bigint")).alias("n_links"))


def kept(docs: DataFrame, forest: Forest = Forest(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with one row of each class, one with the least id (null only if all are null); texts without words stay.

    Of rows with the same id and text one stays, any of them.
    """
    rows, facts = _labelled(docs, forest, doc_id, text)
    least = facts.groupBy("label").agg(F.min(F.struct(F.col("rep_id").isNull().alias("no_id"), "rep_id", "key", "rep_mark")).alias("rep")).select("rep.*")
    own = F.col(doc_id).cast("bigint")
    place = [F.coalesce(own, F.lit(0).cast("bigint")).alias("id"), own.isNull().alias("no_id"), _mark(text).alias("mark")]
    worded = F.coalesce(F.col(text), F.lit("")).rlike(r"[^\x20\x09-\x0D]")
    whole = F.struct(*[docs[c].alias(f"c{i}") for i, c in enumerate(docs.columns)]).alias("row")
    placed = docs.where(worded).select(whole, *place)
    names = ["id", "no_id", "mark"]
    copies = rows.where("key is not null").select(F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id"), "mark").groupBy(*names).agg(F.count(F.lit(1)).alias("copies")).where("copies > 1")
    least = least.select(F.coalesce("rep_id", F.lit(0)).alias("id"), "no_id", F.col("rep_mark").alias("mark"))
    least = saved(least.join(copies, names, "left").withColumn("copies", F.coalesce("copies", F.lit(1).cast("bigint"))), "near-least")
    # a row on its own stays by its place alone; of equal rows one is taken, before they meet
    single = placed.join(least.where("copies = 1").drop("copies"), names, "left_semi").select("row")
    equal = placed.join(least.where("copies > 1").drop("copies"), names, "left_semi").groupBy(*names).agg(F.first("row").alias("row")).select("row")
    return single.unionByName(equal).unionByName(docs.where(~worded).select(whole)).select("row.*").toDF(*docs.columns)
