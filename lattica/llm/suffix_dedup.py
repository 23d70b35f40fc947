"""Suffix-array deduplication of a corpus: bytes of strings of `length` bytes that begin at two places or more.

1. Each window of `length` bytes has a key, the least hash of the short grams in it. Equal windows have equal keys, so a
   window can only be repeated among those with its key. Runs of windows with one key are segments (of a document).
2. Segments are counted by key. A segment whose bytes occur twice or more is repeated as a whole. Where a key has segments
   of different bytes, or a gram comes back within a document, one copy of each distinct segment is sorted.
   A key with many distinct segments (a passage that stands in many surroundings) is divided: its windows take the next least
   grams into their keys, as many as the count asks for, and equal windows still agree in them.
3. Shards of segments, by key, go through the external induced sort, which gives the windows that share their whole length
   with a neighbour in suffix order. All windows of a key are in one shard, so nothing crosses shards.
4. Each document gets the ranges of its repeated windows; their bytes are removed.

Defined results: a null or empty text has no bytes; a document shorter than `length` loses nothing; windows never cross
documents; repeated rows are copies of each other, and null ids are rows like others; an empty table gives an empty table;
other columns pass through `removed` and are not used by `digests`.
Keys are hashes: two different grams of one hash only bring more segments together. Segments count as equal if 128 bits
agree (64 of the key and 64 of the bytes).
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import local_path, saved, shared_root, ship
from .induced_sort import InducedSorter

LENGTH, GRAM = 200, 32
#: Distinct segments that a key may have before its windows are divided by more grams, and by how much each gram is reckoned to divide.
HOT_SEGMENTS, DIVIDED_BY = 64, 8
#: A segment is common if more than one in so many of all segments equal it. Fewer than that many different ones can be, so they are broadcast.
COMMON = 4096
_U = np.uint64
_SLICE = 1 << 18


def _sliding(values: np.ndarray, width: int, pick) -> np.ndarray:
    """pick over values[i : i + width] for all i, by doubling."""
    have = 1
    while 2 * have <= width:
        values = pick(values[:-have], values[have:])
        have *= 2
    return pick(values[: len(values) - (width - have)], values[width - have :]) if have < width else values


def _gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """Mixed hashes of data[i : i + gram]; gram is a power of two."""
    h, power, have = data.astype(_U) + _U(1), _U(0x9E3779B97F4A7C15), 1
    with np.errstate(over="ignore"):
        while have < gram:
            h = h[:-have] * power + h[have:]
            power = power * power
            have *= 2
    h ^= h >> _U(30)
    h *= _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h *= _U(0x94D049BB133111EB)
    h ^= h >> _U(31)
    return h


def segments_of(texts: list[bytes], length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """doc (place in texts), begin, windows, key, digest and again (the key's gram comes back in the document) of all segments."""
    import xxhash

    sizes = np.array([len(t) for t in texts], np.int64)
    data = b"".join(texts)
    empty = np.zeros(0, np.int64)
    if not len(sizes) or sizes.max(initial=0) < length:
        return empty, empty, empty, empty, empty, np.zeros(0, bool)
    starts = np.cumsum(sizes) - sizes
    grams = _gram_hashes(np.frombuffer(data, np.uint8), gram)
    inner = length - gram + 1
    keys = _sliding(grams, inner, np.minimum)
    doc = np.repeat(np.arange(len(texts)), np.maximum(sizes - length + 1, 0))
    place = np.arange(len(doc)) - np.repeat(np.cumsum(np.maximum(sizes - length + 1, 0)) - np.maximum(sizes - length + 1, 0), np.maximum(sizes - length + 1, 0))
    at = starts[doc] + place
    key = keys[at]
    # grams that are the least of one of their document's windows, and those that are so twice
    window = np.zeros(len(grams), _U)
    window[at] = key
    padded = np.concatenate([np.zeros(inner - 1, _U), window])
    least = np.flatnonzero(_sliding(padded, inner, np.maximum) == grams)
    owner = np.searchsorted(starts, least, side="right") - 1
    pair = np.sort(grams[least] ^ (owner.astype(_U) * _U(0xD6E8FEB86659FD93)))
    twice = np.unique(pair[1:][pair[1:] == pair[:-1]])
    heads = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])]))
    windows = np.diff(np.append(heads, len(doc)))
    doc, begin, key, at = doc[heads], place[heads], key[heads], at[heads]
    again = np.isin(key ^ (doc.astype(_U) * _U(0xD6E8FEB86659FD93)), twice)
    view = memoryview(data)
    digest = np.array([xxhash.xxh3_64_intdigest(view[a:b]) for a, b in zip(at.tolist(), (at + windows + length - 1).tolist(), strict=True)], _U)
    return doc, begin, windows, key.view(np.int64), digest.view(np.int64), again


def divided(raw: bytes, key: int, levels: int, length: int = LENGTH, gram: int = GRAM) -> list[tuple[int, int, int]]:
    """begin, windows and key of the runs of a segment's windows that agree in the next `levels` least grams too."""
    grams, inner, none = _gram_hashes(np.frombuffer(raw, np.uint8), gram), length - gram + 1, _U(2**64 - 1)
    runs = [(0, len(raw) - length + 1, _U(key & (2**64 - 1)), [_U(key & (2**64 - 1))])]
    for _ in range(levels):
        out = []
        for begin, n, named, used in runs:
            some = grams[begin : begin + n + inner - 1]
            least = _sliding(np.where(np.isin(some, used), none, some), inner, np.minimum)
            cuts = np.concatenate([[0], np.flatnonzero(least[1:] != least[:-1]) + 1, [n]]).tolist()
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                with np.errstate(over="ignore"):
                    out.append((begin + a, b - a, (named ^ least[a]) * _U(0x9E3779B97F4A7C15) + _U(1), [*used, least[a]]))
        runs = out
    return [(begin, n, int(named.astype(np.int64))) for begin, n, named, _ in runs]


def _slices(batch: pa.RecordBatch, name: str) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    texts = [(t or "").encode() for t in batch.column(batch.schema.get_field_index(name)).to_pylist()]
    start = 0
    while start < len(texts):
        end, size = start, 0
        while end < len(texts) and (end == start or size + len(texts[end]) <= _SLICE):
            size += len(texts[end])
            end += 1
        yield batch.slice(start, end - start), texts[start:end]
        start = end


def _segments(rows: DataFrame, length: int, gram: int) -> DataFrame:
    """rows: id, mark (a hash of the text) and text."""

    def run(batches):
        for batch in batches:
            for some, texts in _slices(batch, "text"):
                doc, begin, windows, key, digest, again = segments_of(texts, length, gram)
                ids, marks = some.column(0).take(pa.array(doc)), some.column(1).take(pa.array(doc))
                yield pa.RecordBatch.from_arrays([ids, marks, pa.array(begin), pa.array(windows.astype(np.int32)), pa.array(key), pa.array(digest), pa.array(again)], ["id", "mark", "begin", "windows", "key", "digest", "again"])

    return rows.mapInArrow(run, "id bigint, mark bigint, begin bigint, windows int, key bigint, digest bigint, again boolean")


def _with_bytes(wanted: DataFrame, rows: DataFrame, length: int, gram: int) -> DataFrame:
    """key, id, mark, begin, windows and bytes of the wanted segments, those with `levels` divided."""
    lists = wanted.groupBy("id", "mark").agg(F.collect_list(F.struct("begin", "windows", "key", "levels")).alias("parts"))  # a document's own segments
    joined = _on_document(rows, lists).select("id", "mark", "text", "parts")

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 64):
                out = []
                for row in batch.slice(a, 64).to_pylist():
                    raw = (row["text"] or "").encode()
                    for p in row["parts"]:
                        own = raw[p["begin"] : p["begin"] + p["windows"] + length - 1]
                        for x, n, key in divided(own, p["key"], p["levels"], length, gram) if p["levels"] else [(0, p["windows"], p["key"])]:
                            out.append({"key": key, "id": row["id"], "mark": row["mark"], "begin": p["begin"] + x, "windows": n, "bytes": own[x : x + n + length - 1]})
                yield pa.RecordBatch.from_pylist(out, pa.schema([("key", pa.int64()), ("id", pa.int64()), ("mark", pa.int64()), ("begin", pa.int64()), ("windows", pa.int32()), ("bytes", pa.binary())]))

    return joined.mapInArrow(run, "key bigint, id bigint, mark bigint, begin bigint, windows int, bytes binary")


def _on_document(rows: DataFrame, lists: DataFrame, how: str = "inner") -> DataFrame:
    """Join on mark (a hash of the text, so never null) and id, null ids being equal."""
    other = lists.select(F.col("id").alias("_id"), F.col("mark").alias("_mark"), "parts")
    return rows.join(other, (F.col("mark") == F.col("_mark")) & F.col("id").eqNullSafe(F.col("_id")), how).drop("_id", "_mark")


def _sorted_ranges(pieces: DataFrame, length: int, spool: str | None) -> DataFrame:
    """id, mark, begin and end of the windows that the sort finds repeated; each partition is a shard."""

    def run(batches):
        fact = np.dtype([("id", np.int64), ("no_id", np.bool_), ("mark", np.int64), ("begin", np.int64), ("windows", np.int64)])

        def spooled(facts):
            for batch in batches:
                for a in range(0, batch.num_rows, 1024):
                    rows = batch.slice(a, 1024)
                    columns = [rows.column(rows.schema.get_field_index(n)).to_pylist() for n in ("id", "mark", "begin", "windows")]
                    facts.write(np.array([(i or 0, i is None, m, b, w) for i, m, b, w in zip(*columns, strict=True)], fact).tobytes())
                    yield from rows.column(rows.schema.get_field_index("bytes")).to_pylist()

        with InducedSorter(spool, length) as sorter:
            path = os.path.join(sorter.folder, "facts")
            with open(path, "wb") as facts:
                loaded = sorter.load(spooled(facts))
            if not loaded:
                return
            marks = sorter.repeated()
            at, out = 1, []
            with open(path, "rb") as facts:
                while some := facts.read(4096 * fact.itemsize):
                    for i, null, m, b, w in np.frombuffer(some, fact).tolist():
                        own = np.flatnonzero(np.diff(np.concatenate([[False], marks[at : at + w], [False]]).astype(np.int8)))
                        out += [(None if null else i, m, b + x, b + y) for x, y in own.reshape(-1, 2).tolist()]
                        at += w + length
                        if len(out) > 10_000:
                            yield _ranges(out)
                            out = []
            if out:
                yield _ranges(out)

    return pieces.mapInArrow(run, "id bigint, mark bigint, begin bigint, end bigint")


def _ranges(rows: list[tuple]) -> pa.RecordBatch:
    names = ["id", "mark", "begin", "end"]
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in range(4)], names)


def spool_folder(spark: SparkSession) -> str | None:
    """Where the sort's queues lie: the shared folder, if it is a file system."""
    path = local_path(shared_root(spark))
    return f"{path}/induced-sort" if path else None


def _common(found: DataFrame) -> DataFrame:
    """key, digest and windows of the common segments, their number n, whether any is `again`, and id, mark and begin of one.

    Keys are counted by buckets first (combined before the shuffle), and segments of full buckets one by one.
    """
    least = max(found.count() // COMMON, 1)
    placed = found.withColumn("bucket", F.pmod(F.xxhash64("key"), F.lit(16 * COMMON)))
    full = placed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > least).select("bucket")  # fewer than COMMON rows
    kinds = placed.join(F.broadcast(full), "bucket", "left_semi").groupBy("key", "digest", "windows")
    kinds = kinds.agg(F.count(F.lit(1)).alias("n"), F.max("again").alias("again"), F.min(F.struct("id", "mark", "begin")).alias("one")).where(F.col("n") > least)
    return saved(kinds.select("key", "digest", "windows", "n", "again", "one.id", "one.mark", "one.begin"), "segments-common")


def repeated_ranges(rows: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """id, mark, begin and end of ranges of windows that begin elsewhere too. rows: id, mark, text."""
    spark = rows.sparkSession
    ship(spark)
    found = saved(_segments(rows, length, gram), "segments")
    # common segments are marked where they lie, and one of each stands for all in the windows below
    kind, common = ["key", "digest", "windows"], _common(found)
    marked = found.join(F.broadcast(common.select(*kind)), kind, "left_semi")
    others = found.join(F.broadcast(common.select(*kind)), kind, "left_anti").withColumn("copies", F.lit(1).cast("bigint"))
    others = others.unionByName(common.withColumnRenamed("n", "copies"))
    same = Window.partitionBy(*kind)
    alike = same.orderBy("id", "mark", "begin")
    # one shuffle by key serves both windows: the finer grouping is within the coarser
    counted = others.repartition("key").withColumns({"n": F.sum("copies").over(same), "any": F.max("again").over(same), "nth": F.row_number().over(alike)})
    whole = Window.partitionBy("key")
    counted = counted.withColumns({"low": F.min("digest").over(whole), "high": F.max("digest").over(whole), "least": F.min("windows").over(whole), "most": F.max("windows").over(whole), "distinct": F.count_if(F.col("nth") == 1).over(whole)})
    mixed = (F.col("low") != F.col("high")) | (F.col("least") != F.col("most")) | F.col("any")
    levels = F.when(F.col("distinct") > HOT_SEGMENTS, F.ceil(F.log(F.col("distinct") / HOT_SEGMENTS) / F.log(F.lit(float(DIVIDED_BY))))).otherwise(0).cast("int")
    counted = saved(counted.where((F.col("n") > 1) | mixed).select("id", "mark", "begin", "windows", "key", "n", (mixed & (F.col("nth") == 1)).alias("sort"), levels.alias("levels")), "segments-repeated")
    full = counted.where("n > 1").select("id", "mark", "begin", "windows").unionByName(marked.select("id", "mark", "begin", "windows"))
    full = full.select("id", "mark", "begin", (F.col("begin") + F.col("windows")).alias("end"))
    pieces = _with_bytes(counted.where("sort"), rows, length, gram)
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    return full.unionByName(_sorted_ranges(pieces.repartition(parts, "key"), length, spool_folder(spark)))


def _spans(parts: list[dict] | None, length: int) -> list[list[int]]:
    """The runs of bytes that the windows cover."""
    out: list[list[int]] = []
    for p in sorted((p["begin"], p["end"]) for p in parts or []):
        if out and p[0] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], p[1] + length - 1)
        else:
            out.append([p[0], p[1] + length - 1])
    return out


def _rest(raw: bytes, spans: list[list[int]]) -> bytes:
    ends = [0, *(e for _, e in spans)]
    begins = [*(b for b, _ in spans), len(raw)]
    return b"".join(raw[e:b] for e, b in zip(ends, begins, strict=True))


def whole_characters(raw: bytes, spans: list[list[int]]) -> list[list[int]]:
    """The spans without the parts of characters at their ends."""
    out = []
    for a, b in spans:
        while a < b and raw[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(raw) and raw[b] & 0xC0 == 0x80:
            b -= 1
        if a < b:
            out.append([a, b])
    return out


def _marked(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    return docs.select(F.col(doc_id).cast("bigint").alias("id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("mark"), F.col(text).alias("text"))


def _listed(ranges: DataFrame) -> DataFrame:
    return ranges.distinct().groupBy("id", "mark").agg(F.collect_list(F.struct("begin", "end")).alias("parts"))  # a document's own ranges


def digests(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 (of the bytes that stay)."""
    rows = _marked(docs, doc_id, text)
    joined = _on_document(rows, _listed(repeated_ranges(rows, length, gram)), "left").select("id", "text", "parts")

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                out = []
                for row in batch.slice(a, 256).to_pylist():
                    raw, spans = (row["text"] or "").encode(), _spans(row["parts"], length)
                    out.append((row["id"], len(raw), sum(e - b for b, e in spans), len(spans), hashlib.sha256(_rest(raw, spans)).hexdigest()))
                columns = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in columns[:4]), pa.array(columns[4], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return joined.mapInArrow(run, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


def removed(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, doc_id: str = "doc_id", text: str = "text", n_chars: str = "n_chars") -> DataFrame:
    """The documents without their repeated strings (whole characters only) and n_chars to match; the columns of docs.

    Documents of which no word is left are dropped; those that had none stay.
    """
    names = docs.columns
    rows = _marked(docs, doc_id, text)
    lists = _listed(repeated_ranges(rows, length, gram))
    carried = docs.select(*[docs[c].alias(f"c{i}") for i, c in enumerate(names)], docs[doc_id].cast("bigint").alias("id"), F.xxhash64(F.coalesce(docs[text], F.lit(""))).alias("mark"))
    joined = _on_document(carried, lists, "left").drop("id", "mark")
    at_text, at_chars = names.index(text), names.index(n_chars) if n_chars in names else None

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                rows = batch.slice(a, 256)
                columns = [rows.column(i) for i in range(len(names))]
                texts, parts, keep = columns[at_text].to_pylist(), rows.column(len(names)).to_pylist(), []
                for k, (t, ps) in enumerate(zip(texts, parts, strict=True)):
                    if ps:
                        raw = t.encode()
                        texts[k] = _rest(raw, whole_characters(raw, _spans(ps, length))).decode()
                    if not ps or texts[k].strip():
                        keep.append(k)
                if at_chars is not None:
                    sizes = columns[at_chars].to_pylist()
                    columns[at_chars] = pa.array([len(t) if ps else n for t, ps, n in zip(texts, parts, sizes, strict=True)], columns[at_chars].type)
                columns[at_text] = pa.array(texts, pa.string())
                yield pa.RecordBatch.from_arrays(columns, [f"c{i}" for i in range(len(names))]).take(pa.array(keep, pa.int64()))

    return joined.mapInArrow(run, T.StructType([T.StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema)])).toDF(*names)
