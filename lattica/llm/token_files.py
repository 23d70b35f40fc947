"""Token ids as flat binary files.

A dataset is a folder of shards. Shard k has `shard-k.ids` (the ids of its documents, one after the other, as unsigned
little-endian integers of 16 bits if the vocabulary has at most 65,536 ids, else of 32 bits), `shard-k.idx` (64-bit
offsets in ids, one more than there are documents) and `shard-k.doc` (64-bit document ids). Documents are in ascending
order of id over all shards, so a shard's base, the number of ids before it, is a prefix sum over the shards' sizes;
`manifest.json` holds them. Readers map the files into memory where the store is a file system.

Defined results: a null or empty text has the end id alone; a null document id comes first and is read back as null;
repeated rows are written one by one, equal ids by text; an empty table gives a dataset without documents; other columns are
not read. Long texts are encoded piece by piece.
"""

from __future__ import annotations

import json
import re
import zlib
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import open_store, publish, quiet_threads, ship
from .wordcache import STICKY, STORE_BYTES, CachedEncoder, slices

NULL_ID = -(2**63)
DOCS_PER_SHARD = 1 << 16
#: Cuts that never part a token: at white space, and between a letter and a full stop or comma.
_CUT = re.compile("[ \n]+|(?<=[^\\W\\d_\u0130])(?=[.,])")
#: So many words are encoded in one call.
_CALL = 512


@lru_cache(maxsize=4)
def _encoder(path: str) -> CachedEncoder:
    """White space ends a word for this kind of tokenizer and is dropped, so texts are cut at spaces."""
    quiet_threads()
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    kind = json.loads(tokenizer.to_str())
    splits = kind["pre_tokenizer"]["pretokenizers"][0]
    if kind["model"]["type"] != "BPE" or kind["post_processor"] or not (splits["type"] == "Split" and splits["invert"] and r"\s" in splits["pattern"]["Regex"]) or any(" " in t["content"] or t["lstrip"] or t["rstrip"] or t["single_word"] for t in kind["added_tokens"]):
        raise ValueError("only BPE tokenizers that drop white space between words are supported")

    ends = np.zeros(vocabulary_size(path), bool)
    suffix = kind["model"]["end_of_word_suffix"]
    ends[[i for w, i in kind["model"]["vocab"].items() if suffix and w.endswith(suffix)]] = True

    def one_by_one(words: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def encode(words: list[str]) -> list[bytes]:
        """Words of letters alone are one unit each, which a single id with the word-end suffix closes: many go in one call."""
        found: dict[str, bytes] = {}
        plain = [w for w in words if w.isalpha() and w.lower().isalpha()]
        for a in range(0, len(plain), _CALL):
            some = plain[a : a + _CALL]
            ids = np.array(tokenizer.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.flatnonzero(ends[ids]) + 1
            if len(cuts) == len(some) and cuts[-1] == len(ids):
                raw, at = ids.tobytes(), (cuts * 4).tolist()
                found.update((w, raw[x:y]) for w, x, y in zip(some, [0, *at[:-1]], at, strict=True))
        rest = [w for w in words if w not in found]
        found.update(zip(rest, one_by_one(rest), strict=True))
        return [found[w] for w in words]

    return CachedEncoder(_words, encode, 2 * STORE_BYTES)


def _words(text: str) -> list[str]:
    """Parts that no token spans, and empty ones."""
    if STICKY.search(text):
        return _CUT.split(text)
    return text.replace("\n", " ").replace(".", " .").replace(",", " ,").split(" ")


def vocabulary_size(path: str) -> int:
    with open(path, encoding="utf-8") as f:
        kind = json.load(f)
    return max([*kind["model"]["vocab"].values(), *(t["id"] for t in kind["added_tokens"])]) + 1


@dataclass(frozen=True)
class Dataset:
    """A written dataset: its folder, the width of an id and the shards (number, documents, ids, base)."""

    path: str
    dtype: str
    shards: list[tuple[int, int, int, int]]

    @staticmethod
    def load(path: str) -> Dataset:
        store, root = open_store(path)
        with store.open_input_file(f"{root}/manifest.json") as f:
            said = json.loads(f.read())
        return Dataset(path, said["dtype"], [tuple(s) for s in said["shards"]])


def write(docs: DataFrame, path: str, tokenizer: str, end_id: int = 1, doc_id: str = "doc_id", text: str = "text", shards: int | None = None) -> Dataset:
    """Encode the documents and write them in ascending order of id, end_id after each."""
    ship(docs.sparkSession)
    dtype = "<u2" if max(vocabulary_size(tokenizer), end_id + 1) <= 1 << 16 else "<u4"
    chosen = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).alias("text"))
    if shards is None:
        shards = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-docs.count() // DOCS_PER_SHARD))
    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        from pyspark import TaskContext

        number = TaskContext.get().partitionId()
        encoder, ids, offsets, spool = _encoder(tokenizer), [], [np.zeros(1, "<i8")], []
        total = 0

        def put(out):
            nonlocal total
            for batch in batches:
                for rows, texts in slices(batch, "text"):
                    got = [x + end for x in encoder.encode(texts)]
                    out.write(np.frombuffer(b"".join(got), "<u4").astype(dtype).tobytes())
                    offsets.append(total + np.cumsum([len(x) // 4 for x in got], dtype="<i8"))
                    total = int(offsets[-1][-1])
                    ids.append(rows.column(0).fill_null(NULL_ID).to_numpy(zero_copy_only=False).astype("<i8"))

        name = f"shard-{number:06d}"
        publish(path, f"{name}.ids", put)
        publish(path, f"{name}.idx", lambda out: out.write(np.concatenate(offsets).tobytes()))
        publish(path, f"{name}.doc", lambda out: out.write(np.concatenate([*ids, np.zeros(0, "<i8")]).tobytes()))
        yield pa.RecordBatch.from_pydict({"shard": [number], "docs": [sum(map(len, ids))], "ids": [total]})

    # beginnings of texts divide rows of one id, or without any, as the order by text does
    ordered = chosen.repartitionByRange(shards, F.asc_nulls_first("doc_id"), F.asc_nulls_first(F.substring("text", 1, 32))).sortWithinPartitions(F.asc_nulls_first("doc_id"), F.asc_nulls_first("text"))
    # one small row for each file: bounded by the number of shards, not by the documents
    done = sorted(tuple(r) for r in ordered.mapInArrow(run, "shard bigint, docs bigint, ids bigint").collect())
    base, rows = 0, []
    for number, count, n in done:
        rows.append((number, count, n, base))
        base += n
    publish(path, "manifest.json", lambda out: out.write(json.dumps({"dtype": dtype, "shards": rows}).encode()))
    return Dataset(path, dtype, rows)


class Shard:
    """Random access to the documents of a shard."""

    def __init__(self, path: str, dtype: str, number: int):
        from pyarrow import fs

        store, root = open_store(path)
        local = isinstance(store, fs.LocalFileSystem)

        def view(kind: str, as_type: str) -> np.ndarray:
            name = f"{root}/shard-{number:06d}.{kind}"
            size = store.get_file_info(name).size
            if size == 0:
                return np.zeros(0, as_type)
            if local:
                return np.memmap(name, as_type, "r")
            with store.open_input_file(name) as f:
                return np.frombuffer(f.read(), as_type)

        self.ids, self.offsets, self.doc_ids = view("ids", dtype), view("idx", "<i8"), view("doc", "<i8")

    def __len__(self) -> int:
        return len(self.doc_ids)

    def __getitem__(self, i: int) -> np.ndarray:
        return self.ids[self.offsets[i] : self.offsets[i + 1]]


def read(spark: SparkSession, data: Dataset, checksum_only: bool = False) -> DataFrame:
    """One row per document: doc_id, start, n_tokens, ids_crc32 and, unless checksum_only, ids."""
    rows = [(n, base) for n, count, _, base in data.shards if count]
    path, dtype = data.path, data.dtype
    schema = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint" + ("" if checksum_only else ", ids array<bigint>")

    def run(batches):
        for batch in batches:
            for number, base in zip(*(batch.column(i).to_pylist() for i in (0, 1)), strict=True):
                shard = Shard(path, dtype, number)
                for a in range(0, len(shard), 1024):
                    b = min(a + 1024, len(shard))
                    at = np.array(shard.offsets[a : b + 1])
                    block = np.array(shard.ids[at[0] : at[-1]]).astype("<u4")
                    raw, cut = memoryview(block).cast("B"), (at - at[0]).tolist()
                    out = {
                        "doc_id": pa.array(shard.doc_ids[a:b], mask=np.array(shard.doc_ids[a:b]) == NULL_ID),
                        "start": pa.array(base + at[:-1]),
                        "n_tokens": pa.array(np.diff(at)),
                        "ids_crc32": pa.array([zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(cut[:-1], cut[1:], strict=True)], pa.int64()),
                    }
                    if not checksum_only:
                        out["ids"] = pa.ListArray.from_arrays(pa.array(cut, pa.int32()), pa.array(block.astype(np.int64)))
                    yield pa.RecordBatch.from_pydict(out)

    ship(spark)
    if not rows:
        return spark.createDataFrame([], schema)
    shards = spark.createDataFrame(rows, "shard int, base bigint").repartition(len(rows))
    return shards.mapInArrow(run, schema)
