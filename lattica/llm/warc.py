"""WARC archives compressed with Zstandard: a shared dictionary first, then one frame per record.

An archive begins with a skippable frame (magic 0x184D2A5D) that holds the dictionary; every record is a frame of its
own, so a reader can stop, resume or skip at any frame. The reader loads the dictionary, decodes frame by frame, and
checks the version line, the headers, the block's length, the payload's length and its digest; anything wrong raises
ArchiveError.

Defined results: a null payload is empty; payloads below `least` bytes are all responses; among equal longer payloads
the rows with the smallest id are the response and the others revisit it (a null id never is the smallest unless all
are null: then all are responses); an empty table gives no archive and no rows; other columns are not written.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import open_store, publish, ship

DICTIONARY_FRAME = 0x184D2A5D
ZSTD_FRAME = 0xFD2FB528
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
LEAST = 100
#: The dictionary is trained on so many payloads at most, so many bytes of each; every payload is compressed with it.
SAMPLE_PAGES, SAMPLE_BYTES, DICTIONARY_BYTES = 256, 8192, 32768
LEVEL = 3
_CHUNK = 1 << 13


class ArchiveError(ValueError):
    pass


def deduplicated(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST, parts: int = 32) -> DataFrame:
    """page_id, url, payload, payload_bytes, payload_digest, record_type, refers_to.

    Only digests that occur more than once reach the join, and they are counted before the shuffle. Rows of one digest are dealt to
    `parts` parts of the join, and payloads below `least` bytes meet nothing, so no task has all copies of a payload.
    """
    ship(pages.sparkSession)
    rows = pages.select(F.col(page_id).cast("bigint").alias("page_id"), F.col(url).cast("string").alias("url"), F.coalesce(F.col(html), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumns({"payload_bytes": F.octet_length("payload").cast("bigint"), "payload_digest": F.sha2("payload", 256)})
    repeated = (
        rows.where(F.col("payload_bytes") >= least)
        .groupBy("payload_digest")
        .agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .select(F.col("payload_digest").alias("of"), "first_id", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))
    )
    own = F.xxhash64("page_id", "url")
    rows = rows.withColumns({"meets": F.when(F.col("payload_bytes") >= least, F.col("payload_digest")).otherwise(F.concat(F.lit("-"), own.cast("string"))), "deal": F.pmod(own, F.lit(parts)).cast("int")})
    revisit = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return rows.join(repeated, (F.col("meets") == F.col("of")) & (F.col("deal") == F.col("part")), "left").select(
        "page_id",
        "url",
        "payload",
        "payload_bytes",
        "payload_digest",
        F.when(revisit, F.lit("revisit")).otherwise("response").alias("record_type"),
        F.when(revisit, F.col("first_id")).alias("refers_to"),
    )


def dictionary_of(samples: list[bytes]) -> bytes:
    """A trained dictionary, or the samples themselves where they are too few to train on."""
    import zstandard

    samples = [s for s in samples if s]
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-DICTIONARY_BYTES:]


def _record_id(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def _page_of(record_id: str) -> int | None:
    if not (record_id.startswith("<urn:page:") and record_id.endswith(">")):
        raise ArchiveError(f"record id {record_id}")
    return None if record_id[10:-1] == "none" else int(record_id[10:-1])


def record_bytes(page_id, url, payload: bytes, size: int, digest: str, kind: str, refers_to) -> bytes:
    """One uncompressed record. A revisit keeps the response's head (so its length) and leaves the payload out."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    block = head + (payload if kind == "response" else b"")
    target = "" if url is None else "WARC-Target-URI: " + "".join(f"%{b:02X}" if b <= 32 or b >= 127 else chr(b) for b in url.encode()) + "\r\n"
    extra = f"WARC-Profile: {PROFILE}\r\nWARC-Refers-To: {_record_id(refers_to)}\r\n" if kind == "revisit" else ""
    lines = (
        f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Record-ID: {_record_id(page_id)}\r\nWARC-Date: 1970-01-01T00:00:00Z\r\n{target}{extra}"
        f"WARC-Payload-Digest: sha256:{digest}\r\nContent-Type: application/http;msgtype=response\r\nContent-Length: {len(block)}\r\n\r\n"
    )
    return lines.encode() + block + b"\r\n\r\n"


def sample_of(pages: DataFrame, page_id: str = "page_id", html: str = "html") -> list[bytes]:
    """The beginnings of up to SAMPLE_PAGES payloads, those whose ids have the least hashes; ids alone are ranked."""
    key = F.xxhash64(F.col(page_id).cast("bigint"))
    least = [r["h"] for r in pages.select(key.alias("h")).orderBy("h").limit(SAMPLE_PAGES).collect()]
    if not least:
        return []
    rows = pages.where(key <= least[-1]).select(F.substring(F.coalesce(F.col(html), F.lit("")).cast("binary"), 1, SAMPLE_BYTES).alias("s"))
    return sorted(bytes(r["s"]) for r in rows.limit(2 * SAMPLE_PAGES).collect())


def write(records: DataFrame, path: str, sample: list[bytes]) -> list[str]:
    """Write the rows of `deduplicated` as archives, one per partition, and return their names; the dictionary is trained on the sample."""
    import zstandard

    trained = dictionary_of(sample)

    def run(batches):
        from pyspark import TaskContext

        name, count = f"archive-{TaskContext.get().partitionId():06d}.warc.zst", 0
        dictionary = zstandard.ZstdCompressionDict(trained)
        packer = zstandard.ZstdCompressor(level=LEVEL, dict_data=dictionary, write_checksum=True, write_content_size=True)

        def put(out):
            nonlocal count
            packed = zstandard.ZstdCompressor(level=19).compress(trained)
            out.write(struct.pack("<II", DICTIONARY_FRAME, len(packed)) + packed)
            for batch in batches:
                for row in zip(*(c.to_pylist() for c in (batch.column(n) for n in ("page_id", "url", "payload", "payload_bytes", "payload_digest", "record_type", "refers_to"))), strict=True):
                    out.write(packer.compress(record_bytes(*row)))
                    count += 1

        publish(path, name, put)
        yield pa.RecordBatch.from_pydict({"name": [name], "records": pa.array([count], pa.int64())})

    # one row for each archive
    return sorted(r["name"] for r in records.mapInArrow(run, "name string, records bigint").collect() if r["records"])


@dataclass(frozen=True)
class Record:
    headers: dict[str, str]
    block: bytes


def frames(source) -> Iterator[bytes]:
    """The decoded frames of an archive, one by one; the dictionary comes from the leading skippable frame."""
    import zstandard

    rest = source.read(_CHUNK)
    unpacker = zstandard.ZstdDecompressor()
    if len(rest) >= 8 and struct.unpack("<I", rest[:4])[0] == DICTIONARY_FRAME:
        size = struct.unpack("<I", rest[4:8])[0]
        while len(rest) < 8 + size:
            more = source.read(_CHUNK)
            if not more:
                raise ArchiveError("the dictionary is cut short")
            rest += more
        raw, rest = rest[8 : 8 + size], rest[8 + size :]
        if raw[:4] == struct.pack("<I", ZSTD_FRAME):
            raw = unpacker.decompress(raw)
        unpacker = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw))
    while rest := rest or source.read(_CHUNK):
        frame, parts = unpacker.decompressobj(), []
        try:
            while True:
                parts.append(frame.decompress(rest))
                if frame.eof:
                    rest = frame.unused_data
                    break
                rest = source.read(_CHUNK)
                if not rest:
                    raise ArchiveError("a frame is cut short")
        except zstandard.ZstdError as error:
            raise ArchiveError(f"bad frame: {error}") from error
        yield b"".join(parts)


def _headers(raw: bytes, what: str) -> dict[str, str]:
    out = {}
    for line in raw.decode("utf-8").split("\r\n"):
        name, colon, value = line.partition(":")
        if not colon or not name or name.lower() in out:
            raise ArchiveError(f"bad {what} header: {line!r}")
        out[name.lower()] = value.strip()
    return out


def parsed(raw: bytes) -> Record:
    """One record of a frame, with its version, headers and length checked."""
    end = raw.find(b"\r\n\r\n")
    if end < 0 or not raw.startswith(b"WARC/1.1\r\n"):
        raise ArchiveError("no WARC head")
    headers = _headers(raw[10:end], "WARC")
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in headers:
            raise ArchiveError(f"no {name}")
    if not headers["content-length"].isdigit():
        raise ArchiveError("bad length")
    size = int(headers["content-length"])
    if len(raw) != end + 4 + size + 4 or raw[-4:] != b"\r\n\r\n":
        raise ArchiveError("the length is not that of the block")
    return Record(headers, raw[end + 4 : end + 4 + size])


def described(record: Record) -> dict:
    """The page of a record; lengths and digests are checked."""
    end = record.block.find(b"\r\n\r\n")
    if end < 0 or not record.block.startswith(b"HTTP/1.1 "):
        raise ArchiveError("no HTTP head")
    head, payload = _headers(record.block[:end].split(b"\r\n", 1)[1], "HTTP"), record.block[end + 4 :]
    size, kind = int(head.get("content-length", "-1")), record.headers["warc-type"]
    method, _, digest = record.headers.get("warc-payload-digest", "").partition(":")
    if method != "sha256" or len(digest) != 64:
        raise ArchiveError("no payload digest")
    if kind == "response":
        if len(payload) != size or hashlib.sha256(payload).hexdigest() != digest:
            raise ArchiveError("the payload is not that of the digest")
        refers = None
    elif kind == "revisit":
        if payload or record.headers.get("warc-profile") != PROFILE or "warc-refers-to" not in record.headers:
            raise ArchiveError("bad revisit")
        refers = _page_of(record.headers["warc-refers-to"])
    else:
        raise ArchiveError(f"record type {kind}")
    return {"page_id": _page_of(record.headers["warc-record-id"]), "url": record.headers.get("warc-target-uri"), "payload": payload if kind == "response" else None, "payload_bytes": size, "payload_digest": digest, "record_type": kind, "refers_to": refers}


def read(spark: SparkSession, path: str, names: list[str], payloads: bool = True) -> DataFrame:
    """One row per record of the archives; the payload of a revisit is null."""
    types = {"page_id": pa.int64(), "url": pa.string(), "payload": pa.binary(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "record_type": pa.string(), "refers_to": pa.int64()}
    if not payloads:
        types.pop("payload")
    sql = {pa.int64(): "bigint", pa.string(): "string", pa.binary(): "binary"}
    schema, arrow = ", ".join(f"{n} {sql[t]}" for n, t in types.items()), pa.schema(list(types.items()))

    def run(batches):
        for batch in batches:
            for name in batch.column(0).to_pylist():
                store, root = open_store(path)
                held, size = [], 0
                with store.open_input_stream(f"{root}/{name}", compression=None) as source:
                    for raw in frames(source):
                        held.append(described(parsed(raw)))
                        size += len(raw)
                        if size > 1 << 22 or len(held) >= 4096:
                            yield pa.RecordBatch.from_pylist([{k: r[k] for k in types} for r in held], arrow)
                            held, size = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist([{k: r[k] for k in types} for r in held], arrow)

    ship(spark)
    if not names:
        return spark.createDataFrame([], schema)
    return spark.createDataFrame([(n,) for n in names], "name string").repartition(len(names)).mapInArrow(run, schema)
