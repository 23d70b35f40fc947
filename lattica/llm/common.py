"""Shared helpers: table access, the shared work folder, text constants."""

from __future__ import annotations

import os
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import fresh_path, saved, shared_root, ship

__all__ = ["SPACES", "WORD_BREAK", "local_path", "open_store", "publish", "quiet_threads", "saved", "shared_root", "ship", "table", "text_or_empty", "tokenizer_path", "workspace"]

#: Characters that end a word; everything else is part of one.
SPACES = " \t\n\x0b\x0c\r"
WORD_BREAK = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def workspace(spark: SparkSession, label: str) -> str:
    """A fresh path below the shared folder."""
    return fresh_path(spark, label)


def local_path(uri: str) -> str | None:
    """The POSIX path of a shared folder, or None if it is in a store that has none."""
    if uri.startswith("file:"):
        return "/" + uri[5:].lstrip("/")
    return uri if uri.startswith("/") else None


def open_store(uri: str):
    """(filesystem, path) of pyarrow for a shared folder."""
    from pyarrow import fs

    path = local_path(uri)
    if path is not None:
        return fs.LocalFileSystem(), path
    return fs.FileSystem.from_uri(uri)


def publish(uri: str, name: str, write) -> str:
    """Write a file under a temporary name and rename it, so that a repeated or lost task leaves one whole file."""
    store, root = open_store(uri)
    store.create_dir(root, recursive=True)
    final, draft = f"{root}/{name}", f"{root}/.{name}.{uuid.uuid4().hex}"
    try:
        with store.open_output_stream(draft, compression=None) as out:
            write(out)
        store.move(draft, final)
    except BaseException:
        if store.get_file_info(draft).is_file:
            store.delete_file(draft)
        raise
    return final


def tokenizer_path(name: str) -> str:
    """The file of a public tokenizer."""
    import public_tokenizers

    return public_tokenizers.path(name)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def quiet_threads() -> None:
    """One thread for each Python worker: Spark's tasks are the parallelism."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    os.environ.setdefault("OMP_NUM_THREADS", "1")
