"""Encode whole texts as joins of encoded pieces, each distinct piece being encoded once.

A text is cut where no token can span the cut, so that encoding the parts and joining them is exact. Ids are kept as
the bytes of little-endian 32-bit integers; the store is emptied when it grows beyond a fixed size, which costs time only.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import pyarrow as pa

STORE_BYTES = 80 << 20
SLICE_CHARS = 1 << 20


#: A full stop or comma after something that is neither a letter nor white space. (U+0130 counts as none: its lower case
#: ends in a mark that joins what follows.)
STICKY = re.compile("[.,](?<![^\\W\\d_\u0130].)(?<!\\s.)")
#: The same, or after white space.
STICKY_OR_LOOSE = re.compile(r"[.,](?<![^\W\d_].)")


class CachedEncoder:
    def __init__(self, cut: Callable[[str], list[str]], encode: Callable[[list[str]], list[bytes]], most: int = STORE_BYTES):
        self._cut, self._encode, self._most, self._new, self._old, self._held = cut, encode, most, {}, {}, 0

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, as bytes."""
        parts = [self._cut(t) for t in texts]
        if self._held > self._most:  # pieces not used since the last change of stores go
            self._new, self._old, self._held = {}, self._new, 0
        store, old = self._new, self._old
        missing = [w for w in set().union(*parts) if w not in store]
        got = {w: old[w] for w in missing if w in old}
        new = [w for w in missing if w not in got] if got else missing
        if new:
            got.update(zip(new, self._encode(new), strict=True))
        store.update(got)
        self._held += sum(map(len, got)) + sum(map(len, got.values())) + 200 * len(got)
        find = store.__getitem__
        return [b"".join(map(find, p)) for p in parts]


def slices(batch: pa.RecordBatch, column: str) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Runs of rows with about SLICE_CHARS characters at most (one row at least), and their texts with null as ''."""
    texts = [t or "" for t in batch.column(batch.schema.get_field_index(column)).to_pylist()]
    start = 0
    while start < len(texts):
        end, size = start, 0
        while end < len(texts) and (end == start or size + len(texts[end]) <= SLICE_CHARS):
            size += len(texts[end])
            end += 1
        yield batch.slice(start, end - start), texts[start:end]
        start = end
