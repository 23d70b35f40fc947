"""License scan: exact phrases, and a fuzzy search for short notices.

A text is lower-cased (A-Z) and reduced to its words (letters, digits and all non-ASCII characters) with one space
between them. A notice with at most k edits, cut into k + 1 pieces, has at least one piece unharmed, so exact
occurrences of the pieces (seeds) give all places where it can stand; there the regex library's bounded-error matching
decides, counts the edits and gives the span. A place goes to the matcher only if the letters around it could make the notice:
each edit supplies one letter at most, so a window that lacks more than k of the notice's letters (counted with repeats) holds no match.

Defined results: a null or empty text has no words and no spans; the whole of a long text is searched; repeated rows are
scanned alike; other columns pass through, and `spans` or `n_words` are replaced.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import ship

# Exact phrases and their labels.
PHRASES = {
    "cc by": "cc-by",
    "general public license": "gpl",
    "all rights reserved": "reserved",
}


@dataclass(frozen=True)
class Notice:
    """A short notice (words in lower case) and the edits that it may have suffered."""

    label: str
    text: str
    edits: int


# Usual short notices.
NOTICES = (
    Notice("apache-2.0", "licensed under the apache license version 2 0", 4),
    Notice("bsd", "redistribution and use in source and binary forms", 5),
    Notice("cc-by", "licensed under a creative commons attribution", 4),
    Notice("cc-by-nc", "licensed under cc by nc 4 0", 2),
    Notice("gpl", "licensed under the gnu general public license", 4),
    Notice("isc", "permission to use copy modify and or distribute this software", 6),
    Notice("mit", "permission is hereby granted free of charge to any person obtaining a copy", 7),
    Notice("mit", "released under the mit license", 3),
    Notice("mpl", "subject to the terms of the mozilla public license", 5),
    Notice("reserved", "all rights reserved", 2),
)

_SPAN = pa.struct([("label", pa.string()), ("first_word", pa.int64()), ("n_words", pa.int64()), ("edits", pa.int32()), ("base", pa.bool_()), ("similarity", pa.float64())])
_SPANS = T.ArrayType(T.StructType([T.StructField("label", T.StringType()), T.StructField("first_word", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("edits", T.IntegerType()), T.StructField("base", T.BooleanType()), T.StructField("similarity", T.DoubleType())]))
_KEEP = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def normalised(text: str) -> bytes:
    """The words of a text in UTF-8, one space between two."""
    return b" ".join(text.encode().translate(_KEEP).split())


def seeds(notice: Notice) -> list[tuple[int, bytes]]:
    """The k + 1 pieces of a notice and their places in it."""
    raw, parts = notice.text.encode(), notice.edits + 1
    cuts = [len(raw) * i // parts for i in range(parts + 1)]
    return [(a, raw[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


class Scanner:
    def __init__(self, notices: tuple[Notice, ...] = NOTICES, phrases: dict[str, str] | None = None):
        import regex

        self.phrases = [(b" " + p.encode() + b" ", label, len(p.split())) for p, label in (PHRASES if phrases is None else phrases).items()]
        self.letters = {n: [(bytes([c]), k) for c, k in sorted(Counter(n.text.encode()).items())] for n in notices}
        self.notices = [(n, seeds(n), regex.compile(f"(?b)(?:{regex.escape(n.text)}){{e<={n.edits}}}")) for n in notices]

    @staticmethod
    def _places(hay: bytes, needle: bytes) -> list[int]:
        out, at = [], hay.find(needle)
        while at >= 0:
            out.append(at)
            at = hay.find(needle, at + 1)
        return out

    def _able(self, hay: bytes, window: tuple[int, int], notice: Notice) -> bool:
        """Whether the window lacks no more letters of the notice than it may have edits."""
        lacking = 0
        for letter, n in self.letters[notice]:
            if (have := hay.count(letter, *window)) < n:
                lacking += n - have
                if lacking > notice.edits:
                    return False
        return True

    @staticmethod
    def _matches(pattern, piece: str) -> list:
        """The best match of a window, then the best ones of what stands before and after it, and so on."""
        out, ranges = [], [(0, len(piece))]
        while ranges:
            a, b = ranges.pop()
            m = pattern.search(piece, a, b) if a < b else None
            if m and m.end() > m.start():
                out.append(m)
                ranges += [(a, m.start()), (m.end(), b)]
        return out

    def scan(self, text: str) -> tuple[int, list[dict]]:
        """Number of words, and the spans in order."""
        words = normalised(text)
        padded = b" " + words + b" "  # a word begins after each space but the last
        found: list[tuple[int, int, str, int, int, bool, float]] = []
        for needle, label, n in self.phrases:
            found += [(at, at + len(needle) - 2, label, n, 0, True, 1.0) for at in self._places(padded, needle)]
        for notice, parts, pattern in self.notices:
            size, k, windows = len(notice.text), notice.edits, []  # an edit may be a character of four bytes
            for offset, seed in parts:
                windows += [w for at in self._places(padded, seed) if self._able(padded, w := (max(0, at - offset - 4 * k), at - offset + size + 4 * k), notice)]
            if not windows:
                continue
            windows.sort()
            joined = [list(windows[0])]
            for a, b in windows[1:]:
                if a <= joined[-1][1]:
                    joined[-1][1] = max(b, joined[-1][1])
                else:
                    joined.append([a, b])
            for a, b in joined:
                while a and padded[a] & 0xC0 == 0x80:
                    a -= 1
                piece = padded[a:b].decode("utf-8", "ignore")
                for m in self._matches(pattern, piece):
                    start = a + len(piece[: m.start()].encode())
                    inner = piece[m.start() : m.end()]
                    start += len(inner) - len(inner.lstrip(" "))
                    end, edits = start + len(inner.strip(" ").encode()), sum(m.fuzzy_counts)
                    if end > start:
                        found.append((start - 1, end, notice.label, padded.count(b" ", start, end) + 1, edits, False, 1 - edits / size))
        found.sort()
        spans, at, before = [], 0, -1
        for start, _, label, n, edits, base, similarity in found:
            before += padded.count(b" ", at, max(start, 0) + 1)
            at = max(start, 0) + 1
            spans.append({"label": label, "first_word": max(before, 0), "n_words": n, "edits": edits, "base": base, "similarity": similarity})
        return (words.count(b" ") + 1 if words else 0), spans


@lru_cache(maxsize=4)
def _scanner(notices: tuple[Notice, ...], phrases: tuple[tuple[str, str], ...]) -> Scanner:
    return Scanner(notices, dict(phrases))


def scanned(docs: DataFrame, notices: tuple[Notice, ...] = NOTICES, phrases: dict[str, str] | None = None, text: str = "text", keep_text: bool = True) -> DataFrame:
    """Adds n_words and spans (label, first_word, n_words, edits, base, similarity): base spans are exact phrases."""
    fields = [f for f in docs.schema if f.name not in ("n_words", "spans") and (keep_text or f.name != text)]
    names, chosen = [f.name for f in fields], tuple((PHRASES if phrases is None else phrases).items())

    def run(batches):
        scanner = _scanner(notices, chosen)
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                rows = batch.slice(a, 512)
                got = [scanner.scan(t.as_py() or "") for t in rows.column(rows.schema.get_field_index(text))]
                yield pa.RecordBatch.from_arrays(
                    [*(rows.column(rows.schema.get_field_index(n)) for n in names), pa.array([n for n, _ in got], pa.int64()), pa.array([s for _, s in got], pa.list_(_SPAN))],
                    [*names, "n_words", "spans"],
                )

    source = docs if keep_text else docs.select(*dict.fromkeys([*names, text]))
    ship(docs.sparkSession)
    return source.mapInArrow(run, T.StructType([*fields, T.StructField("n_words", T.LongType()), T.StructField("spans", _SPANS)]))
