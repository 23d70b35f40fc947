"""SentencePiece BPE encoding and decoding by vectorised merge rounds.

All words of a slice lie in one flat array of symbols. A round finds, for each segment, the least rank among its
adjacent pairs, merges all its leftmost non-overlapping occurrences at once, and closes the gaps; segments without a
pair are taken out; the rounds end when none is left. The result equals the library's, whose priority queue merges
one pair at a time:

* segments end where two neighbouring characters stand next to each other in no piece, so no merge crosses them;
* merging all occurrences of a piece at once is the same as one by one if no better piece contains it; a piece that
  a better one contains is merged once a round, leftmost first;
* pieces of spaces alone share the lowest score, so they come last, leftmost first: a run is cut into the longest
  pieces from the left.

Defined results: a null or empty text has no ids and decodes to ''; the text of any length is encoded whole; repeated
rows are encoded alike; other columns pass through, and one with the output's name is replaced.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import ship
from .wordcache import STICKY_OR_LOOSE, CachedEncoder, slices

SPACE = "▁"
_SHIFT = 21
_NONE = np.int32(2**31 - 1)
#: Parts of a text: words with the spaces before them. The second form also cuts at line ends and between a letter and
#: a full stop or comma; it holds for models where no piece joins those.
_PARTS = re.compile(" *[^ ]+| +")
_FINE_PARTS = re.compile(r" *[^\W\d_]+(?=[ .,\n]|$)| *[^ \n]+|\n| +")


def _utf8_ids(points: np.ndarray, byte_ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Number of UTF-8 bytes of each code point, and the byte pieces of all of them in order."""
    n = 1 + (points >= 0x80).astype(np.int64) + (points >= 0x800) + (points >= 0x10000)
    start = np.concatenate([[0], np.cumsum(n)])
    out = np.empty(start[-1], np.int64)
    lead = np.array([0, 0, 0xC0, 0xE0, 0xF0])
    for size in range(1, 5):
        at = np.flatnonzero(n == size)
        for k in range(size):
            bits = points[at] >> (6 * (size - 1 - k))
            out[start[at] + k] = (bits | lead[size]) if k == 0 else (bits & 0x3F) | 0x80
    return n, byte_ids[out]


class PieceBpe:
    """A BPE model of the sentencepiece library with identity normalisation, a dummy prefix and byte fallback."""

    def __init__(self, model_path: str):
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        with open(model_path, "rb") as f:
            model.ParseFromString(f.read())
        norm, train = model.normalizer_spec, model.trainer_spec
        kinds = {p.type for p in model.pieces}
        if train.model_type != 2 or norm.precompiled_charsmap or not norm.add_dummy_prefix or norm.remove_extra_whitespaces or train.treat_whitespace_as_suffix or not norm.escape_whitespaces or not train.byte_fallback or not kinds <= {1, 2, 3, 6}:
            raise ValueError("only BPE models with identity normalisation, a dummy prefix and byte fallback are supported")
        self.size = len(model.pieces)
        normal = {p.piece: (i, p.score) for i, p in enumerate(model.pieces) if p.type == 1}
        self.byte_ids = np.zeros(256, np.int64)
        self.surface: list[bytes] = []
        for i, p in enumerate(model.pieces):
            if p.type == 6:
                self.byte_ids[int(p.piece[3:5], 16)] = i
                self.surface.append(bytes([int(p.piece[3:5], 16)]))
            else:
                self.surface.append({2: train.unk_surface, 3: ""}.get(p.type, p.piece.replace(SPACE, " ")).encode())
        blank = {p for p in normal if not p.strip(SPACE)}
        longest = max(map(len, blank), default=0)
        sizes = {len(p) for p in blank}
        if 1 not in sizes or any(SPACE in p[1:] for p in normal.keys() - blank):
            raise ValueError("unsupported pieces with spaces")
        # blanks[total, place]: the piece that begins at this place of a run of so many spaces, or -1
        self.blanks = np.full((longest + 1, longest), -1, np.int64)
        for total in range(1, longest + 1):
            place = 0
            for k in self._run_of_spaces(total, sizes):
                self.blanks[total, place] = normal[SPACE * k][0]
                place += k
        if any(self._run_of_spaces(longest + k, sizes) != [longest, *self._run_of_spaces(k, sizes)] for k in range(1, 2 * longest)):
            raise ValueError("unsupported pieces with spaces")
        words = [p for p in normal if p not in blank and len(p) > 1]
        scores = [normal[p][1] for p in words]
        if len(set(scores)) != len(scores) or scores and min(scores) <= max(normal[p][1] for p in blank):
            raise ValueError("unsupported ties of scores")
        order = {p: r for r, p in enumerate(sorted(words, key=lambda p: -normal[p][1]))}
        self.rank_to_id = np.array([normal[p][0] for p in order], np.int64)
        single = {p: i for p, (i, _) in normal.items() if len(p) == 1}
        self.chars = np.arange(0x110000, dtype=np.int64) + self.size  # a character without a piece of its own stays apart
        for c, i in single.items():
            self.chars[ord(c)] = i

        def symbol(p: str) -> int | None:
            return int(self.chars[ord(p)]) if len(p) == 1 else normal[p][0] if p in normal else None

        keys, ranks, near, contained = [], [], set(), {}
        for p, r in order.items():
            for i in range(1, len(p)):
                left, right = symbol(p[:i]), symbol(p[i:])
                near.add((ord(p[i - 1]) << _SHIFT) | ord(p[i]))
                if left is not None and right is not None:
                    keys.append((left << _SHIFT) | right)
                    ranks.append(r)
            for i in range(len(p)):
                for j in range(i + 2, len(p) + (i > 0)):
                    if (q := p[i:j]) in order:
                        contained[q] = min(contained.get(q, r), r)
        at = np.argsort(np.array(keys, np.int64))
        self.keys, self.ranks = np.array(keys, np.int64)[at], np.array(ranks, np.int32)[at]
        self.near = np.array(sorted(near), np.int64)
        joined = {(chr(k >> _SHIFT), chr(k & ((1 << _SHIFT) - 1))) for k in near}
        self.parts = _PARTS if any("\n" in j or j[1] in ".," and j[0].isalpha() for j in joined) else _FINE_PARTS
        self.safe = np.array([contained.get(p, len(order)) > r for p, r in order.items()])

    @staticmethod
    def _run_of_spaces(total: int, sizes: set[int]) -> list[int]:
        """The lengths of the pieces of a run of spaces: equal scores, so the leftmost pair that makes a piece goes first."""
        run = [1] * total
        while (at := next((i for i in range(len(run) - 1) if run[i] + run[i + 1] in sizes), None)) is not None:
            run[at : at + 2] = [run[at] + run[at + 1]]
        return run

    def _find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = (left << _SHIFT) | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.ranks[at], _NONE)

    def _rounds(self, sym: np.ndarray, seg: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Symbols after all merges, and the segment of each."""
        done: list[tuple[np.ndarray, np.ndarray]] = []
        rank = np.full(len(sym), _NONE, np.int32)  # of the pair that begins here
        inner = np.flatnonzero(seg[:-1] == seg[1:])
        rank[inner] = self._find(sym[inner], sym[inner + 1])
        while len(sym):
            first = np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1]]))
            best = np.minimum.reduceat(rank, first)
            size = np.diff(np.concatenate([first, [len(sym)]]))
            least = np.repeat(best, size)
            live = least != _NONE
            if not live.all():
                done.append((seg[~live], sym[~live]))
                sym, seg, rank, least = sym[live], seg[live], rank[live], least[live]
                if not len(sym):
                    break
            hit = rank == least
            at = np.flatnonzero(hit)
            run = np.concatenate([[True], np.diff(at) != 1])  # overlapping occurrences stand side by side: every other one
            place = np.arange(len(at)) - np.maximum.accumulate(np.where(run, np.arange(len(at)), 0))
            at = at[place % 2 == 0]
            firsts = np.concatenate([[True], seg[at[1:]] != seg[at[:-1]]])
            at = at[self.safe[rank[at]] | firsts]
            sym[at] = self.rank_to_id[rank[at]]
            keep = np.ones(len(sym), bool)
            keep[at + 1] = False
            stale = np.zeros(len(sym), bool)
            stale[at] = True
            stale[at[at > 0] - 1] = True  # the pair before; if that symbol goes too, its own merge is marked
            before = at[at > 1] - 2
            stale[before[~keep[before + 1]]] = True
            sym, seg, rank, stale = sym[keep], seg[keep], rank[keep], np.flatnonzero(stale[keep])
            rank[stale] = _NONE
            stale = stale[stale < len(sym) - 1]
            stale = stale[seg[stale] == seg[stale + 1]]
            rank[stale] = self._find(sym[stale], sym[stale + 1])
        if not done:
            return sym, seg
        seg, sym = (np.concatenate(x) for x in zip(*done, strict=True))
        order = np.argsort(seg, kind="stable")
        return sym[order], seg[order]

    def encode_parts(self, parts: list[str]) -> list[bytes]:
        """Ids of each part (spaces, then a word) as bytes of 32-bit integers."""
        length = np.fromiter(map(len, parts), np.int64, len(parts))
        points = np.frombuffer("".join(parts).replace(" ", SPACE).encode("utf-32-le"), np.uint32).astype(np.int64)
        if not len(points):
            return [b""] * len(parts)
        word = np.repeat(np.arange(len(parts)), length)
        pair = (points[:-1] << _SHIFT) | points[1:]
        at = np.minimum(np.searchsorted(self.near, pair), len(self.near) - 1)
        cut = np.concatenate([[False], (self.near[at] != pair) | (word[1:] != word[:-1])])
        segment = np.cumsum(cut)
        word_of = word[np.concatenate([[0], np.flatnonzero(cut)])]
        sym, seg = self._rounds(self.chars[points], segment)
        word = word_of[seg]
        blank = sym == self.blanks[1, 0]
        if blank.any():  # runs of spaces, each within its word's part
            at = np.flatnonzero(blank)
            begins = np.concatenate([[True], (np.diff(at) != 1) | (word[at[1:]] != word[at[:-1]])])
            begin = np.flatnonzero(begins)
            run = np.diff(np.concatenate([begin, [len(at)]]))
            place, total, most = np.arange(len(at)) - np.repeat(begin, run), np.repeat(run, run), len(self.blanks) - 1
            rest = np.minimum(total - place // most * most, most)
            sym = sym.copy()
            sym[at] = self.blanks[rest, place % most]
            sym, word = sym[sym >= 0], word[sym >= 0]
        other = sym >= self.size
        if other.any():
            n, ids = _utf8_ids(sym[other] - self.size, self.byte_ids)
            count = np.ones(len(sym), np.int64)
            count[other] = n
            word = np.repeat(word, count)
            filled = np.repeat(sym, count)
            filled[np.repeat(other, count)] = ids
            sym = filled
        raw = sym.astype("<i4").tobytes()
        ends = (np.cumsum(np.bincount(word, minlength=len(parts))) * 4).tolist()
        return [raw[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]

    def parts_of(self, text: str) -> list[str]:
        if not text:
            return []
        text = " " + text.replace(SPACE, " ")
        if self.parts is _PARTS or "\x1f" in text or "  " in text or STICKY_OR_LOOSE.search(text):
            return self.parts.findall(text)
        return text.replace(" ", "\x1f ").replace(".", "\x1f.").replace(",", "\x1f,").replace("\n", "\x1f\n\x1f").split("\x1f")

    def decode(self, ids: list[int]) -> str:
        """The library's text for ids that encode a text: pieces joined, the prefix taken off, byte pieces as UTF-8."""
        whole = b"".join(map(self.surface.__getitem__, ids))
        return (whole[1:] if whole[:1] == b" " else whole).decode("utf-8", "replace")


@lru_cache(maxsize=4)
def model(path: str) -> PieceBpe:
    return PieceBpe(path)


@lru_cache(maxsize=4)
def _encoder(path: str) -> CachedEncoder:
    return CachedEncoder(model(path).parts_of, model(path).encode_parts)


def encoded(docs: DataFrame, model_path: str, text: str = "text", ids: str = "ids", keep_text: bool = True) -> DataFrame:
    """Adds the ids of each text as array<int>; without begin or end ids."""
    fields = [f for f in docs.schema if f.name != ids and (keep_text or f.name != text)]
    names = [f.name for f in fields]
    source = docs if keep_text else docs.select(*dict.fromkeys([*names, text]))
    ship(docs.sparkSession)

    def run(batches):
        encoder = _encoder(model_path)
        for batch in batches:
            for rows, texts in slices(batch, text):
                got = encoder.encode(texts)
                ends = np.cumsum([0, *map(len, got)], dtype=np.int64) // 4
                values = pa.array(np.frombuffer(b"".join(got), "<i4"))
                column = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), values)
                yield pa.RecordBatch.from_arrays([*(rows.column(rows.schema.get_field_index(n)) for n in names), column], [*names, ids])

    return source.mapInArrow(run, T.StructType([*fields, T.StructField(ids, T.ArrayType(T.IntegerType()))]))


def decoded(docs: DataFrame, model_path: str, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """Adds the text of each row's ids; null ids give ''."""
    ship(docs.sparkSession)
    fields = [f for f in docs.schema if f.name != text]
    names = [f.name for f in fields]

    def run(batches):
        bpe = model(model_path)
        for batch in batches:
            at = 0
            while at < batch.num_rows:  # a few rows at a time bound the memory
                rows = batch.slice(at, 256)
                at += 256
                column = rows.column(rows.schema.get_field_index(ids))
                texts = [bpe.decode(x.values.to_pylist() if x.is_valid else []) for x in column]
                yield pa.RecordBatch.from_arrays([*(rows.column(rows.schema.get_field_index(n)) for n in names), pa.array(texts, pa.string())], [*names, text])

    return docs.mapInArrow(run, T.StructType([*fields, T.StructField(text, T.StringType())]))
