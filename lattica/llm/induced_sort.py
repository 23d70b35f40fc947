"""External induced suffix sorting with common-prefix values.

The text of a shard is a row of segments with a separator before, between and after them; separators are all different,
so no common prefix runs over the end of a segment. Whatever has an entry for each symbol or seed (text, types, seeds,
their order, digests and ranks, marks) is a file mapped into memory once it outgrows its bound, and is made and read in
blocks; the queues are spools on disk. The steps:

1. Suffixes whose type turns from larger-than-next to smaller-than-next are the seeds. A first induction from seeds that
   are ordered by one symbol gives the order of the substrings between seeds, and so their names.
2. Names repeat until the order of the seeds is known: tuples (rank, rank of the seed 2^r further) are sorted, in runs that
   are merged from disk, for r = 0, 1, ... Only the first `depth` symbols count, so this ends after log2(depth) rounds.
3. The second induction carries, with each suffix, the length of its common prefix with the one before it: seeds bring
   theirs, and a suffix induced after another by the same symbol gets one more than the least value in between.

A queue holds one spool per first symbol. Suffixes are pushed in their order, so each spool is sorted, and taking the
spools by symbol is taking the least (or, in the second half, the greatest) of a priority queue. Work on a spool is done
in blocks as array operations; suffixes pushed into the spool that is being read form its next block.
"""

from __future__ import annotations

import os
import shutil
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np

BLOCK = 1 << 20
#: Bytes that a set of queues may hold in memory; arrays above a quarter of it are files.
MEMORY = 64 << 20


class Spools:
    """Queues of (position, common prefix) pairs by symbol. They stay in memory up to a bound that all share, and go to disk beyond it."""

    def __init__(self, folder: str, name: str, memory: int):
        self._folder, self._name, self._memory, self._used = folder, name, memory, 0
        self._held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        self._flushed: dict[int, int] = {}
        self._count: dict[int, int] = {}

    def size(self, c: int) -> int:
        return self._count.get(c, 0)

    def _paths(self, c: int) -> tuple[str, str]:
        base = os.path.join(self._folder, f"{self._name}{c}")
        return f"{base}.p", f"{base}.c"

    def push(self, c: int, positions: np.ndarray, common: np.ndarray) -> None:
        self._held.setdefault(c, []).append((positions, common))
        self._count[c] = self.size(c) + len(positions)
        self._used += positions.nbytes + common.nbytes
        if self._used > self._memory:
            for k, parts in self._held.items():
                if parts:
                    with open(self._paths(k)[0], "ab") as p, open(self._paths(k)[1], "ab") as q:
                        for positions, common in parts:
                            p.write(positions.astype(np.int64).tobytes())
                            q.write(common.tobytes())
                    self._flushed[k], self._held[k] = self._count[k], []
            self._used = 0

    def read(self, c: int, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """The pairs of a symbol from a to b, in the order in which they were pushed."""
        parts, at = [], self._flushed.get(c, 0)
        if a < at:
            n = min(b, at) - a
            with open(self._paths(c)[0], "rb") as p, open(self._paths(c)[1], "rb") as q:
                p.seek(8 * a)
                q.seek(2 * a)
                parts.append((np.frombuffer(p.read(8 * n), np.int64), np.frombuffer(q.read(2 * n), np.uint16)))
        for positions, common in self._held.get(c, []):
            x, y = max(a, at), min(b, at + len(positions))
            if x < y:
                parts.append((positions[x - at : y - at], common[x - at : y - at]))
            at += len(positions)
        if not parts:
            return np.zeros(0, np.int64), np.zeros(0, np.uint16)
        return np.concatenate([p for p, _ in parts]).astype(np.int64), np.concatenate([q for _, q in parts])

    def drop(self, c: int) -> None:
        """A queue that was read to its end goes."""
        self._used -= sum(p.nbytes + q.nbytes for p, q in self._held.pop(c, []))
        self._count.pop(c, None)
        if self._flushed.pop(c, 0):
            for path in self._paths(c):
                os.remove(path)


def _range_min(values: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """min(values[low..high]) for many ranges."""
    out = np.empty(len(low), values.dtype)
    level = np.log2(high - low + 1).astype(np.int64)
    table, width = values, 1
    for k in range(int(level.max()) + 1):
        at = np.flatnonzero(level == k)
        out[at] = np.minimum(table[low[at]], table[high[at] - width + 1])
        table = np.minimum(table[:-width], table[width:]) if len(table) > width else table
        width *= 2
    return out


class InducedSorter:
    """Sorts the suffixes of a spooled shard; `repeated` gives what deduplication needs."""

    def __init__(self, folder: str | None = None, depth: int = 200, block: int = BLOCK, memory: int = MEMORY):
        if folder:
            os.makedirs(folder, exist_ok=True)
        self.folder = tempfile.mkdtemp(prefix="induced-", dir=folder)
        self.depth, self.block, self.memory = depth, block, memory
        self.carrying = True  # common prefixes: the naming pass needs none

    def close(self) -> None:
        shutil.rmtree(self.folder, ignore_errors=True)

    def __enter__(self):
        return self

    def __exit__(self, *_):
        self.close()

    def _array(self, name: str, dtype, n: int) -> np.ndarray:
        if n * np.dtype(dtype).itemsize <= self.memory // 4:
            return np.zeros(n, dtype)
        return np.asarray(np.memmap(os.path.join(self.folder, name), dtype, "w+", shape=(n,)))

    def _gathered(self, name: str, dtype, parts: Iterable[np.ndarray]) -> np.ndarray:
        """The parts in a row: in memory up to the bound of an array, in a file beyond it."""
        path, held, size, count, out = os.path.join(self.folder, name), [], 0, 0, None
        try:
            for part in parts:
                held.append(np.asarray(part, dtype))
                size, count = size + held[-1].nbytes, count + len(part)
                if size > self.memory // 4:
                    out = out or open(path, "wb")  # noqa: SIM115
                    for h in held:
                        out.write(h.tobytes())
                    held, size = [], 0
            if out is None:
                return np.concatenate(held) if held else np.zeros(0, dtype)
            for h in held:
                out.write(h.tobytes())
        finally:
            if out is not None:
                out.close()
        return np.asarray(np.memmap(path, dtype, "r", shape=(count,)))

    def _blocks(self, n: int) -> Iterator[tuple[int, int]]:
        return ((a, min(a + self.block, n)) for a in range(0, n, self.block))

    def load(self, segments: Iterable[bytes]) -> int:
        """Spool the segments (not empty) as symbols byte + 1, separated by 0; returns their number."""
        path, count = os.path.join(self.folder, "text"), 0
        with open(path, "wb") as out:
            out.write(np.zeros(1, np.uint16).tobytes())
            for s in segments:
                symbols = np.zeros(len(s) + 1, np.uint16)
                symbols[:-1] = np.frombuffer(s, np.uint8)
                symbols[:-1] += 1
                out.write(symbols.tobytes())
                count += 1
            size = out.tell() // 2
            out.write(np.zeros(8, np.uint16).tobytes())  # for reads of several symbols at the end
        whole = np.asarray(np.memmap(path, np.uint16, "r", shape=(size + 8,)))
        self.text, self.size = whole[:size], size
        self._four = np.lib.stride_tricks.as_strided(whole.view(np.uint8), (size, 8), (2, 1))
        self._types()
        return count

    def _types(self) -> None:
        """small[i]: suffix i is smaller than suffix i + 1; made from the right, block by block."""
        text, n = self.text, self.size
        self.small = self._array("small", np.bool_, n)
        self.small[n - 1] = True
        for b in range(n - 1, 0, -self.block):
            a = max(0, b - self.block)
            now, after = text[a:b], text[a + 1 : b + 1]
            differ = np.flatnonzero(now != after)
            nearest = np.append(differ, b - a)[np.searchsorted(differ, np.arange(b - a))]
            kind = np.append(now < after, self.small[b])
            self.small[a:b] = kind[nearest]

    def _seeds(self) -> np.ndarray:
        """Positions of the seeds, ascending (separators are seeds)."""

        def parts():
            yield np.zeros(1, np.int64)
            for a in range(1, self.size, self.block):
                b = min(a + self.block, self.size)
                yield a + np.flatnonzero(self.small[a:b] & ~self.small[a - 1 : b - 1])

        return self._gathered("seeds", np.int64, parts())

    def _common(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Common prefixes of pairs of suffixes, up to depth; separators differ from each other."""
        out = np.zeros(len(left), np.uint16)
        for s in range(0, len(left), self.block):
            a, b = left[s : s + self.block], right[s : s + self.block]
            done = np.zeros(len(a), np.int64)
            active = np.arange(len(a))
            limit = self.size - 4
            while len(active):
                x, y = a[active] + done[active], b[active] + done[active]
                near = np.maximum(x, y) <= limit
                same = np.zeros(len(active), bool)
                if near.any():
                    p = np.ascontiguousarray(self._four[x[near]]).view(np.uint64).ravel()
                    q = np.ascontiguousarray(self._four[y[near]]).view(np.uint64).ravel()
                    zero = (p - np.uint64(0x0001000100010001)) & ~p & np.uint64(0x8000800080008000)
                    same[near] = (p == q) & (zero == 0)
                done[active[same]] += 4
                active = active[same & (done[active] < self.depth)]
            for _ in range(4):
                x, y = np.minimum(a + done, self.size - 1), np.minimum(b + done, self.size - 1)
                step = (self.text[x] == self.text[y]) & (self.text[x] != 0) & (x != y)
                if not step.any():
                    break
                done += step
            out[s : s + self.block] = np.minimum(done, self.depth)
        return out

    def _push(self, positions: np.ndarray, common: np.ndarray, small: bool, queue: Spools, state: tuple[np.ndarray, np.ndarray]) -> None:
        """Induce from a block of suffixes in scan order; common[k] is with the suffix scanned before k."""
        carry, begun = state
        before = positions - 1
        ok = before >= 0
        before = np.maximum(before, 0)
        symbol = self.text[before]
        k = np.flatnonzero(ok & (symbol != 0) & (self.small[before] == small))
        if len(k):
            target = symbol[k].astype(np.int64)
            order = np.argsort(target, kind="stable")
            k, target = k[order], target[order]
            first = np.concatenate([[True], target[1:] != target[:-1]])
            if self.carrying:
                low = np.where(first, 0, np.concatenate([[0], k[:-1] + 1]))
                least = _range_min(common, low, k)
                least[first] = np.minimum(least[first], carry[target[first]])
                value = np.minimum(least + 1, self.depth).astype(np.uint16)
                value[first] = np.where(begun[target[first]], value[first], 0)
            else:
                value = np.zeros(len(k), np.uint16)
            cuts = np.append(np.flatnonzero(first), len(k))
            np.minimum(carry, common.min(), out=carry)
            tail = np.append(np.minimum.accumulate(common[::-1])[::-1], np.uint16(self.depth))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                c = int(target[a])
                places = before[k[a:b]]
                queue.push(c, places.astype(np.uint32) if self.size < 1 << 32 else places, value[a:b])
                carry[c], begun[c] = tail[k[b - 1] + 1], True
        else:
            np.minimum(carry, common.min(), out=carry)

    def _state(self) -> tuple[np.ndarray, np.ndarray]:
        return np.full(257, self.depth, np.uint16), np.zeros(257, bool)

    def _induce(self, seeds: np.ndarray, common: np.ndarray | None, names: str) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All suffixes but those of separators, from the greatest down, in blocks, each with its common prefix with the one before it in this order. Seeds are in the order of their first symbols."""
        bounds = np.concatenate([[0], np.cumsum(self._symbols(seeds))])
        larger, state = Spools(self.folder, f"{names}-l", self.memory), self._state()
        for c in range(257):
            at, last = 0, None
            while at < larger.size(c):
                end = min(larger.size(c), at + self.block)
                positions, values = larger.read(c, at, end)
                at, last = end, positions[-1:]
                self._push(positions, values, False, larger, state)
            begin, finish = int(bounds[c]), int(bounds[c + 1])
            for a in range(begin, finish, self.block):
                b = min(a + self.block, finish)
                positions, values = np.array(seeds[a:b]), np.zeros(b - a, np.uint16) if common is None else np.array(common[a:b])
                if a == begin:
                    values[0] = self._common(last, positions[:1])[0] if last is not None else 0
                self._push(positions, values, False, larger, state)
        smaller, state = Spools(self.folder, f"{names}-s", self.memory), self._state()
        for c in range(256, 0, -1):
            at, last = 0, None
            while at < smaller.size(c):
                end = min(smaller.size(c), at + self.block)
                positions, values = smaller.read(c, at, end)
                at, last = end, positions[-1:]
                self._push(positions, values, True, smaller, state)
                yield positions, values
            smaller.drop(c)
            end = total = larger.size(c)
            while end > 0:
                a = max(0, end - self.block)
                positions, values = larger.read(c, a, min(end + 1, total))
                values = np.append(values[1:], np.uint16(0)) if end == total else values[1:]
                positions = positions[: end - a][::-1]
                values = values[::-1].copy()
                if end == total and last is not None:
                    values[0] = self._common(last, positions[:1])[0]
                end = a
                self._push(positions, values, True, smaller, state)
                yield positions, values
            larger.drop(c)

    def _symbols(self, seeds: np.ndarray) -> np.ndarray:
        """How many of the seeds begin with each symbol."""
        out = np.zeros(257, np.int64)
        for a, b in self._blocks(len(seeds)):
            out += np.bincount(self.text[seeds[a:b]], minlength=257)
        return out

    def _by_symbol(self, seeds: np.ndarray) -> np.ndarray:
        """The seeds in the order of their first symbols."""
        count = self._symbols(seeds)
        free = np.cumsum(count) - count
        out = self._array("start", np.int64, len(seeds))
        for a, b in self._blocks(len(seeds)):
            some = seeds[a:b]
            symbol = self.text[some]
            order = np.argsort(symbol, kind="stable")
            here = np.bincount(symbol, minlength=257)
            out[np.repeat(free - (np.cumsum(here) - here), here) + np.arange(b - a)] = some[order]
            free += here
        return out

    def _sorted_pairs(self, key: np.ndarray) -> np.ndarray:
        """The order of 64-bit keys: sorted runs on disk, merged block by block."""
        n = len(key)
        if n <= self.block:
            return np.argsort(key, kind="stable")
        out = self._array("order", np.int64, n)
        runs, all_keys, all_places = [], self._array("run-keys", np.int64, n), self._array("run-places", np.int64, n)
        for a, b in self._blocks(n):
            part = np.asarray(key[a:b])
            order = np.argsort(part, kind="stable")
            keys, places = all_keys[a:b], all_places[a:b]
            keys[:], places[:] = part[order], order + a
            runs.append([keys, places, 0])
        step, done = max(1, self.block // len(runs)), 0
        while runs:
            bound = min(int(keys[min(at + step, len(keys)) - 1]) for keys, _, at in runs)
            taken = []
            for r in runs:  # what is below the bound fits into a block
                end = r[2] + int(np.searchsorted(r[0][r[2] :], bound, side="left"))
                taken.append((np.array(r[0][r[2] : end]), np.array(r[1][r[2] : end])))
                r[2] = end
            keys, places = (np.concatenate(x) for x in zip(*taken, strict=True))
            order = np.argsort(keys, kind="stable")
            out[done : done + len(keys)] = places[order]
            done += len(keys)
            for r in runs:  # what equals it may be of any size, and is in order already
                end = r[2] + int(np.searchsorted(r[0][r[2] :], bound, side="right"))
                for a in range(r[2], end, self.block):
                    b = min(a + self.block, end)
                    out[done : done + b - a] = r[1][a:b]
                    done += b - a
                r[2] = end
            runs = [r for r in runs if r[2] < len(r[0])]
        return out

    def _ordered_seeds(self) -> np.ndarray:
        seeds = self._seeds()
        n = len(seeds)
        # names by an induction from seeds in the order of their first symbol
        order = self._array("seed-order", np.int64, n)
        number = self._array("number", np.uint32 if n < 1 << 32 else np.int64, self.size)
        for a, b in self._blocks(n):
            number[seeds[a:b]] = np.arange(a, b)
        at, self.carrying = n, False
        for positions, _ in self._induce(self._by_symbol(seeds), None, "a"):
            previous = np.maximum(positions - 1, 0)
            some = positions[self.small[positions] & ~self.small[previous]]
            order[at - len(some) : at] = number[some][::-1]
            at -= len(some)
        at = 0
        for a, b in self._blocks(n):
            some = a + np.flatnonzero(self.text[seeds[a:b]] == 0)
            order[at : at + len(some)] = some
            at += len(some)
        # equal substrings get equal names; equality by length and a 64-bit hash
        digest = self._digests(seeds)
        # a rank is the place of its group's first member, so groups that are settled need no more work
        first, rank = self._array("first", np.bool_, n + 1), self._array("rank", np.int64, n)
        first[0] = first[n] = True
        for a, b in self._blocks(n - 1):
            here, before = order[a + 1 : b + 1], order[a:b]
            new = self._lengths(seeds, here) != self._lengths(seeds, before)
            first[a + 1 : b + 1] = new | (digest[here] != digest[before]) | (self.text[seeds[here]] == 0) | (self.text[seeds[before]] == 0)
        leader = 0
        for a, b in self._blocks(n):
            leaders = np.maximum.accumulate(np.maximum(np.where(first[a:b], np.arange(a, b), 0), leader))
            rank[order[a:b]] = leaders
            leader = int(leaders[-1])
        places = self._gathered("places0", np.int64, (a + np.flatnonzero(~(first[a:b] & first[a + 1 : b + 1])) for a, b in self._blocks(n)))
        reach = 1
        while len(places) and 2 * reach < self.depth + 2:  # a substring is two symbols long at least, but for those at the ends
            places = self._refined(order, rank, places, reach)
            reach *= 2
        out = self._array("ordered", np.int64, n)
        for a, b in self._blocks(n):
            out[a:b] = seeds[order[a:b]]
        return out

    def _refined(self, order: np.ndarray, rank: np.ndarray, places: np.ndarray, reach: int) -> np.ndarray:
        """One round over the places of groups that are open: order and rank by 2 * reach names; the places that stay open."""
        n, m = len(order), len(places)
        some, key = self._array("some", np.int64, m), self._array("key", np.int64, m)
        for a, b in self._blocks(m):
            now = order[places[a:b]]
            second = np.where(now + reach < n, rank[np.minimum(now + reach, n - 1)] + 1, 0)
            some[a:b], key[a:b] = now, rank[now] * (n + 2) + second
        sorted_ = np.asarray(self._sorted_pairs(key))

        def left():
            leader, last = 0, None
            for a, b in self._blocks(m):
                now, keys = some[sorted_[a:b]], key[sorted_[a : b + 1]]  # one key more, to see whether the last group goes on
                first = np.concatenate([np.array([last is None or keys[0] != last]), keys[1:] != keys[:-1], np.ones(int(b == m), bool)])
                leaders = np.maximum.accumulate(np.maximum(np.where(first[: b - a], np.arange(a, b), 0), leader))
                order[places[a:b]] = now
                rank[now] = places[leaders]
                leader, last = int(leaders[-1]), keys[b - a - 1]
                yield places[a:b][~(first[: b - a] & first[1 : b - a + 1])]

        return self._gathered(f"places{2 * reach}", np.int64, left())

    def _lengths(self, seeds: np.ndarray, which: np.ndarray) -> np.ndarray:
        """Symbols from each of these seeds up to the next one's first (the last seed's end is the text's)."""
        after = np.minimum(which + 1, len(seeds) - 1)
        return np.where(which + 1 < len(seeds), seeds[after], self.size - 1) - seeds[which]

    def _digests(self, seeds: np.ndarray) -> np.ndarray:
        """A hash of the symbols from each seed up to the next one's first."""
        out = self._array("digests", np.uint64, len(seeds))
        a, count = 0, len(seeds)
        while a < count:  # as many seeds as a block of text has, one at least
            limit = min(a + self.block // 4 + 1, count)
            size = max(1, int(np.searchsorted(seeds[a:limit], seeds[a] + self.block)) - 1)
            s = np.array(seeds[a : a + size])
            e = np.append(s[1:], seeds[a + size] if a + size < count else self.size - 1)
            lo, hi = int(s[0]), int(e[-1]) + 1
            length = e - s  # the seed at the end is added apart, so that the ranges don't overlap
            place = np.arange(hi - lo - 1) - np.repeat(s - lo, length) if hi - lo > 1 else np.zeros(0, np.int64)
            powers = np.ones(int(length.max(initial=0)) + 2, np.uint64)
            powers[1:] = np.uint64(0x9E3779B97F4A7C15)
            powers = np.multiply.accumulate(powers)
            symbols = np.asarray(self.text[lo:hi]).astype(np.uint64) + np.uint64(1)
            sums = np.zeros(len(s), np.uint64)
            some = length > 0
            if some.any():
                sums[some] = np.add.reduceat(symbols[:-1] * powers[place], (s - lo)[some])
            sums += symbols[e - lo] * powers[length]
            sums ^= sums >> np.uint64(31)
            out[a : a + len(s)] = sums * np.uint64(0xBF58476D1CE4E5B9)
            a += len(s)
        return out

    def suffixes(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Blocks of (position, common prefix with the suffix before in this order, at most depth), from the greatest suffix down."""
        seeds = self._ordered_seeds()
        self.carrying = True
        common = self._array("common", np.uint16, len(seeds))
        for a, b in self._blocks(len(seeds) - 1):
            common[a + 1 : b + 1] = self._common(seeds[a:b], seeds[a + 1 : b + 1])
        yield from self._induce(seeds, common, "b")

    def repeated(self) -> np.ndarray:
        """Marks of the positions whose first `depth` symbols also begin at another position."""
        marks = self._array("marks", np.bool_, self.size)
        last = None
        if self.size <= 1:
            return marks
        for positions, common in self.suffixes():
            deep = common >= self.depth
            marks[positions[deep]] = True
            at = np.flatnonzero(deep)
            if len(at) and at[0] == 0 and last is not None:
                marks[last] = True
            marks[positions[at[at > 0] - 1]] = True
            last = positions[-1]
        return marks
