"""Operators over a whole table: mixing, neighbours, near duplicates, WARC, suffix deduplication, chat, pipeline."""

import hashlib
import io
import itertools
import random
import re
from collections import Counter

import numpy as np
import pytest

from lattica.llm import chat, mixing, near_duplicates, neighbours, suffix_dedup, warc
from lattica.llm.common import workspace
from lattica.llm.components import components
from lattica.llm.induced_sort import InducedSorter

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def table(spark, texts, sources=None):
    rows = [(i, t, "en", sources[k] if sources else "s", len(t or "")) for k, (i, t) in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def words(rng, n):
    return " ".join("".join(rng.choice("abcdefgh") for _ in range(4)) for _ in range(n))


# ---- mixing


def test_targets():
    weights = mixing.weights_of(["b", None, "a", "c"])
    assert weights == {"a": 5, "b": 2, "c": 1, None: 5}
    assert mixing.targets_of({"a": 10, "b": 1000}, {"a": 5, "b": 2}) == {"a": 30.0, "b": 980.0}
    assert mixing.targets_of({"a": 0, "b": 7}, {"a": 5, "b": 2}) == {"a": 0.0, "b": 7.0}


@pytest.mark.parametrize("n", [1, 2, 3, 17, 1000])
def test_permutation(n):
    images = mixing.permuted(np.arange(n), n, [3, 5, 7, 9])
    assert sorted(images.tolist()) == list(range(n)) and mixing.permuted(images, n, [3, 5, 7, 9], back=True).tolist() == list(range(n))


def mix_case():
    rng = random.Random(1)
    texts = [(i, words(rng, rng.choice([0, 1, 30, 400, 3000]))) for i in range(60)] + [(None, "a b c"), (5, None), (7, "same text"), (7, "same text")]
    return texts, [rng.choice(["x", "y", None, "z"]) for _ in texts]


def test_draws():
    sizes = mixing.group_sizes(100_000, 1024, 16)
    assert sum(sizes) == 100_000 and sizes[-1] <= mixing.LAST and len(sizes) < 16 + 20 and mixing.group_sizes(0, 8, 4) == []
    owed = [50_000.0, 30_000.0, 20_000.0, 0.0]
    rows = [mixing.drawn_counts(owed, [60_000, 60_000, 20_000, 9], sizes, seed) for seed in (1, 2)]
    for r in rows:
        assert r.sum(1).tolist() == sizes and (r.sum(0) <= [60_000, 60_000, 20_000, 9]).all() and np.abs(r.sum(0) - owed).max() <= 16
        assert np.abs(r[0] / sizes[0] - [0.5, 0.3, 0.2, 0]).max() < 0.03
    assert (rows[0] != rows[1]).any() and (rows[0].sum(0) != rows[1].sum(0)).any()
    shards = mixing.shards_of(rows[0][0], 1024, [1, 0])
    assert shards.sum(0).tolist() == rows[0][0].tolist() and (shards.sum(1)[:-1] == 1024).all()


def test_mix(spark):
    texts, sources = mix_case()
    docs = table(spark, texts, sources)
    options = {"block": 16, "shard_slots": 64, "draws": 8}
    rows = mixing.taken(docs, **options).collect()
    assert len(rows) == len(texts) and sorted(map(str, rows)) == sorted(map(str, mixing.taken(docs, **options).collect()))
    total, targets = Counter(), {}
    for r in rows:
        assert 0 <= r["taken"] <= 3 * r["size"]
        total[r["source"]] += r["taken"]
        targets[r["source"]] = r["target"]
    assert all(abs(total[s] - t) <= 20 * 16 for s, t in targets.items())
    assert sorted(map(str, rows)) != sorted(map(str, mixing.taken(docs, **options, seed=5).collect()))
    mixed = mixing.mixed_documents(docs, **options)
    assert mixed.columns == docs.columns
    by = Counter()
    for r in mixed.collect():
        by[r["source"]] += len(r["text"].split())
        assert r["n_chars"] == len(r["text"])
    assert by == +total
    slots = mixing.packed(docs, **options).collect()
    assert sum(len(r["text"].split()) for r in slots) == sum(r["n_words"] for r in slots) == sum(total.values())
    assert max(r["n_words"] for r in slots) == 16 and len({(r["group"], r["shard"], r["place"]) for r in slots}) == len(slots)
    for empty in (docs.limit(0),):
        assert mixing.taken(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0 and mixing.packed(empty).count() == 0


def test_mix_row_by_row(spark):
    """Streams, blocks, draws and permutations followed word by word in plain Python, on the same order of documents."""
    texts, sources = mix_case()
    docs, block, seed = table(spark, texts, sources), 16, mixing.SEED
    layout, plans = mixing.laid_out(docs, block=block)
    placed = sorted(((r["source"], r["begin"], r["size"], r["doc_id"]) for r in layout.collect() if r["size"]), key=lambda r: (r[0] or "", r[0] is None, r[1]))
    streams = {}
    for source, begin, size, doc_id in placed:
        stream = streams.setdefault(source, [])
        assert begin == len(stream)  # documents tile their source's stream
        stream += [(doc_id, begin)] * size
    want = Counter()
    sizes = mixing.group_sizes(round(sum(p.owed for p in plans)), 64, 8)
    counts = mixing.drawn_counts([p.owed for p in plans], [3 * p.blocks for p in plans], sizes, seed).sum(0)
    for p, n in zip(plans, counts.tolist(), strict=True):
        for slot in range(n):
            b = int(mixing.permuted(np.array([slot % p.blocks]), p.blocks, mixing._keys(p.source, slot // p.blocks, seed))[0])
            for doc_id, begin in streams[p.source][b * block : (b + 1) * block]:
                want[p.source, doc_id, begin] += 1
    mix = mixing.segments(layout, plans, block, seed, 64, 8)
    got = Counter()
    for r in mix.collect():
        got[r["source"], r["doc_id"], r["begin"]] += r["n_words"]
    assert got == want


# ---- neighbours


def test_recall_and_unusable_vectors(spark):
    rng = np.random.default_rng(3)
    data = rng.normal(size=(900, 24)).astype(np.float32)
    data[300:500] = data[300] + 0.01 * rng.normal(size=(200, 24))
    rows = [(i, v.tolist(), 0) for i, v in enumerate(data)]
    rows += [(2000, None, 0), (2020, [0.0] * 24, 0), (2040, [float("nan")] * 24, 0), (2060, [None] * 24, 0), (2080, [1.0, 2.0], 0), (None, [1.0] * 24, 0), (2100, [], 0)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int")
    got = neighbours.nearest(df, df["vec_id"] % 20 == 0, 20, shard_rows=300).collect()
    by = {}
    for r in sorted(got, key=lambda r: (r["query_id"], r["rank"])):
        by.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert set(by) == set(range(0, 900, 20))
    hits = 0
    exact = data.astype(np.float64) @ data.astype(np.float64).T
    for q, found in by.items():
        assert len(found) == 20 and q not in [v for v, _ in found] and found == sorted(found, key=lambda x: (-x[1], x[0]))
        assert all(abs(s - exact[q, v]) < 1e-9 for v, s in found)
        exact[q, q] = -np.inf
        hits += sum(s >= np.sort(exact[q])[-20] - 1e-9 for _, s in found)
    assert hits / (20 * len(by)) >= 0.9
    assert neighbours.nearest(df.limit(0), df["vec_id"] % 20 == 0).count() == 0
    few = neighbours.nearest(df.where("vec_id < 5"), df["vec_id"] == 0).collect()
    assert [r["rank"] for r in sorted(few, key=lambda r: r["rank"])] == [1, 2, 3, 4]


def shard_recall(data, k=20):
    """Recall of one shard against all inner products."""
    ids, data = np.arange(len(data)), data.astype(np.float64)
    graph, entry = neighbours.packed_graph(data)
    asked = ids[::20]
    row = {"width": data.shape[1], "ids": ids.tobytes(), "vectors": data.tobytes(), "graph": graph, "entry": entry, "q_ids": asked.tobytes(), "q_vectors": data[asked].tobytes()}
    exact = data[asked] @ data.T
    exact[np.arange(len(asked)), asked] = -np.inf
    least = dict(zip(asked.tolist(), np.sort(exact, 1)[:, -k], strict=True))
    got = [(r["query_id"], r["vec_id"], r["score"]) for b in neighbours._answers(row, k, neighbours.SEARCH_BEAM) for r in b.to_pylist()]
    assert len(got) == len({x[:2] for x in got}) == k * len(asked) and all(q != v for q, v, _ in got)
    return sum(s >= least[q] - 1e-9 * abs(least[q]) for q, _, s in got) / len(got)


@pytest.mark.parametrize("kind", ["unit", "gaussian", "unequal", "outlier", "copies"])
def test_recall_of_a_large_shard(kind):
    rng = np.random.default_rng(4)
    data = rng.normal(size=(4096, 64))
    if kind != "gaussian":
        data /= np.sqrt((data**2).sum(1))[:, None]
    if kind == "unequal":
        data *= np.exp(rng.normal(size=(4096, 1)))
    if kind == "outlier":
        data[77] *= 1e4
    if kind == "copies":
        data[rng.permutation(4096)[:1400]] = data[5]
    assert shard_recall(data) >= 0.95


@pytest.mark.parametrize("kind", ["many", "one", "near"])
def test_recall_with_copies(kind):
    rng = np.random.default_rng(0)
    data = rng.normal(size=(2400, 32)).astype(np.float32)
    data[1600:] = data[rng.integers(0, 20, 800)] if kind == "many" else data[5]
    data = data.astype(np.float64)
    if kind == "near":
        data[1600:] += 1e-9 * rng.normal(size=(800, 32))
    assert shard_recall(data[rng.permutation(2400)]) >= 0.93


def test_copies_are_ordered_by_id(spark):
    rows = [(i % 50, [1.0, 2.0]) for i in range(200)] + [(1000, [1.0, 2.0])] + [(2000 + i, [0.5, 0.5]) for i in range(5)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = {q: [r["vec_id"] for r in sorted(neighbours.nearest(df, df["vec_id"] == q, 18).collect(), key=lambda r: r["rank"])] for q in (1000, 2000)}
    assert got[1000] == [0] * 4 + [1] * 4 + [2] * 4 + [3] * 4 + [4] * 2 and got[2000] == got[1000]


# ---- near duplicates


def brute_classes(texts):
    def shingles(text):
        found = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        return {tuple(found[i : i + 5]) for i in range(max(len(found) - 4, 1))} if found else set()

    sets = [shingles(t) for _, t in texts]
    links, parent = Counter(), list(range(len(texts)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(range(len(texts)), 2):
        if sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
            links[a] += 1
            links[b] += 1
            parent[max(find(a), find(b))] = min(find(a), find(b))
    out = []
    for i, (doc_id, _) in enumerate(texts):
        ids = [texts[k][0] for k in range(len(texts)) if find(k) == find(i) and texts[k][0] is not None]
        out.append((doc_id, (min(ids) if ids else None) if sets[i] else doc_id, links[i]))
    return sorted(out, key=str)


def near_case():
    rng = random.Random(2)
    base = words(rng, 200).split()
    texts = [(0, None), (1, ""), (2, "a b"), (3, "a b"), (4, "a  b"), (None, "null id"), (5, words(rng, 50)), (5, words(rng, 50))]
    for i in range(10, 60):  # a group of near copies, larger than a block
        copy = list(base)
        copy[rng.randrange(200)] = "edit" + str(i)
        texts.append((i, " ".join(copy)))
    texts += [(i, " ".join(base)) for i in range(60, 90)]
    for i in range(100, 140):
        copy = list(base[:100])
        for _ in range(rng.randint(0, 12)):
            copy[rng.randrange(100)] = words(rng, 1)
        texts.append((i, " ".join(copy)))
    return texts


def test_near_duplicates(spark):
    texts = near_case()
    for forest in (near_duplicates.Forest(block=16, connected=20), near_duplicates.Forest(block=16)):
        got = sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in near_duplicates.joined(table(spark, texts), forest).collect()), key=str)
        assert got == brute_classes(texts)
    assert near_duplicates.joined(table(spark, texts).limit(0)).count() == 0
    kept = near_duplicates.kept(table(spark, texts), forest)
    assert kept.columns == SCHEMA.replace(",", "").split()[::2]
    ids = {r["doc_id"] for r in kept.collect()}
    assert ids == {c for d, c, _ in brute_classes(texts) if d is not None} | {None}


def test_forest_levels():
    f = near_duplicates.Forest()
    assert f.recall_at(f.first) >= f.floor > f.recall_at(f.first + 1)
    low, high = np.zeros(near_duplicates.STEPS, int), np.zeros(near_duplicates.STEPS, int)
    low[0], high[-5] = 1000, 1000
    assert f.reached(f.first, high) >= f.recall > f.reached(f.first, low)  # pairs near the threshold ask for shorter prefixes
    assert f.reached(f.first - 1, low) > f.reached(f.first, low)
    with pytest.raises(ValueError):
        near_duplicates.Forest(deepest=11)


def test_signatures_share_prefixes_as_often_as_sets_do():
    rng = np.random.default_rng(2)
    f, hits, n = near_duplicates.Forest(), 0, 60
    for _ in range(n):
        a = rng.integers(0, 1 << 63, 400).astype(np.uint64)
        b = np.concatenate([a[:360], rng.integers(0, 1 << 63, 40).astype(np.uint64)])
        x, y = near_duplicates.signatures([np.unique(a), np.unique(b)], f).view(np.int64) >> f.shift(6)
        hits += int((x == y).sum())
    expected = n * f.trees * (360 / 440) ** 6
    assert abs(hits - expected) < 6 * expected**0.5


def test_components(spark):
    rng = random.Random(9)
    edges = [(rng.randrange(400), rng.randrange(400)) for _ in range(260)] + [(i, i + 1) for i in range(1000, 1040)]
    got = {r["node"]: r["label"] for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        parent[find(a)] = find(b)
    same = {}
    for a, b in edges:
        if a != b:
            same.setdefault(find(a), set()).add(got[a])
            same[find(a)].add(got[b])
    assert all(len(v) == 1 for v in same.values()) and len({next(iter(v)) for v in same.values()}) == len(same)


# ---- WARC


def test_archives(spark):
    big = "<html>" + "pay load " * 5000
    rows = [(3, "http://a/3", big), (1, "http://a/ü", big), (2, None, None), (4, "u", ""), (5, "u", "short"), (6, "u", "short"), (None, "u", big), (7, "u", "y" * 100), (8, "u", "y" * 100)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    path = workspace(spark, "warc")
    names = warc.write(warc.deduplicated(pages), path, warc.sample_of(pages))
    got = {r["page_id"]: r for r in warc.read(spark, path, names).collect()}
    assert len(got) == len(rows)
    for page_id, _, html in rows:
        raw = (html or "").encode()
        assert got[page_id]["payload_bytes"] == len(raw) and got[page_id]["payload_digest"] == hashlib.sha256(raw).hexdigest()
        assert got[page_id]["payload"] == (raw if got[page_id]["record_type"] == "response" else None)
    assert {k: r["refers_to"] for k, r in got.items() if r["record_type"] == "revisit"} == {3: 1, None: 1, 8: 7}
    none = pages.limit(0)
    assert warc.write(warc.deduplicated(none), workspace(spark, "warc"), warc.sample_of(none)) == []


def test_bad_archives():
    import struct

    import zstandard

    digest = hashlib.sha256(b"abc").hexdigest()
    raw = warc.record_bytes(1, "u", b"abc", 3, digest, "response", None)
    trained = b"dictionary text " * 50
    packer = zstandard.ZstdCompressor(dict_data=zstandard.ZstdCompressionDict(trained))
    whole = struct.pack("<II", warc.DICTIONARY_FRAME, len(trained)) + trained + packer.compress(raw) + packer.compress(raw)
    assert list(warc.frames(io.BytesIO(whole))) == [raw, raw]
    assert warc.described(warc.parsed(raw))["payload"] == b"abc"
    for cut in (whole[:-3], whole[:20]):
        with pytest.raises(warc.ArchiveError):
            list(warc.frames(io.BytesIO(cut)))
    bad = [raw[:-1], raw.replace(b"abc", b"abd"), raw.replace(b"WARC/1.1", b"WARC/9.9"), raw.replace(b"WARC-Date", b"WARC-Type"), raw.replace(b"Content-Length: 3", b"Content-Length: 4")]
    for r in bad:
        with pytest.raises(warc.ArchiveError):
            warc.described(warc.parsed(r))


# ---- suffix deduplication


def brute_marks(segments, depth):
    seen = Counter(s[i : i + depth] for s in segments for i in range(len(s) - depth + 1))
    out = [False]
    for s in segments:
        out += [i + depth <= len(s) and seen[s[i : i + depth]] > 1 for i in range(len(s))] + [False]
    return out


@pytest.mark.parametrize("seed", range(60))
def test_induced_sort(seed):
    rng = random.Random(seed)
    depth, letters = rng.choice([1, 2, 3, 5, 20]), bytes(rng.sample(range(256), rng.choice([1, 2, 3, 10])))
    segments = [bytes(rng.choice(letters) for _ in range(rng.choice([1, 2, 10, 60]))) for _ in range(rng.choice([1, 5, 20]))]
    segments += [rng.choice(segments)[rng.randrange(3) :] or b"x" for _ in range(4)]
    with InducedSorter(None, depth, block=rng.choice([7, 64, 1 << 20]), memory=rng.choice([64, 1000, 1 << 26])) as s:
        s.load(segments)
        assert s.repeated().tolist() == brute_marks(segments, depth)
        found = list(s.suffixes())
        order = np.concatenate([p for p, _ in found])[::-1]
        assert sorted(order.tolist()) == [i for i in range(s.size) if s.text[i] != 0]


@pytest.mark.parametrize("kind", ["prose", "one letter", "copies"])
def test_induced_sort_holds_no_more_than_its_bound(kind):
    import tracemalloc

    rng = np.random.default_rng(5)
    letters = np.frombuffer(b"etaoin shrdlu", np.uint8)

    def segments(n):
        some = letters[rng.integers(0, len(letters), 1000)].tobytes()
        for _ in range(n):
            yield b"ab" * 500 if kind == "one letter" else some if kind == "copies" else letters[rng.integers(0, len(letters), 1000)].tobytes()

    most = []
    for n in (500, 2000):
        with InducedSorter(None, 20, block=1 << 13, memory=1 << 18) as s:
            s.load(segments(n))
            tracemalloc.start()
            for _ in s.suffixes():
                pass
            most.append(tracemalloc.get_traced_memory()[1])
            tracemalloc.stop()
    assert most[1] < 1.5 * most[0] and most[1] < 6 << 20, most


@pytest.mark.parametrize("common", [1, 8, suffix_dedup.COMMON])
def test_suffix_dedup(spark, monkeypatch, common):
    # 1: no segment is common; 8: some are; else all that occur twice
    monkeypatch.setattr(suffix_dedup, "COMMON", common)
    rng = random.Random(8)
    shared = words(rng, 80)
    texts = [(1, None), (2, ""), (3, "short"), (4, "a" * 500), (5, "ab" * 101), (6, "é" * 150), (None, "é" * 150), (7, words(rng, 30) + shared + words(rng, 30)), (8, words(rng, 3) + shared + "tail"), (9, words(rng, 400)), (10, "x" * 200), (10, "x" * 200), *((20 + i, shared) for i in range(12))]
    raw = [(t or "").encode() for _, t in texts]
    seen = Counter(b[i : i + 200] for b in raw for i in range(len(b) - 199))
    want = []
    for (doc_id, _), b in zip(texts, raw, strict=True):
        gone = {i + k for i in range(len(b) - 199) if seen[b[i : i + 200]] > 1 for k in range(200)}
        spans = sum(1 for i in gone if i - 1 not in gone)
        want.append((doc_id, len(b), len(gone), spans, hashlib.sha256(bytes(x for i, x in enumerate(b) if i not in gone)).hexdigest()))
    docs = table(spark, texts)
    assert sorted(map(str, map(tuple, suffix_dedup.digests(docs).collect()))) == sorted(map(str, want))
    left = {r["doc_id"]: r for r in suffix_dedup.removed(docs).collect()}
    assert 4 not in left and left[3]["text"] == "short" and left[1]["text"] is None and shared not in left[7]["text"] and left[7]["n_chars"] == len(left[7]["text"])
    assert suffix_dedup.digests(docs.limit(0)).count() == 0


@pytest.mark.parametrize("levels", [1, 2, 4])
def test_divided_windows_keep_equal_ones_together(levels):
    rng = random.Random(levels)
    shared = words(rng, 70).encode()
    keys, runs = {}, 0
    for _ in range(30):
        raw = words(rng, rng.randrange(60)).encode() + shared[rng.randrange(60) :] + words(rng, rng.randrange(60)).encode() + b"ab" * rng.randrange(120)
        if len(raw) < 200:
            continue
        parts = suffix_dedup.divided(raw, 77, levels)
        assert [p[0] for p in parts] == np.cumsum([0, *(p[1] for p in parts)])[:-1].tolist() and sum(p[1] for p in parts) == len(raw) - 199
        runs += len(parts)
        for begin, n, key in parts:
            for i in range(begin, begin + n):
                assert keys.setdefault(raw[i : i + 200], key) == key
    assert runs > 60


def test_suffix_dedup_divides_hot_passages(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT_SEGMENTS", 2)
    rng = random.Random(6)
    shared = words(rng, 70)
    texts = [(i, words(rng, rng.randrange(5, 40)) + " " + shared[: rng.choice([260, 300, 349])] + words(rng, rng.randrange(5, 40))) for i in range(40)]
    raw = [t.encode() for _, t in texts]
    seen = Counter(b[i : i + 200] for b in raw for i in range(len(b) - 199))
    want = {i: len({x + k for x in range(len(b) - 199) if seen[b[x : x + 200]] > 1 for k in range(200)}) for (i, _), b in zip(texts, raw, strict=True)}
    assert {r["doc_id"]: r["n_removed"] for r in suffix_dedup.digests(table(spark, texts)).collect()} == want


def test_whole_characters():
    raw = "aéb".encode()
    assert suffix_dedup.whole_characters(raw, [[2, 4]]) == [[3, 4]] and suffix_dedup.whole_characters(raw, [[0, 2]]) == [[0, 1]]


# ---- chat


def test_chat(spark):
    rows = []
    for conv, turns in {1: "ab", 2: "abc", 3: "abc", 4: "abd", 5: "x", 6: "a"}.items():
        rows += [(conv, i, "user" if i % 2 == 0 else "assistant", t) for i, t in enumerate(turns)]
    rows += [(7, 0, None, None), (None, 0, "user", "q"), (8, None, "user", "z"), (8, 300, "user", "zz"), (9, 0, "user", "z")]
    turns = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    out = {r["conv_id"]: r for r in chat.formatted(turns).collect()}
    assert set(out) == {2, 4, 5, 7, 8, None} and out[2]["n_copies"] == 2
    assert out[2]["rendered"] == "<|user|>\na\n<|end|>\n<|assistant|>\nb\n<|end|>\n<|user|>\nc\n<|end|>\n"
    assert "Python" not in chat.formatted(turns)._jdf.queryExecution().executedPlan().toString()
    assert chat.formatted(turns.limit(0)).count() == 0


def test_long_conversation(spark):
    long = [(1, i, "user", f"t{i}") for i in range(700)]
    turns = spark.createDataFrame(long + [(2, i + 5, "user", f"t{i}") for i in range(600)], "conv_id bigint, turn bigint, role string, text string")
    out = chat.formatted(turns).collect()
    assert [(r["conv_id"], r["n_turns"]) for r in out] == [(1, 700)]


# ---- pipeline


def test_pipeline(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(11)
    prose = ["the", "of", "and", "to", *words(rng, 60).split()]
    texts = [(i, " ".join(rng.choice(prose) for _ in range(rng.choice([40, 120])))) for i in range(40)]
    texts += [(100 + i, texts[i][1]) for i in range(5)] + [(200, "too short"), (201, None)]
    table(spark, texts, [f"s{i % 3}" for i in range(len(texts))]).write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for name, stage in corpus_pipeline.STAGES[:2]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == SCHEMA.replace(",", "").split()[::2], name
    assert {r["doc_id"] for r in docs.collect()} == set(range(40))
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert out and {r["doc_id"] for r in out} <= set(range(40)) and all(r["n_tokens"] == len(r["ids"]) for r in out)


def test_repeated_rows_and_ids_keep_one_text(spark):
    rng = random.Random(12)
    a, b, c, d, e = (words(rng, 100) for _ in range(5))
    near = a.rsplit(" ", 1)[0] + " other"
    texts = [(1, a), (2, near), (2, b), (3, c), (3, c), (3, c), (None, d), (None, d), (None, e), (4, e), (5, None), (5, None), (6, b.replace(" ", "  "))]
    docs = table(spark, texts)
    first = near_duplicates.kept(docs)
    want = sorted([(1, a), (2, b), (3, c), (None, d), (4, e), (5, None), (5, None)], key=str)
    assert sorted(((r["doc_id"], r["text"]) for r in first.collect()), key=str) == want
    left = suffix_dedup.removed(first)
    assert sorted(((r["doc_id"], r["text"]) for r in left.collect()), key=str) == want


def test_stages_on_odd_rows(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, columns with names that stages use inside."""
    import corpus_pipeline

    rng = random.Random(21)
    long = " ".join("the " + words(rng, 8) for _ in range(4000))
    prose = ["the " + " and the ".join(words(rng, 6) for _ in range(8)) for _ in range(4)]
    texts = [(None, None), (None, prose[0]), (1, prose[1]), (1, prose[1]), (2, prose[1]), (3, ""), (4, " \n\t"), (5, long), (6, prose[2]), (7, prose[3])]
    sources = [None, "a", "a", "a", "b", None, "b", None, "b", "a"]
    docs = table(spark, texts, sources)
    for more in ("row", "key", "mark", "id", "place", "parts", "_words", "begin", "copy", "label", "size", "block"):
        docs = docs.withColumn(more, docs["doc_id"] + 1)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, "")
        rows = out.collect()
        assert out.columns == docs.columns, name
        got = {r["doc_id"] for r in rows}
        if name in ("quality_rules", "source_mix"):
            assert {5, 6, 7} <= got and not {3, 4} & got, name
        if name == "near_duplicate_join":
            assert sorted(map(str, (r["doc_id"] for r in rows))) == sorted(map(str, [None, None, 1, 3, 4, 5, 6, 7]))
        if name == "repeated_strings":
            assert {3, 4, 5, 6, 7} <= got and next(r["text"] for r in rows if r["doc_id"] == 5) == long
        assert all(r["key"] == (None if r["doc_id"] is None else r["doc_id"] + 1) for r in rows), name
        assert stage(spark, docs.limit(0), "").count() == 0
    ids = corpus_pipeline.STAGES[-1][1](spark, docs, "")
    assert ids.count() == len(texts) and ids.where("n_tokens = 0").count() == 2
    assert corpus_pipeline.STAGES[-1][1](spark, docs.limit(0), "").count() == 0
