"""Approximate nearest neighbours by inner product: robust-pruned directed graphs for each shard.

Vectors are dealt by hash into shards of bounded bytes, and within a shard into ranges of nearly equal length, by the factor
NORM_STEP. In a range, points are inserted in batches: greedy searches from the entry point propose neighbours, pruning keeps a neighbour only if no nearer one already kept is closer to it by the
factor alpha, and edges are also added backwards and pruned again where a point has too many. A second pass with the
relaxed factor makes long edges. Inner products become distances by one more coordinate, sqrt(m^2 - |x|^2), which stays small as lengths in a
range differ little. Ranges of up to SCANNED points need no graph: they are compared whole, neighbouring ranges together. All searches
of a batch move in step, as numpy arrays. Rows whose vectors agree in single precision are one point of the graph, so that
copies take no edges from each other; a point that is found stands for all its rows. Every shard answers every block of queries by beam search, in one row of an
equi-join on the shard's number: its ranges are searched from the longest vectors down, and a range is left out for queries whose
results so far no vector of its length can better. The answers are ranked again by exact inner products in double precision.

Defined results: vectors that are null, zero, or hold nulls or non-finite values, and rows with a null id, take no part;
vectors of another length are no candidates of a query; rows that share the query's id are not its candidates; equal
scores are ordered by id; fewer candidates than asked for give fewer rows; an empty table gives no rows; repeated rows
count one by one; other columns are not used.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import saved, ship

#: A shard's vectors have so many bytes at most in double precision (16,384 rows of 64 numbers).
SHARD_BYTES = 8 << 20
DEGREE, BUILD_BEAM, SEARCH_BEAM, ALPHA, QUERY_BLOCK = 32, 64, 192, 1.2, 2048
#: Lengths within a range differ by this factor at most; so many points are compared without a graph.
NORM_STEP, SCANNED = 1.15, 512
_BATCH, _WIDTH, _ROWS = 256, 4, 1 << 16


def beam_search(data: np.ndarray, graph: np.ndarray, entry: int, queries: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and squared distances of the `beam` nearest found for each query, nearest first (-1 where there are none).

    graph[i] holds the neighbours of i, padded by i itself.
    """
    q, n = len(queries), len(data)
    seen = np.zeros((q, n), bool)
    mark = np.zeros((q, n), np.int32)
    row = np.arange(q)
    ids = np.full((q, beam), -1, np.int64)
    dist = np.full((q, beam), np.inf, np.float32)
    open_ = np.zeros((q, beam), bool)
    norms, own = (data**2).sum(1), (queries**2).sum(1)
    ids[:, 0], open_[:, 0], seen[:, entry] = entry, True, True
    dist[:, 0] = norms[entry] + own - 2 * queries @ data[entry]
    active = row
    while len(active):
        # the nearest unexpanded points of each beam; beams are sorted, so they are the first open ones
        rank = np.cumsum(open_[active], axis=1)
        chosen = open_[active] & (rank <= _WIDTH)
        who, where = np.nonzero(chosen)
        open_[active[who], where] = False
        step = np.full((len(active), _WIDTH), -1, np.int64)
        step[who, rank[who, where] - 1] = ids[active[who], where]
        step = np.where(step < 0, step[:, :1], step)
        new = graph[step].reshape(len(active), -1)
        rows = active[:, None]
        place = np.broadcast_to(np.arange(new.shape[1], dtype=np.int32), new.shape)
        mark[rows, new] = place
        fresh = ~seen[rows, new] & (mark[rows, new] == place)
        seen[rows, new] = True
        who, where = np.nonzero(fresh)
        points = new[who, where]
        near = np.full(new.shape, np.inf, np.float32)
        near[who, where] = norms[points] + own[active[who]] - 2 * np.einsum("ij,ij->i", data[points], queries[active[who]])
        all_d = np.concatenate([dist[active], near], axis=1)
        all_i = np.concatenate([ids[active], np.where(fresh, new, -1)], axis=1)
        all_o = np.concatenate([open_[active], fresh], axis=1)
        order = np.argpartition(all_d, beam - 1, axis=1)[:, :beam]
        order = np.take_along_axis(order, np.argsort(np.take_along_axis(all_d, order, 1), axis=1, kind="stable"), 1)
        dist[active], ids[active], open_[active] = (np.take_along_axis(x, order, 1) for x in (all_d, all_i, all_o))
        active = active[open_[active].any(axis=1)]
    return ids, dist


def robust_prune(data: np.ndarray, points: np.ndarray, candidates: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """The kept neighbours of each point, padded by the point itself. Candidates: ids, -1 for none; the point itself and repeats are left out."""
    candidates = np.where(candidates == points[:, None], -1, candidates)
    order = np.argsort(candidates, axis=1, kind="stable")
    candidates = np.take_along_axis(candidates, order, 1)
    candidates[:, 1:][candidates[:, 1:] == candidates[:, :-1]] = -1
    vectors = data[candidates] - data[points][:, None, :]  # seen from the point, so that rounding is small where distances are
    dist = (vectors**2).sum(-1)
    dist[candidates < 0] = np.inf
    order = np.argsort(dist, axis=1, kind="stable")
    candidates, dist = np.take_along_axis(candidates, order, 1), np.take_along_axis(dist, order, 1)
    vectors = np.take_along_axis(vectors, order[:, :, None], 1)
    own = (vectors**2).sum(-1)
    between = own[:, :, None] + own[:, None, :] - 2 * vectors @ vectors.transpose(0, 2, 1)
    alive = np.isfinite(dist)
    out = np.repeat(points[:, None], degree, 1)
    row = np.arange(len(points))
    for k in range(degree):
        first = alive.argmax(axis=1)
        ok = alive[row, first]
        if not ok.any():
            break
        out[ok, k] = candidates[row[ok], first[ok]]
        alive[row, first] = False
        alive &= ~(ok[:, None] & (alpha * alpha * between[row, first] <= dist))
    return out


def build(data: np.ndarray, degree: int = DEGREE, beam: int = BUILD_BEAM, alpha: float = ALPHA, seed: int = 1) -> tuple[np.ndarray, int]:
    """The graph of a shard and its entry point."""
    n = len(data)
    rng = np.random.default_rng(seed)
    entry = int(((data - data.mean(0)) ** 2).sum(1).argmin())
    graph = rng.integers(0, n, (n, degree)) if n > 1 else np.zeros((1, degree), np.int64)
    beam = min(beam, n)
    for factor in (1.0, alpha):
        order = rng.permutation(n)
        for a in range(0, n, _BATCH):
            points = order[a : a + _BATCH]
            found, _ = beam_search(data, graph, entry, data[points], beam)
            graph[points] = robust_prune(data, points, np.concatenate([found, graph[points]], 1), degree, factor)
            target, source = graph[points].ravel(), np.repeat(points, degree)
            target, source = target[target != source], source[target != source]
            by = np.argsort(target, kind="stable")
            target, source = target[by], source[by]
            heads, first, count = np.unique(target, return_index=True, return_counts=True)
            for size in np.unique(np.minimum(count, _BATCH)):  # points with as many new edges go together
                at = np.flatnonzero(np.minimum(count, _BATCH) == size)
                more = source[first[at][:, None] + np.arange(size)]
                for b in range(0, len(at), _BATCH):
                    some = heads[at[b : b + _BATCH]]
                    graph[some] = robust_prune(data, some, np.concatenate([graph[some], more[b : b + _BATCH]], 1), degree, factor)
    return graph, entry


def lifted(vectors: np.ndarray) -> np.ndarray:
    """Vectors with one more coordinate, so that all have the same length and near means a large inner product."""
    square = (vectors.astype(np.float64) ** 2).sum(1)
    return np.concatenate([vectors, np.sqrt(np.maximum(square.max() - square, 0))[:, None]], 1).astype(np.float32)


def alike(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first row of each distinct vector, and the number of each row's vector among them."""
    plain = np.ascontiguousarray(vectors + vectors.dtype.type(0))  # one zero only
    _, first, number = np.unique(plain.view(np.dtype((np.void, plain.itemsize * plain.shape[1]))).ravel(), return_index=True, return_inverse=True)
    return first, number.ravel()


def points_of(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The points of a shard's graph and each row's point."""
    first, number = alike(vectors.astype(np.float32))
    return vectors[first], number


def ranges_of(points: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int, bool]]]:
    """The order of the points from the longest down, and the ranges in it: begin, end, and whether it has a graph."""
    norm = np.sqrt((points**2).sum(1))
    order = np.argsort(-norm, kind="stable")
    step = np.floor(np.log(norm[order]) / np.log(NORM_STEP))
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(step)) + 1, [len(order)]]).tolist()
    out: list[tuple[int, int, bool]] = []
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        if out and not out[-1][2] and b - out[-1][0] <= SCANNED:
            out[-1] = (out[-1][0], b, False)
        else:
            out.append((a, b, b - a > SCANNED))
    return order, out


def packed_graph(vectors: np.ndarray, *options) -> tuple[bytes, bytes]:
    """The graphs over a shard's ranges as bytes, one after the other, and their entries."""
    points, _ = points_of(vectors)
    order, ranges = ranges_of(points)
    built = [build(lifted(points[order[a:b]]), *options) for a, b, large in ranges if large]
    return b"".join(g.astype(np.int32).tobytes() for g, _ in built), np.array([e for _, e in built], np.int64).tobytes()


def usable(vector: Column) -> Column:
    """Not null or zero, and finite throughout."""
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.coalesce(vector.isNotNull() & fine & F.exists(vector, lambda x: x != 0), F.lit(False))


def _packed(rows: DataFrame, keys: list[str], work) -> DataFrame:
    """One row for each group (of bounded size): its ids and vectors as bytes, and what `work` makes of them."""

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values("vec_id", kind="stable")
        vectors = np.array(pdf["vector"].tolist(), np.float64)
        extra, entry = work(vectors)
        return pd.DataFrame({**{k: [int(pdf[k].iloc[0])] for k in keys}, "ids": [pdf["vec_id"].to_numpy(np.int64).tobytes()], "vectors": [vectors.tobytes()], "graph": [extra], "entry": [entry]})

    return rows.groupBy(*keys).applyInPandas(run, ", ".join(f"{k} bigint" for k in keys) + ", ids binary, vectors binary, graph binary, entry binary")


def indexed(rows: DataFrame, shard_rows: int | None = None, degree: int = DEGREE, beam: int = BUILD_BEAM, alpha: float = ALPHA) -> tuple[DataFrame, dict[int, int]]:
    """The index of all rows (vec_id, vector, width), one row per shard, and the number of shards for each width of vectors. shard_rows: rows of a shard, in place of SHARD_BYTES."""
    shards = {r["width"]: math.ceil(r["n"] / (shard_rows or max(SCANNED, SHARD_BYTES // (8 * r["width"])))) for r in rows.groupBy("width").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row per width
    if not shards:
        return rows.sparkSession.createDataFrame([], "width bigint, shard bigint, ids binary, vectors binary, graph binary, entry binary"), shards
    dealt = rows.withColumn("shard", F.pmod(F.xxhash64("vec_id", F.lit("shard")), _by_width(shards)))

    total = max(sum(shards.values()), 1)
    return saved(_packed(dealt.repartition(3 * total, "width", "shard"), ["width", "shard"], lambda v: packed_graph(v, degree, beam, alpha)), "graph-index"), shards


def _by_width(numbers: dict[int, int]) -> Column:
    out = F.lit(None).cast("bigint")
    for width, n in sorted(numbers.items()):
        out = F.when(F.col("width") == width, F.lit(n).cast("bigint")).otherwise(out)
    return out


def nearest(table: DataFrame, is_query: Column, k: int = 20, vec_id: str = "vec_id", vector: str = "embedding", search_beam: int = SEARCH_BEAM, shard_rows: int | None = None, query_block: int = QUERY_BLOCK) -> DataFrame:
    """query_id, rank (from 1), vec_id, score of the k nearest rows found for each query row; is_query is over the column vec_id."""
    rows = table.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(vector).alias("vector")).where(F.col("vec_id").isNotNull() & usable(F.col("vector")))
    rows = rows.withColumns({"vector": F.col("vector").cast("array<double>"), "width": F.size("vector").cast("bigint")})
    ship(table.sparkSession)
    index, shards = indexed(rows, shard_rows)
    schema = "query_id bigint, vec_id bigint, score double"
    asked = rows.where(is_query)
    counts = {r["width"]: math.ceil(r["n"] / query_block) for r in asked.groupBy("width").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row per width
    if counts:
        blocks = asked.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit("query")), _by_width(counts)))
        blocks = _packed(blocks, ["width", "block"], lambda v: (b"", b"")).select("width", "block", F.col("ids").alias("q_ids"), F.col("vectors").alias("q_vectors"))
        blocks = blocks.withColumn("shard", F.explode(F.sequence(F.lit(0).cast("bigint"), _by_width(shards) - 1)))
        tasks = sum(counts[w] * shards[w] for w in counts)
        pairs = blocks.join(index, ["width", "shard"]).repartition(2 * tasks, "width", "shard", "block")

        def run(batches):
            for batch in batches:
                for row in range(batch.num_rows):
                    yield from _answers({n: batch.column(n)[row].as_py() for n in batch.schema.names}, k, search_beam)

        found = pairs.mapInArrow(run, schema)
    else:
        found = table.sparkSession.createDataFrame([], schema)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _answers(row: dict, k: int, search_beam: int):
    width = row["width"]
    ids, data = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["vectors"]).reshape(-1, width)
    points, number = points_of(data)
    order, ranges = ranges_of(points)
    graph, entries = np.frombuffer(row["graph"], np.int32), np.frombuffer(row["entry"], np.int64).tolist()
    q_ids, queries = np.frombuffer(row["q_ids"], np.int64), np.frombuffer(row["q_vectors"]).reshape(-1, width)
    # the rows of each point: of equal vectors only those of the least ids can be among the best, besides the query's own
    same = alike(data)[1]
    by = np.argsort(same, kind="stable")
    place = np.empty(len(ids), np.int64)
    place[by] = np.arange(len(ids)) - np.searchsorted(same[by], same[by])
    rows = np.flatnonzero(place < k + np.unique(ids, return_counts=True)[1].max())
    rows = rows[np.argsort(number[rows], kind="stable")]
    begin = np.searchsorted(number[rows], np.arange(len(points) + 1))
    # one length for all queries: the order by distance doesn't depend on it
    length = np.sqrt((queries**2).sum(1))
    flat = np.concatenate([queries / length[:, None], np.zeros((len(queries), 1))], 1).astype(np.float32)
    large = sum(b - a for a, b, has in ranges if has)
    degree, at, parts = len(graph) // large if large else 0, 0, []
    for a, b, has in ranges:
        some = points[order[a:b]]
        links = graph[at : at + (b - a) * degree].reshape(b - a, degree).astype(np.int64) if has else None
        at += (b - a) * degree if has else 0
        parts.append((order[a:b], some, np.sqrt((some**2).sum(1).max()), links, entries.pop(0) if has else 0, lifted(some) if has else None))
    for a in range(0, len(queries), _BATCH):
        yield from _batch(ids, data, rows, begin, parts, flat[a : a + _BATCH], q_ids[a : a + _BATCH], queries[a : a + _BATCH], length[a : a + _BATCH], k, search_beam)


def _batch(ids, data, rows, begin, parts, flat, own, queries, length, k, search_beam):
    """The k best rows of some queries, over all ranges of a shard."""
    q = len(queries)
    found = [np.zeros((q, 0), np.int64)]
    # the (k + 2)nd best score so far: two points may be the query's own or hold no row for it
    best = np.full((q, k + 2), -np.inf)
    for at, some, most, links, entry, high in parts:
        left = np.flatnonzero(best[:, -1] < length * most * (1 + 1e-6))
        if not len(left):
            break
        if links is None:
            score = queries[left] @ some.T
            chosen = np.argsort(-score, axis=1, kind="stable")[:, : max(search_beam, 2 * k)]
        else:
            chosen, _ = beam_search(high, links, entry, flat[left], min(max(search_beam, 2 * k), len(some)))
            score = None
        new = np.full((q, chosen.shape[1]), -1, np.int64)
        new[left] = np.where(chosen >= 0, at[chosen], -1)
        exact = np.full((q, chosen.shape[1]), -np.inf)
        values = np.take_along_axis(score, chosen, 1) if score is not None else np.einsum("ijk,ik->ij", some[chosen], queries[left])
        exact[left] = np.where(chosen >= 0, values, -np.inf)
        found.append(new)
        best = -np.sort(-np.concatenate([best, exact], axis=1), axis=1)[:, : k + 2]
    points = np.concatenate(found, axis=1)
    count = np.where(points >= 0, begin[points + 1] - begin[points], 0)
    part = np.cumsum(count.sum(1)) // _ROWS
    for b, e in zip(*(np.searchsorted(part, np.unique(part), side=x).tolist() for x in ("left", "right")), strict=True):
        yield _best(ids, data, rows, begin[points[b:e]], count[b:e], own[b:e], queries[b:e], k)


def _best(ids: np.ndarray, data: np.ndarray, rows: np.ndarray, begin: np.ndarray, count: np.ndarray, own: np.ndarray, queries: np.ndarray, k: int) -> pa.RecordBatch:
    """The k best rows of each query among rows[begin : begin + count] of the points found for it."""
    count, who = count.ravel(), np.repeat(np.arange(len(own)), count.sum(1))
    at = rows[np.arange(len(who)) + np.repeat(begin.ravel() - (np.cumsum(count) - count), count)]
    other = ids[at] != own[who]
    who, at = who[other], at[other]
    score = (data[at] * queries[who]).sum(1)
    order = np.lexsort((ids[at], -score, who))
    who, at, score = who[order], at[order], score[order]
    keep = np.arange(len(who)) - np.searchsorted(who, who) < k
    return pa.RecordBatch.from_pydict({"query_id": own[who[keep]], "vec_id": ids[at[keep]], "score": score[keep]})
