"""Approximate nearest neighbours by inner product: each shard is a robust-pruned directed graph. Greedy searches propose a node's neighbours, relaxed
distance pruning keeps diverse edges, and a beam search answers queries in every shard; the best of all shards are the answer.

Inner product becomes Euclidean distance by one more component, sqrt(M^2 - |x|^2) with M the shard's largest norm, so pruning has a metric.
Equal vectors are one node of the graph; of their ids only the k + 1 least can be in an answer of k, as ties go to the smaller id.
"""

from __future__ import annotations

import itertools
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, pick

#: Production values: answers, edges of a node, beams of building and searching, relaxation of the pruning, vectors of a shard, queries of a block.
K, DEGREE, BUILD_BEAM, BEAM, ALPHA, SHARD_ROWS, QUERY_BLOCK = 20, 32, 48, 96, 1.2, 4_000, 512


def beam_search(points: np.ndarray, graph: np.ndarray, start: np.ndarray, queries: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """For each query the nodes met nearest to it, and their squared distances, in ascending order; all queries advance together.

    graph: neighbours of each node, -1 where there are fewer. start: entry nodes. Unfilled places are -1 with infinite distance."""
    n, q = len(points), len(queries)
    norms = (points**2).sum(1)
    rows = np.arange(q)[:, None]
    seen = np.zeros((q, n), dtype=bool)

    def distances(nodes: np.ndarray) -> np.ndarray:
        return norms[nodes] - 2 * np.einsum("qnd,qd->qn", points[nodes], queries)

    nodes = np.broadcast_to(start, (q, len(start)))
    seen[:, start] = True
    beam, dist = np.full((q, width), -1), np.full((q, width), np.inf)
    beam[:, : len(start)], dist[:, : len(start)] = nodes, distances(nodes)
    done = np.zeros((q, width), dtype=bool)
    while True:
        open_ = np.where(done | (beam < 0), np.inf, dist)
        pick_ = open_.argmin(1)
        live = np.flatnonzero(np.isfinite(open_[np.arange(q), pick_]))
        if len(live) == 0:
            break
        at = pick_[live]
        done[live, at] = True
        near = graph[beam[live, at]]
        fresh = (near >= 0) & ~seen[live[:, None], near]
        seen[live[:, None], np.where(near >= 0, near, beam[live, at][:, None])] = True
        some = np.where(fresh, near, 0)
        d = norms[some] - 2 * np.einsum("qnd,qd->qn", points[some], queries[live])
        d[~fresh] = np.inf
        all_d, all_n = np.hstack([dist[live], d]), np.hstack([beam[live], np.where(fresh, near, -1)])
        all_e = np.hstack([done[live], np.zeros_like(fresh)])
        keep = np.argpartition(all_d, width - 1, axis=1)[:, :width]
        dist[live], beam[live], done[live] = (np.take_along_axis(x, keep, 1) for x in (all_d, all_n, all_e))
    order = np.argsort(dist, axis=1, kind="stable")
    return beam[rows, order], dist[rows, order] + (queries**2).sum(1)[:, None]


def robust_prune(points: np.ndarray, node: np.ndarray, candidates: np.ndarray, dist: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Neighbours of each of the given nodes: the nearest candidate stays, those that are alpha times nearer to it than to the node go, and so on.

    candidates, dist: ascending by distance, -1 and infinite where unfilled. All nodes are pruned together."""
    b, c = candidates.shape
    alive = (candidates >= 0) & (candidates != node[:, None])
    own = points[np.maximum(candidates, 0)]
    squares = (own**2).sum(2)
    apart = squares[:, :, None] + squares[:, None, :] - 2 * (own @ own.transpose(0, 2, 1))
    out = np.full((b, degree), -1)
    rows = np.arange(b)
    for k in range(degree):
        has = alive.any(1)
        if not has.any():
            break
        first = alive.argmax(1)
        out[has, k] = candidates[rows, first][has]
        alive &= alpha * alpha * apart[rows, first] > dist
        alive[rows, first] = False
    return out


def build_graph(points: np.ndarray, degree: int = DEGREE, beam: int = BUILD_BEAM, alpha: float = ALPHA, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Graph and entry nodes of a shard. Two passes over all nodes in blocks: first alpha 1, then the relaxed one."""
    n = len(points)
    rng = np.random.default_rng(seed)
    graph = np.full((n, degree), -1)
    if n == 1:
        return graph, np.zeros(1, np.int64)
    graph[:, : min(degree, n - 1)] = (np.arange(n)[:, None] + 1 + np.argsort(rng.random((n, n - 1)), axis=1)[:, : min(degree, n - 1)]) % n if n <= 64 else rng.integers(0, n, (n, degree))
    graph[graph == np.arange(n)[:, None]] = -1
    centre = ((points - points.mean(0)) ** 2).sum(1).argmin()
    start = np.unique(np.append(rng.choice(n, min(n, 8), replace=False), centre))
    for a in (1.0, alpha):
        order = rng.permutation(n)
        size = 64 if a == 1.0 else 256
        at = 0
        while at < n:
            block = order[at : at + size]
            at += size
            near, dist = beam_search(points, graph, start, points[block], beam)
            known = graph[block]
            extra = ((points[np.maximum(known, 0)] - points[block][:, None, :]) ** 2).sum(2)
            extra[(known < 0) | (known[:, :, None] == near[:, None, :]).any(2)] = np.inf
            cand, d = np.hstack([near, known]), np.hstack([dist, extra])
            cand = np.where(np.isfinite(d), cand, -1)
            o = np.argsort(d, axis=1, kind="stable")
            graph[block] = robust_prune(points, block, np.take_along_axis(cand, o, 1), np.take_along_axis(d, o, 1), degree, a)
            _add_back(points, graph, block, degree, a)
    return graph, start


def _add_back(points: np.ndarray, graph: np.ndarray, block: np.ndarray, degree: int, alpha: float) -> None:
    """The reverse of each new edge; nodes that get too many are pruned."""
    targets = graph[block]
    src, dst = np.repeat(block, targets.shape[1]), targets.reshape(-1)
    src, dst = src[dst >= 0], dst[dst >= 0]
    order = np.argsort(dst, kind="stable")
    src, dst = src[order], dst[order]
    nodes, first, count = np.unique(dst, return_index=True, return_counts=True)
    width = int(count.max()) if len(count) else 0
    if not width:
        return
    new = np.full((len(nodes), width), -1)
    new[np.repeat(np.arange(len(nodes)), count), np.arange(len(dst)) - np.repeat(first, count)] = src
    old = graph[nodes]
    new[(new[:, :, None] == old[:, None, :]).any(2)] = -1
    cand = np.hstack([old, new])
    d = ((points[np.maximum(cand, 0)] - points[nodes][:, None, :]) ** 2).sum(2)
    d[cand < 0] = np.inf
    o = np.argsort(d, axis=1, kind="stable")
    cand, d = np.take_along_axis(cand, o, 1), np.take_along_axis(d, o, 1)
    few = (cand >= 0).sum(1) <= degree
    graph[nodes[few]] = cand[few, :degree] if cand.shape[1] >= degree else np.pad(cand[few], ((0, 0), (0, degree - cand.shape[1])), constant_values=-1)
    if (~few).any():
        graph[nodes[~few]] = robust_prune(points, nodes[~few], cand[~few], d[~few], degree, alpha)


def lifted(vectors: np.ndarray) -> np.ndarray:
    """One more component makes all norms equal, so that the nearest is the one of largest inner product."""
    squares = (vectors**2).sum(1)
    return np.hstack([vectors, np.sqrt(np.maximum(0, squares.max() - squares))[:, None]])


def usable(df: DataFrame) -> DataFrame:
    """vec_id, embedding (doubles) of the rows that take part: not null, no null or non-finite component, not zero."""
    rows = pick(df, "vec_id", "embedding").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    finite = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return rows.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.coalesce(finite, F.lit(False)) & F.exists("embedding", lambda x: x != 0))


def search(df: DataFrame, every: int = 20, k: int = K, degree: int = DEGREE, build_beam: int = BUILD_BEAM, beam: int = BEAM, alpha: float = ALPHA, shard_rows: int = SHARD_ROWS, query_block: int = QUERY_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: for each row whose vec_id is divisible by `every` its k nearest other rows by inner product.

    Null, zero and non-finite vectors take no part; vectors of another length than most are compared within their length only; fewer than k other rows
    give fewer answers; a repeated vec_id counts once (its least vector); ties go to the smaller vec_id; an empty table gives no rows; other columns
    are ignored. Every shard is one partition: its vectors become a graph, and blocks of queries come to it one after another, each once, so a task holds a
    shard and a block. Of a query's answers a shard sends on k + 1 at most, and more only where scores tie."""
    rows = usable(df).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    rows = cut(rows.withColumn("dim", F.size("embedding")).withColumn("h", F.xxhash64("embedding")))
    rank = F.row_number().over(Window.partitionBy("h", "embedding").orderBy("vec_id"))
    distinct = cut(rows.withColumn("r", rank).where(F.col("r") <= k + 1).groupBy("dim", "h", "embedding").agg(F.array_sort(F.collect_list("vec_id")).alias("ids")))
    sizes = sorted((r["dim"], r["count"]) for r in distinct.groupBy("dim").count().collect())
    if not sizes:
        return df.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    # shards are numbered through, those of a length one after another
    per = {dim: -(-n // shard_rows) for dim, n in sizes}
    first = dict(zip(per, accumulate(per.values(), initial=0), strict=False))
    shards_of, first_of = (F.create_map(*[F.lit(x) for pair in m.items() for x in pair])[F.col("dim")] for m in (per, first))
    total = sum(per.values())
    none = {"embedding": "array<double>", "ids": "array<bigint>", "queries": "array<struct<query_id:bigint,embedding:array<double>>>"}
    vectors = distinct.select((first_of + F.pmod("h", shards_of)).cast("int").alias("shard"), F.lit(-1).alias("block"), "h", "embedding", "ids", F.lit(None).cast(none["queries"]).alias("queries"))
    queries = rows.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), "dim", "embedding")
    blocks = max(1, -(-queries.count() // query_block))
    packed = cut(queries.withColumn("block", F.pmod(F.xxhash64("query_id"), F.lit(blocks)).cast("int")).groupBy("dim", "block").agg(F.collect_list(F.struct("query_id", "embedding")).alias("queries")))
    shard = F.explode(F.sequence(first_of, first_of + shards_of - 1))
    asked = packed.select(shard.alias("shard"), "block", F.lit(0).cast("long").alias("h"), F.lit(None).cast(none["embedding"]).alias("embedding"), F.lit(None).cast(none["ids"]).alias("ids"), "queries")
    dealt = vectors.unionByName(asked).repartitionById(total, "shard").sortWithinPartitions("shard", "block", "h")
    # a build is not to be done twice, so what the shards say is written
    met = cut(dealt.mapInArrow(lambda batches: _answers(batches, k, degree, build_beam, beam, alpha), "query_id long, vec_id long, score double"))
    nearest = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return met.withColumn("rank", F.row_number().over(nearest)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


class Shard:
    """Distinct vectors of one length with their ids, and the graph over them."""

    def __init__(self, vectors: np.ndarray, ids: list[list[int]], degree: int, build_beam: int, alpha: float):
        self.vectors, self.ids = vectors, ids
        self.points = lifted(vectors).astype(np.float32)
        self.graph, self.start = build_graph(self.points, degree, build_beam, alpha)

    def nearest(self, queries: np.ndarray, k: int, beam: int) -> list[np.ndarray]:
        """Nodes near each query. A query whose search meets fewer nodes than k, as in a graph of several parts, is compared with all."""
        near, _ = beam_search(self.points, self.graph, self.start, np.hstack([queries, np.zeros((len(queries), 1))]).astype(np.float32), max(beam, k, len(self.start)))
        found = [nodes[nodes >= 0] for nodes in near]
        every = np.arange(len(self.ids))
        return [nodes if len(nodes) >= min(k, len(every)) else every for nodes in found]

    def answers(self, asked: list[dict], k: int, beam: int) -> list[tuple[int, int, float]]:
        """query_id, vec_id and score of the k + 1 best of each query (its own vector may be one), and of those that tie with the last."""
        out = []
        for at in range(0, len(asked), 256):
            part = asked[at : at + 256]
            q = np.array([x["embedding"] for x in part])
            for x, y, nodes in zip(part, q, self.nearest(q, k + 1, beam), strict=True):
                scores, left, last = self.vectors[nodes] @ y, k + 1, np.inf
                for j in np.argsort(-scores, kind="stable"):
                    if left <= 0 and scores[j] < last:
                        break
                    last = scores[j]
                    for v in self.ids[nodes[j]]:
                        if v != x["query_id"]:
                            out.append((x["query_id"], v, float(scores[j])))
                            left -= 1
        return out


def _answers(batches, k: int, degree: int, build_beam: int, beam: int, alpha: float):
    """Rows come by shard, its vectors before the blocks of queries to it."""
    now, vectors, ids, shard = None, [], [], None
    for b in batches:
        numbers, block = b.column("shard").to_numpy(), b.column("block").to_numpy()
        cuts = [0, *(np.flatnonzero((np.diff(numbers) != 0) | (block[1:] >= 0)) + 1).tolist(), b.num_rows]
        for lo, hi in itertools.pairwise(cuts):
            if lo == hi:
                continue
            if numbers[lo] != now:
                now, vectors, ids, shard = numbers[lo], [], [], None
            part = b.slice(lo, hi - lo)
            if block[lo] < 0:
                lists = part.column("embedding")
                vectors.append(lists.flatten().to_numpy(zero_copy_only=False).reshape(hi - lo, -1))
                ids += part.column("ids").to_pylist()
                continue
            if not vectors:
                continue
            shard = shard or Shard(np.concatenate(vectors), ids, degree, build_beam, alpha)
            out = shard.answers(part.column("queries")[0].as_py(), k, beam)
            cols = list(zip(*out, strict=True)) or [[]] * 3
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["query_id", "vec_id", "score"])
