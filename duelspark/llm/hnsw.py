"""Nearest neighbours by hierarchical navigable small-world graphs, one for each shard.

Equal vectors are one point, which keeps its smallest ids (k + 1 of them: no query can show more). Points are dealt to shards of
about `shard_rows` by a hash. A shard's graph is stored as flat neighbour arrays: for each level the ids of its points and a
matrix of neighbours, filled up with -1. Neighbours are chosen by the usual diversity rule among the nearest points of the
level, which are found by blocked matrix products (a shard is small, so its candidate search can be exact); links are made
mutual and pruned by the same rule. A query descends greedily through the upper levels and searches the lowest one with a beam;
all queries of a block move through the graph together, in numpy.

Every shard answers every block of queries; the answers are scored in double precision on the original vectors and merged by a
window of k rows. Queries travel to the shards in blocks, and only ids, scores and ranks come back.

Defined results: vectors that are null, zero, or hold null or non-finite components take no part; vectors are compared with those
of their own length; with fewer candidates than k all are returned; ties go to the smaller id; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise


@dataclass(frozen=True)
class Graph:
    """Parameters: neighbours per point on upper levels (twice as many on the lowest), candidates while building, beam width while searching."""

    m: int = 16
    candidates: int = 64
    beam: int = 160
    shard_rows: int = 8192
    block: int = 1024
    k: int = 10
    seed: int = 5


def _squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1) - 2 * (a @ b.T), 0)


def _diverse(points: np.ndarray, own: np.ndarray, near: np.ndarray, m: int) -> np.ndarray:
    """For each point the first m of its candidates (nearest first, -1 for none) that are nearer to it than to any one chosen before."""
    n, c = near.shape
    out = np.full((n, m), -1, np.int32)
    for k in range(0, n, 256):
        at = near[k : k + 256]
        x = points[at.clip(0)]
        gap = ((x - own[k : k + 256, None]) ** 2).sum(axis=2)
        gram = np.einsum("icd,ied->ice", x, x)
        square = np.einsum("icc->ic", gram)
        between = square[:, :, None] + square[:, None, :] - 2 * gram
        closest, taken, rows = np.full(at.shape, np.inf, np.float32), np.zeros(len(at), int), np.arange(len(at))
        chosen = np.zeros(at.shape, bool)
        for j in range(c):
            take = (at[:, j] >= 0) & (taken < m) & (gap[:, j] < closest[:, j])
            out[k + rows[take], taken[take]] = at[take, j]
            taken += take
            chosen[:, j] = take
            closest = np.where(take[:, None], np.minimum(closest, between[:, j]), closest)
        for j in range(c):  # what is left over fills the free places, nearest first
            take = (at[:, j] >= 0) & (taken < m) & ~chosen[:, j]
            out[k + rows[take], taken[take]] = at[take, j]
            taken += take
    return out


def _level(points: np.ndarray, m: int, candidates: int) -> np.ndarray:
    """Neighbour matrix (n x m) of the points of one level."""
    n = len(points)
    c = min(candidates, n - 1)
    if c < 1:
        return np.full((n, m), -1, np.int32)
    near = np.empty((n, c), np.int32)
    for k in range(0, n, 1024):
        d = _squares(points[k : k + 1024], points)
        d[np.arange(len(d)), np.arange(k, k + len(d))] = np.inf
        part = np.argpartition(d, c - 1, axis=1)[:, :c]
        near[k : k + 1024] = np.take_along_axis(part, np.argsort(np.take_along_axis(d, part, 1), axis=1, kind="stable"), 1)
    chosen = _diverse(points, points, near, max(1, m // 2))
    # links are made mutual; where a point gets more than m, the rule chooses again
    a, slot = np.nonzero(chosen >= 0)
    b = chosen[a, slot]
    pairs = np.unique(np.concatenate((a * np.int64(n) + b, b * np.int64(n) + a)))
    u, v = pairs // n, pairs % n
    order = np.lexsort((((points[u] - points[v]) ** 2).sum(axis=1), u))
    u, v = u[order], v[order]
    count = np.bincount(u, minlength=n)
    place = np.arange(len(u)) - np.repeat(np.cumsum(count) - count, count)
    full = np.full((n, int(min(count.max(), 4 * m))), -1, np.int32)
    fits = place < full.shape[1]
    full[u[fits], place[fits]] = v[fits]
    out = full[:, :m] if full.shape[1] >= m else np.hstack((full, np.full((n, m - full.shape[1]), -1, np.int32)))
    over = np.flatnonzero(count > m)
    if len(over):
        out = out.copy()
        out[over] = _diverse(points, points[over], full[over], m)
    return out


def build(points: np.ndarray, graph: Graph) -> list[tuple[np.ndarray, np.ndarray]]:
    """Levels from the highest to the lowest: ids of the level's points, and their neighbours as positions in the level below's numbering of all points."""
    rng = np.random.default_rng(graph.seed)
    height = np.minimum((-np.log(1 - rng.random(len(points))) / np.log(graph.m)).astype(int), 8)
    levels = []
    for h in range(int(height.max(initial=0)), -1, -1):
        ids = np.flatnonzero(height >= h).astype(np.int32)
        near = _level(points[ids], graph.m * (2 if h == 0 else 1), graph.candidates)
        levels.append((ids, np.where(near >= 0, ids[near.clip(0)], -1).astype(np.int32)))
    return levels


def search(points: np.ndarray, levels: list[tuple[np.ndarray, np.ndarray]], queries: np.ndarray, k: int, beam: int) -> np.ndarray:
    """Positions of about the k nearest points of every query, nearest first, -1 for none."""
    q, n = len(queries), len(points)
    at = np.full(q, levels[0][0][0], np.int32)
    best = ((queries - points[at]) ** 2).sum(axis=1)
    for ids, near in levels[:-1]:
        row = np.full(n, -1, np.int32)
        row[ids] = np.arange(len(ids), dtype=np.int32)
        going = np.arange(q)
        while len(going):
            to = near[row[at[going]]]
            d = np.where(to >= 0, ((points[to.clip(0)] - queries[going, None]) ** 2).sum(axis=2), np.inf)
            j = d.argmin(axis=1)
            low = d[np.arange(len(j)), j]
            better = low < best[going]
            at[going[better]], best[going[better]] = to[better, j[better]], low[better]
            going = going[better]
    near = levels[-1][1]
    beam = min(max(beam, k), n)
    seen = np.zeros((q, n), bool)
    ids, d, done = np.full((q, beam), -1, np.int32), np.full((q, beam), np.inf, np.float32), np.ones((q, beam), bool)
    ids[:, 0], d[:, 0], done[:, 0] = at, best, False
    seen[np.arange(q), at] = True
    going = np.arange(q)
    while len(going):
        # the four nearest open points of every query are opened at once
        open_d = np.where(done[going], np.inf, d[going])
        pick = np.argpartition(open_d, min(3, beam - 1), axis=1)[:, : min(4, beam)]
        is_open = np.isfinite(np.take_along_axis(open_d, pick, 1))
        alive = is_open.any(axis=1)
        going, pick, is_open = going[alive], pick[alive], is_open[alive]
        if not len(going):
            break
        done[going[:, None], pick] = True
        opened = np.where(is_open, ids[going[:, None], pick], -1)
        to = np.where(opened[:, :, None] >= 0, near[opened.clip(0)], -1).reshape(len(going), -1)
        to = np.sort(to, axis=1)
        fresh = (to >= 0) & ~seen[going[:, None], to.clip(0)]
        fresh[:, 1:] &= to[:, 1:] != to[:, :-1]
        r, c = np.nonzero(fresh)
        seen[going[r], to[r, c]] = True
        gaps = np.full(to.shape, np.inf, np.float32)
        gaps[r, c] = ((points[to[r, c]] - queries[going[r]]) ** 2).sum(axis=1)
        all_d, all_ids = np.hstack((d[going], gaps)), np.hstack((ids[going], to))
        all_done = np.hstack((done[going], ~fresh))
        keep = np.argpartition(all_d, beam - 1, axis=1)[:, :beam]
        d[going], ids[going], done[going] = (np.take_along_axis(x, keep, 1) for x in (all_d, all_ids, all_done))
    order = np.argsort(d, axis=1, kind="stable")[:, :k]
    return np.where(np.isfinite(np.take_along_axis(d, order, 1)), np.take_along_axis(ids, order, 1), -1)


def usable(vector: Column) -> Column:
    """Neither null nor zero, and all components finite."""
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vector.isNotNull() & F.coalesce(finite, F.lit(False)) & F.exists(vector, lambda x: x != 0)


def vectors_of(embeddings: DataFrame) -> DataFrame:
    """id, v: the usable vectors in their own precision; of rows that repeat an id the smallest vector counts, once."""
    kind = dict(embeddings.dtypes)["embedding"]
    v = F.col("embedding").cast(kind if kind in ("array<float>", "array<double>") else "array<double>")
    return embeddings.select(F.col("vec_id").cast("long").alias("id"), v.alias("v")).where(F.col("id").isNotNull() & usable(F.col("v"))).groupBy("id").agg(F.min("v").alias("v"))


def index(embeddings: DataFrame, graph: Graph) -> DataFrame:
    """shard, dim, ids (array of arrays: the smallest ids of each point), points (bytes of the vectors' own precision), levels (array of structs of flat arrays)."""
    vectors = vectors_of(embeddings)
    precision = np.float64 if dict(vectors.dtypes)["v"] == "array<double>" else np.float32
    rank = F.row_number().over(W.partitionBy("v").orderBy("id"))
    points = vectors.withColumn("rank", rank).where(F.col("rank") <= graph.k + 1).groupBy("v").agg(F.array_sort(F.collect_list("id")).alias("ids"))  # k + 1 ids at most
    points = materialise(points.withColumn("dim", F.size("v")), "points")
    shards = {r["dim"]: max(1, -(-r["n"] // graph.shard_rows)) for r in points.groupBy("dim").agg(F.count("*").alias("n")).collect()}
    count = F.lit(1)
    for dim, n in shards.items():
        count = F.when(F.col("dim") == dim, n).otherwise(count)
    dealt = points.withColumn("shard", F.pmod(F.xxhash64("v"), count).cast("int"))
    kinds = pa.schema([("dim", pa.int32()), ("shard", pa.int32()), ("ids", pa.list_(pa.list_(pa.int64()))), ("points", pa.binary()), ("levels", pa.list_(pa.struct([("ids", pa.list_(pa.int32())), ("near", pa.list_(pa.int32()))])))])

    def make(group: pa.Table) -> pa.Table:
        group = group.combine_chunks().sort_by([("first", "ascending")])
        dim = group["dim"][0].as_py()
        x = group["v"].combine_chunks().flatten().to_numpy().reshape(-1, dim).astype(precision)
        levels = build(x.astype(np.float32), graph)
        row = {"dim": dim, "shard": group["shard"][0].as_py(), "ids": group["ids"].to_pylist(), "points": x.tobytes(), "levels": [{"ids": i, "near": n.ravel()} for i, n in levels]}
        return pa.Table.from_pylist([row], schema=kinds)

    made = dealt.withColumn("first", F.get("ids", F.lit(0))).groupBy("dim", "shard").applyInArrow(make, "dim int, shard int, ids array<array<bigint>>, points binary, levels array<struct<ids: array<int>, near: array<int>>>")
    return materialise(made, "graphs")


def nearest(embeddings: DataFrame, every: int = 100, graph: Graph = Graph()) -> DataFrame:
    """query_id, rank, vec_id, score: for each vector whose id `every` divides, its nearest other vectors."""
    graphs = index(embeddings, graph)
    asked = vectors_of(embeddings).where(F.col("id") % every == 0).withColumn("dim", F.size("v"))
    precision = np.float64 if dict(asked.dtypes)["v"] == "array<double>" else np.float32
    sizes = {r["dim"]: r["n"] for r in asked.groupBy("dim").agg(F.count("*").alias("n")).collect()}  # a row for each length of vectors
    shards = {r["dim"]: r["n"] for r in graphs.groupBy("dim").agg(F.count("*").alias("n")).collect()}
    by_dim = lambda values: F.coalesce(*(F.when(F.col("dim") == d, v) for d, v in values.items()), F.lit(1))
    parts = by_dim({d: max(1, -(-n // graph.block)) for d, n in sizes.items()})
    # a part of the queries (bounded) meets every shard of its dimension; shards are sent to each part, once
    dealt = asked.withColumn("part", F.pmod(F.xxhash64("id"), parts).cast("int")).select("dim", "part", "id", "v", F.explode(F.sequence(F.lit(0), by_dim(shards) - 1)).alias("shard"))
    wide = graphs.withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1)))

    def answer(queries: pa.Table, shard: pa.Table) -> pa.Table:
        if not queries.num_rows or not shard.num_rows:
            return pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        dim = queries["dim"][0].as_py()
        q_ids, q = queries["id"].to_numpy(), queries["v"].combine_chunks().flatten().to_numpy().reshape(-1, dim)
        own, points = shard["ids"][0].values, np.frombuffer(shard["points"][0].as_buffer(), precision).reshape(-1, dim)
        levels = [(np.asarray(x["ids"].values), np.asarray(x["near"].values).reshape(len(x["ids"]), -1)) for x in shard["levels"][0].values]
        found = search(points.astype(np.float32), levels, q.astype(np.float32), graph.k + 6, graph.beam)
        r, c = np.nonzero(found >= 0)
        at = found[r, c]
        score = np.sqrt(((points[at].astype(np.float64) - q[r].astype(np.float64)) ** 2).sum(axis=1))
        starts, flat = np.asarray(own.offsets), np.asarray(own.values)
        length = np.diff(starts)[at]
        ends = np.cumsum(length)
        ids = flat[np.repeat(starts[at], length) + np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - length, length)]
        who, score = np.repeat(q_ids[r], length), np.repeat(score, length)
        keep = who != ids
        who, ids, score = who[keep], ids[keep], score[keep]
        order = np.lexsort((ids, score, who))
        who, ids, score = who[order], ids[order], score[order]
        top = np.arange(len(who)) - np.searchsorted(who, who) < graph.k
        return pa.table({"query_id": pa.array(who[top], pa.int64()), "vec_id": pa.array(ids[top], pa.int64()), "score": pa.array(score[top], pa.float64())})

    key = ("dim", "shard", "part")
    answers = dealt.groupBy(*key).cogroup(wide.groupBy(*key)).applyInArrow(answer, "query_id long, vec_id long, score double")
    ranked = answers.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy("score", "vec_id")))
    return ranked.where(F.col("rank") <= graph.k).select("query_id", "rank", "vec_id", "score")
