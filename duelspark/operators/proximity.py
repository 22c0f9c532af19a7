"""Farthest and nearest records from a query record. A metric set is a DataFrame (id, payload)."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metric_arrays import form_of
from ..functions.metrics import Metric, euclid, planted
from ..functions.ticks import threshold
from ..functions.tosses import Field
from . import cells, centers, extremum, sampling, scores
from .judges import Judge, pair_id
from .kcenter import as_literal, extract_core
from .votes import count_yes, items, nearer_by_anchors


def distances(df: DataFrame, query_id: int, metric: Metric) -> DataFrame:
    """id, val: distances from the query record to all others; the query row is broadcast."""
    query = F.broadcast(df.where(F.col("id") == query_id).select(F.col("payload").alias("q")))
    return df.where(F.col("id") != query_id).crossJoin(query).select("id", metric(F.col("payload"), F.col("q")).alias("val"))


def _asked(df: DataFrame, query_id: int, metric: Metric) -> DataFrame:
    """Distances with the id of the pair, by which answers persist in all methods: one question has one answer."""
    return distances(df, query_id, metric).select(pair_id(F.lit(query_id).cast("long"), F.col("id").cast("long")).alias("id"), "val")


def _named(found: DataFrame, query_id: int) -> DataFrame:
    """The winner of pairs as the record that is not the query."""
    return found.withColumn("winner_id", F.when(F.col("winner_id.k1") == query_id, F.col("winner_id.k2")).otherwise(F.col("winner_id.k1")))


def farthest_band(df: DataFrame, query_id: int, metric: Metric, judge: Judge, **more) -> DataFrame:
    """At least the largest distance divided by (1 + mu)**3, with probability 1 - delta."""
    return _named(extremum.robust_band(_asked(df, query_id, metric), judge.on_pairs(), want="max", **more), query_id)


def nearest_band(df: DataFrame, query_id: int, metric: Metric, judge: Judge, **more) -> DataFrame:
    return _named(extremum.robust_band(_asked(df, query_id, metric), judge.on_pairs(), want="min", **more), query_id)


def farthest_coin_rank(df: DataFrame, query_id: int, metric: Metric, judge: Judge, **more) -> DataFrame:
    """Of a rank of the order of log(n / delta)**2."""
    return _named(extremum.robust_coin(_asked(df, query_id, metric), judge.on_pairs(), want="max", **more), query_id)


def nearest_coin(df: DataFrame, query_id: int, metric: Metric, judge: Judge, **more) -> DataFrame:
    return _named(extremum.robust_coin(_asked(df, query_id, metric), judge.on_pairs(), want="min", **more), query_id)


def _by_anchors(df: DataFrame, query_id: int, anchors: list, metric: Metric, judge: Judge, share: float, want: str):
    """Records (id, val) whose val are the items to the anchors, and the comparison of two such entries."""
    rows = df.where(F.col("id") != query_id).select("id", items(F.col("id"), F.col("payload"), as_literal(anchors), metric).alias("val"))
    nearer = lambda x, y: nearer_by_anchors(x["val"], y["val"], judge, share)
    return rows, (lambda x, y: ~nearer(x, y)) if want == "max" else nearer


def anchored_scores(df: DataFrame, query_id: int, anchors: list, metric: Metric, judge: Judge, share: float = 0.5, want: str = "max") -> DataFrame:
    """id, wins of a small pool where each question is a vote of the anchors (rows id, payload near the query)."""
    rows, beats = _by_anchors(df, query_id, anchors, metric, judge, share, want)
    return scores.round_robin(rows, None, None, beats).select("id", "wins")


def farthest_coin_anchored(df: DataFrame, query_id: int, anchors: list, metric: Metric, judge: Judge, share: float = 0.5, seed: int = 7, t: int = 1, want: str = "max") -> DataFrame:
    """At least the largest distance less 6 alpha, if all anchors are within alpha: a sample and the winners of heats meet in a round robin.

    Every comparison, in the heats too, is a vote of the anchors; no question is asked alone. want = min gives the nearest record.
    """
    if anchors and t > 0 and centers.fits(df, 1, metric):
        found = _anchored(df.where(F.col("id") != query_id), anchors, metric, judge, share, seed, t, want)
        return found.join(distances(df, query_id, metric).withColumnsRenamed({"id": "winner_id", "val": "winner_val"}), "winner_id")
    rows, beats = _by_anchors(df, query_id, anchors, metric, judge, share, want)
    found = extremum.robust_band(rows, judge, t=t, seed=seed, want=want, beats=beats).select("winner_id", "win_score", (F.col("questions") * len(anchors)).alias("questions"))
    return found.join(distances(df, query_id, metric).withColumnsRenamed({"id": "winner_id", "val": "winner_val"}), "winner_id")


class _Votes:
    """Records with their distances to the anchors, and the comparison of two of them by votes."""

    def __init__(self, ids: np.ndarray, gaps: np.ndarray, known: np.ndarray, judge: Judge, share: float, want: str):
        self.ids, self.gaps, self.known, self.judge, self.share, self.want = ids, gaps, known, judge.on_pairs(), share, want

    def _items(self, at: np.ndarray) -> tuple:
        ids, known = np.repeat(self.ids[at], len(self.known)), np.tile(self.known, len(at))
        return np.minimum(ids, known), np.maximum(ids, known), self.gaps[at].ravel()

    def beats(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        m, nearer = len(self.known), np.zeros(len(x), bool)
        for low in range(0, len(x), 1 << 15):
            part = slice(low, low + (1 << 15))
            yes = self.judge.answers(self._items(x[part]), self._items(y[part])).reshape(-1, m).sum(axis=1)
            nearer[part] = yes * 1_000_000 >= m * int(self.share * 1_000_000)
        return ~nearer if self.want == "max" else nearer


def _anchored(df: DataFrame, anchors: list, metric: Metric, judge: Judge, share: float, seed: int, t: int, want: str) -> DataFrame:
    """winner_id, win_score, questions of the robust search by votes: heats in arrays, some to a task, and the finalists' duels in rows of them."""
    form, session = form_of(metric), df.sparkSession
    table, named = form.rows, lambda x: [c.alias(n) for n, c in form.columns(F.col("payload")).items()]
    flat = df.select(F.col("id").cast("long").alias("id"), "payload")
    near = session.range(1).select(F.explode(as_literal(anchors)).alias("x")).select("x.id", F.col("x.payload").alias("payload")).select("id", *named(0)).toPandas()
    known, n = near["id"].to_numpy(np.int64), flat.count()
    heats, size = max(1, math.ceil(math.sqrt(n))), math.ceil(math.sqrt(n)) * t

    def votes(part: pd.DataFrame) -> _Votes:
        rows, m = table(pd.concat([near, part[near.columns]], ignore_index=True)), len(near)
        return _Votes(part["id"].to_numpy(np.int64), np.stack([rows.to(i)[m:] for i in range(m)], axis=1), known, judge, share, want)

    def played(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["heat", "pos", "id"], ignore_index=True)
        won = centers._knocked(np.arange(len(part)), part["heat"].to_numpy(), votes(part).beats)
        return part[part["mark"] | part.index.isin(won)][near.columns]

    dealt = sampling.deal_heats(flat.withColumnRenamed("payload", "val"), heats, t, seed, sampling.drawn(size, n, seed)).withColumnRenamed("val", "payload")
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in flat.select("id", *named(0)).schema)
    tasks = dealt.select("round", "heat", "pos", "mark", "id", *named(0), F.pmod("heat", F.lit(64)).alias("task")).repartition(64, "round", "task")
    pool = tasks.groupBy("round", "task").applyInPandas(played, fields).dropDuplicates(["id"]).toPandas().sort_values("id", ignore_index=True)  # about 2 sqrt(n) t rows
    m = len(pool)

    def duels(parts):
        field = votes(pool)
        for part in parts:
            wins = np.zeros(m, np.int64)
            for i in part["id"].tolist():
                others = np.arange(i + 1, m)
                above = field.beats(np.full(len(others), i), others)
                wins[i] += above.sum()
                wins[i + 1 :] += ~above
            yield pd.DataFrame({"id": field.ids, "wins": wins})

    scored = session.range(m).repartition(max(1, min(64, m // 16))).mapInPandas(duels, "id long, wins long").groupBy("id").agg(F.sum("wins").alias("wins"))
    return scores.pick(scored, seed).select(F.col("id").alias("winner_id"), F.col("wins").alias("win_score"), F.lit(((n - heats) * t + m * (m - 1) // 2) * len(anchors)).cast("long").alias("questions"))


def anchor_counts(near: DataFrame, far: DataFrame, anchors: list, weight: float, judge: Judge) -> DataFrame:
    """n, pairs: for how many pairs of a near and a far record (planted payloads, labels apart by `weight`) n anchors call the near one at most as far. All pairs are asked.

    Ids of near and far are different, and none of the far ones is an anchor's.
    """
    flat = lambda df: df.select(F.col("id").cast("long").alias("id"), F.col("payload.v").alias("payload"), F.col("payload.label").alias("label"))
    if judge.kind != "coin" or judge.flipped or not (cells.plain(flat(near)) and cells.plain(flat(far))):
        metric, members = planted(weight), as_literal(anchors)
        x, y = (df.select(items(F.col("id").cast("long"), F.col("payload"), members, metric).alias(name)) for df, name in ((near, "x"), (far, "y")))
        return scores.opponents(x, y, F.lit(True)).groupBy(count_yes("x", "y", judge).cast("long").alias("n")).agg(F.count("*").alias("pairs"))
    known = [(int(a["id"]), np.asarray(a["payload"]["v"], np.float64), a["payload"]["label"]) for a in anchors]
    seed, bar = judge.seed, threshold(judge.p)

    def work(x: cells.Vectors, y: cells.Vectors) -> pd.DataFrame:
        gaps = lambda side: [side.ticks(v, np.where(side.labels == label, 0.0, weight * weight)) for _, v, label in known]
        xs, ys, field, seen = gaps(x), gaps(y), Field(y.ids), np.zeros(len(known) + 1, np.int64)
        for k, id_ in enumerate(x.ids.tolist()):
            s, said = int(np.searchsorted(y.ids, id_)), np.zeros(len(y.ids), np.int64)
            for (anchor, _, _), dx, dy in zip(known, xs, ys, strict=True):
                t, own = int(np.searchsorted(y.ids, anchor)), f"{min(id_, anchor)}|{max(id_, anchor)}"
                # pairs with an anchor are ordered as their records are
                low, high = min(s, t), max(s, t)
                between = field.coins(f"{seed}|{anchor}|", f"|{own}", t, s) if t < s else field.coins(f"{seed}|{own}|", f"|{anchor}", s, t)
                tossed = np.concatenate([field.coins(f"{seed}|", f"|{anchor}|{own}", 0, low), between, field.coins(f"{seed}|{own}|{anchor}|", "", high)]) < bar
                said[:s] += ~((dy[:s] <= dx[k]) ^ tossed[:s])
                said[s:] += (dx[k] <= dy[s:]) ^ tossed[s:]
            seen += np.bincount(said, minlength=len(seen))
        return pd.DataFrame({"n": np.arange(len(seen)), "pairs": seen})

    return cells.over(flat(near), flat(far), work, "n long, pairs long", 64).groupBy("n").agg(F.sum("pairs").alias("pairs"))


def core_anchors(df: DataFrame, query_id: int, metric: Metric, judge: Judge, near: DataFrame, size: int, seed: int = 7) -> list:
    """Anchors of a query from judged answers alone: the core, around the query, of the records `near` (id, payload), a cluster that holds it."""
    query = df.where(F.col("id") == query_id).select("id", "payload").first()
    return extract_core(near.where(F.col("id") != query_id), query, metric, judge, size + 1, seed)[1:]


RECORDS = 2_000_000  # that a task of queries holds
COPIES = 1 << 26  # records sent to tasks of queries, all tasks together
CELL, ROWS = 4096, 512  # records to a side of a cell, and queries measured at once


def _plain_vectors(df: DataFrame) -> bool:
    """Whether all payloads are finite vectors of one length and ids are never null; others are measured one by one."""
    whole = F.col("id").isNotNull() & F.col("payload").isNotNull() & F.forall("payload", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < 1e100))
    found = df.agg(F.bool_and(F.coalesce(whole, F.lit(False))).alias("whole"), F.min(F.size("payload")).alias("least"), F.max(F.size("payload")).alias("most")).first()
    return bool(found["whole"]) and 0 < found["least"] == found["most"]


def _screened(df: DataFrame, queries: DataFrame, want: str) -> DataFrame:
    """query_id, id, val: of every cell of queries and records each query's best by euclid. A matrix product bounds the distances; all records that may be the best are measured as the metric does."""
    parts, asked = (max(1, math.ceil(x.count() / CELL)) for x in (df, queries))
    dealt = lambda x, own, n, other, m: x.select("id", "payload", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias(other)).groupBy("r", "c")

    def best(q: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(q) and len(e):
            e = e.sort_values("id")
            xs, ys = (np.stack(t["payload"].to_numpy()).astype(np.float64) for t in (q, e))
            names, ids = q["id"].to_numpy(), e["id"].to_numpy()
            square = lambda v: np.einsum("ij,ij->i", v, v)
            for first in range(0, len(xs), ROWS):
                x, name = xs[first : first + ROWS], names[first : first + ROWS]
                off = 1e-12 * (square(x).max() + square(ys).max())
                near = square(x)[:, None] + square(ys)[None, :] - 2 * x @ ys.T
                low, high = np.sqrt(np.maximum(near - off, 0)), np.sqrt(np.maximum(near, 0) + off)
                own = name[:, None] == ids[None, :]
                if want == "max":
                    low[own], high[own] = -np.inf, -np.inf
                    i, j = np.nonzero((high >= low.max(axis=1)[:, None] - 1.1e-6) & ~own)
                else:
                    low[own], high[own] = np.inf, np.inf
                    i, j = np.nonzero((low <= high.min(axis=1)[:, None] + 1.1e-6) & ~own)
                total = np.zeros(len(i))
                for k in range(x.shape[1]):
                    total += (x[i, k] - ys[j, k]) ** 2
                out.append(pd.DataFrame({"query_id": name[i], "id": ids[j], "val": np.floor(np.sqrt(total) * 1_000_000).astype(np.int64)}))
                out[-1] = out[-1].sort_values(["val", "id"], ascending=[want == "min", True]).drop_duplicates("query_id")
        return pd.concat(out) if out else pd.DataFrame({"query_id": [], "id": [], "val": []}).astype("int64")

    return dealt(queries, "r", asked, "c", parts).cogroup(dealt(df, "c", parts, "r", asked)).applyInPandas(best, "query_id long, id long, val long")


def _each_query(df: DataFrame, queries: DataFrame, metric: Metric, work, schema: str) -> DataFrame | None:
    """What work(query's id, ids of the other records in order, distances) makes of every query: a task holds all records and about 64 queries, or more where copies of the records would be many.

    None where Spark has to measure: no form of the metric, payloads that are not plain, ids that repeat, or more records than a task holds.
    """
    form, names = form_of(metric), [f.split()[0] for f in schema.split(", ")]
    whole = lambda x: centers.fits(x, 1, metric)
    n = df.count()
    if form is None or not whole(df) or not whole(queries) or n > RECORDS:
        return None
    table, parts = form.rows, max(8, min(math.ceil(queries.count() / 64), math.ceil(COPIES / max(1, n))))
    flat = lambda x, part: x.select(F.col("id").cast("long").alias("id"), *(c.alias(n) for n, c in form.columns(F.col("payload")).items()), part.alias("part"))
    asked = flat(queries, F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    dealt = flat(df, F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))

    def answered(q: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        e = e.sort_values("id")
        ids, rows, out = e["id"].to_numpy(np.int64), table(pd.concat([e, q], ignore_index=True)), []
        for k, id_ in enumerate(q["id"].tolist()):
            others = ids != id_
            if others.any():
                out.append(work(id_, ids[others], rows.to(len(ids) + k)[: len(ids)][others]))
        return pd.DataFrame(out, columns=names) if out else pd.DataFrame({n: [] for n in names}).astype("int64")

    # tasks of all queries are spread by their own key, so none waits behind another
    return asked.repartition(parts, "part").groupBy("part").cogroup(dealt.repartition(parts, "part").groupBy("part")).applyInPandas(answered, schema)


def batch_exact(df: DataFrame, queries: DataFrame, metric: Metric, want: str = "max") -> DataFrame:
    """query_id, winner_id, winner_val for many queries at once, by true distances. Vectors under euclid meet in cells of matrix products; else up to BROADCAST_ROWS queries are broadcast, more go in cells."""
    best = F.max(F.struct("val", (-F.col("id")).alias("n"))) if want == "max" else F.min(F.struct("val", F.col("id").alias("n")))
    if metric is euclid and _plain_vectors(df) and _plain_vectors(queries):
        gaps = _screened(df, queries, want)
        return gaps.groupBy("query_id").agg(best.alias("w")).select("query_id", (F.abs("w.n")).alias("winner_id"), F.col("w.val").alias("winner_val"))
    side = max if want == "max" else min

    def first(id_: int, ids: np.ndarray, gaps: np.ndarray) -> tuple:
        val = int(side(gaps.max(), gaps.min()))
        return id_, int(ids[gaps == val][0]), val

    found = _each_query(df, queries, metric, first, "query_id long, winner_id long, winner_val long")
    if found is not None:
        return found
    asked = queries.select(F.col("id").alias("query_id"), F.col("payload").alias("q"))
    gaps = scores.opponents(df.select("id", "payload"), asked, F.col("id") != F.col("query_id")).select("query_id", "id", metric(F.col("payload"), F.col("q")).alias("val"))
    return gaps.groupBy("query_id").agg(best.alias("w")).select("query_id", (F.abs("w.n")).alias("winner_id"), F.col("w.val").alias("winner_val"))


def batch_band(df: DataFrame, queries: DataFrame, metric: Metric, judge: Judge, t: int = 1, want: str = "max", seed: int = 7) -> DataFrame:
    """The same by noisy answers: the robust search for all queries at once; heats and finalists are kept by query."""
    directed, others = extremum._directed(judge.on_pairs(), want), df.count() - 1
    heats, kept = max(1, math.ceil(math.sqrt(max(0, others)))), centers._kept(math.ceil(math.sqrt(max(0, others))) * t, others)

    def search(id_: int, ids: np.ndarray, gaps: np.ndarray) -> tuple:
        field, at = Field(ids), int(np.searchsorted(ids, id_))
        toss = lambda name: np.append(field.coins(f"{seed}|{name}|{{", f", {id_}}}", 0, at), field.coins(f"{seed}|{name}|{{{id_}, ", "}", at)).astype(np.int64)
        pairs, pool, asked = (np.minimum(ids, id_), np.maximum(ids, id_), gaps), [np.nonzero(toss(f"draw|{id_}") < kept)[0]], 0
        for turn in range(1, t + 1):
            pos = toss(f"heat|{id_}|{turn}")
            order = np.argsort((pos % heats << 32) | pos, kind="stable")
            pool.append(centers._knocked(order, pos % heats, lambda y, x: ~directed.answers(centers._taken(pairs, y), centers._taken(pairs, x))))
            asked += len(ids) - len(pool[-1])
        pool = np.unique(np.concatenate(pool))
        best, m = pool[centers._champion(centers._taken(pairs, pool), directed, seed, id_)], len(pool)
        return id_, int(ids[best]), int(gaps[best]), m, asked + m * (m - 1) // 2

    found = _each_query(df, queries, metric, search, "query_id long, winner_id long, winner_val long, pool_size long, questions long")
    if found is not None:
        return found
    asked = queries.select(F.col("id").alias("query_id"), F.col("payload").alias("q"))
    gaps = scores.opponents(df.select("id", "payload"), asked, F.col("id") != F.col("query_id")).select("query_id", pair_id(F.col("query_id").cast("long"), F.col("id").cast("long")).alias("id"), metric(F.col("payload"), F.col("q")).alias("val"))
    won = extremum.robust_band_by(gaps, "query_id", judge.on_pairs(), df.count() - 1, t, None, want, seed)
    return won.withColumn("winner_id", F.when(F.col("winner_id.k1") == F.col("query_id"), F.col("winner_id.k2")).otherwise(F.col("winner_id.k1")))
