"""k-center clustering from noisy comparisons. A metric set is a DataFrame (id, payload).

Centers are few: each round brings one row to the driver and sends it to all records as a literal. The state keeps, per record,
its distances to the centers so far and their duel scores, so a round costs one map over the records; it is
materialised every few rounds, so plans do not grow with k.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..functions.ticks import coin
from ..plans.lineage import cut
from . import extremum, sampling, scores, votes
from .judges import Judge, item, pair_id

CUT_EVERY = 8  # rounds after which the state is materialised
AT_ONCE = 4  # arrays of distances and scores that the search for centers in a task holds

def literal(value, kind=None) -> Column:
    """A collected payload as a constant column."""
    if hasattr(value, "asDict"):
        return F.struct(*(literal(v).alias(k) for k, v in value.asDict().items()))
    if isinstance(value, (list, tuple)):
        return F.array(*(F.lit(v) for v in value))
    return F.lit(value)


def as_literal(rows: list) -> Column:
    """Rows (id, payload) as a constant array of structs."""
    return F.array(*(F.struct(F.lit(r["id"]).cast("long").alias("id"), literal(r["payload"]).alias("payload")) for r in rows))


def first_center(df: DataFrame, seed: int = 7):
    return df.orderBy(coin(seed, F.lit("first"), F.col("id")), "id").limit(1).select("id", "payload").collect()[0]


def _center(df: DataFrame, id_: int):
    return df.where(F.col("id") == id_).select("id", "payload").limit(1).collect()[0]


def _named(ids: list[int]) -> Column:
    return F.array(*(F.lit(i).cast("long") for i in ids))


def exact_greedy(df: DataFrame, k: int, metric: Metric, first: int | None = None, seed: int = 7) -> tuple[DataFrame, list[int]]:
    """Farthest-point traversal on true distances; ties go to the smaller id. Returns (id, center_id, center_rank, dist) and the centers."""
    center = _center(df, first) if first is not None else first_center(df, seed)
    state = df.select("id", "payload", metric(F.col("payload"), literal(center["payload"])).alias("dist"), F.lit(center["id"]).cast("long").alias("center_id"), F.lit(1).alias("center_rank"))
    centers = [center["id"]]
    for rank in range(2, k + 1):
        far = state.agg(F.max(F.struct("dist", (-F.col("id")).alias("n"))).alias("w")).first()["w"]
        if far is None or far["dist"] == 0:
            break
        center = _center(df, -far["n"])
        centers.append(center["id"])
        new = metric(F.col("payload"), literal(center["payload"]))
        state = state.withColumn("__new", new).select("id", "payload", F.least("dist", "__new").alias("dist"), F.when(F.col("__new") < F.col("dist"), F.lit(center["id"]).cast("long")).otherwise(F.col("center_id")).alias("center_id"), F.when(F.col("__new") < F.col("dist"), rank).otherwise(F.col("center_rank")).alias("center_rank"))
        if rank % CUT_EVERY == 0:
            state = cut(state)
    return state.select("id", "center_id", "center_rank", "dist"), centers


def start(df: DataFrame) -> DataFrame:
    """The state before the first center: d, the distances to the centers, wins, the duels won by each, and cur, the present one."""
    return df.select("id", "payload", F.array().cast("array<bigint>").alias("d"), F.array().cast("array<int>").alias("wins"), F.lit(0).alias("cur"))


def meet(state: DataFrame, earlier: list[int], new, metric: Metric, judge: Judge, assign: str = "all_pairs") -> DataFrame:
    """The state after a new center has met the earlier ones in duels: one distance and i - 1 questions a record, nothing is asked again.

    all_pairs: the center with most duels won (the earliest of equal ones); incumbent: the new one if it beats the present one.
    A center keeps itself.
    """
    i, ids, pairs = len(earlier), _named([*earlier, new["id"]]), judge.on_pairs()
    side = lambda j: item(pair_id(F.col("id").cast("long"), F.get(ids, j)), F.get("d", j))
    out = state.withColumn("d", F.concat("d", F.array(metric(F.col("payload"), literal(new["payload"])))))
    own = F.array_position(ids, F.col("id").cast("long")).cast("int")
    if not i:
        return out.withColumn("wins", F.array(F.lit(0)))
    if assign == "incumbent":
        to = F.when(pairs.at_most(side(F.lit(i)), side(F.col("cur"))), i).otherwise(F.col("cur"))
        return out.withColumn("cur", F.when(own > 0, own - 1).otherwise(to))
    nearer = F.transform(F.sequence(F.lit(0), F.lit(i - 1)), lambda j: pairs.at_most(side(F.lit(i)), side(j)).cast("int"))
    out = out.withColumn("__nearer", nearer)
    won = F.concat(F.zip_with("wins", "__nearer", lambda w, y: w + 1 - y), F.array(F.aggregate("__nearer", F.lit(0), lambda n, y: n + y)))
    out = out.withColumn("wins", won).drop("__nearer")
    return out.withColumn("cur", F.when(own > 0, own - 1).otherwise(F.array_position("wins", F.array_max("wins")).cast("int") - 1))


def assign_duels(df: DataFrame, centers: list, metric: Metric, judge: Judge) -> DataFrame:
    """id, payload, d, wins, cur for given centers, by the duels of all pairs of them."""
    state = start(df)
    for i, c in enumerate(centers):
        state = meet(state, [x["id"] for x in centers[:i]], c, metric, judge)
        if (i + 1) % CUT_EVERY == 0:
            state = cut(state)
    return state


def band(df: DataFrame, k: int, metric: Metric, judge: Judge, first: int | None = None, t: int = 1, seed: int = 7, frontier: str = "robust", assign: str = "all_pairs") -> tuple[DataFrame, list[int]]:
    """Greedy k-center under band noise, within 2 + O(mu) of the best for small mu.

    frontier: robust (the method's), knockout or sampled (the baselines'). assign: all_pairs (scores of all duels between
    centers) or incumbent (the new center against the present one alone). Questions are about pairs (record, center), so that one
    asked again in a later round has the same answer. A set whose distances a task holds is clustered in arrays with the same draws
    and answers, others by rounds of Spark.
    """
    from . import centers as arrays

    if frontier in arrays.METHODS and arrays.fits(df, AT_ONCE * k, metric):
        return arrays.band(df, k, metric, judge, first, t, seed, frontier, assign)
    n = df.count()
    centers = [_center(df, first) if first is not None else first_center(df, seed)]
    state, asked = start(df), judge.on_pairs()
    while True:
        ids = [c["id"] for c in centers]
        state = meet(state, ids[:-1], centers[-1], metric, judge, assign)
        if len(centers) % CUT_EVERY == 0:
            state = cut(state)
        if len(centers) == k or len(centers) >= n:
            break
        reach = state.where(~F.col("id").isin(ids)).select(pair_id(F.col("id").cast("long"), F.get(_named(ids), F.col("cur"))).alias("id"), F.get("d", F.col("cur")).alias("val"))
        left, draw = n - len(centers), seed + len(centers)
        if frontier == "knockout":
            first_heats = extremum.heat_winners(reach, asked, max(1, math.isqrt(left)), 1, draw).select("id", "val")
            far = extremum.heat_winners(first_heats, asked, 1, 1, draw + 1).select(F.col("id").alias("winner_id"), F.col("val").alias("winner_val"))
        elif frontier == "sampled":
            size = max(1, math.ceil(k * math.log(max(2, n))))
            far = extremum.round_robin(sampling.draw(reach, size, left, draw), asked, seed=draw)
        else:
            far = extremum.robust_band(reach, asked, t=t, seed=draw, n=left)
        got = far.select("winner_id", "winner_val").collect()  # one row
        if not got or got[0]["winner_val"] == 0:
            break
        one, other = got[0]["winner_id"]
        centers.append(_center(df, other if one in ids else one))
    return finish(state, ids), ids


def finish(state: DataFrame, centers: list[int]) -> DataFrame:
    """id, center_id, center_rank, dist."""
    ids = _named(centers)
    return state.select("id", F.get(ids, F.col("cur")).alias("center_id"), (F.col("cur") + 1).alias("center_rank"), F.get("d", F.col("cur")).alias("dist"))


def core_size(n: int, delta: float = 0.1, gamma: float = sampling.GAMMA) -> int:
    return max(1, math.ceil(8 * gamma * math.log(max(2, n) / delta) / 9))


def core_scores(cluster: DataFrame, center, metric: Metric, judge: Judge) -> DataFrame:
    """id, payload, score: how many other members are judged at least as far from the center. The cluster is a sampled, small one."""
    gaps = cluster.where(F.col("id") != center["id"]).select("id", "payload", pair_id(F.col("id").cast("long"), F.lit(center["id"]).cast("long")).alias("pair"), metric(F.col("payload"), literal(center["payload"])).alias("val"))
    asked = gaps.select(F.col("pair").alias("id"), "val")
    scored = scores.loss_scores(asked, asked, judge.on_pairs()).select(F.col("id").alias("pair"), F.col("wins").alias("score"))
    return gaps.select("id", "payload", "pair").join(scored, "pair").select("id", "payload", "score")


def extract_core(cluster: DataFrame, center, metric: Metric, judge: Judge, size: int, seed: int = 7) -> list:
    """The center and the members that score best."""
    scored = core_scores(cluster, center, metric, judge)
    return [center, *scored.orderBy(F.desc("score"), coin(seed, F.lit("core"), F.col("id")), "id").limit(max(0, size - 1)).select("id", "payload").collect()]


def small_core(core: list, seed: int = 7) -> list:
    """About the square root of a core's members: its first ones, which score best."""
    return core[: max(1, math.isqrt(len(core)))]


def nested(cores: list[list]) -> Column:
    """Cores as a constant array of arrays of structs; the center is the first of its core."""
    return F.array(*(as_literal(core) for core in cores))


def sweep_assign(rest: DataFrame, cores: list[list], metric: Metric, judge: Judge, share: float = 0.5) -> DataFrame:
    """id, payload, cur: records visit centers 2..k in order and move when the core of their present center votes for the new one.

    One map, in one expression however many centers there are: the distances to all core members are kept in an array.
    """
    near = F.transform(nested(cores), lambda core: votes.items(F.col("id").cast("long"), F.col("payload"), core, metric))
    moves = lambda cur, i: votes.joins_core(F.get(F.get("__near", i), F.lit(0)), F.get("__near", cur), judge, share, True)
    visited = F.aggregate(F.sequence(F.lit(1), F.lit(len(cores) - 1)), F.lit(0), lambda cur, i: F.when(moves(cur, i), i).otherwise(cur)) if len(cores) > 1 else F.lit(0)
    return rest.select("id", "payload", near.alias("__near")).select("id", "payload", visited.alias("cur"))


def coin_noise(df: DataFrame, k: int, m: int, metric: Metric, judge: Judge, delta: float = 0.1, gamma: float = sampling.GAMMA, first: int | None = None, share: float = 0.5, thin: bool = True, t: int | None = None, seed: int = 7) -> tuple[DataFrame, list[int]]:
    """k-center under coin noise, within a constant factor for clusters of at least m records.

    Records are thinned. The frontier is the robust maximum, sqrt(n) heats and t = log(n / delta) rounds, in which every comparison is
    a vote of the cores of the two records' centers; cores vote in assignments too, and a last map sweeps all other records over
    the centers. The state keeps each record's distances to the core it belongs to, so a comparison measures nothing.
    """
    n, id_ = df.count(), F.col("id").cast("long")
    sample = (sampling.thin(df, m, n, delta, gamma, seed) if thin else df).select("id", "payload")
    size = min(core_size(n, delta, gamma), max(2, m // 2))
    centers = [_center(df, first) if first is not None else first_center(sample, seed)]
    sample = cut(sample.where(F.col("id") != centers[0]["id"]).unionByName(df.where(F.col("id") == centers[0]["id"]).select("id", "payload").limit(1)))
    kept = sample.count()
    cores = [extract_core(sample, centers[0], metric, judge, size, seed)]
    state = cut(sample.select("id", "payload", F.lit(0).alias("cur"), votes.items(id_, F.col("payload"), as_literal(cores[0]), metric).alias("near")))
    t = sampling.rounds_for("kcenter_coin", kept, delta=delta) if t is None else t
    while len(centers) < min(k, kept):
        ids = [c["id"] for c in centers]
        entries = state.where(~F.col("id").isin(ids)).select("id", F.struct("cur", "near").alias("val"))
        farther = lambda x, y: ~votes.nearer_by_cores(x["val"], y["val"], judge, share)
        far = extremum.robust_band(entries, judge, t=t, seed=seed + len(centers), n=kept - len(centers), beats=farther).select("winner_id").collect()  # one row
        centers.append(_center(df, far[0]["winner_id"]))
        to, settled = len(centers) - 1, [c["id"] for core in cores for c in core]
        new = item(pair_id(id_, F.lit(centers[-1]["id"]).cast("long")), metric(F.col("payload"), literal(centers[-1]["payload"])))
        moves = (F.col("id") == centers[-1]["id"]) | (~F.col("id").isin(settled) & votes.joins_core(F.col("__new"), F.col("near"), judge, share))
        moved = cut(state.withColumn("__new", new).select("id", "payload", F.when(moves, to).otherwise(F.col("cur")).alias("cur"), "near"))
        cores.append(extract_core(moved.where(F.col("cur") == to), centers[-1], metric, judge, size, seed))
        state = cut(moved.withColumn("near", F.when(F.col("cur") == to, votes.items(id_, F.col("payload"), as_literal(cores[-1]), metric)).otherwise(F.col("near"))))
    placed = state.select("id", "payload", "cur")
    if thin:
        placed = placed.unionByName(sweep_assign(df.join(sample.select("id"), "id", "left_anti"), cores, metric, judge, share))
    d = F.array(*(metric(F.col("payload"), literal(c["payload"])) for c in centers))
    ids = [c["id"] for c in centers]
    return placed.select("id", F.get(_named(ids), F.col("cur")).alias("center_id"), (F.col("cur") + 1).alias("center_rank"), F.get(d, F.col("cur")).alias("dist")), ids
