"""Queries of the methods, baselines, measures and experiments on the given tables, with DuckDB SQL where SQL can say the same."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import metrics
from .functions.ticks import coin, coin_sql, threshold, ticks
from .operators import baselines, blocking, extremum, kcenter, linkage, measures, noisefit, proximity, sampling, scores, votes
from .operators.judges import Judge, grade, item, same_cluster
from .plans import ledger
from .sources import tables

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SEED, DELTA = 7, 0.1
HELD = "SELECT TRUE AS held"
TICK = "CAST(floor({} * 1e6) AS BIGINT)"
FLAT = f"(SELECT o_orderkey AS id, {TICK.format('o_totalprice')} AS val FROM orders)"
SKEWED = f"(SELECT event_id AS id, {TICK.format('value')} AS val FROM events WHERE value IS NOT NULL AND {TICK.format('value')} > 0)"
SHIFTED = f"(SELECT c_custkey AS id, {TICK.format('(c_acctbal + 1000)')} AS val FROM customer)"
GAP = "CAST(floor(1e6 * sqrt(list_sum(list_transform(list_zip({0}.embedding, {1}.embedding), lambda z: (CAST(z[1] AS DOUBLE) - CAST(z[2] AS DOUBLE)) * (CAST(z[1] AS DOUBLE) - CAST(z[2] AS DOUBLE)))){2})) AS BIGINT)"


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def held(df: DataFrame, condition) -> DataFrame:
    return df.agg(F.coalesce(F.bool_and(condition), F.lit(True)).alias("held"))


def winner(df: DataFrame) -> DataFrame:
    return df.select("winner_id", "winner_val")


# --- ground rules


@query(f"SELECT o_orderkey AS id, {TICK.format('o_totalprice')} AS val FROM orders")
def tick_parity(spark, sf_dir):
    return tables.values_flat(spark, sf_dir)


@query(f"SELECT o_orderkey AS id, {coin_sql(SEED, 'o_orderkey', 'o_custkey')} AS coin FROM orders")
def coin_parity(spark, sf_dir):
    return tables.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), coin(SEED, F.col("o_orderkey"), F.col("o_custkey")).alias("coin"))


# --- judges: which of two orders of a customer is the smaller?


def customer_questions(spark, sf_dir) -> DataFrame:
    orders = tables.table(spark, sf_dir, "orders").select("o_custkey", F.col("o_orderkey").alias("id"), ticks(F.col("o_totalprice")).alias("val"))
    one, two = (orders.select("o_custkey", item(F.col("id"), F.col("val")).alias(s)) for s in "ab")
    return one.join(two, "o_custkey").where("a.id < b.id")


QUESTIONS = f"""WITH o AS (SELECT o_custkey, o_orderkey AS id, {TICK.format("o_totalprice")} AS val FROM orders),
q AS (SELECT x.id AS a, y.id AS b, x.val <= y.val AS truth, greatest(x.val, y.val) AS hi, least(x.val, y.val) AS lo FROM o x JOIN o y ON x.o_custkey = y.o_custkey AND x.id < y.id) """


def answers(spark, sf_dir, judge: Judge) -> DataFrame:
    return customer_questions(spark, sf_dir).select(F.col("a.id").alias("a"), F.col("b.id").alias("b"), judge.at_most(F.col("a"), F.col("b")).alias("yes"))


@query(QUESTIONS + "SELECT a, b, truth AS yes FROM q")
def judge_exact_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.exact())


@query(QUESTIONS + f"SELECT a, b, CASE WHEN hi * 1000 <= lo * 1500 THEN {coin_sql(SEED, 'a', 'b')} < {1 << 31} ELSE truth END AS yes FROM q")
def judge_band_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.band(0.5, "coinflip", seed=SEED))


@query(QUESTIONS + "SELECT a, b, CASE WHEN hi * 1000 <= lo * 2000 THEN NOT truth ELSE truth END AS yes FROM q")
def judge_band_worst_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.band(1.0))


@query(QUESTIONS + f"SELECT a, b, truth <> ({coin_sql(SEED, 'a', 'b')} < {threshold(0.3)}) AS yes FROM q")
def judge_coin_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.coin(0.3, seed=SEED))


@query(QUESTIONS + "SELECT a, b, CASE WHEN hi - lo < 50000000000 THEN NOT truth ELSE truth END AS yes FROM q")
def judge_additive_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.additive_band(50_000_000_000))


@query(QUESTIONS + "SELECT a, b, truth <> (" + coin_sql(SEED, "a", "b", "'attempt2'") + f" < {threshold(0.2)}) AS yes FROM q")
def judge_fresh_grid(spark, sf_dir):
    return answers(spark, sf_dir, Judge.fresh_coin(0.2, 2, seed=SEED))


@query(QUESTIONS + "SELECT a, b, 2 * (" + " + ".join(f"CAST(truth <> ({coin_sql(SEED, 'a', 'b', str(w))} < {threshold(0.2)}) AS INTEGER)" for w in range(3)) + ") > 3 AS yes FROM q")
def crowd_majority_answers(spark, sf_dir):
    return answers(spark, sf_dir, Judge.crowd(0.2, seed=SEED))


@query("SELECT 7 AS judges, TRUE AS held")
def judge_antisymmetry(spark, sf_dir):
    """Swapped questions get the negated answer, and asking again the same one."""
    kinds = [Judge.exact(), Judge.band(0.5, "coinflip"), Judge.band(1.0), Judge.additive_band(50_000_000_000), Judge.coin(0.3), Judge.fresh_coin(0.2, 1), Judge.crowd(0.2)]
    a, b = F.col("a"), F.col("b")
    fine = F.lit(True)
    for judge in kinds:
        fine = fine & (judge.at_most(a, b) == ~judge.at_most(b, a)) & (judge.reversed().at_most(a, b) == ~judge.at_most(a, b))
    return customer_questions(spark, sf_dir).agg(F.lit(len(kinds)).alias("judges"), F.bool_and(fine).alias("held"))


# --- scores and extremes


def _score_sql(beats: str) -> str:
    return f"""WITH v AS {SHIFTED}, q AS (SELECT x.id AS a, y.id AS b, x.val <= y.val AS truth, greatest(x.val, y.val) AS hi, least(x.val, y.val) AS lo FROM v x JOIN v y ON x.id < y.id),
s AS (SELECT a, b, {beats} AS yes FROM q), c AS (SELECT a AS id, CAST(NOT yes AS INTEGER) AS w FROM s UNION ALL SELECT b, CAST(yes AS INTEGER) FROM s), t AS (SELECT id, CAST(sum(w) AS BIGINT) AS wins FROM c GROUP BY id) """


BAND_SQL = "CASE WHEN hi * 1000 <= lo * 2000 THEN NOT truth ELSE truth END"
COIN_SQL = f"truth <> ({coin_sql(SEED, 'a', 'b')} < {threshold(0.3)})"


def _wins(spark, sf_dir, judge):
    df = tables.values_shifted(spark, sf_dir)
    return scores.win_scores(df, df, judge)


@query(_score_sql("truth") + "SELECT * FROM t")
def win_scores_exact(spark, sf_dir):
    return _wins(spark, sf_dir, Judge.exact())


@query(_score_sql(BAND_SQL) + "SELECT * FROM t")
def win_scores_band(spark, sf_dir):
    return _wins(spark, sf_dir, Judge.band(1.0))


@query(_score_sql(COIN_SQL) + "SELECT * FROM t")
def win_scores_coin(spark, sf_dir):
    return _wins(spark, sf_dir, Judge.coin(0.3, seed=SEED))


@query(_score_sql(BAND_SQL) + "SELECT id, (SELECT count(*) - 1 FROM v) - wins AS wins FROM t")
def loss_scores_band(spark, sf_dir):
    df = tables.values_shifted(spark, sf_dir)
    return scores.loss_scores(df, df, Judge.band(1.0))


def _pick_sql(order: str) -> str:
    return f"SELECT t.id AS winner_id, val AS winner_val, wins AS win_score FROM t JOIN v USING (id) ORDER BY wins {order}, {coin_sql(SEED, chr(39) + 'tie' + chr(39), 't.id')}, t.id LIMIT 1"


@query(_score_sql(BAND_SQL) + _pick_sql("DESC"))
def round_robin_band(spark, sf_dir):
    return extremum.round_robin(tables.values_shifted(spark, sf_dir), Judge.band(1.0), seed=SEED).select("winner_id", "winner_val", "win_score")


@query(_score_sql(COIN_SQL) + _pick_sql("DESC"))
def round_robin_coin(spark, sf_dir):
    return extremum.round_robin(tables.values_shifted(spark, sf_dir), Judge.coin(0.3, seed=SEED), seed=SEED, grid=4).select("winner_id", "winner_val", "win_score")


@query(_score_sql(BAND_SQL) + _pick_sql("DESC"))
def bracket_full(spark, sf_dir):
    return extremum.bracket(tables.values_shifted(spark, sf_dir), Judge.band(1.0), fanout=1 << 30, seed=SEED).select("winner_id", "winner_val", "win_score")


def _bracket_bound(spark, sf_dir, fanout):
    df = tables.values_shifted(spark, sf_dir)
    exact = extremum.bracket(df, Judge.exact(), fanout, SEED)
    noisy = measures.against_best(df, extremum.bracket(df, Judge.band(0.2), fanout, SEED))
    best = measures.against_best(df, exact)
    limit = 1.2 ** (2 * math.ceil(math.log(max(2, df.count()), fanout)))
    return noisy.select((F.col("ratio") <= limit).alias("bound")).crossJoin(best.select((F.col("gap") == 0).alias("exact"))).select((F.col("bound") & F.col("exact")).alias("held"))


@query(HELD)
def bracket_fan2(spark, sf_dir):
    return _bracket_bound(spark, sf_dir, 2)


@query(HELD)
def bracket_fan3(spark, sf_dir):
    return _bracket_bound(spark, sf_dir, 3)


MAX_SQL, MIN_SQL = "SELECT id AS winner_id, val AS winner_val FROM {} ORDER BY val DESC, id DESC LIMIT 1", "SELECT id AS winner_id, val AS winner_val FROM {} ORDER BY val, id LIMIT 1"


@query(MAX_SQL.format(FLAT))
def exact_max_flat(spark, sf_dir):
    return winner(extremum.robust_band(tables.values_flat(spark, sf_dir), Judge.exact(), seed=SEED, t=1))


@query(MAX_SQL.format(SKEWED))
def exact_max_skewed(spark, sf_dir):
    return winner(extremum.robust_band(tables.values_skewed(spark, sf_dir), Judge.exact(), seed=SEED, t=1))


@query(MIN_SQL.format(SKEWED))
def exact_min_skewed(spark, sf_dir):
    return winner(extremum.robust_band(tables.values_skewed(spark, sf_dir), Judge.exact(), seed=SEED, t=1, want="min"))


@query(MAX_SQL.format(SKEWED))
def robust_band_events(spark, sf_dir):
    """The largest event stands alone in its band at mu = 0.05, so it must be found."""
    return winner(extremum.robust_band(tables.values_skewed(spark, sf_dir), Judge.band(0.05), seed=SEED))


@query(HELD)
def robust_band_bound(spark, sf_dir):
    df = tables.values_flat(spark, sf_dir)
    return held(measures.against_best(df, extremum.robust_band(df, Judge.band(0.5), seed=SEED)), F.col("ratio") <= 1.5**3)


@query(HELD)
def robust_min_bound(spark, sf_dir):
    df = tables.values_flat(spark, sf_dir)
    return held(measures.against_best(df, extremum.robust_band(df, Judge.band(0.5), seed=SEED, want="min"), "min"), F.col("ratio") <= 1.5**3)


@query(HELD)
def robust_additive_bound(spark, sf_dir):
    df, theta = tables.values_shifted(spark, sf_dir), 200_000_000
    return held(measures.against_best(df, extremum.robust_band(df, Judge.additive_band(theta), seed=SEED)), F.col("gap") <= 3 * theta)


def _rank_bound(df, judge, want):
    n = df.count()
    found = extremum.robust_coin(df, judge, seed=SEED, want=want)
    flipped = df if want == "max" else df.select("id", (-F.col("val")).alias("val"))
    ranked = measures.rank_of(flipped, found if want == "max" else found.withColumn("winner_val", -F.col("winner_val")))
    return held(ranked, F.col("rank") <= 4 * math.log(n / DELTA) ** 2)


@query(HELD)
def robust_coin_rank(spark, sf_dir):
    return _rank_bound(tables.values_flat(spark, sf_dir), Judge.coin(0.3, seed=SEED), "max")


@query(HELD)
def robust_coin_min_rank(spark, sf_dir):
    return _rank_bound(tables.values_skewed(spark, sf_dir), Judge.coin(0.2, seed=SEED), "min")


@query(f"SELECT id, val FROM {FLAT} WHERE {coin_sql(SEED, chr(39) + 'thin' + chr(39), 'id')} < CAST(floor(least(1.0, 2 * ln((SELECT count(*) FROM orders) / 0.1) / 100) * 4294967296) AS BIGINT)")
def thin_sample(spark, sf_dir):
    df = tables.values_flat(spark, sf_dir)
    return sampling.thin(df, 100, df.count(), DELTA, 2, SEED)


@query(HELD)
def draw_samples(spark, sf_dir):
    """The map-only draw keeps about as many distinct records as draws with replacement into slots hold."""
    df = tables.values_flat(spark, sf_dir)
    n = df.count()
    size = n // 2
    expected = n * (1 - (1 - 1 / n) ** size)
    dense = tables.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id")).distinct()
    from pyspark.sql import Window as W

    slots = sampling.draw_slots(dense.withColumn("at", F.row_number().over(W.orderBy("id")) - 1), size, n, SEED)
    counts = sampling.draw(df, size, n, SEED).agg(F.count("*").alias("kept")).crossJoin(slots.agg(F.countDistinct("id").alias("drawn"), F.count("*").alias("all")))
    near = lambda c: F.abs(F.col(c) - expected) < 6 * math.sqrt(n)
    return held(counts, near("kept") & near("drawn") & (F.col("all") == size))


@query(HELD)
def heat_winners_band(spark, sf_dir):
    """The largest event wins its heat in every round, and heats are of nearly equal size."""
    df = tables.values_skewed(spark, sf_dir)
    best = df.agg(F.max("val").alias("best"))
    won = extremum.heat_winners(df, Judge.band(0.05), math.isqrt(df.count()), 3, SEED)
    return held(won.crossJoin(best).groupBy("round").agg(F.max((F.col("val") == F.col("best")).cast("int")).alias("there")), F.col("there") == 1)


def _confusion_sql(values: str, name: str) -> str:
    return f"SELECT '{name}' AS data, count(*) AS n, CAST(sum(CAST(m * 1000 <= val * 2000 AS INTEGER)) AS BIGINT) AS confused, round(sum(CAST(m * 1000 <= val * 2000 AS INTEGER)) / count(*), 6) AS share FROM (SELECT val, max(val) OVER () AS m FROM {values})"


@query(_confusion_sql(FLAT, "flat") + " UNION ALL " + _confusion_sql(SKEWED, "skewed"))
def confusion_share(spark, sf_dir):
    one = lambda name, f: measures.confusion_set(f(spark, sf_dir), 1.0).select(F.lit(name).alias("data"), "n", "confused", "share")
    return one("flat", tables.values_flat).unionByName(one("skewed", tables.values_skewed))


@query(MAX_SQL.format(SKEWED) + "")
def knockout_max(spark, sf_dir):
    return winner(baselines.knockout(tables.values_skewed(spark, sf_dir), Judge.exact(), seed=SEED))


@query(f"WITH v AS {SKEWED}, n AS (SELECT count(*) AS n FROM v) SELECT id AS winner_id, val AS winner_val FROM v, n WHERE {coin_sql(SEED, chr(39) + 'draw' + chr(39), 'id')} < CAST(floor((1 - pow(1 - 1.0 / n, ceil(sqrt(n)))) * 4294967296) AS BIGINT) ORDER BY val DESC, id DESC LIMIT 1")
def sampled_max(spark, sf_dir):
    """The sampler finds the largest of its sample, which is hardly ever that of the set."""
    return winner(baselines.sampled_round_robin(tables.values_skewed(spark, sf_dir), Judge.exact(), seed=SEED))


BASKETS = f"o AS (SELECT o_custkey, o_orderkey AS id, {TICK.format('o_totalprice')} AS val FROM orders)"


def baskets(spark, sf_dir) -> DataFrame:
    """o_custkey, id, val: every customer's orders as a small set."""
    return tables.table(spark, sf_dir, "orders").select("o_custkey", F.col("o_orderkey").alias("id"), ticks(F.col("o_totalprice")).alias("val"))


@query(f"""WITH {BASKETS}, w AS (SELECT o_custkey, list_reduce(list({{'id': id, 'val': val}} ORDER BY id), lambda b, x: CASE WHEN (b.val <= x.val) <> (greatest(b.val, x.val) * 1000 <= least(b.val, x.val) * 2000) THEN x ELSE b END) AS w FROM o GROUP BY o_custkey)
SELECT o_custkey, w.id AS winner_id, TRUE AS robust_is_better FROM w""")
def running_champion_chain(spark, sf_dir):
    """Every customer's orders in a chain, all confusable answers wrong: the running champion falls step by step, and on average it is worse than the robust search."""
    df, judge = baskets(spark, sf_dir), Judge.band(1.0)
    champion = extremum.running_champion(df, judge, by="o_custkey")
    robust = extremum.robust_band_by(df, "o_custkey", judge, 16, 4, seed=SEED).select("o_custkey", F.col("winner_val").alias("robust_val"))
    best = df.groupBy("o_custkey").agg(F.max("val").alias("best"))
    loss = lambda c: F.avg(F.col("best") / F.col(c))
    better = champion.join(robust, "o_custkey").join(best, "o_custkey").agg((loss("robust_val") < loss("winner_val")).alias("robust_is_better"))
    return champion.select("o_custkey", "winner_id").crossJoin(F.broadcast(better))


@query(HELD)
def ledger_formula(spark, sf_dir):
    """The questions that heats and finalists were counted to ask are those of the closed form, but for heats left empty by the hash."""
    df = tables.values_flat(spark, sf_dir)
    n = df.count()
    counted = extremum.robust_band_by(extremum.runs_of(df, 1), "run", Judge.band(1.0, pairs=True), n, 1, seed=SEED)
    heats, pool = math.ceil(math.sqrt(n)), F.col("pool_size")
    in_heats = F.col("questions") - pool * (pool - 1) / 2
    form = extremum.robust_band(df, Judge.band(1.0), t=1, seed=SEED)
    return held(counted, in_heats.between(n - heats, n - 0.9 * heats) & (pool <= 2 * heats + 3 * math.sqrt(heats))).crossJoin(held(form, F.col("questions") == ledger.robust_band(n, 0, 1) + pool * (pool - 1) / 2).withColumnRenamed("held", "formed")).select((F.col("held") & F.col("formed")).alias("held"))


@query()
def scaling_questions(spark, sf_dir):
    """Questions of the robust minimum on sets of different size, and per record."""
    out = None
    for name, f in (("customer", tables.values_shifted), ("orders", tables.values_flat), ("events", tables.values_skewed)):
        df = f(spark, sf_dir)
        row = extremum.robust_band(df, Judge.band(1.0), t=1, seed=SEED, want="min").select(F.lit(name).alias("data"), F.lit(df.count()).alias("n"), "pool_size", "questions")
        out = row if out is None else out.unionByName(row)
    return out.withColumn("per_record", F.round(F.col("questions") / F.col("n"), 3))


# --- farthest and nearest


ALL_GAPS = f"SELECT q.vec_id AS query_id, e.vec_id AS id, {GAP.format('q', 'e', '')} AS val FROM embeddings q JOIN embeddings e ON q.vec_id <> e.vec_id"


@query(f"WITH g AS ({ALL_GAPS} WHERE q.vec_id = 0) SELECT id AS winner_id, val AS winner_val FROM g ORDER BY val DESC, id DESC LIMIT 1")
def farthest_exact(spark, sf_dir):
    return winner(proximity.farthest_band(tables.vectors(spark, sf_dir), 0, metrics.euclid, Judge.exact(), t=1))


@query(f"WITH g AS ({ALL_GAPS} WHERE q.vec_id = 0) SELECT id AS winner_id, val AS winner_val FROM g ORDER BY val, id LIMIT 1")
def nearest_exact(spark, sf_dir):
    return winner(proximity.nearest_band(tables.vectors(spark, sf_dir), 0, metrics.euclid, Judge.exact(), t=1))


@query(f"SELECT query_id, id AS winner_id, val AS winner_val FROM ({ALL_GAPS}) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY val DESC, id) = 1")
def batch_farthest(spark, sf_dir):
    df = tables.vectors(spark, sf_dir)
    return proximity.batch_exact(df, df, metrics.euclid)


@query(f"SELECT query_id, id AS winner_id, val AS winner_val FROM ({ALL_GAPS}) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY val, id) = 1")
def batch_nearest(spark, sf_dir):
    df = tables.vectors(spark, sf_dir)
    return proximity.batch_exact(df, df, metrics.euclid, "min")


@query(HELD)
def farthest_coin_rank(spark, sf_dir):
    df = tables.customer_tree(spark, sf_dir)
    gaps = proximity.distances(df, 1, metrics.tree)
    return held(measures.rank_of(gaps, proximity.farthest_coin_rank(df, 1, metrics.tree, Judge.coin(0.2, seed=SEED))), F.col("rank") <= 4 * math.log(gaps.count() / DELTA) ** 2)


@query(HELD)
def farthest_anchored_6alpha(spark, sf_dir):
    """Anchors of the query's own planted cluster lie within alpha; votes lose at most 6 alpha, and find a record of another cluster."""
    df = tables.planted(spark, sf_dir)
    metric = metrics.planted(4.0)
    gaps = proximity.distances(df, 0, metric)
    near = gaps.orderBy("val", "id").limit(24)
    anchors = df.join(near, "id").select("id", "payload", "val").collect()
    found = proximity.farthest_coin_anchored(df, 0, anchors, metric, Judge.coin(0.2, seed=SEED))
    return held(measures.against_best(gaps, found), (F.col("gap") <= 6 * max(a["val"] for a in anchors)) & (F.col("winner_val") >= 4_000_000))


# --- k-center


@query("SELECT label AS truth, count(*) AS n, 1 AS centers FROM embeddings GROUP BY label")
def kcenter_band_planted(spark, sf_dir):
    """At mu = 1 only distances within a planted cluster are confusable, so every cluster is found."""
    df = tables.planted(spark, sf_dir)
    found, _ = kcenter.band(df.select("id", "payload"), 10, metrics.planted(4.0), Judge.band(1.0, seed=SEED), seed=SEED)
    return found.join(df.select("id", "truth"), "id").groupBy("truth").agg(F.count("*").alias("n"), F.countDistinct("center_id").cast("int").alias("centers"))


@query("SELECT n_regionkey AS truth, count(*) AS n, 1 AS centers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def kcenter_band_regions(spark, sf_dir):
    df = tables.customer_tree(spark, sf_dir)
    found, _ = kcenter.band(df.select("id", "payload"), 5, metrics.tree, Judge.band(1.0, seed=SEED), seed=SEED)
    return found.join(df.select("id", "truth"), "id").groupBy("truth").agg(F.count("*").alias("n"), F.countDistinct("center_id").cast("int").alias("centers"))


def _greedy_sql(k: int) -> str:
    gap = GAP.format("e", "c", "")
    parts = [f"c1 AS (SELECT * FROM embeddings WHERE vec_id = 0), s1 AS (SELECT e.vec_id, {gap} AS d FROM embeddings e, c1 c)"]
    for i in range(2, k + 1):
        parts.append(f"c{i} AS (SELECT e.* FROM embeddings e JOIN (SELECT vec_id FROM s{i - 1} ORDER BY d DESC, vec_id LIMIT 1) USING (vec_id)), s{i} AS (SELECT e.vec_id, least(s.d, {gap}) AS d FROM embeddings e JOIN s{i - 1} s USING (vec_id), c{i} c)")
    return "WITH " + ", ".join(parts) + f" SELECT vec_id AS id, d AS dist FROM s{k}"


@query(_greedy_sql(5))
def kcenter_exact_greedy(spark, sf_dir):
    return kcenter.exact_greedy(tables.vectors(spark, sf_dir), 5, metrics.euclid, first=0)[0].select("id", "dist")


@query(f"SELECT max(dist) AS radius FROM ({_greedy_sql(5)})")
def kcenter_objective(spark, sf_dir):
    return measures.objective(kcenter.exact_greedy(tables.vectors(spark, sf_dir), 5, metrics.euclid, first=0)[0])


@query("SELECT e.vec_id AS id, CAST(CASE WHEN e.vec_id = 0 THEN 0 WHEN e.vec_id = 1 THEN 1 WHEN e.vec_id = 2 THEN 2 ELSE (CASE WHEN a <= b AND a <= c THEN 0 WHEN b <= c THEN 1 ELSE 2 END) END AS INTEGER) AS cur FROM (SELECT e.vec_id, " + ", ".join(f"{GAP.format('e', x, '')} AS {x}" for x in "abc") + " FROM embeddings e, (SELECT * FROM embeddings WHERE vec_id = 0) a, (SELECT * FROM embeddings WHERE vec_id = 1) b, (SELECT * FROM embeddings WHERE vec_id = 2) c) e")
def kcenter_assign_duels(spark, sf_dir):
    df = tables.vectors(spark, sf_dir)
    centers = df.where("id < 3").orderBy("id").select("id", "payload").collect()
    return kcenter.assign_duels(df, centers, metrics.euclid, Judge.exact()).select("id", F.col("cur").cast("int").alias("cur"))


@query(HELD)
def kcenter_assign_bound(spark, sf_dir):
    df = tables.vectors(spark, sf_dir)
    centers = df.where("id < 5").orderBy("id").select("id", "payload").collect()
    state = kcenter.assign_duels(df, centers, metrics.euclid, Judge.band(0.2))
    found = kcenter.finish(state, [c["id"] for c in centers])
    return held(measures.assignment_quality(found, df, centers, metrics.euclid), F.col("worst") <= 1.2**2)


@query(f"SELECT e.vec_id AS id, CAST((SELECT count(*) FROM ({ALL_GAPS} WHERE q.vec_id = 0) o WHERE o.id <> g.id AND (g.val < o.val OR (g.val = o.val AND g.id < o.id))) AS BIGINT) AS score FROM embeddings e JOIN ({ALL_GAPS} WHERE q.vec_id = 0) g ON g.id = e.vec_id")
def core_extract_exact(spark, sf_dir):
    df = tables.vectors(spark, sf_dir)
    center = df.where("id = 0").select("id", "payload").first()
    return kcenter.core_scores(df, center, metrics.euclid, Judge.exact()).select("id", F.col("score").cast("long").alias("score"))


# --- hierarchies


@query("WITH s AS (SELECT CAST(floor((s_acctbal + 1000) * 1e6) AS BIGINT) AS v FROM supplier) SELECT d AS link_dist, count(*) AS n FROM (SELECT lead(v) OVER (ORDER BY v) - v AS d FROM s) WHERE d IS NOT NULL GROUP BY d")
def linkage_single_line(spark, sf_dir):
    """On a line the single-linkage merges are the gaps between neighbours."""
    df = tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("payload"))
    return baselines.linkage_exact(df, linkage.line).groupBy("link_dist").agg(F.count("*").alias("n"))


@query()
def linkage_methods(spark, sf_dir):
    """Mean merged distance over the exact hierarchy's: ours and the baselines, both linkages, band noise."""
    df = tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("payload"))
    judge, out = Judge.band(0.5, seed=SEED), None
    for link in ("single", "complete"):
        exact = baselines.linkage_exact(df, linkage.line, link)
        runs = {"ours": linkage.hierarchy(df, linkage.line, judge, link), "sampler": baselines.linkage_sampled(df, linkage.line, judge, link), "knockout": baselines.linkage_knockout(df, linkage.line, judge, link)}
        for name, found in runs.items():
            row = measures.merge_ratio(found, exact).crossJoin(found.agg(F.max("questions").alias("questions"))).select(F.lit(link).alias("link"), F.lit(name).alias("method"), "ratio", "questions")
            out = row if out is None else out.unionByName(row)
    return out


def line_edges(df: DataFrame, width: int = 8) -> DataFrame:
    """a, b, dist: every record (id, v) of a line with the next `width` in order. Each edge left out is the longest of a cycle through neighbours, so a minimum spanning tree is whole."""
    from pyspark.sql import Window as W

    after = W.orderBy("v", "id").rowsBetween(1, width)
    near = df.select("id", "v", F.collect_list(F.struct("id", "v")).over(after).alias("near")).select("id", "v", F.explode("near").alias("o"))
    return near.select(F.least("id", "o.id").alias("a"), F.greatest("id", "o.id").alias("b"), (F.col("o.v") - F.col("v")).alias("dist"))


@query("WITH v AS (SELECT s_suppkey AS id, CAST(floor((s_acctbal + 1000) * 1e6) AS BIGINT) AS v FROM supplier) SELECT CAST(sum(d) AS BIGINT) AS total FROM (SELECT lead(v) OVER (ORDER BY v) - v AS d FROM v)")
def linkage_parallel_rounds(spark, sf_dir):
    """The edges the simultaneous merges take weigh as much as the minimum spanning tree, which lies in the graph of neighbours on the line."""
    return linkage.parallel_rounds(line_edges(tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("v")))).agg(F.sum("dist").alias("total"))


@query("""WITH t AS (SELECT p_partkey AS id, unnest(list_distinct(list_filter(regexp_split_to_array(lower(p_brand || ' ' || p_name), '[^a-z0-9]+'), lambda x: x <> ''))) AS token FROM part)
SELECT x.id AS a, y.id AS b, count(*) AS common FROM t x JOIN t y ON x.token = y.token AND x.id < y.id GROUP BY 1, 2 HAVING count(*) >= 2""")
def token_block_pairs(spark, sf_dir):
    """Parts that share two tokens or more."""
    df = tables.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.concat_ws(" ", "p_brand", "p_name").alias("words"))
    return blocking.token_pairs(df, "words", 2)


# --- how judges err


PAIR_SQL = "SELECT x.c_custkey AS a, y.c_custkey AS b, x.c_nationkey = y.c_nationkey AS truth FROM customer x JOIN customer y ON x.c_custkey < y.c_custkey AND x.c_mktsegment = y.c_mktsegment"


@query(f"WITH q AS ({PAIR_SQL}), s AS (SELECT truth, CASE WHEN truth THEN {coin_sql(SEED, 'a', 'b')} >= {threshold(0.5)} ELSE {coin_sql(SEED, 'a', 'b')} < {threshold(0.001)} END AS yes FROM q) SELECT CAST(sum(CAST(yes AS INTEGER)) AS BIGINT) AS pairs_said, CAST(sum(CAST(truth AS INTEGER)) AS BIGINT) AS pairs_same, CAST(sum(CAST(yes AND truth AS INTEGER)) AS BIGINT) AS pairs_both FROM s")
def same_cluster_precision_recall(spark, sf_dir):
    """Same-nation questions with half of the pairs missed: high precision, recall one half."""
    df = tables.table(spark, sf_dir, "customer").select("c_mktsegment", F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("truth"))
    both = df.alias("x").join(df.alias("y"), (F.col("x.c_mktsegment") == F.col("y.c_mktsegment")) & (F.col("x.id") < F.col("y.id")))
    said = both.select((F.col("x.truth") == F.col("y.truth")).alias("truth"), same_cluster(F.col("x.truth"), F.col("y.truth"), F.col("x.id"), F.col("y.id"), 0.5, 0.001, SEED).alias("yes"))
    return measures.pair_answers_fscore(said).select("pairs_said", "pairs_same", "pairs_both")


@query("SELECT TRUE AS same_within, TRUE AS other_within")
def grade_error(spark, sf_dir):
    """Distance grades are off by at most 20 % inside clusters and 50 % across."""
    off = noisefit.most_off(tables.planted(spark, sf_dir), 4.0)
    return off.select((F.col("s") <= 0.2001).alias("same_within"), (F.col("o") <= 0.5001).alias("other_within"))


def _questions(spark, sf_dir, per_cell: int | None = 200) -> DataFrame:
    df = tables.vectors(spark, sf_dir)
    per_cell = per_cell or noisefit.per_cell(df.count())
    return noisefit.sample_questions(noisefit.lowest_pairs(df, metrics.euclid, 10, 1_000_000, 1_800_000, per_cell, SEED), per_cell, SEED)


def _grid(spark, sf_dir, judge: Judge, per_cell: int | None = 200) -> DataFrame:
    return noisefit.ask(_questions(spark, sf_dir, per_cell), judge)


def _grid_sql(said: str, out: str) -> str:
    keys = ("x1", "x2", "y1", "y2")
    coin = lambda *more: coin_sql(SEED, *keys, *more)
    return f"""WITH p AS (SELECT x.vec_id AS a, y.vec_id AS b, {GAP.format("x", "y", "")} AS dist FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id),
k AS (SELECT *, CAST(least(greatest(floor((dist - 1000000.0) * 10 / 800000) + 1, 1), 10) AS INTEGER) AS bucket FROM p),
r AS (SELECT *, row_number() OVER (PARTITION BY bucket ORDER BY {coin_sql(SEED, "'cell'", "a", "b")}, a, b) AS slot FROM k),
n AS (SELECT CAST(ceil(ln(count(*))) AS BIGINT) AS n FROM embeddings),
q AS (SELECT o.bucket AS bucket1, t.bucket AS bucket2, o.a < t.a OR (o.a = t.a AND o.b < t.b) AS fore, o.*, t.a AS ta, t.b AS tb, t.dist AS td FROM r o JOIN r t ON t.slot = o.slot + 1 AND o.bucket <= t.bucket, n WHERE o.slot <= n),
c AS (SELECT bucket1, bucket2, CASE WHEN fore THEN a ELSE ta END AS x1, CASE WHEN fore THEN b ELSE tb END AS x2, CASE WHEN fore THEN ta ELSE a END AS y1, CASE WHEN fore THEN tb ELSE b END AS y2, CASE WHEN fore THEN dist <= td ELSE td <= dist END AS truth, least(dist, td) AS lo, greatest(dist, td) AS hi FROM q),
w AS (SELECT bucket1, bucket2, truth = ({said.format(coin=coin(), **{f"coin{i}": coin(str(i)) for i in range(3)})}) AS correct FROM c) {out}"""


ACCURACY = "count(*) AS asked, round(avg(CAST(correct AS DOUBLE)), 6) AS accuracy FROM w"


@query(_grid_sql(f"CASE WHEN hi * 1000 <= lo * 1100 THEN {{coin}} < {1 << 31} ELSE truth END", f"SELECT bucket1, bucket2, {ACCURACY} GROUP BY 1, 2"))
def accuracy_grid(spark, sf_dir):
    """Accuracy by buckets of distance, ln n questions for each two buckets, under band noise."""
    return noisefit.accuracy_grid(_grid(spark, sf_dir, Judge.band(0.1, "coinflip", seed=SEED), None))


@query(_grid_sql("(" + " + ".join(f"CAST(truth <> ({{coin{i}}} < {threshold(0.2)}) AS INTEGER)" for i in range(3)) + ") * 2 > 3", f"SELECT coalesce(bucket1, -1) AS bucket1, coalesce(bucket2, -1) AS bucket2, {ACCURACY} GROUP BY CUBE (bucket1, bucket2)"))
def accuracy_cube(spark, sf_dir):
    """The same with its margins, for a majority of three workers."""
    return noisefit.accuracy_cube(_grid(spark, sf_dir, Judge.crowd(0.2, seed=SEED), None))


@query("SELECT 'band' AS band, 'coin' AS coin, TRUE AS mu_near, TRUE AS p_near")
def fit_noise_model(spark, sf_dir):
    """The model, mu and p are recovered from answers."""
    questions = _questions(spark, sf_dir).persist()
    band, toss = noisefit.ask(questions, Judge.band(0.1, "coinflip", seed=SEED)), noisefit.ask(questions, Judge.coin(0.2, seed=SEED))
    out = noisefit.choose_model(band).select(F.col("model").alias("band")).crossJoin(noisefit.choose_model(toss).select(F.col("model").alias("coin")))
    out = out.crossJoin(noisefit.estimate_mu(band)).crossJoin(noisefit.estimate_p(toss))
    return out.select("band", "coin", (F.abs(F.col("mu_milli") - 100) <= 30).alias("mu_near"), (F.abs(F.col("p") - 0.2) <= 0.05).alias("p_near"))


# --- worked examples


WON = f"s AS (SELECT a, b, {BAND_SQL} AS yes FROM q), c AS (SELECT a AS id, CAST(NOT yes AS INTEGER) AS w FROM s UNION ALL SELECT b, CAST(yes AS INTEGER) FROM s UNION ALL SELECT id, 0 FROM {{}}) SELECT id AS x, CAST(sum(w) AS BIGINT) AS n FROM c GROUP BY id"


def _around_sql(which: str) -> str:
    """Gaps g of every customer's orders to the first or the last one, and the questions q about them."""
    return f"""WITH {BASKETS}, m AS (SELECT o_custkey, {which}(id) AS mid, arg_{which}(val, id) AS mval FROM o GROUP BY o_custkey), g AS (SELECT o_custkey, id, abs(val - mval) AS val FROM o JOIN m USING (o_custkey) WHERE id <> mid),
q AS (SELECT x.id AS a, y.id AS b, x.val <= y.val AS truth, greatest(x.val, y.val) AS hi, least(x.val, y.val) AS lo FROM g x JOIN g y ON x.o_custkey = y.o_custkey AND x.id < y.id), """


def around(spark, sf_dir, which) -> DataFrame:
    """o_custkey, id, val: gaps of every customer's orders to the first or the last one (which: F.min or F.max)."""
    df = baskets(spark, sf_dir)
    center = df.groupBy("o_custkey").agg(which(F.struct("id", "val")).alias("m"))
    return df.join(center, "o_custkey").where("id <> m.id").select("o_custkey", "id", metrics.gap(F.col("val"), F.col("m.val")).alias("val"))


def _won(df: DataFrame) -> DataFrame:
    return scores.win_scores_by(df, "o_custkey", Judge.band(1.0)).select(F.col("id").alias("x"), F.col("wins").alias("n"))


@query(QUESTIONS.rstrip() + ", " + WON.format("o"))
def worked_scores(spark, sf_dir):
    """Win scores of every customer's orders at mu = 1, all confusable answers wrong."""
    return _won(baskets(spark, sf_dir))


@query(_around_sql("max") + WON.format("g"))
def worked_kcenter(spark, sf_dir):
    """Every customer's last order as the first center: duels for the farthest order, all confusable answers wrong."""
    return _won(around(spark, sf_dir, F.max))


REGIONS = "c AS (SELECT c_custkey AS id, c_nationkey AS nation, n_regionkey AS region FROM customer JOIN nation ON c_nationkey = n_nationkey)"


@query(f"WITH {REGIONS}, p AS (SELECT x.region = y.region AS truth, x.nation = y.nation AS yes FROM c x JOIN c y ON x.id < y.id) SELECT round(2.0 * count(*) FILTER (WHERE truth AND yes) / (count(*) FILTER (WHERE yes) + count(*) FILTER (WHERE truth)), 6) AS pairwise, CAST(1.0 AS DOUBLE) AS comparisons FROM p")
def six_items_fscore(spark, sf_dir):
    """Customers in clusters by region: answers about all pairs that know the same nation only, against k-center by distance comparisons."""
    df = tables.customer_tree(spark, sf_dir)
    pairs = measures.class_pairs(df.select(F.col("truth"), F.col("payload.nation").alias("nation")))
    answered = pairs.select((F.col("x.truth") == F.col("y.truth")).alias("truth"), (F.col("x.nation") == F.col("y.nation")).alias("yes"), "n")
    full = measures.pair_fscore(kcenter.band(df.select("id", "payload"), 5, metrics.tree, Judge.band(0.5, seed=SEED), seed=SEED)[0], df.select("id", "truth"))
    return measures.pair_answers_fscore(answered).select(F.col("fscore").alias("pairwise")).crossJoin(full.select(F.col("fscore").alias("comparisons")))


# --- experiments with a crowd judge, and sweeps over k


SETS = {"embeddings": (tables.vectors, metrics.euclid, 0), "customers": (tables.customer_tree, metrics.tree, 1), "parts": (tables.part_catalogue, metrics.catalogue, 1)}


def _crowd(spark, sf_dir, want):
    judge, out = Judge.crowd(0.15, seed=SEED), None
    for name, (load, metric, at) in SETS.items():
        gaps = proximity.distances(load(spark, sf_dir), at, metric)
        for method, found in (("ours", extremum.robust_band(gaps, judge, t=1, want=want, seed=SEED)), ("knockout", baselines.knockout(gaps, judge, want, SEED)), ("sampler", baselines.sampled_round_robin(gaps, judge, want, SEED))):
            row = measures.against_best(gaps, found, want).select(F.lit(name).alias("data"), F.lit(method).alias("method"), "winner_val", "best_val", "questions")
            out = row if out is None else out.unionByName(row)
    return out.withColumn("dollars", F.round(F.col("questions") * measures.QUESTION_PRICE, 2))


@query()
def farthest_crowd(spark, sf_dir):
    """Farthest record under a majority of three workers: ours, knockout, sampler, and the true optimum, on three metrics."""
    return _crowd(spark, sf_dir, "max")


@query()
def nearest_crowd(spark, sf_dir):
    return _crowd(spark, sf_dir, "min")


@query(HELD)
def kcenter_ratio(spark, sf_dir):
    """The band-noise radius over ten planted clusters is within (1 + mu)**9 of greedy's on true distances, below the distance of clusters."""
    df, metric = tables.planted(spark, sf_dir).select("id", "payload"), metrics.planted(4.0)
    ours, _ = kcenter.band(df, 10, metric, Judge.band(0.05, seed=SEED), seed=SEED)
    exact, _ = kcenter.exact_greedy(df, 10, metric, seed=SEED)
    both = measures.objective(ours).crossJoin(measures.objective(exact).withColumnRenamed("radius", "best"))
    return held(both, (F.col("radius") <= F.col("best") * measures.kcenter_bound(0.05) / 2) & (F.col("radius") < 4_000_000))


@query()
def kcenter_feature_greedy(spark, sf_dir):
    """Clusters of the parts by the similarity of their names alone, without a question."""
    df = tables.part_catalogue(spark, sf_dir)
    found, _ = baselines.feature_greedy(df.select("id", F.col("payload.words").alias("payload")), 6, metrics.jaccard)
    return measures.pair_fscore(found, df.select("id", "truth"))


@query()
def same_cluster_questions(spark, sf_dir):
    """Clusters from 150 same-cluster questions, against the regions."""
    df = tables.customer_tree(spark, sf_dir).select("id", "truth")
    pairs = baselines.same_cluster_pairs(df, 150, SEED)
    named = pairs.join(df.withColumnsRenamed({"id": "a", "truth": "ta"}), "a").join(df.withColumnsRenamed({"id": "b", "truth": "tb"}), "b")
    yes = named.where(same_cluster(F.col("ta"), F.col("tb"), F.col("a"), F.col("b"), 0.5, 0.02, SEED)).select("a", "b")
    return measures.pair_fscore(baselines.clusters_of_yes(df, yes), df)


@query(f"""WITH c AS (SELECT * FROM embeddings WHERE vec_id = 0), r AS (SELECT * FROM embeddings WHERE vec_id IN (10, 20, 30, 40, 50))
SELECT u.vec_id AS id, CAST(sum(CASE WHEN {GAP.format("u", "c", "")} < {GAP.format("u", "r", "")} OR ({GAP.format("u", "c", "")} = {GAP.format("u", "r", "")}) THEN 1 ELSE 0 END) AS BIGINT) AS yes FROM embeddings u, c, r WHERE u.vec_id NOT IN (0, 10, 20, 30, 40, 50) GROUP BY 1""")
def assign_by_core_votes(spark, sf_dir):
    """How many of five core members say that a record is at least as near to the new center 0 as to themselves, by an exact judge."""
    df = tables.vectors(spark, sf_dir).select("id", "payload")
    core = kcenter.as_literal(df.where(F.col("id").isin(10, 20, 30, 40, 50)).orderBy("id").collect())
    center = kcenter.as_literal(df.where("id = 0").collect())[0]
    rest = df.where(~F.col("id").isin(0, 10, 20, 30, 40, 50))
    return rest.select("id", votes.core_yes(F.struct("id", "payload"), center, core, Judge.exact(), metrics.euclid).cast("long").alias("yes"))


@query(HELD)
def sweep_assign_exact(spark, sf_dir):
    """Under an exact judge the final sweep over planted clusters puts every record with a center of its own label."""
    df = tables.planted(spark, sf_dir)
    metric = metrics.planted(4.0)
    first = df.groupBy("truth").agg(F.min("id").alias("id")).orderBy("id")
    centers = df.join(first.select("id"), "id").orderBy("id").select("id", "payload", "truth").collect()
    size = kcenter.core_size(df.count(), DELTA)
    cores = [kcenter.extract_core(df.where(F.col("truth") == c["truth"]), c, metric, Judge.exact(), size, SEED) for c in centers]
    label = F.array(*(F.lit(c["truth"]) for c in centers))
    swept = kcenter.sweep_assign(df, cores, metric, Judge.exact()).join(df.select("id", "truth"), "id")
    return held(swept, F.get(label, F.col("cur")) == F.col("truth"))


@query()
def ledger_largest(spark, sf_dir):
    """Questions and seconds of the robust and the baseline extremes on lineitem at mu = 1."""
    import time

    df, judge, book = tables.values_large(spark, sf_dir), Judge.band(1.0, seed=SEED), ledger.Ledger()
    for want in ("max", "min"):
        for method, run in (("ours", lambda w: extremum.robust_band(df, judge, t=1, want=w, seed=SEED)), ("knockout", lambda w: baselines.knockout(df, judge, w, SEED)), ("sampler", lambda w: baselines.sampled_round_robin(df, judge, w, SEED))):
            began = time.monotonic()
            row = run(want).first()
            book.record(method, want, row["questions"], seconds=round(time.monotonic() - began, 3))
    return book.frame(spark)


def _suppliers(spark, sf_dir):
    return tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("payload"))


@query(HELD)
def linkage_complete_exact(spark, sf_dir):
    """Neighbour pointers and witness pairs give the distances of the search over all cluster pairs."""
    df = _suppliers(spark, sf_dir)
    fast, slow = (linkage.hierarchy(df, linkage.line, Judge.exact(), "complete", naive=naive).select("step", "link_dist") for naive in (False, True))
    return held(fast.join(slow.withColumnRenamed("link_dist", "other"), "step"), F.col("link_dist") == F.col("other"))


@query(HELD)
def linkage_single_band(spark, sf_dir):
    """Merged distances under band noise are on average within (1 + mu)**3 of the exact hierarchy's."""
    df = _suppliers(spark, sf_dir)
    return held(measures.merge_ratio(linkage.hierarchy(df, linkage.line, Judge.band(0.5, seed=SEED)), baselines.linkage_exact(df, linkage.line)), F.col("ratio") <= 1.5**3)


@query(HELD)
def linkage_complete_band(spark, sf_dir):
    df = _suppliers(spark, sf_dir)
    return held(measures.merge_ratio(linkage.hierarchy(df, linkage.line, Judge.band(0.5, seed=SEED), "complete"), baselines.linkage_exact(df, linkage.line, "complete")), F.col("ratio") <= 1.5**3)


@query(HELD)
def nearest_coin_rank(spark, sf_dir):
    df = tables.customer_tree(spark, sf_dir)
    gaps = proximity.distances(df, 1, metrics.tree)
    found = proximity.nearest_coin(df, 1, metrics.tree, Judge.coin(0.2, seed=SEED)).withColumn("winner_val", -F.col("winner_val"))
    return held(measures.rank_of(gaps.select("id", (-F.col("val")).alias("val")), found), F.col("rank") <= 4 * math.log(gaps.count() / DELTA) ** 2)


@query()
def anchored_asymmetry(spark, sf_dir):
    """Share of right votes by anchors, for questions in both orders, by vote mode: 0.3 protects one direction only."""
    df = tables.planted(spark, sf_dir)
    metric, p = metrics.planted(4.0), 0.3
    gaps = proximity.distances(df, 0, metric)
    anchors = df.join(gaps.orderBy("val", "id").limit(24), "id").select("id", "payload").collect()  # 24 rows
    joined = df.join(gaps, "id")
    counted = proximity.anchor_counts(joined.where(F.col("val") < 2_000_000), joined.where(F.col("val") >= 3_000_000), anchors, 4.0, Judge.coin(p, seed=SEED)).persist()
    part = lambda c: F.round(F.sum(F.when(c, F.col("pairs")).otherwise(0)) / F.sum("pairs"), 4)
    out = None
    for mode in votes.MODES:
        share = votes.vote_share(mode, p) * 24
        row = counted.agg(F.lit(mode).alias("mode"), part(F.col("n") >= share).alias("nearer_first"), part(24 - F.col("n") < share).alias("farther_first"))  # swapped questions get the negated answers
        out = row if out is None else out.unionByName(row)
    return out


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The robust maximum of the order totals under band noise, mu = 1."""
    return extremum.robust_band(tables.values_flat(spark, sf_dir), Judge.band(1.0, seed=SEED), seed=SEED)
