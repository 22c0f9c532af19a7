"""Maximum and minimum from noisy comparisons.

A set is a DataFrame (id, val); val is what the judge sees and what a result reports, never what a method decides by.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ticks import threshold
from ..functions.tosses import Field
from ..plans.lineage import cut
from . import sampling, scores
from .judges import Judge, constant, item

SORTED = 5_000_000  # records whose values one task sorts; more meet in a grid
BATCH = 10_000  # records for a task of arrays, at least
LEAVES = 100_000  # records of a range that one task ranks


def _directed(judge: Judge, want: str) -> Judge:
    if want not in ("max", "min"):
        raise ValueError("want is max or min")
    return judge.reversed() if want == "min" else judge


def _extremum(scored: DataFrame, pool_size: Column | int, questions: int | Column, seed: int) -> DataFrame:
    size = F.lit(pool_size) if isinstance(pool_size, int) else pool_size
    asked = F.lit(questions) if isinstance(questions, int) else questions
    return scores.pick(scored, seed).select(F.col("id").alias("winner_id"), F.col("val").alias("winner_val"), F.col("wins").alias("win_score"), size.cast("long").alias("pool_size"), asked.cast("long").alias("questions"))


def running_champion(df: DataFrame, judge: Judge, want: str = "max", by: str | None = None) -> DataFrame:
    """One scan in order of id, of the set or of every set `by`; the champion is replaced when it is judged below the next. For small sets: it is serial by nature."""
    judge, keys = _directed(judge, want), [by] if by else []
    rows = df.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("id", "val"))).alias("rows"))
    start = F.struct(F.get("rows", F.lit(0))["id"].alias("id"), F.get("rows", F.lit(0))["val"].alias("val"))
    last = F.aggregate("rows", start, lambda best, x: F.when(judge.beats(x, best), F.struct(x["id"].alias("id"), x["val"].alias("val"))).otherwise(best))
    return rows.where(F.size("rows") > 0).select(*keys, last.alias("w"), (F.size("rows") - 1).cast("long").alias("questions")).select(*keys, F.col("w.id").alias("winner_id"), F.col("w.val").alias("winner_val"), "questions")


def round_robin(df: DataFrame, judge: Judge, want: str = "max", seed: int = 7, grid: int | None = None) -> DataFrame:
    """All pairs: never below the maximum by more than a factor (1 + mu)**2. Where values alone decide, many records' duels are counted in order of values."""
    n = df.count()
    if grid is None and scores.BROADCAST_ROWS < n <= SORTED and _countable(df, judge):
        return _extremum(_counted(df, _directed(judge, want)), n, n * (n - 1) // 2, seed)
    return _extremum(scores.round_robin(df, _directed(judge, want), grid or _grid(n)), n, n * (n - 1) // 2, seed)


def _countable(df: DataFrame, judge: Judge) -> bool:
    """Whether Judge.firsts gives all answers: numbers as ids, each once, and values that are not negative."""
    if not judge.by_value or judge.pairs or dict(df.dtypes).get("id") != "bigint":
        return False
    seen = df.agg(F.count("*").alias("n"), F.countDistinct("id").alias("ids"), F.count("val").alias("vals"), F.min("val").alias("least"), F.max("val").alias("most")).first()
    return seen["n"] == seen["ids"] == seen["vals"] and seen["least"] >= 0 and seen["most"] < (1 << 62) // (1000 + judge.mu_milli)


def _counted(df: DataFrame, judge: Judge) -> DataFrame:
    """id, val, wins as scores.round_robin gives them, in one task."""

    def count(part: pd.DataFrame) -> pd.DataFrame:
        part = part[["id", "val"]]
        return part.assign(wins=len(part) - 1 - judge.firsts((part["id"].to_numpy(),), part["val"].to_numpy()))

    return df.select(F.lit(0).alias("all"), "id", "val").groupBy("all").applyInPandas(count, "id long, val long, wins long")


def array_bracket(heat: Column, judge: Judge | None, beats: scores.Beats | None = None) -> Column:
    """Winner of a knockout in an array of (pos, id, val) in this order; an odd one out goes on unopposed.

    beats(b, a), if given, compares two entries in place of a question to the judge.
    """
    side = lambda x: item(x["id"], x["val"])
    above = beats or (lambda b, a: judge.beats(side(b), side(a)))

    def level(entries: Column, _: Column) -> Column:
        last = F.floor((F.size(entries) + 1) / 2).cast("int") - 1

        def match(i: Column) -> Column:
            a, b = F.get(entries, i * 2), F.get(entries, i * 2 + 1)
            return F.when(b.isNull(), a).when(above(b, a), b).otherwise(a)

        return F.transform(F.sequence(F.lit(0), last), match)

    rounds = F.ceil(F.log2(F.greatest(F.size(heat), F.lit(2)).cast("double"))).cast("int")
    return F.get(F.aggregate(F.sequence(F.lit(1), rounds), heat, level), F.lit(0))


def _heats(df: DataFrame, heats: int, rounds: int, seed: int, marked: Column | None = None) -> DataFrame:
    return sampling.deal_heats(df, heats, rounds, seed, marked).groupBy("round", "heat").agg(F.array_sort(F.collect_list(F.struct("pos", "id", "val", "mark"))).alias("entries"))


def heat_winners(df: DataFrame, judge: Judge | None, heats: int, rounds: int = 1, seed: int = 7, beats: scores.Beats | None = None) -> DataFrame:
    """round, heat, id, val: the knockout winner of every heat, in one shuffle for all rounds."""
    return _heats(df, heats, rounds, seed).select("round", "heat", array_bracket(F.col("entries"), judge, beats).alias("w")).select("round", "heat", "w.id", "w.val")


def leaves(df: DataFrame, n: int, seed: int) -> DataFrame:
    """id, val, pos: positions 0 to n - 1 in an order by coins. Records are ranked inside ranges of coins, so no task sorts them all."""
    from pyspark.sql import Window as W

    parts = max(1, n // LEAVES)
    coined = df.select("id", "val", sampling.coin(seed, F.lit("leaf"), F.col("id")).alias("coin")).withColumn("part", F.floor(F.col("coin") * parts / sampling.COIN_RANGE).cast("int"))
    counts = coined.groupBy("part").agg(F.count("*").alias("n"))  # a row for about LEAVES records
    before = counts.select("part", (F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, 0)) - F.col("n")).alias("before"))
    ranked = coined.withColumn("within", F.row_number().over(W.partitionBy("part").orderBy("coin", "id")) - 1)
    return ranked.join(F.broadcast(before) if parts <= scores.BROADCAST_ROWS else before, "part").select("id", "val", (F.col("before") + F.col("within")).alias("pos"))


def bracket(df: DataFrame, judge: Judge, fanout: int = 2, seed: int = 7, want: str = "max") -> DataFrame:
    """A tournament tree with random leaves: round robins of `fanout` on every level.

    Each level is one aggregation by the integer quotient of the position; levels shrink by the factor `fanout`.
    """
    n = df.count()
    fanout = max(2, min(fanout, max(2, n)))
    if fanout >= n:
        return round_robin(df, judge, want, seed)
    directed = _directed(judge, want)
    now, questions, width = leaves(df, n, seed), 0, n
    side = lambda x: item(x["id"], x["val"])
    while width > 1:
        full, rest = divmod(width, fanout)
        questions += full * fanout * (fanout - 1) // 2 + rest * (rest - 1) // 2
        grouped = now.groupBy(F.floor(F.col("pos") / fanout).alias("pos")).agg(F.collect_list(F.struct("id", "val")).alias("entries"))
        scored = F.transform("entries", lambda x: F.struct(F.aggregate("entries", F.lit(0), lambda s, y: s + (directed.beats(side(x), side(y)) & (x["id"] != y["id"])).cast("int")).alias("wins"), (-sampling.coin(seed, F.lit("tie"), x["id"])).alias("tie"), x["id"].alias("id"), x["val"].alias("val")))
        now = grouped.select("pos", F.array_max(scored).alias("w")).select("pos", "w.id", "w.val")
        width = -(-width // fanout)
    return now.select(F.col("id").alias("winner_id"), F.col("val").alias("winner_val"), F.lit(questions).cast("long").alias("questions"))


def finalists(df: DataFrame, judge: Judge | None, n: int, t: int, heats: int, seed: int, final_pool: str = "both", beats: scores.Beats | None = None) -> DataFrame:
    """The sample and the winners of the heats of all rounds, each once, from one scan and one shuffle; `final_pool` = sample or both."""
    size = math.ceil(math.sqrt(n)) * t
    if final_pool == "sample":
        return sampling.draw(df.select("id", "val"), size, n, seed)
    both = F.concat(F.filter("entries", lambda x: x["mark"]), F.array(array_bracket(F.col("entries"), judge, beats)))
    return _heats(df, heats, t, seed, sampling.drawn(size, n, seed)).select(F.explode(both).alias("e")).select("e.id", "e.val").dropDuplicates(["id"])


def _grid(rows: int) -> int | None:
    return None if rows <= scores.BROADCAST_ROWS else max(2, math.ceil(rows / 4096))


def robust_band(df: DataFrame, judge: Judge, delta: float = 0.1, t: int | None = None, heats: int | None = None, want: str = "max", seed: int = 7, n: int | None = None, final_pool: str = "both", grid: int | None = None, beats: scores.Beats | None = None) -> DataFrame:
    """Robust maximum (minimum) under band noise: within (1 + mu)**3 with probability 1 - delta, without knowing mu.

    A sample of sqrt(n) t records and the winners of t rounds of sqrt(n) knockout heats meet in a round robin. One shuffle for the
    heats, whose finalists are materialised, and one for the scores. beats(x, y), if given, is the comparison of two entries
    (id, val) in place of single questions: a vote, for coin noise; val may then be whatever the vote needs.
    """
    directed = None if beats else _directed(judge, want)
    n = df.count() if n is None else n
    t = sampling.rounds_for("max", n, delta=delta) if t is None else t
    heats = max(1, math.ceil(math.sqrt(n))) if heats is None else heats
    pool = cut(finalists(df, directed, n, t, heats, seed, final_pool, beats))
    size = pool.count()
    return _extremum(scores.round_robin(pool, directed, grid or _grid(size), beats), size, (n - heats) * t + size * (size - 1) // 2, seed)


def robust_band_by(df: DataFrame, by: str, judge: Judge, n: int, t: int = 1, heats: int | None = None, want: str = "max", seed: int = 7) -> DataFrame:
    """by, winner_id, winner_val, pool_size, questions: the robust search for many sets (by, id, val) of about n records at once.

    One shuffle deals the records to (set, round, heat), one gathers the finalists of each set, about 2 sqrt(n) t, which then meet in
    an array; so every task holds one heat or one set's finalists.
    """
    directed = _directed(judge, want)
    heats, size = max(1, math.ceil(math.sqrt(n))) if heats is None else heats, math.ceil(math.sqrt(n)) * t
    kept = int((1 - (1 - 1 / max(1, n)) ** size) * sampling.COIN_RANGE)
    dealt = df.select(by, "id", "val", (sampling.coin(seed, F.lit("draw"), F.col(by), F.col("id")) < kept).alias("mark"), F.explode(F.sequence(F.lit(1), F.lit(t))).alias("round"))
    placed = dealt.withColumn("pos", sampling.coin(seed, F.lit("heat"), F.col(by), F.col("round"), F.col("id")))
    heat = placed.groupBy(by, "round", F.pmod("pos", F.lit(heats)).alias("heat")).agg(F.array_sort(F.collect_list(F.struct("pos", "id", "val", (F.col("mark") & (F.col("round") == 1)).alias("mark")))).alias("entries"))
    both = heat.select(by, (F.size("entries") - 1).alias("asked"), F.concat(F.filter("entries", lambda x: x["mark"]), F.array(array_bracket(F.col("entries"), directed))).alias("e"))
    pool = both.groupBy(by).agg(F.array_sort(F.array_distinct(F.transform(F.flatten(F.collect_list("e")), lambda x: item(x["id"], x["val"])))).alias("pool"), F.sum("asked").alias("asked"))
    return _champions(pool, by, directed, seed)


def round_robin_by(df: DataFrame, by: str, judge: Judge, want: str = "max", seed: int = 7) -> DataFrame:
    """by, winner_id, winner_val, pool_size, questions: all pairs of each small set (by, id, val)."""
    directed = _directed(judge, want)
    pool = df.groupBy(by).agg(F.array_sort(F.collect_list(item(F.col("id"), F.col("val")))).alias("pool"))
    return _champions(pool.withColumn("asked", F.lit(0)), by, directed, seed)


def _champions(pool: DataFrame, by: str, directed: Judge, seed: int) -> DataFrame:
    wins = lambda x: F.aggregate("pool", F.lit(0), lambda s, y: s + ((x["id"] != y["id"]) & directed.beats(x, y)).cast("int"))
    best = F.array_max(F.transform("pool", lambda x: F.struct(wins(x).alias("wins"), (-sampling.coin(seed, F.lit("tie"), F.col(by), x["id"])).alias("tie"), x["id"].alias("id"), x["val"].alias("val"))))
    m = F.size("pool")
    won = pool.select(by, best.alias("w"), m.cast("long").alias("pool_size"), (F.col("asked") + m * (m - 1) / 2).cast("long").alias("questions"))
    return won.select(by, F.col("w.id").alias("winner_id"), F.col("w.val").alias("winner_val"), "pool_size", "questions")


def runs_of(df: DataFrame, runs: int) -> DataFrame:
    """run, id, val: the set so many times over. The run is part of the id, so a judge on pairs errs anew in every run."""
    many = df.withColumn("run", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(runs - 1).cast("long"))))
    return many.select("run", F.struct(F.col("run").alias("k1"), F.col("id").cast("long").alias("k2")).alias("id"), "val")


def robust_coin(df: DataFrame, judge: Judge, delta: float = 0.1, sample_const: float = 2.0, keep_share: float = 0.5, want: str = "max", seed: int = 7) -> DataFrame:
    """Robust maximum (minimum) under coin noise: rank of the order of log(n / delta)**2 with probability 1 - delta, without knowing p.

    In every round all survivors are scored against a small sample, and those below half of it go; what is left meets the
    samples in a round robin. A record with a share q above it wins ((1 - q)(1 - p) + q p) of its questions, which is one half at
    q = 1/2 for every p, so a round halves the field.
    """
    directed = _directed(judge, want)
    now, n = df.select("id", "val"), df.count()
    tossed = judge.kind == "coin" and judge.pairs and _numbered(now)
    if tossed:
        now = cut(now.repartition(max(1, min(64, n // BATCH))))
    size, asked = max(1, math.ceil(sample_const * math.log(max(2, n) / delta))), 0
    kept_samples: list[tuple] = []
    for turn in range(math.ceil(math.log2(max(2, n)))):
        left = now.count()
        if left <= 2 * size:
            break
        drawn = [(r["id"], r["val"]) for r in now.orderBy(sampling.coin(seed, F.lit("S"), F.lit(turn), F.col("id")), "id").limit(size).collect()]  # a sample of logarithmic size
        kept_samples += drawn
        if tossed:
            asked += (left - len(drawn)) * len(drawn)
            now = cut(_above(now, drawn, directed, keep_share * len(drawn)))
            continue
        sample = F.array(*(F.struct(constant(i).alias("id"), constant(v).alias("val")) for i, v in drawn))
        wins = F.aggregate(sample, F.lit(0), lambda s, x: s + directed.beats(item(F.col("id"), F.col("val")), x).cast("int"))
        rest = now.where(~F.exists(sample, lambda x: x["id"] == F.col("id")))
        asked += (left - len(drawn)) * len(drawn)
        now = cut(rest.where(wins >= F.lit(keep_share * len(drawn))))
    pool = now
    if kept_samples:
        pool = now.unionByName(df.sparkSession.createDataFrame(kept_samples, now.schema)).distinct()
    pool = cut(pool)
    final = pool.count()
    return _extremum(scores.round_robin(pool, directed, _grid(final)), final, asked + final * (final - 1) // 2, seed)


def _numbered(df: DataFrame) -> bool:
    """Whether all ids are pairs of numbers from 0 on and no value is null, so that questions can be asked in arrays."""
    if [f.name for f in df.schema if f.dataType.simpleString() == "struct<k1:bigint,k2:bigint>"] != ["id"]:
        return False
    whole = (F.col("id.k1") >= 0) & (F.col("id.k2") >= 0) & F.col("val").isNotNull()
    return bool(df.agg(F.bool_and(F.coalesce(whole, F.lit(False)))).first()[0])


def _above(now: DataFrame, drawn: list, directed: Judge, least: float) -> DataFrame:
    """Of records (id, val) with pairs as ids those not drawn that are judged above `least` of the drawn ones: answers of a batch are arrays."""
    sample = [(i["k1"], i["k2"], v) for i, v in drawn]

    def kept(parts):
        for part in parts:
            a, b, val = (part[c].to_numpy(np.int64) for c in ("k1", "k2", "val"))
            wins, own = np.zeros(len(part), np.int64), np.zeros(len(part), bool)
            for one in sample:
                wins += ~directed.answers((a, b, val), tuple(np.full(len(part), x, np.int64) for x in one))
                own |= (a == one[0]) & (b == one[1])
            yield part[~own & (wins >= least)]

    flat = now.select("id.k1", "id.k2", "val").mapInPandas(kept, "k1 long, k2 long, val long")
    return flat.select(F.struct("k1", "k2").alias("id"), "val")


def robust_coin_by(df: DataFrame, judge: Judge, delta: float = 0.1, sample_const: float = 2.0, want: str = "max", seed: int = 7) -> DataFrame:
    """run, winner_id, winner_val, pool_size, questions: robust_coin in every run of runs_of, for a coin judge on pairs and ids from 0 on.

    A group of a task holds the records of one run, whose answers are tossed for as arrays; 64 partitions keep small runs apart.
    """
    if judge.kind != "coin" or not judge.pairs or want not in ("max", "min"):
        raise ValueError("a coin judge on pairs, and max or min")
    flipped, bar = judge.flipped != (want == "min"), threshold(judge.p)

    def search(part: pd.DataFrame) -> pd.DataFrame:
        run, part = int(part["run"].iloc[0]), part.sort_values("id")
        ids, vals = part["id"].to_numpy(np.int64), part["val"].to_numpy(np.int64)

        def beats(field: Field, val: np.ndarray, id_: int, other: int) -> np.ndarray:
            """Whether the records of the field, `id_` not among them, are judged above it."""
            at = int(np.searchsorted(field.numbers, id_))
            lower, upper = field.coins(f"{judge.seed}|{run}|", f"|{run}|{id_}", 0, at), field.coins(f"{judge.seed}|{run}|{id_}|{run}|", "", at)
            at_most = np.append((val[:at] <= other) ^ (lower < bar), ~((other <= val[at:]) ^ (upper < bar)))
            return at_most if flipped else ~at_most

        size, asked, now, samples = max(1, math.ceil(sample_const * math.log(max(2, len(ids)) / delta))), 0, np.arange(len(ids)), []
        for turn in range(math.ceil(math.log2(max(2, len(ids))))):
            if len(now) <= 2 * size:
                break
            drawn = np.lexsort((ids[now], Field(ids[now]).coins(f"{seed}|S|{turn}|{run}|")))[:size]
            samples.append(now[drawn])
            rest = np.delete(now, drawn)
            field, wins = Field(ids[rest]), np.zeros(len(rest), np.int64)
            for k in samples[-1].tolist():
                wins += beats(field, vals[rest], int(ids[k]), int(vals[k]))
            asked += len(rest) * size
            now = rest[2 * wins >= size]
        pool = np.sort(np.concatenate([now, *samples]))
        m, wins, field = len(pool), np.zeros(len(pool), np.int64), Field(ids[pool])
        for k in range(m):  # each pair is asked once and both ends are credited
            tossed = field.coins(f"{judge.seed}|{run}|{ids[pool[k]]}|{run}|", "", k + 1)
            at_most = (vals[pool[k]] <= vals[pool[k + 1 :]]) ^ (tossed < bar)
            won = at_most if flipped else ~at_most
            wins[k] += won.sum()
            wins[k + 1 :] += ~won
        best = pool[np.lexsort((ids[pool], field.coins(f"{seed}|tie|{run}|"), -wins))[0]]
        return pd.DataFrame({"run": [run], "winner_id": [ids[best]], "winner_val": [vals[best]], "pool_size": [m], "questions": [asked + m * (m - 1) // 2]})

    flat = df.select("run", F.col("id.k2").alias("id"), "val")
    return flat.repartition(64, "run").groupBy("run").applyInPandas(search, "run long, winner_id long, winner_val long, pool_size long, questions long")


def top_k(pool: DataFrame, judge: Judge, k: int, seed: int = 7, want: str = "max") -> DataFrame:
    """The k records with the highest scores of a round robin."""
    return scores.round_robin(pool, _directed(judge, want), _grid(pool.count())).orderBy(F.desc("wins"), sampling.coin(seed, F.lit("tie"), F.col("id")), "id").limit(k)
