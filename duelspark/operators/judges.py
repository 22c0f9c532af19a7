"""Judges: answers to "is the first at most the second?", exact or wrong in a given way.

An item is a struct (id, val): a record with its hidden value, or a pair of records with its hidden distance, whose id is then a
struct (k1, k2). A judge is an expression over two items, so questions are asked inside generated code. Answers are
persistent: they depend on the seed and on the two ids in canonical order; the swapped question gets the negated answer.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace
from hashlib import md5

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ticks import COIN_RANGE, coin, threshold
from ..functions.tosses import coins_of

POLICIES = ("worst", "coinflip", "truthful", "protect", "favour")


def item(id_: Column, val: Column) -> Column:
    return F.struct(id_.alias("id"), val.cast("long").alias("val"))


def pair_id(a: Column, b: Column) -> Column:
    """Id of an unordered pair."""
    return F.struct(F.least(a, b).alias("k1"), F.greatest(a, b).alias("k2"))


def constant(value) -> Column:
    """A collected id or value: a number, or a pair of numbers as a struct."""
    if hasattr(value, "asDict"):
        return F.struct(*(constant(v).alias(k) for k, v in value.asDict().items()))
    return F.lit(value).cast("long")


@dataclass(frozen=True)
class Judge:
    """kind: exact, band (mu_milli), additive (theta), coin (p), fresh (p, attempt), crowd (p, workers). pairs: ids are structs (k1, k2)."""

    kind: str = "exact"
    mu_milli: int = 0
    theta: int = 0
    p: float = 0.0
    policy: str = "worst"
    ids: tuple[int, ...] = ()
    seed: int = 7
    attempt: int = 0
    workers: int = 3
    pairs: bool = False
    flipped: bool = False

    @classmethod
    def exact(cls, **more) -> Judge:
        return cls("exact", **more)

    @classmethod
    def band(cls, mu: float, policy: str = "worst", **more) -> Judge:
        """Certain where the larger exceeds the smaller by a factor over 1 + mu; inside of that the policy answers."""
        if policy not in POLICIES or mu < 0:
            raise ValueError(f"no such band: {mu}, {policy}")
        return cls("band", mu_milli=round(mu * 1000), policy=policy, **more)

    @classmethod
    def additive_band(cls, theta: int, policy: str = "worst", **more) -> Judge:
        """Certain where the difference is at least theta ticks."""
        return cls("additive", theta=theta, policy=policy, **more)

    @classmethod
    def coin(cls, p: float, **more) -> Judge:
        """Wrong with probability p, always alike for the same question."""
        if not 0 <= p < 0.5:
            raise ValueError("a coin judge needs 0 <= p < 1/2")
        return cls("coin", p=p, **more)

    @classmethod
    def fresh_coin(cls, p: float, attempt: int = 0, **more) -> Judge:
        """Wrong with probability p, drawn anew for each attempt."""
        return cls("fresh", p=p, attempt=attempt, **more)

    @classmethod
    def crowd(cls, worker_error: float, workers: int = 3, **more) -> Judge:
        """The majority of an odd number of workers, each wrong with the given probability."""
        return cls("crowd", p=worker_error, workers=workers, **more)

    def reversed(self) -> Judge:
        """For minimum problems: says the opposite."""
        return replace(self, flipped=not self.flipped)

    def on_pairs(self) -> Judge:
        return replace(self, pairs=True)

    def keys(self, a: Column, b: Column) -> list[Column]:
        return [a["id"]["k1"], a["id"]["k2"], b["id"]["k1"], b["id"]["k2"]] if self.pairs else [a["id"], b["id"]]

    def votes(self, a: Column, b: Column, truth: Column) -> Column:
        """Answers of the workers to a question in canonical order."""
        return F.array(*(truth != (coin(self.seed, *self.keys(a, b), F.lit(w)) < threshold(self.p)) for w in range(self.workers)))

    def _policy(self, a: Column, b: Column, truth: Column) -> Column:
        flip = coin(self.seed, *self.keys(a, b)) < COIN_RANGE // 2
        named = F.lit(False)
        for x in self.ids:
            for key in self.keys(a, b):
                named = named | (key == x)
        if self.policy == "favour":  # a favoured record is always called the larger
            large = lambda side: self.keys(a, b)[0 if side == "a" else len(self.keys(a, b)) // 2].isin(*self.ids)
            return F.when(large("b"), True).when(large("a"), False).otherwise(truth)
        return {"worst": ~truth, "coinflip": flip, "truthful": truth, "protect": F.when(named, truth).otherwise(~truth)}[self.policy]

    def _canonical(self, a: Column, b: Column) -> Column:
        truth = a["val"] <= b["val"]
        low, high = F.least(a["val"], b["val"]), F.greatest(a["val"], b["val"])
        if self.kind == "band":
            inside = high.cast("decimal(38,0)") * 1000 <= low.cast("decimal(38,0)") * (1000 + self.mu_milli)
            return F.when(inside, self._policy(a, b, truth)).otherwise(truth)
        if self.kind == "additive":
            return F.when(high - low < self.theta, self._policy(a, b, truth)).otherwise(truth)
        if self.kind == "coin":
            return truth != (coin(self.seed, *self.keys(a, b)) < threshold(self.p))
        if self.kind == "fresh":
            return truth != (coin(self.seed, *self.keys(a, b), F.lit(f"attempt{self.attempt}")) < threshold(self.p))
        if self.kind == "crowd":
            yes = F.aggregate(self.votes(a, b, truth), F.lit(0), lambda n, v: n + v.cast("int"))
            return yes * 2 > self.workers
        return truth

    def at_most(self, left: Column, right: Column) -> Column:
        """The answer for two items."""
        swapped = left["id"] > right["id"]
        said = F.when(left["id"] == right["id"], True).otherwise(self._canonical(F.least(left, right), F.greatest(left, right)) != swapped)
        return ~said if self.flipped else said

    def beats(self, left: Column, right: Column) -> Column:
        """Whether the first is believed to be larger (or smaller, after reversed())."""
        return ~self.at_most(left, right)

    # the same answers in plain Python, for work inside one task
    def answer(self, left: tuple, right: tuple) -> bool:
        """left and right are (id, val); an id is a number or a pair of numbers."""
        if left[0] == right[0]:
            return not self.flipped
        (a, x), (b, y) = sorted((left, right), key=lambda i: i[0])
        truth, keys = x <= y, [*a, *b] if self.pairs else [a, b]
        toss = lambda *more: int(md5("|".join(map(str, (self.seed, *keys, *more))).encode()).hexdigest()[:8], 16)
        low, high = min(x, y), max(x, y)
        if self.kind in ("band", "additive"):
            inside = high * 1000 <= low * (1000 + self.mu_milli) if self.kind == "band" else high - low < self.theta
            if inside and self.policy != "truthful":
                if self.policy == "coinflip":
                    truth = toss() < COIN_RANGE // 2
                elif self.policy == "worst" or self.policy == "protect" and not set(self.ids) & set(keys):
                    truth = not truth
                elif self.policy == "favour":
                    half = len(keys) // 2
                    truth = True if keys[half] in self.ids else False if keys[0] in self.ids else truth
        elif self.kind == "coin":
            truth ^= toss() < threshold(self.p)
        elif self.kind == "fresh":
            truth ^= toss(f"attempt{self.attempt}") < threshold(self.p)
        elif self.kind == "crowd":
            truth = sum(truth ^ (toss(w) < threshold(self.p)) for w in range(self.workers)) * 2 > self.workers
        return (truth ^ (left[0] > right[0])) ^ self.flipped

    def answers(self, left: tuple, right: tuple) -> np.ndarray:
        """answer() for arrays of pairs (k1, k2, val), k1 <= k2; answers are found for all at once where ids are from 0 on, but for policies that ask ids."""
        (a, b, x), (c, d, y) = left, right
        low, high = np.minimum(x, y), np.maximum(x, y)
        large = len(x) and self.kind == "band" and int(high.max()) >= (1 << 62) // (1000 + self.mu_milli)
        tossed = self.kind in ("coin", "fresh", "crowd") and len(x) and min(int(a.min()), int(c.min())) >= 0
        if not tossed and (self.kind not in ("exact", "band", "additive") or self.policy not in ("worst", "truthful") or large):
            one, two = (zip(zip(p.tolist(), q.tolist(), strict=True), v.tolist(), strict=True) for p, q, v in (left, right))
            return np.fromiter(map(self.answer, one, two), bool, len(x))
        swapped = (a > c) | ((a == c) & (b > d))
        truth = np.where(swapped, y <= x, x <= y)
        if tossed:
            keys = [np.where(swapped, *two) for two in ((c, a), (d, b), (a, c), (b, d))]
            toss = lambda more="": coins_of(f"{self.seed}|", keys[0], "|", keys[1], "|", keys[2], "|", keys[3], more) < threshold(self.p)
            if self.kind == "crowd":
                truth = sum((truth ^ toss(f"|{w}")).astype(np.int64) for w in range(self.workers)) * 2 > self.workers
            else:
                truth = truth ^ toss(f"|attempt{self.attempt}" if self.kind == "fresh" else "")
        elif self.kind != "exact" and self.policy == "worst":
            truth ^= high * 1000 <= low * (1000 + self.mu_milli) if self.kind == "band" else high - low < self.theta
        return (((a == c) & (b == d)) | (truth ^ swapped)) ^ self.flipped

    @property
    def by_value(self) -> bool:
        """Whether values alone decide, so that a record's wins can be counted in their order."""
        return self.kind in ("exact", "band", "additive") and (self.kind == "exact" or self.policy in ("worst", "truthful"))

    def firsts(self, keys: tuple, val: np.ndarray) -> np.ndarray:
        """For each of several pairs (keys k1, k2; values not negative), how many of the others it is judged at most: counted in order of values, for a judge by_value."""
        m, order = len(val), np.lexsort((*reversed(keys), val))
        ranked = val[order]
        left, right = np.searchsorted(ranked, val, "left"), np.searchsorted(ranked, val, "right")
        place = np.empty(m, np.int64)
        place[order] = np.arange(m)
        new = np.append(True, np.any([ranked[1:] != ranked[:-1], *(k[order][1:] != k[order][:-1] for k in keys)], axis=0))[:m]
        same, ends = np.cumsum(new) - 1, np.append(np.nonzero(new)[0], m)  # a pair there several times: the earlier goes before the later
        first, last = np.empty(m, np.int64), np.empty(m, np.int64)
        first[order], last[order] = ends[same], ends[same + 1] - 1
        none = self.kind == "exact" or self.policy == "truthful" or self.kind == "additive" and self.theta <= 0
        if none:
            won = m - 1 - place
        else:
            low, high = (-(-val * 1000 // (1000 + self.mu_milli)), val * (1000 + self.mu_milli) // 1000) if self.kind == "band" else (val - self.theta + 1, val + self.theta - 1)
            won = m - np.searchsorted(ranked, high, "right") + left - np.searchsorted(ranked, low, "left") + first - left + last - place
        return m - 1 - won if self.flipped else won


def from_table(questions: DataFrame, answers: DataFrame, fallback: Column, keys: Sequence[str] = ("k1", "k2", "k3", "k4")) -> DataFrame:
    """questions with `yes`: the stored answer where there is one, else the fallback. The first stored answer counts."""
    stored = answers.groupBy(*keys).agg(F.min("yes").alias("__stored"))
    return questions.join(stored, list(keys), "left").withColumn("yes", F.coalesce("__stored", fallback)).drop("__stored")


def same_cluster(truth_a: Column, truth_b: Column, a: Column, b: Column, missed: float = 0.0, false_yes: float = 0.0, seed: int = 7) -> Column:
    """ "Do the two belong together?", with a share of missed pairs and of wrong yes."""
    toss = coin(seed, F.least(a, b), F.greatest(a, b))
    return F.when(truth_a == truth_b, toss >= threshold(missed)).otherwise(toss < threshold(false_yes))


def grade(distance: Column, a: Column, b: Column, same: Column, error_same: float = 0.2, error_other: float = 0.5, seed: int = 7) -> Column:
    """An estimated distance in ticks, off by up to 20 % for the same entity and 50 % for others."""
    share = coin(seed, F.least(a, b), F.greatest(a, b)) / float(COIN_RANGE) * 2 - 1
    return F.floor(distance * (1 + share * F.when(same, error_same).otherwise(error_other))).cast("long")
