"""Votes of near sets in place of single questions, for persistent coin noise."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from .judges import Judge, item, pair_id

MODES = ("fixed", "half_correct", "majority")


def vote_share(mode: str = "majority", p: float = 0.4) -> float:
    """The share of yes that decides: 0.3 as published, (1 - p) / 2, or one half."""
    return {"fixed": 0.3, "half_correct": (1 - p) / 2, "majority": 0.5}[mode]


def _passes(yes: Column, total: Column, share: float, inclusive: bool) -> Column:
    left, right = yes * 1_000_000, total * int(share * 1_000_000)
    return left >= right if inclusive else left > right


def anchored_yes(a: Column, b: Column, anchors: Column, judge: Judge, metric: Metric) -> Column:
    """How many anchors x say d(a, x) <= d(b, x). a, b and the elements of the array anchors are structs (id, payload)."""
    pairs = judge.on_pairs()
    ask = lambda x: pairs.at_most(item(pair_id(a["id"], x["id"]), metric(a["payload"], x["payload"])), item(pair_id(b["id"], x["id"]), metric(b["payload"], x["payload"])))
    return F.aggregate(anchors, F.lit(0), lambda n, x: n + ask(x).cast("int"))


def anchored_vote(a: Column, b: Column, anchors: Column, judge: Judge, metric: Metric, share: float = 0.5, inclusive: bool = True) -> Column:
    """Is a nearer than b to the record the anchors are near to? Without anchors nothing is known and the answer is yes."""
    return F.when(F.size(anchors) == 0, True).otherwise(_passes(anchored_yes(a, b, anchors, judge, metric), F.size(anchors), share, inclusive))


def core_yes(u: Column, center: Column, core: Column, judge: Judge, metric: Metric) -> Column:
    """How many members v of a core say d(u, center) <= d(u, v)."""
    pairs = judge.on_pairs()
    ask = lambda v: pairs.at_most(item(pair_id(u["id"], center["id"]), metric(u["payload"], center["payload"])), item(pair_id(u["id"], v["id"]), metric(u["payload"], v["payload"])))
    return F.aggregate(core, F.lit(0), lambda n, v: n + ask(v).cast("int"))


def core_vote(u: Column, center: Column, core: Column, judge: Judge, metric: Metric, share: float = 0.5, inclusive: bool = False) -> Column:
    """Does u belong to a new center rather than to the core of its old one?"""
    return _passes(core_yes(u, center, core, judge, metric), F.size(core), share, inclusive)


def items(id_: Column, payload: Column, members: Column, metric: Metric) -> Column:
    """The hidden distances of a record to an array of members (id, payload), as items of a judge on pairs."""
    return F.transform(members, lambda x: item(pair_id(id_, x["id"]), metric(payload, x["payload"])))


def _count(said: Column) -> Column:
    return F.aggregate(said, F.lit(0), lambda n, yes: n + yes.cast("int"))


def count_yes(xs: Column | str, ys: Column | str, judge: Judge) -> Column:
    """How many anchors call the first of two records at most as far, from items of both to the same anchors."""
    return _count(F.zip_with(xs, ys, judge.on_pairs().at_most))


def nearer_by_anchors(xs: Column, ys: Column, judge: Judge, share: float = 0.5) -> Column:
    """The anchors' vote from items of two records to the same anchors: is the first one nearer?"""
    return (F.size(xs) == 0) | _passes(count_yes(xs, ys, judge), F.size(xs), share, True)


def joins_core(new: Column, own: Column, judge: Judge, share: float = 0.5, inclusive: bool = False) -> Column:
    """core_vote from items: `new` to the new center, `own` to the members of the present core."""
    pairs = judge.on_pairs()
    return _passes(_count(F.transform(own, lambda v: pairs.at_most(new, v))), F.size(own), share, inclusive)


def nearer_by_cores(x: Column, y: Column, judge: Judge, share: float = 0.5) -> Column:
    """cross_core_vote from structs (cur, near): the cluster, and the items to the members of its core, best first."""
    pairs = judge.on_pairs()
    small = lambda own: F.slice(own, 1, F.greatest(F.lit(1), F.floor(F.sqrt(F.size(own).cast("double"))).cast("int")))
    crossed = F.flatten(F.transform(small(x["near"]), lambda p: F.transform(small(y["near"]), lambda q: pairs.at_most(p, q))))
    said = F.when(x["cur"] == y["cur"], F.zip_with(x["near"], y["near"], pairs.at_most)).otherwise(crossed)
    return F.aggregate(said, F.struct(F.lit(0).alias("yes"), F.lit(0).alias("all")), lambda n, yes: F.struct((n["yes"] + yes.cast("int")).alias("yes"), (n["all"] + 1).alias("all")), lambda n: _passes(n["yes"], n["all"], share, True))


def cross_core_vote(u: Column, v: Column, same: Column, core_u: Column, small_u: Column, small_v: Column, judge: Judge, metric: Metric, share: float = 0.5) -> Column:
    """Is u nearer to its center than v to its own? With one center its whole core votes, else all pairs of the two small cores."""
    pairs = judge.on_pairs()
    ask = lambda x, y: pairs.at_most(item(pair_id(u["id"], x["id"]), metric(u["payload"], x["payload"])), item(pair_id(v["id"], y["id"]), metric(v["payload"], y["payload"])))
    one = F.aggregate(core_u, F.lit(0), lambda n, x: n + ask(x, x).cast("int"))
    two = F.aggregate(small_u, F.lit(0), lambda n, x: n + F.aggregate(small_v, F.lit(0), lambda k, y: k + ask(x, y).cast("int")))
    return F.when(same, _passes(one, F.size(core_u), share, True)).otherwise(_passes(two, F.size(small_u) * F.size(small_v), share, True))
