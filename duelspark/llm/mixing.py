"""Mixing documents to target weights by soft membership.

A naive Bayes classifier over hashed words, trained on the labelled table, gives each document a posterior over domains. Nonnegative
rates for all documents are then fitted by least squares so that the expected tokens of each domain, sum of rate x tokens x
posterior, meet the targets. The descent is projected: from rate 1 each step moves all rates along the gradient, scaled by the
inverse of the domains' own Gram matrix over the documents with positive rate, and cuts them at 0. A step needs one aggregation
to a few sums (domains squared); a rate is a function of a document's posterior alone, so nothing is stored per document.

Only DataFrame functions run on the executors. At most about `max_training` labelled documents are used for training, drawn by
a hash of doc_id (a documented bound); the sums cover all documents.

Defined results: a null or empty text has no tokens, the prior as its posterior, and its rate follows from that; labels that are
null or belong to no document are left out; without any label each domain has the same prior and all rates are those of that
posterior. Targets that cannot be met (a domain without mass) are approached as closely as least squares allows.
Repeated rows are rows of their own.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise

DOMAINS = ("high", "low", "toxic")


@dataclass(frozen=True)
class Mixture:
    """Targets as shares of all tokens, and the classifier's parameters."""

    weights: dict[str, float] = field(default_factory=lambda: {"high": 0.72, "low": 0.23, "toxic": 0.05})
    buckets: int = 4096
    max_training: int = 20_000
    smoothing: float = 1.0
    evidence: int = 100
    steps: int = 40
    tolerance: float = 1e-7


def domain() -> Column:
    """Domain of a row of the labelled table; null if it has none."""
    return F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "high").when(F.col("quality") == 0, "low")


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[ \\t-\\r]"), lambda w: w != "")


def train(documents: DataFrame, labels: DataFrame, mixture: Mixture) -> tuple[np.ndarray, np.ndarray]:
    """Log priors, and log probabilities (domains x buckets)."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), domain().alias("domain")).where("doc_id IS NOT NULL AND domain IS NOT NULL").dropDuplicates(["doc_id"])
    share = min(1.0, mixture.max_training / max(1, known.count()))
    sample = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) < int(share * 1_000_003) + 1)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id")  # max_training rows at most
    counted = texts.select("domain", F.explode(words(F.col("text"))).alias("w")).groupBy("domain", F.pmod(F.xxhash64("w"), F.lit(mixture.buckets)).alias("bucket")).agg(F.count("*").alias("n"))
    counts = np.full((len(DOMAINS), mixture.buckets), mixture.smoothing)
    for row in counted.collect():  # domains x buckets at most
        counts[DOMAINS.index(row["domain"]), row["bucket"]] += row["n"]
    prior = np.ones(len(DOMAINS))
    for row in sample.groupBy("domain").count().collect():
        prior[DOMAINS.index(row["domain"])] += row["count"]
    return np.log(prior / prior.sum()), np.log(counts / counts.sum(axis=1, keepdims=True))


def with_posteriors(documents: DataFrame, model: tuple[np.ndarray, np.ndarray], mixture: Mixture) -> DataFrame:
    """The documents with __tokens and __p (posteriors in the order of DOMAINS)."""
    prior, weights = model
    constant = lambda values: F.split(F.lit(",".join(f"{v:.6f}" for v in values)), ",").cast("array<double>")  # noqa: E731  folded into a literal
    ids = F.transform(words(F.col("text").cast("string")), lambda w: F.pmod(F.xxhash64(w), F.lit(mixture.buckets)).cast("int"))
    hashed = documents.withColumn("__ids", ids)
    zero = F.lit(0.0)
    summed = lambda table: F.aggregate("__ids", zero, lambda total, i: total + F.get(table, i))
    odds = [summed(constant(weights[d] - weights[0])) for d in range(1, len(DOMAINS))]
    scored = hashed.withColumns({"__tokens": F.size("__ids").cast("long"), **{f"__odds{d}": odd for d, odd in enumerate(odds, 1)}}).drop("__ids")
    limited = F.least(F.lit(1.0), F.lit(float(mixture.evidence)) / F.greatest(F.col("__tokens"), F.lit(1)))
    z = [F.lit(float(prior[0])), *(F.col(f"__odds{d}") * limited + float(prior[d]) for d in range(1, len(DOMAINS)))]
    top = F.greatest(*z)
    raw = F.array(*(F.exp(x - top) for x in z))
    total = F.aggregate(raw, zero, lambda a, x: a + x)
    return scored.withColumn("__p", F.transform(raw, lambda x: F.round(x / total, 9))).drop(*(f"__odds{d}" for d in range(1, len(DOMAINS))))


def rate(steps: list[np.ndarray]) -> Column:
    """A document's rate after these steps."""
    p = [F.get("__p", F.lit(d)) for d in range(len(DOMAINS))]
    move = lambda r, y: F.greatest(F.lit(0.0), r + reduce(lambda a, b: a + b, (x * float(v) for x, v in zip(p, y, strict=True))))
    return reduce(move, steps, F.lit(1.0))


def fit(scored: DataFrame, mixture: Mixture) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Steps, the targets and the totals reached."""
    d = len(DOMAINS)
    share = np.array([mixture.weights[x] for x in DOMAINS])
    t = F.col("__tokens").cast("double")
    p = [F.get("__p", F.lit(i)) for i in range(d)]

    def sums(steps: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, float]:
        r = F.col("__r")
        row = scored.withColumn("__r", rate(steps)).agg(
            *(F.sum(r * t * p[i]) for i in range(d)), *(F.sum(F.when(r > 0, t * p[i] * p[j])) for i in range(d) for j in range(d)), F.sum(t)
        ).first()
        got = np.array([x or 0.0 for x in row])
        return got[:d], got[d:-1].reshape(d, d), got[-1]

    steps: list[np.ndarray] = []
    totals, gram, tokens = sums(steps)
    targets = share / share.sum() * tokens
    size, scale = 1.0, max(1.0, tokens)
    for _ in range(mixture.steps):
        off = targets - totals
        if np.abs(off).max() <= mixture.tolerance * scale:
            break
        move = np.linalg.lstsq(gram / scale + 1e-9 * np.eye(d), off / scale, rcond=None)[0]
        trial = [*steps, np.round(move * size, 12)]
        after = sums(trial)
        if np.linalg.norm(targets - after[0]) < np.linalg.norm(off) * (1 - 1e-6):
            steps, (totals, gram, _), size = trial, after, min(1.0, size * 2)
        elif size < 1e-3:
            break
        else:
            size /= 2
    return steps, targets, totals


def mixed(documents: DataFrame, labels: DataFrame, mixture: Mixture = Mixture()) -> DataFrame:
    """The documents with __tokens, __p, and their fitted __rate."""
    scored = materialise(with_posteriors(documents, train(documents, labels, mixture), mixture), "posteriors")
    return scored.withColumn("__rate", rate(fit(scored, mixture)[0]))


def copies() -> Column:
    """How often a document with this rate is taken: the whole part, and one more by a hash of doc_id with the chance of the rest."""
    chance = F.pmod(F.xxhash64("doc_id", F.lit("mix")), F.lit(1_000_000)) / 1_000_000.0
    return F.floor(F.round(F.col("__rate"), 6) + chance).cast("int")


def rates(documents: DataFrame, labels: DataFrame, mixture: Mixture = Mixture()) -> DataFrame:
    """doc_id, domain (most likely), tokens, a posterior for each domain, rate, copies."""
    out = mixed(documents.select("doc_id", "text"), labels, mixture)
    p = {x: F.get("__p", F.lit(i)) for i, x in enumerate(DOMAINS)}
    best = F.array(*map(F.lit, DOMAINS))[(F.array_position("__p", F.array_max("__p")) - 1).cast("int")]
    return out.select("doc_id", best.alias("domain"), F.col("__tokens").alias("tokens"), *(c.alias(f"p_{x}") for x, c in p.items()), F.round("__rate", 6).alias("rate"), copies().alias("copies"))


def resampled(documents: DataFrame, labels: DataFrame, mixture: Mixture = Mixture()) -> DataFrame:
    """The documents, all columns, each as often as its rate says."""
    out = mixed(documents, labels, mixture).withColumn("__n", copies()).where("__n > 0")
    return out.withColumn("__n", F.explode(F.sequence(F.lit(1), F.col("__n")))).select(*(F.col(f"`{c}`") for c in documents.columns))
