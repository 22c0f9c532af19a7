"""Distances between payload columns, in ticks. Each function takes two columns and returns a column."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from .ticks import ticks

Metric = Callable[[Column, Column], Column]


def _folded(a: Column, b: Column, term: Callable[[Column, Column], Column]) -> Column:
    gaps = F.zip_with(a, b, lambda x, y: term(x.cast("double"), y.cast("double")))
    return F.aggregate(gaps, F.lit(0.0), lambda total, x: total + x)


def squared(a: Column, b: Column) -> Column:
    """Squared Euclidean distance as a double, summed from left to right."""
    return _folded(a, b, lambda x, y: (x - y) * (x - y))


def euclid(a: Column, b: Column) -> Column:
    return ticks(F.sqrt(squared(a, b)))


def manhattan(a: Column, b: Column) -> Column:
    return ticks(_folded(a, b, lambda x, y: F.abs(x - y)))


def angular(a: Column, b: Column) -> Column:
    """Angle divided by pi."""
    dot = lambda x, y: _folded(x, y, lambda p, q: p * q)
    cosine = dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
    return ticks(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cosine))) / 3.141592653589793)


def haversine(a: Column, b: Column) -> Column:
    """Great-circle kilometres between structs with lat and lon in degrees."""
    half = lambda x, y: F.pow(F.sin(F.radians(x - y) / 2), 2)
    h = half(a["lat"], b["lat"]) + F.cos(F.radians(a["lat"])) * F.cos(F.radians(b["lat"])) * half(a["lon"], b["lon"])
    return ticks(F.lit(2 * 6371.0088) * F.asin(F.sqrt(F.least(F.lit(1.0), h))))


def planted(weight: float) -> Metric:
    """Euclidean distance with an extra orthogonal step where labels differ; payload is struct(v, label)."""
    from .metric_arrays import stepped

    metric = lambda a, b: ticks(F.sqrt(squared(a["v"], b["v"]) + F.when(a["label"] != b["label"], weight * weight).otherwise(0.0)))
    metric.form = stepped(("label", weight * weight))
    return metric


def tree(a: Column, b: Column) -> Column:
    """Customers: 8 across regions, 2 across nations, 1 across segments, and a balance gap under 1; payload is struct(region, nation, segment, bal)."""
    level = F.when(a["region"] != b["region"], 8).when(a["nation"] != b["nation"], 2).when(a["segment"] != b["segment"], 1).otherwise(0)
    return (level.cast("long") * 1_000_000 + F.floor(F.abs(a["bal"] - b["bal"]) / 20_000)).cast("long")


def catalogue(a: Column, b: Column) -> Column:
    """Parts: 8 across types, 2 across brands, half the token distance of the names, and a size gap up to one half."""
    level = F.when(a["p_type"] != b["p_type"], 8.0).when(a["p_brand"] != b["p_brand"], 2.0).otherwise(0.0)
    return ticks(level + 0.5 * (1 - jaccard(a["words"], b["words"])) + F.abs(a["p_size"] - b["p_size"]) / 100.0)


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two token arrays, as a double; two empty ones are equal."""
    both, union = F.size(F.array_intersect(a, b)), F.size(F.array_union(a, b))
    return F.when(union == 0, 1.0).otherwise(both / union)


def one_minus(similarity: Callable[[Column, Column], Column]) -> Metric:
    """An automatic distance from a similarity between 0 and 1."""
    return lambda a, b: ticks(1.0 - similarity(a, b))


def gap(a: Column, b: Column) -> Column:
    """Distance of two positions on a line, already in ticks."""
    return F.abs(a - b)


def custom(distance) -> Metric:
    """A metric from a function of two pandas Series that returns one; it runs in Arrow batches, so built-in metrics are to be preferred."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def measured(a: pd.Series, b: pd.Series) -> pd.Series:
        return distance(a, b).astype("float64")

    return measured
