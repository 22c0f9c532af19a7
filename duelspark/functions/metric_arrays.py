"""The distances of metrics.py for whole tables inside one task, with the same ticks to the last bit.

A form names the plain columns it reads from a payload, what makes a payload plain, and a class whose `to(i)` gives the distances of
all rows, or of some, to row i. Metrics without a form are measured by Spark.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from . import metrics


@dataclass(frozen=True)
class Form:
    columns: Callable[[Column], dict[str, Column]]
    plain: Callable[[Column], Column]
    rows: Callable[[pd.DataFrame], object]


def _ticks(distance: np.ndarray) -> np.ndarray:
    return np.floor(distance * 1_000_000).astype(np.int64)


class TreeRows:
    def __init__(self, part: pd.DataFrame):
        self.region, self.nation, self.bal = (part[c].to_numpy(np.int64) for c in ("region", "nation", "bal"))
        self.segment = pd.factorize(part["segment"])[0]

    def to(self, i: int, rows: slice | np.ndarray = slice(None)) -> np.ndarray:
        level = np.where(self.region[rows] != self.region[i], 8, np.where(self.nation[rows] != self.nation[i], 2, np.where(self.segment[rows] != self.segment[i], 1, 0)))
        return level * 1_000_000 + np.floor(np.abs(self.bal[rows] - self.bal[i]) / 20_000).astype(np.int64)


class CatalogueRows:
    def __init__(self, part: pd.DataFrame):
        self.type, self.brand = (pd.factorize(part[c])[0] for c in ("p_type", "p_brand"))
        self.size = part["p_size"].to_numpy(np.int64)
        self.names, kinds = pd.factorize(part["words"])
        self.sets = [frozenset(k.split(" ")) if k else frozenset() for k in kinds]

    def to(self, i: int, rows: slice | np.ndarray = slice(None)) -> np.ndarray:
        own = self.sets[self.names[i]]
        both = np.array([len(own & s) for s in self.sets], np.float64)
        union = np.array([len(own | s) for s in self.sets], np.float64)
        alike = np.where(union == 0, 1.0, both / np.maximum(union, 1))
        level = np.where(self.type[rows] != self.type[i], 8.0, np.where(self.brand[rows] != self.brand[i], 2.0, 0.0))
        return _ticks(level + 0.5 * (1 - alike)[self.names[rows]] + np.abs(self.size[rows] - self.size[i]) / 100.0)


class StepRows:
    """Vectors, and steps (squares) where labels differ, the first label that does counts."""

    def __init__(self, part: pd.DataFrame, steps: tuple[tuple[str, float], ...]):
        self.axes = np.ascontiguousarray(np.stack(part["v"].to_numpy()).astype(np.float64).T) if len(part) else np.empty((0, 0))
        self.steps = [(part[c].to_numpy(), step) for c, step in steps]

    def to(self, i: int, rows: slice | np.ndarray = slice(None)) -> np.ndarray:
        total = np.zeros(len(self.axes[0][rows]))
        for axis in self.axes:
            off = axis[rows] - axis[i]
            total += off * off
        apart = np.zeros(len(total))
        for labels, step in reversed(self.steps):
            apart = np.where(labels[rows] != labels[i], step, apart)
        return _ticks(np.sqrt(total + apart))


class GapRows:
    def __init__(self, part: pd.DataFrame):
        self.at = part["at"].to_numpy(np.int64)

    def to(self, i: int, rows: slice | np.ndarray = slice(None)) -> np.ndarray:
        return np.abs(self.at[rows] - self.at[i])


def _all(payload: Column, *names: str) -> Column:
    whole = payload.isNotNull()
    for name in names:
        whole = whole & payload[name].isNotNull()
    return whole


def _as_is(*names: str) -> Callable[[Column], dict[str, Column]]:
    return lambda payload: {n: payload[n] for n in names}


def stepped(*steps: tuple[str, float]) -> Form:
    """Of payloads with a vector v and labels."""
    names = [c for c, _ in steps]
    finite = lambda p: F.forall(p["v"], lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < 1e100))
    return Form(_as_is("v", *names), lambda p: _all(p, "v", *names) & finite(p) & (F.size(p["v"]) > 0), lambda part: StepRows(part, steps))


TREE = Form(_as_is("region", "nation", "segment", "bal"), lambda p: _all(p, "region", "nation", "segment", "bal") & (F.abs(p["bal"]) < 1 << 52), TreeRows)
CATALOGUE = Form(
    lambda p: {"p_type": p["p_type"], "p_brand": p["p_brand"], "p_size": p["p_size"], "words": F.array_join(F.array_sort(p["words"]), " ")},
    lambda p: _all(p, "p_type", "p_brand", "p_size", "words") & F.forall(p["words"], lambda w: w.isNotNull() & (w != "") & ~F.contains(w, F.lit(" "))) & (F.size(p["words"]) == F.size(F.array_distinct(p["words"]))),
    CatalogueRows,
)


GAP = Form(lambda p: {"at": p.cast("long")}, lambda p: p.isNotNull() & (F.abs(p) < 1 << 61), GapRows)


def form_of(metric: metrics.Metric) -> Form | None:
    """The form of a metric, if it has one; a metric made elsewhere carries its own as `form`."""
    return {metrics.tree: TREE, metrics.catalogue: CATALOGUE, metrics.gap: GAP}.get(metric, getattr(metric, "form", None))
