"""Work on all pairs of two sets of vectors, in cells of a grid: arrays inside a task, with the distances of metrics.py to the last bit."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROWS, COLUMNS = 1024, 16384  # records to a side of a cell


def plain(df: DataFrame) -> bool:
    """Whether all records (id, payload, perhaps label) have an id from 0 on, a finite vector, all of one length, and a label. Other sets are worked on row by row."""
    whole = F.col("id").isNotNull() & (F.col("id") >= 0) & F.col("payload").isNotNull() & F.forall("payload", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < 1e100))
    if "label" in df.columns:
        whole = whole & F.col("label").isNotNull()
    found = df.agg(F.bool_and(F.coalesce(whole, F.lit(False))).alias("whole"), F.min(F.size("payload")).alias("least"), F.max(F.size("payload")).alias("most")).first()
    return bool(found["whole"]) and 0 < found["least"] == found["most"]


class Vectors:
    """One side of a cell in order of id, coordinate by coordinate."""

    def __init__(self, part: pd.DataFrame):
        part = part.sort_values("id")
        self.ids = part["id"].to_numpy(np.int64)
        self.axes = np.ascontiguousarray(np.stack(part["payload"].to_numpy()).astype(np.float64).T)
        self.labels = part["label"].to_numpy() if "label" in part else None

    def ticks(self, point: np.ndarray, steps: np.ndarray | float = 0.0, low: int = 0) -> np.ndarray:
        """Distances of a point to the vectors from place `low` on; steps are squares that are added. Summed from left to right, as SQL does."""
        total = np.zeros(len(self.ids) - low)
        for axis, x in zip(self.axes, point, strict=True):
            off = axis[low:] - x
            off *= off
            total += off
        total += steps
        return np.floor(np.sqrt(total) * 1_000_000).astype(np.int64)


def over(rows: DataFrame, columns: DataFrame, work: Callable[[Vectors, Vectors], pd.DataFrame | None], schema: str, side: int = ROWS) -> DataFrame:
    """What `work` makes of every cell. Each record of one side meets each one of the other in one cell, and a task holds one cell, of `side` rows or so."""
    parts, others = max(1, math.ceil(rows.count() / side)), max(1, math.ceil(columns.count() / COLUMNS))
    kept = [c for c in rows.columns if c in ("id", "payload", "label")]
    names = [f.split()[0] for f in schema.split(", ")]

    def dealt(df: DataFrame, own: str, n: int, other: str, m: int) -> DataFrame:
        part = F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")
        return df.select(*kept, F.lit(own).alias("side"), part.alias(own), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias(other))

    def cell(both: pd.DataFrame) -> pd.DataFrame:
        x, y = (both[both["side"] == side] for side in "rc")
        found = work(Vectors(x), Vectors(y)) if len(x) and len(y) else None
        return pd.DataFrame({n: [] for n in names}) if found is None else found

    both = dealt(rows, "r", parts, "c", others).unionByName(dealt(columns, "c", others, "r", parts))
    return both.repartition(min(2000, 2 * parts * others), "r", "c").groupBy("r", "c").applyInPandas(cell, schema)
