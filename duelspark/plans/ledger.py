"""Closed forms of the number of questions, and a ledger of runs."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "method string, phase string, asked long, distinct_asked long, rounds int, seconds double"


@dataclass(frozen=True)
class Row:
    method: str
    phase: str
    asked: int
    distinct_asked: int
    rounds: int
    seconds: float


class Ledger:
    def __init__(self) -> None:
        self.rows: list[Row] = []

    def record(self, method: str, phase: str, asked: int, distinct: int | None = None, rounds: int = 1, seconds: float = 0.0) -> None:
        self.rows.append(Row(method, phase, asked, asked if distinct is None else distinct, rounds, seconds))

    @contextmanager
    def timed(self, method: str, phase: str) -> Iterator[dict]:
        """The caller puts `asked` into the dictionary."""
        seen, began = {"asked": 0}, time.monotonic()
        yield seen
        self.record(method, phase, seen["asked"], seconds=time.monotonic() - began)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(asdict(r).values()) for r in self.rows], SCHEMA)


def round_robin(n: int) -> int:
    return n * (n - 1) // 2


def knockout(n: int, heats: int = 1) -> int:
    return max(0, n - heats)


def robust_band(n: int, pool: int, t: int, heats: int | None = None) -> int:
    return t * knockout(n, math.ceil(math.sqrt(n)) if heats is None else heats) + round_robin(pool)


def duels(n: int, centers: int) -> int:
    """All center pairs for all records; scores are kept, so the last round includes the earlier ones."""
    return n * centers * (centers - 1) // 2


def kcenter_band(n: int, k: int, t: int = 1) -> int:
    pool = 2 * math.ceil(math.sqrt(n)) * t
    return duels(n, k) + (k - 1) * robust_band(n, pool, t)


def anchored(questions: int, anchors: int) -> int:
    return questions * anchors
