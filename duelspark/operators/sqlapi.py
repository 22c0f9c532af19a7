"""The methods in SQL: an aggregate for groups and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from .judges import Judge

LIMIT = 100_000


def judge_of(mu: float, seed: int) -> Judge:
    """Without noise nothing is confusable: equal values are in order of their ids, where the band's policy would turn their answers round."""
    return Judge.band(mu, seed=seed) if mu else Judge.exact(seed=seed)


def register(spark: SparkSession, seed: int = 7) -> None:
    """Adds round_robin_agg(id, val, mu) -> id, robust_max(TABLE(...), mu) for tables (id, val) of at most LIMIT rows, and line_linkage(TABLE(...) PARTITION BY key, mu)."""

    @pandas_udf("long")
    def round_robin_agg(ids: pd.Series, values: pd.Series, mu: pd.Series) -> int:
        judge, items = judge_of(float(mu.iloc[0]), seed), sorted(zip(ids.tolist(), values.tolist(), strict=True))
        wins = [sum(not judge.answer(x, y) for y in items if y[0] != x[0]) for x in items]
        return items[max(range(len(items)), key=lambda i: (wins[i], items[i][0]))][0]

    spark.udf.register("round_robin_agg", round_robin_agg)

    @udtf
    class RobustMax:
        @staticmethod
        def analyze(table: AnalyzeArgument, mu: AnalyzeArgument) -> AnalyzeResult:
            return AnalyzeResult(schema=T.StructType([T.StructField("winner_id", T.LongType()), T.StructField("winner_val", T.LongType()), T.StructField("questions", T.LongType())]), withSinglePartition=True)

        def __init__(self) -> None:
            self.items, self.mu = [], 0.0

        def eval(self, row: T.Row, mu: float):
            if len(self.items) >= LIMIT:
                raise ValueError(f"robust_max takes at most {LIMIT} rows; use extremum.robust_band for more")
            self.items.append((row[0], row[1]))
            self.mu = float(mu)

        def terminate(self):
            import random

            from .linkage import robust_minimum

            if self.items:
                asked, judge = [0], judge_of(self.mu, seed).reversed()

                def ask(x, y) -> bool:
                    asked[0] += 1
                    return judge.answer(x, y)

                winner = robust_minimum(sorted(self.items), ask, 1, random.Random(seed))
                yield winner[0], winner[1], asked[0]

    spark.udtf.register("robust_max", RobustMax)

    @udtf(returnType="step int, left_id long, right_id long, size long, link_dist long")
    class LineLinkage:
        """Single linkage of positions on a line: rows (key, id, position), one hierarchy for each key (PARTITION BY)."""

        def __init__(self) -> None:
            self.items, self.mu = [], 0.0

        def eval(self, row: T.Row, mu: float):
            if len(self.items) >= 3000:
                raise ValueError("line_linkage takes at most 3000 rows of a key")
            self.items.append((row[1], row[2]))
            self.mu = float(mu)

        def terminate(self):
            from .linkage import agglomerate, line

            ids, positions = zip(*sorted(self.items), strict=True) if self.items else ((), ())
            for step, left, right, _, size, _, _, dist, _, _ in agglomerate(list(ids), list(positions), line, Judge.band(self.mu, seed=seed)):
                yield step, left, right, size, dist

    spark.udtf.register("line_linkage", LineLinkage)


def group_maxima(df, by: str, mu: float):
    """The winner of a round robin of every (small) group, by the aggregate."""
    register(df.sparkSession)
    df.createOrReplaceTempView("__judged")
    return df.sparkSession.sql(f"SELECT {by}, round_robin_agg(id, val, CAST({mu} AS DOUBLE)) AS winner_id FROM __judged GROUP BY {by}")


