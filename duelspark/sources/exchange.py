"""Questions out to annotators and answers back, and an append-only log of answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

QUESTION = "k1 long, k2 long, k3 long, k4 long"
ANSWER = f"{QUESTION}, yes boolean, judge string, seed int"


def write_questions(questions: DataFrame, path: str, kind: str = "json") -> None:
    """Each question once, as JSON, CSV, ORC or Parquet."""
    writer = questions.dropDuplicates(["k1", "k2", "k3", "k4"]).write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def read_answers(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    reader = spark.read.schema(ANSWER)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def log_answers(answers: DataFrame, path: str) -> None:
    """Appends answers, partitioned by judge and seed."""
    answers.write.mode("append").partitionBy("judge", "seed").parquet(path)


def unanswered(questions: DataFrame, log: DataFrame) -> DataFrame:
    """Questions without a stored answer, each once: nothing is asked twice."""
    keys = ["k1", "k2", "k3", "k4"]
    return questions.dropDuplicates(keys).join(log.select(*keys), keys, "left_anti")


def majority(votes: DataFrame) -> DataFrame:
    """k1..k4, yes, votes from one row per worker."""
    return votes.groupBy("k1", "k2", "k3", "k4").agg((F.sum(F.col("yes").cast("int")) * 2 > F.count("*")).alias("yes"), F.count("*").alias("votes"))
