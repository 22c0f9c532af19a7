"""Helpers the training-data operators share."""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read through Spark alone so that any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Only a session in one process may do without it; it takes a temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = os.path.join(tempfile.gettempdir(), "duelspark-checkpoints")
        os.makedirs(found, exist_ok=True)
    return found.rstrip("/")


def materialise(df: DataFrame, what: str) -> DataFrame:
    """Writes df as a compressed table in the shared folder and reads it back: lineage is cut, lost executors lose nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/duelspark-{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def unmaterialise(df: DataFrame) -> None:
    """Deletes a table that materialise() wrote, once nothing lazy depends on it any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/duelspark-" in folder:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def join_hot(df: DataFrame, groups: DataFrame, keys: list[str], hot: DataFrame, spread: Column) -> DataFrame:
    """df left-joined with groups on keys, where keys that hold many rows of df do not meet in one task.

    `hot` are the rows of groups with such keys, a set of bounded size, which are broadcast; groups holds all. Rows of hot keys pass
    through the other join under a key of their own, made from `spread`.
    """
    added = [c for c in groups.columns if c not in keys]
    few = hot.select(*keys, F.struct(*added).alias("__hot"))
    marked = df.join(F.broadcast(few), keys, "left")
    rest = groups.select(*(F.col(k).alias(f"__{k}") for k in keys), F.lit(0).cast("long").alias("__spread"), F.struct(*added).alias("__cold"))
    found = F.col("__hot").isNotNull()
    same = (F.when(found, F.coalesce(spread, F.lit(0)) * 2 + 1).otherwise(0) == F.col("__spread")) & ~found
    for k in keys:
        same = same & (F.col(k) == F.col(f"__{k}"))
    joined = marked.join(rest, same, "left").withColumn("__both", F.coalesce("__hot", "__cold"))
    return joined.select(*df.columns, *(F.col(f"__both.{c}").alias(c) for c in added))


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Lowers the session's rows to an Arrow batch, which the JVM and its Python worker both hold whole, to so many at most. Results do not depend on it."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= rows:
        spark.conf.set(name, str(rows))


def slices(batches: Iterator[pa.RecordBatch], rows: int = 500) -> Iterator[pa.RecordBatch]:
    """Smaller batches, so that what a worker makes of one stays small; memory that is free at the end goes back to the system."""
    for batch in batches:
        for k in range(0, batch.num_rows, rows):
            yield batch.slice(k, rows)
    give_back()


def give_back() -> None:
    """Returns a worker's free memory to the system: Arrow's, and the heap's where the C library can."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass
