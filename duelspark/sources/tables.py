"""The given tables as value sets (id, val) and metric sets (id, payload, truth)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.ticks import ticks
from ..operators.blocking import tokens

SHIFT = 1_000  # dollars added to balances, whose minimum is above -1000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def judged(df: DataFrame, id_: str, value: str, positive: bool = True) -> DataFrame:
    """id, val in ticks; rows a judge cannot compare (null, not a number, or not positive under a ratio model) are left out, repeated ids once."""
    kept = df.select(F.col(id_).cast("long").alias("id"), F.col(value).cast("double").alias("v")).where(F.col("id").isNotNull() & F.col("v").isNotNull() & ~F.isnan("v"))
    out = kept.select("id", ticks(F.col("v")).alias("val"))
    return (out.where("val > 0") if positive else out).dropDuplicates(["id"])


def values_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order totals: half of them within a factor 2 of the largest."""
    return judged(table(spark, sf_dir, "orders"), "o_orderkey", "o_totalprice")


def values_skewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event values: a heavy tail."""
    return judged(table(spark, sf_dir, "events"), "event_id", "value")


def values_large(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prices of lineitem, which has no key: the id is the head of an md5 over the columns that tell rows apart."""
    df = table(spark, sf_dir, "lineitem")
    key = F.md5(F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", ticks(F.col("l_extendedprice")), F.col("l_shipdate").cast("string")))
    return judged(df.select(F.conv(F.substring(key, 1, 15), 16, 10).cast("long").alias("id"), "l_extendedprice"), "id", "l_extendedprice")


def values_shifted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer balances, shifted so that all are positive."""
    df = table(spark, sf_dir, "customer").withColumn("v", F.col("c_acctbal") + SHIFT)
    return judged(df, "c_custkey", "v")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("payload"), F.col("label").alias("truth"))


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings whose labels count as a further dimension, which makes them true clusters."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.struct(F.col("embedding").alias("v"), "label").alias("payload"), F.col("label").alias("truth"))


def customer_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = F.broadcast(table(spark, sf_dir, "nation"))  # 25 rows
    df = table(spark, sf_dir, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    payload = F.struct(F.col("n_regionkey").alias("region"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"), ticks(F.col("c_acctbal") + SHIFT).alias("bal"))
    return df.select(F.col("c_custkey").alias("id"), payload.alias("payload"), F.col("n_regionkey").alias("truth"))


def part_catalogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "part")
    return df.select(F.col("p_partkey").alias("id"), F.struct("p_type", "p_brand", "p_size", tokens(F.col("p_name")).alias("words")).alias("payload"), F.col("p_type").alias("truth"))
