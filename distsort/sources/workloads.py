"""The nine input distributions and four record types, on the given tables or for any number of rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .io import load

NAMES = ("uniform", "exponential", "almost_sorted", "root_dups", "square_dups", "eighth_dups", "sorted", "reverse", "ones")


def residues(i: Column, n: int, name: str) -> Column:
    """The three distributions that are defined on an index 0 .. n - 1; powers are reduced at each squaring, so that they fit for n < 2**31."""
    i = i.cast("long")
    if name == "root_dups":
        return F.pmod(i, F.lit(max(1, math.isqrt(n))))
    power = i
    for _ in range({"square_dups": 1, "eighth_dups": 3}[name]):
        power = F.pmod(power * power, F.lit(n))
    return F.pmod(power + n // 2, F.lit(n))


def swapped(i: Column, n: int) -> Column:
    """A sorted index with about sqrt(n) neighbours at fixed distances exchanged."""
    step = max(2, math.isqrt(n))
    at = i % step
    return F.when((at == 0) & (i + 1 < n), i + 1).when(at == 1, i - 1).otherwise(i)


def make(spark: SparkSession, name: str, n: int, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """(i, key double) of n rows."""
    base = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    i = F.col("id")
    key = {
        "uniform": lambda: F.rand(seed),
        "exponential": lambda: -F.log(1 - F.rand(seed)),
        "almost_sorted": lambda: swapped(i, n),
        "sorted": lambda: i,
        "reverse": lambda: n - 1 - i,
        "ones": lambda: F.lit(1.0),
    }.get(name, lambda: residues(i, n, name))()
    return base.select(i.alias("i"), key.cast("double").alias("key"))


def on_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(i, key double) from the given tables."""
    if name in ("root_dups", "square_dups", "eighth_dups", "almost_sorted"):
        df = load(spark, sf_dir, "orders", "o_orderkey")
        n = df.count()
        key = swapped(F.col("o_orderkey"), n) if name == "almost_sorted" else residues(F.col("o_orderkey"), n, name)
        return df.select(F.col("o_orderkey").alias("i"), key.cast("double").alias("key"))
    df = load(spark, sf_dir, "events", "event_id", "value", "ts")
    if name == "uniform":
        df = load(spark, sf_dir, "orders", "o_orderkey", "o_totalprice")
        return df.select(F.col("o_orderkey").alias("i"), F.col("o_totalprice").alias("key"))
    key = {"exponential": F.col("value"), "sorted": F.col("event_id"), "reverse": F.lit(df.count() - 1) - F.col("event_id"), "ones": F.lit(1.0)}[name]
    return df.select(F.col("event_id").alias("i"), key.cast("double").alias("key"))
