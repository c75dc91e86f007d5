"""Interval and range joins and sorted arrays over whole tables, and ranges that touch several buckets."""

from pyspark.sql import functions as F

import __spark_entry__ as entry
from distsort.operators import relational as R


def test_every_event_is_on_both_sides(spark, tiny):
    got = entry.queries()["q_join_interval_full"](spark, tiny)
    n = spark.read.parquet(f"{tiny}/events.parquet").count()
    assert got.where("a = b").count() == n == got.select("b").distinct().count()


def test_every_element_is_returned(spark, tiny):
    t = spark.read.parquet(f"{tiny}/embeddings.parquet")
    assert entry.queries()["q_sort_within_array_full"](spark, tiny).count() == t.agg(F.sum(F.size("embedding"))).first()[0]


def test_wide_ranges(spark):
    points = spark.range(3000).select(F.col("id").alias("i"), (F.col("id") * 7 % 3000).alias("at"))
    ranges = spark.range(40).select(F.col("id").alias("j"), (F.col("id") * 70 - 200).alias("lo"), (F.col("id") * 70 - 200 + F.col("id") * 60).alias("hi"))
    got = sorted((r.at, r.j) for r in R.range_join(points, ranges, "at", "lo", "hi").collect())
    assert got == sorted((at, j) for j in range(40) for at in range(3000) if j * 70 - 200 <= at < j * 130 - 200)
