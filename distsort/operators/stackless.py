"""The sort without a recursion stack over a written table: the driver's state is one cursor.

One distribution step leaves buckets in order, each in a folder of its own.  A turn takes the bucket that follows the
cursor, found as the least number behind it; a bucket of more than `most` rows is split once more, else sorted and
appended.  A run that stops goes on from its cursor."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.keys import KeySpec
from ..plans.params import SortParams
from ..sources.io import fresh_path
from .sort import distribute, plan_sort, sort_global


def stackless_sort(df: DataFrame, keys, p: SortParams = SortParams(), most: int | None = None) -> DataFrame:
    spec, spark = KeySpec.of(keys), df.sparkSession
    tree, _, plan = plan_sort(df, spec, SortParams(**{**p.__dict__, "equality": False}))
    path, out, zone_path = (fresh_path(spark, x) for x in ("buckets", "sorted", "zones"))
    distribute(df, tree, False, plan, p).drop("_bucket", "_cls").write.partitionBy("_pid").parquet(path)
    if not sum(plan.sizes):
        return df.withColumn("pos", F.lit(0).cast("long"))
    table = spark.read.parquet(path)
    table.groupBy("_pid").agg(F.count(F.lit(1)).alias("n")).write.parquet(zone_path)
    zones = spark.read.parquet(zone_path)
    limit = most or max(1, 2 * sum(plan.sizes) // max(1, plan.partitions))
    cursor, start = -1, 0
    while turn := zones.where(F.col("_pid") > cursor).orderBy("_pid").limit(1).collect():
        cursor, n = turn[0]["_pid"], turn[0]["n"]
        own = table.where(F.col("_pid") == cursor).drop("_pid")  # reads one folder
        run = sort_global(own, spec, p, rows=n) if n > limit else sort_global(own, spec, SortParams(partitions=1, k=1), rows=n)
        run.withColumn("pos", F.col("pos") + start).write.mode("append").parquet(out)
        start += n
    return spark.read.parquet(out)
