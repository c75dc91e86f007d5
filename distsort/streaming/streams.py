"""Classification, histograms, windows and state over streams of files; what an unbounded input allows of the method.

A global order of an unbounded stream is not offered: micro-batches become sorted runs, and runs are merged later."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.classify import SplitterTree
from ..plans.params import SortParams
from ..sources.io import fresh_path


def sliced(df: DataFrame, by: str, slices: int = 4) -> str:
    """df as files in `slices` batches by ranges of a column; the folder."""
    path = fresh_path(df.sparkSession, "slices")
    df.repartitionByRange(slices, by).sortWithinPartitions(by).write.parquet(path)
    return path


def source(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that the stream yields until its source is used up, written and read back; complete and update modes keep the last version of each batch's rows."""
    spark = stream.sparkSession
    out, state = fresh_path(spark, "out"), fresh_path(spark, "state")
    schema = stream.schema
    if mode == "append":
        q = stream.writeStream.format("parquet").option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start(out)
    else:
        def put(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

        q = stream.writeStream.foreachBatch(put).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if mode == "complete":
        every = spark.read.parquet(out)
        return every.where(F.col("batch") == every.agg(F.max("batch")).first()[0]).drop("batch")
    return spark.read.schema(schema).parquet(out) if mode == "append" else spark.read.parquet(out)


def classify_stream(stream: DataFrame, tree: SplitterTree) -> DataFrame:
    """Splitters are fixed; rows need no state."""
    return tree.with_bucket(stream, "bucket")


def bucket_histogram(stream: DataFrame, tree: SplitterTree) -> DataFrame:
    return classify_stream(stream, tree).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def sorted_runs(stream: DataFrame, order: list[str], merge: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Each micro-batch is written as a sorted run; then the runs are merged."""
    spark = stream.sparkSession
    out, state = fresh_path(spark, "runs"), fresh_path(spark, "state")

    def put(batch: DataFrame, number: int) -> None:
        batch.sortWithinPartitions(*order).write.mode("overwrite").parquet(f"{out}/run={number}")

    stream.writeStream.foreachBatch(put).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return merge(spark.read.parquet(out).drop("run"))


def running_extremes(stream: DataFrame, tree: SplitterTree, key: str) -> DataFrame:
    """bucket, lo, hi, n of all rows so far, by arbitrary state; the last row of a bucket is its newest."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(group, frames, state):
        lo, hi, n = state.get if state.exists else (float("inf"), float("-inf"), 0)
        for f in frames:
            if len(f):
                lo, hi, n = min(lo, float(f[key].min())), max(hi, float(f[key].max())), n + len(f)
        state.update((lo, hi, n))
        yield pd.DataFrame({"bucket": [group[0]], "lo": [lo], "hi": [hi], "n": [n]})

    schema = "bucket int, lo double, hi double, n long"
    return classify_stream(stream, tree).groupBy("bucket").applyInPandasWithState(step, schema, "lo double, hi double, n long", "update", GroupStateTimeout.NoTimeout)


PARAMS = SortParams()
