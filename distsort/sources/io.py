"""Tables in and out."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.keys import KeySpec
from ..plans.params import SortParams

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
LINE_ID = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table, or some columns of it."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def register_views(spark: SparkSession, sf_dir: str, names: dict[str, str] | None = None) -> None:
    """Views of tables; names: table to view, each table under its own name if not given."""
    for t, view in (names or {t: t for t in TABLES}).items():
        load(spark, sf_dir, t).createOrReplaceTempView(view)


def shared_folder(spark: SparkSession) -> str:
    """Where written intermediate tables go: under spark.checkpoint.dir, or a local folder in local mode."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = getattr(sc, "_distsort_tables", None)
        if not found:
            found = sc._distsort_tables = "file://" + tempfile.mkdtemp(prefix="distsort-tables-")
    return f"{found}/distsort-tables/{sc.applicationId}"


#: Paths that the open block of `passing` has named, in each thread.
_passing: ContextVar[list[str] | None] = ContextVar("_passing", default=None)


def fresh_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    if (own := _passing.get()) is not None:
        own.append(path)
    return path


def delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Within the block, tables at fresh paths are for the block only and are deleted at its end."""
    own: list[str] = []
    outer = _passing.set(own)
    try:
        yield
    finally:
        _passing.reset(outer)
        for path in own:
            delete(spark, path)


@contextmanager
def freed(spark: SparkSession) -> Iterator[None]:
    """Within the block, a query's shuffle files are deleted when it has ended, not when the driver happens to collect its garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def write_any(df: DataFrame, path: str, fmt: str = "parquet", **options) -> None:
    df.write.format(fmt).options(**options).mode("overwrite").save(path)


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """df written in a format and read back with its schema."""
    path = fresh_path(df.sparkSession, fmt)
    write_any(df, path, fmt, **options)
    return read_any(df.sparkSession, path, fmt, df.schema, **options)


def write_sorted(df: DataFrame, keys, path: str, p: SortParams = SortParams()) -> None:
    """Files in key order: one for each partition of the distribution sort."""
    from ..operators.sort import sort_global

    sort_global(df, keys, p, with_pos=False).write.mode("overwrite").parquet(path)


def write_partitioned(df: DataFrame, by: list[str], path: str) -> None:
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def write_relabelled(df: DataFrame, keys, path: str, p: SortParams = SortParams()) -> DataFrame:
    """Rows are written once, each task's rows of a bucket to a file of their own, and no exchange moves them; what is sorted is the manifest.

    Returns it: seq, bucket, file, n, in the order in which to read."""
    from pyspark.sql import Window

    from ..operators.sort import plan_sort

    spark = df.sparkSession
    tree, _, _ = plan_sort(df, keys, p)
    tree.with_bucket(df, "bucket", p.backend).write.mode("overwrite").partitionBy("bucket").parquet(path)
    files = spark.read.parquet(path).groupBy("bucket", F.input_file_name().alias("file")).agg(F.count(F.lit(1)).alias("n"))
    return files.withColumn("seq", F.row_number().over(Window.orderBy("bucket", "file")) - 1)  # one row for each file


def write_bucketed(df: DataFrame, key: str, buckets: int, table: str) -> DataFrame:
    """A table dealt by key, so that later joins and aggregations on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)
    return df.sparkSession.table(table)


def write_index(df: DataFrame, key: str, path: str) -> DataFrame:
    """A zone map of the files at path: file, lowest and highest key, rows.  df: what is there, read with its file names."""
    zones = df.groupBy(F.input_file_name().alias("file")).agg(F.min(key).alias("lo"), F.max(key).alias("hi"), F.count(F.lit(1)).alias("n"))
    zones.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(zones.schema).parquet(path)


def lookup(spark: SparkSession, zones: DataFrame, key: str, lo, hi, most_files: int = 10_000) -> DataFrame:
    """Rows with lo <= key <= hi, read from the files whose zone can hold some; too many files are read by their common folder."""
    files = [r[0] for r in zones.where((F.col("hi") >= lo) & (F.col("lo") <= hi)).select("file").limit(most_files + 1).collect()]
    if not files:
        files = [r[0] for r in zones.select("file").limit(1).collect()]
    base = [files[0].rsplit("/", 1)[0]] if len(files) > most_files else files
    return spark.read.parquet(*base).where(F.col(key).between(lo, hi))


def key_order(keys) -> list:
    return KeySpec.of(keys).order()
