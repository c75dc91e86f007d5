"""What the training-data operators share: the scratch folder, written tables, text measures."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs without these: space and the bytes 0x09 to 0x0D.
BLANKS = "[\\x20\\x09-\\x0D]+"

#: Rows that a side may have to be broadcast with a hint; beyond it Spark deals both sides out.
BROADCAST_ROWS = 200_000
#: Bytes on disk, compressed, that a written table may have for that.
BROADCAST_BYTES = 32 << 20
#: Where a table's rows are bounded beforehand, so many rows a file, and TASKS files more at most: small tables are few files.
ROWS_A_FILE, TASKS = 100_000, 6


def ready(spark: SparkSession) -> SparkSession:
    """Let Python workers that share this machine import the package, wherever the driver was started."""
    env = spark.sparkContext.environment
    root = str(Path(__file__).resolve().parents[2])
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH", "")) if x)
    return spark


def scratch(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a local one in local mode."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = getattr(sc, "_distsort_scratch", None)
        if not found:
            found = sc._distsort_scratch = "file://" + tempfile.mkdtemp(prefix="distsort-")
    return f"{found}/distsort/{sc.applicationId}"


def written(df: DataFrame, label: str, most: int | None = None, rows_a_file: int = ROWS_A_FILE) -> DataFrame:
    """Write df once to the shared folder and read it back: its lineage is cut, and no lost executor costs it.

    most: rows that df has at most, if that is known; rows that cost much may be fewer to a file."""
    spark, seen = ready(df.sparkSession), Observation()
    path = f"{scratch(spark)}/{label}-{uuid.uuid4().hex}"
    dealt = df if most is None else df.coalesce(TASKS + most // rows_a_file)
    dealt.observe(seen, F.count(F.lit(1)).alias("n")).write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_rows, out._written_path = seen.get["n"], path
    fs, at = _folder(spark, path)
    out._written_bytes = fs.getContentSummary(at).getLength()
    if _passing:
        _passing[-1].append(path)
    return out


#: Paths that the open blocks of `passing` have written, the innermost last.
_passing: list[list[str]] = []


@contextmanager
def passing(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Within the block, `written` tables are for the block only and are deleted at its end; those that are handed to what it yields stay."""
    own: list[str] = []

    def keep(df: DataFrame) -> DataFrame:
        own.remove(df._written_path)
        if len(_passing) > 1:
            _passing[-2].append(df._written_path)
        return df

    _passing.append(own)
    try:
        yield keep
    finally:
        _passing.pop()
        for path in own:
            _delete(spark, path)


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


def _folder(spark: SparkSession, path: str) -> tuple:
    """Its file system and itself, as Hadoop names them."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def _delete(spark: SparkSession, path: str) -> None:
    fs, at = _folder(spark, path)
    fs.delete(at, True)


def rows_of(df: DataFrame) -> int:
    """The rows of a table, known if it comes from `written`."""
    n = getattr(df, "_written_rows", None)
    return df.count() if n is None else n


def release(spark: SparkSession) -> None:
    """Delete every table that `written` has left in the shared folder for this application."""
    _delete(spark, scratch(spark))


def small(df: DataFrame, rows: int | None = None, most: int = BROADCAST_ROWS, table: DataFrame | None = None) -> DataFrame:
    """df with a broadcast hint if it has at most `most` rows, else as it is; rows: its count, or that of what its lists hold, if known.

    table: the written table whose rows df has; its bytes, or df's own, count as well if neither `rows` nor `most` says otherwise."""
    table = df if table is None else table
    n = getattr(table, "_written_rows", None) if rows is None else rows
    n = df.limit(most + 1).count() if n is None else n
    fits = most != BROADCAST_ROWS or getattr(table, "_written_bytes", 0) <= BROADCAST_BYTES
    return F.broadcast(df) if n <= most and fits else df


def unused(df: DataFrame, *wanted: str) -> list[str]:
    """Column names like the wanted ones that df doesn't have, in any case of letters."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in wanted:
        name = f"_{name}"
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def words(text: Column | str) -> Column:
    """The words of a text as an array; none for null."""
    c = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(F.coalesce(c, F.lit("")), BLANKS), lambda w: w != "")


def ascii_lower(text: Column) -> Column:
    """A-Z lower-cased, all else as it is."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    df = ready(spark).read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df
