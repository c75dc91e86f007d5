"""Whether a result is sorted and holds the rows it should."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.keys import KeySpec


def run_of(pos: str) -> Column:
    """The run of 65,536 positions that a position is in."""
    return F.shiftright(F.col(pos).cast("long"), 16)


def digests(df: DataFrame, names: list[str], pos: str = "pos") -> dict[int | None, tuple]:
    """Of each run of positions its rows and two hashes of these with their positions; the driver gets one row a run.

    Unequal digests may mean equal rows (zeros of both signs); equal ones mean unequal rows once in 2 to the power of 128."""
    absent = [F.col(n).isNull() for n in names]  # a hash passes nulls over
    hashes = [F.bit_xor(F.xxhash64(*order, *absent)) for order in ([F.col(pos).cast("long"), *names], [*reversed(names), F.col(pos).cast("long")])]
    return {r[0]: tuple(r)[1:] for r in df.groupBy(run_of(pos).alias("_run")).agg(F.count(F.lit(1)), *hashes).collect()}


def descents(df: DataFrame, keys, pos: str = "pos", run: int = 1 << 16) -> DataFrame:
    """One row: pairs of neighbouring positions that are out of order, and positions that are missing or double.  Windows are runs of positions; their edges meet in a table of one row each."""
    spec = KeySpec.of(keys)
    w = Window.partitionBy("_p").orderBy(pos)
    rows = df.withColumn("_p", F.floor(F.col(pos) / run))
    names = [k.name for k in spec.keys]
    lagged = rows.select("*", *[F.lag(n).over(w).alias(f"_b_{n}") for n in names], F.row_number().over(w).alias("_i"), F.min(pos).over(w).alias("_first"))
    down = F.when(F.col("_i") > 1, spec.before([F.col(f"_b_{n}") for n in names])).otherwise(False)
    gap = F.col(pos) != F.col("_first") + F.col("_i") - 1
    each = lagged.groupBy("_p").agg(F.sum(down.cast("long")).alias("down"), F.sum(gap.cast("long")).alias("gaps"), *[F.min_by(n, pos).alias(n) for n in names], *[F.max_by(n, pos).alias(f"_z_{n}") for n in names])
    e = Window.orderBy("_p")
    edges = each.select("down", "gaps", *names, F.row_number().over(e).alias("_i"), *[F.lag(f"_z_{n}").over(e).alias(f"_b_{n}") for n in names])
    over = F.when(F.col("_i") > 1, spec.before([F.col(f"_b_{n}") for n in names])).otherwise(False)
    return edges.agg((F.coalesce(F.sum("down"), F.lit(0)) + F.coalesce(F.sum(over.cast("long")), F.lit(0))).alias("descents"), F.coalesce(F.sum("gaps"), F.lit(0)).alias("gaps"))


def same_multiset(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of one that the other lacks, counted with repeats, in both directions."""
    cols = sorted(a.columns)
    both = a.select(*cols, F.lit(1).alias("_s")).unionAll(b.select(*cols, F.lit(-1).alias("_s")))
    diff = both.groupBy(*cols).agg(F.sum("_s").alias("_d")).where("_d <> 0")
    return diff.agg(F.coalesce(F.sum(F.when(F.col("_d") > 0, F.col("_d"))), F.lit(0)).alias("only_first"), F.coalesce(F.sum(F.when(F.col("_d") < 0, -F.col("_d"))), F.lit(0)).alias("only_second"))
