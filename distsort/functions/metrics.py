"""Cost measures: models of what a method moves and compares, and what is measured on tables."""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes of memory traffic for each row byte: read and write in classification, permutation and base case; the copying form also
#: reads and writes its stored buckets, and new memory is read before it is written.
PASSES = {"distribution": 6.0, "copying": 10.75}


def _log(x: float | Column, least: float, base: float) -> float | Column:
    """The logarithm of x, or of the least value that counts; of a number or of a column."""
    return F.log(float(base), F.greatest(x, F.lit(float(least)))) if isinstance(x, Column) else math.log(max(x, least), base)


def comparisons(n: int | Column, k: int, levels: int, n0: int = 16, equality: bool = False) -> float | Column:
    """Each level log2 k comparisons a row and one for equality classes; then insertion in base cases."""
    return n * levels * (math.log2(k) + equality) + n * n0 / 4


def io_volume(n: int | Column, s: int, levels: int = 1, method: str = "distribution") -> float | Column:
    once = PASSES[method] - 2
    return n * s * (once * levels + 2)


def block_transfers(n: int | Column, t: int, b: int, k: int, n0: int) -> float | Column:
    """Transfers of b rows in parallel by t workers: n / (t b) for each of log_k(n / n0) levels."""
    levels = _log(n / n0, 1.0, k)
    return n / (t * b) * (F.greatest(F.lit(1.0), levels) if isinstance(n, Column) else max(1.0, levels))


def assumptions_hold(n: int, k: int, t: int, transfer: int, block: int, memory: int, n0: int, alpha: float) -> dict[str, bool]:
    """What the bound on transfers takes for granted, with constants of one."""
    return {"block": block >= t * transfer, "memory": memory >= k * t * transfer, "base": n0 <= memory, "alpha": math.log2(max(2, t)) <= alpha <= max(t, 1), "n": n >= max(k, t) * t * t * transfer}


def extra_space(k: int, b: int, t: int, n: int | Column, n0: int, stack: bool = True) -> float | Column:
    """Rows of buffers, and frames of recursion unless it goes without a stack."""
    return k * b * t + (_log(n / n0, 1.0, k) if stack else 0.0)


def branch_proxy(n: int | Column, n0: int = 16, method: str = "branchy") -> float | Column:
    """Branches that hang on data; a stand-in for the mispredictions that Spark can't see.  Half of a two-way partition's are taken against the odds."""
    base = n * n0 / 4
    return n * _log(n / n0, 2.0, 2) + base if method == "branchy" else base


def balance(sizes: DataFrame, column: str = "n") -> DataFrame:
    """max_over_avg and spread of bucket sizes."""
    return sizes.agg((F.max(column) / F.avg(column)).alias("max_over_avg"), F.stddev_pop(column).alias("spread"))


def heavy_keys(df: DataFrame, key: str, k: int, n: int | None = None) -> DataFrame:
    """Keys with more than n / k rows: likely splitters, and then classes of their own."""
    rows = df.count() if n is None else n
    return df.groupBy(key).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") * k > rows)


def factor(own: float, others: Iterable[float]) -> float:
    """How many times faster own is than the best of the others."""
    return min(others) / own


def speedup(one: float | Column, many: float | Column) -> float | Column:
    return one / many
