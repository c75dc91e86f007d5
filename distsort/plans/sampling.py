"""Samples and the splitters that come from them."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .keys import KeySpec


def row_digest(rowid: Sequence[str], seed: int) -> Column:
    """A digest of the row id that another engine can compute as well."""
    return F.md5(F.concat(F.concat_ws("-", *[F.col(c).cast("string") for c in rowid]), F.lit(f":{seed}")))


def draw_sample(df: DataFrame, keys, m: int, seed: int = 7, method: str = "bernoulli", rowid: Sequence[str] = (), rows: int | None = None) -> DataFrame:
    """About (bernoulli, per_partition) or exactly (digest, hash) m rows: row id and key columns.  No method sorts the table."""
    spec = KeySpec.of(keys)
    cols = list(dict.fromkeys([*rowid, *spec.names]))
    thin = df.select(*cols)
    if method == "digest":
        return thin.orderBy(row_digest(rowid, seed), *rowid).limit(m)
    if method == "hash":
        return thin.orderBy(F.xxhash64(F.lit(seed), *(rowid or spec.names)), *cols).limit(m)
    if method == "bernoulli":
        n = df.count() if rows is None else rows
        return thin.sample(min(1.0, 1.2 * m / max(1, n) + 1e-9), seed) if m < n else thin
    if method == "per_partition":
        order = Window.partitionBy(F.spark_partition_id()).orderBy(F.xxhash64(F.lit(seed), *cols))
        parts = 1 + (thin.select(F.spark_partition_id().alias("p")).agg(F.max("p")).first()[0] or 0)
        return thin.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= -(-m // parts)).drop("_r")
    raise ValueError(method)


def sketched_quantiles(df: DataFrame, key: str, k: int, accuracy: int = 10_000) -> list:
    """k - 1 approximate splitters of one numeric key from a mergeable sketch, without a sample."""
    got = df.agg(F.percentile_approx(key, [i / k for i in range(1, k)], accuracy)).first()[0]
    return list(got or [])


@dataclass(frozen=True)
class SplitterSet:
    values: tuple[tuple, ...]
    use_equality: bool

    def __len__(self) -> int:
        return len(self.values)


def pick_splitters(sample: list[tuple], k: int) -> list[tuple]:
    """k - 1 values at equal distances of a sorted sample."""
    if not sample or k < 2:
        return []
    n = len(sample) + 1
    return [sample[min(len(sample), max(1, round(i * n / k))) - 1] for i in range(1, k)]


def dedupe_splitters(values: list[tuple]) -> SplitterSet:
    """Neighbouring equal splitters become one; only then are equality classes worth their comparison."""
    kept: list[tuple] = []
    for v in values:
        if not kept or not _same(kept[-1], v):
            kept.append(v)
    return SplitterSet(tuple(kept), len(kept) < len(values))


def _same(a: tuple, b: tuple) -> bool:
    return all(x == y or (x != x and y != y) for x, y in zip(a, b))
