"""Operators that reuse the distribution: co-partitioned and skewed joins, range and as-of joins, ranks, sums and selection by buckets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.classify import SplitterTree, literal_array
from ..plans.keys import KeySpec
from ..plans.params import SortParams
from .sort import class_counts, distribute, plan_sort, sort_global


def distribution_merge_join(left: DataFrame, right: DataFrame, key: str, p: SortParams = SortParams()) -> DataFrame:
    """Inner join on key; both sides go through one set of splitters, so that the join needs no exchange of its own."""
    tree, _, plan = plan_sort(left.select(key), [key], p)
    sides = [distribute(df, tree, False, plan_of(df, tree, plan), p).drop("_bucket", "_cls") for df in (left, right)]
    return sides[0].join(sides[1], ["_pid", key]).drop("_pid")


def plan_of(df: DataFrame, tree: SplitterTree, plan):
    """Both sides share a plan; classes of one side only exist in it as well, since it covers all buckets."""
    from ..plans.recursion import DistributionPlan

    return DistributionPlan(plan.first, (1,) * len(plan.first), plan.sizes)


def skew_join(left: DataFrame, right: DataFrame, key: str, k: int = 64, salts: int = 8) -> DataFrame:
    """Inner join where left has heavy keys (over 1/k of its rows): their rows are spread, and right's rows for them are copied to each place."""
    n = left.count()
    heavy = left.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") * k > n).select(key, F.lit(True).alias("_heavy"))  # fewer than k rows
    salt = F.pmod(F.xxhash64(*[c for c in left.columns]), F.lit(salts)).cast("int")
    a = left.join(F.broadcast(heavy), key, "left").withColumn("_salt", F.when(F.col("_heavy"), salt).otherwise(0)).drop("_heavy")
    b = right.join(F.broadcast(heavy), key, "left").withColumn("_salt", F.explode(F.when(F.col("_heavy"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("_heavy")
    return a.join(b, [key, "_salt"]).drop("_salt")


def range_join(points: DataFrame, ranges: DataFrame, point: str, lo: str, hi: str, p: SortParams = SortParams()) -> DataFrame:
    """Pairs with lo <= point < hi: both sides are classified by the points' splitters, ranges once for each bucket that they touch."""
    tree, _, _ = plan_sort(points.select(point), [point], p)
    a = tree.with_bucket(points, "_b", p.backend)
    edge = lambda name, out: SplitterTree(KeySpec.of([name]), tree.splitters, tree.types).with_bucket
    r = edge(lo, "_lo")(ranges, "_lo", p.backend)
    r = edge(hi, "_hi")(r, "_hi", p.backend)
    r = r.where(F.col(lo) < F.col(hi)).withColumn("_b", F.explode(F.sequence("_lo", "_hi"))).drop("_lo", "_hi")
    return a.join(r, "_b").where((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, out: str, p: SortParams = SortParams()) -> DataFrame:
    """left with the value of the latest right row of the same `by` at or before `at`: no pairs.

    The union is dealt by `by` and bucket of `at`, so that a frequent `by` is many tasks'; what the buckets before have last is added from a table of one row each."""
    a = left.select(*left.columns, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(*[F.col(c) if c in (by, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.lit(0).alias("_side"), F.col(value).alias("_v"))
    tree, _, _ = plan_sort(left.select(at), [at], p)
    rows = tree.with_bucket(a.unionByName(b), "_bucket", p.backend)
    known = F.col("_v").isNotNull()
    ends = rows.groupBy(by, "_bucket").agg(F.max_by(F.when(known, F.col("_v")), F.when(known, F.col(at))).alias("_end"))
    earlier = Window.partitionBy(by).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select(F.col(by).alias("_by"), F.col("_bucket").alias("_of"), F.last("_end", True).over(earlier).alias("_carried"))
    w = Window.partitionBy(by, "_bucket").orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    joined = rows.withColumn(out, F.last("_v", True).over(w)).where("_side = 1").join(carried, F.col(by).eqNullSafe(F.col("_by")) & (F.col("_bucket") == F.col("_of")), "left")
    return joined.withColumn(out, F.coalesce(out, "_carried")).drop("_side", "_v", "_bucket", "_by", "_of", "_carried")


def sorted_with_pid(df: DataFrame, keys, p: SortParams = SortParams()) -> tuple[DataFrame, int]:
    """df with pos and _pid, sorted within partitions; windows by _pid need no further exchange."""
    n = df.count()
    spec = KeySpec.of(keys)
    tree, _, plan = plan_sort(df, spec, SortParams(**{**p.__dict__, "equality": False}), n)
    moved = distribute(df, tree, False, plan, p).drop("_bucket", "_cls")
    starts, at = [0] * plan.partitions, 0
    for f, s in zip(plan.first, plan.sizes):
        starts[f] += s
    for i, s in enumerate(starts):
        starts[i], at = at, at + s
    start = F.get(literal_array(starts, T.LongType()), F.col("_pid"))
    return moved.withColumn("pos", start + F.row_number().over(Window.partitionBy("_pid").orderBy(*spec.order())) - 1), n


def global_rank(df: DataFrame, keys, tie: list[str], tiles: int = 10, p: SortParams = SortParams()) -> DataFrame:
    """row_number, rank, dense_rank, percent_rank, cume_dist and ntile of all rows, from bucket offsets.

    Buckets are cut by the keys alone, so that rows of equal keys are in one partition."""
    spec = KeySpec.of(keys)
    placed, n = sorted_with_pid(df, spec, p)
    w = Window.partitionBy("_pid").orderBy(*spec.order())
    own = Window.partitionBy("_pid").orderBy(*spec.order(), *KeySpec.of(tie).order())
    rows = Window.partitionBy("_pid")
    first = F.min("pos").over(rows)
    local = placed.withColumn("_first", first).withColumn("row_number", F.col("_first") + F.row_number().over(own)).withColumn("rank", F.col("_first") + F.rank().over(w)).withColumn("_dense", F.dense_rank().over(w))
    local = local.withColumn("_upto", F.col("_first") + F.count(F.lit(1)).over(w.rangeBetween(Window.unboundedPreceding, Window.currentRow)))
    each = local.groupBy("_pid").agg(F.max("_dense").alias("_m"))  # one row for each partition
    before = each.select("_pid", (F.sum("_m").over(Window.orderBy("_pid")) - F.col("_m")).alias("_before"))
    out = local.join(F.broadcast(before), "_pid").withColumn("dense_rank", (F.col("_before") + F.col("_dense")).cast("long"))
    i, big, size = F.col("row_number") - 1, n % tiles, n // tiles
    tile = F.when(i < big * (size + 1), F.floor(i / (size + 1))).otherwise(big + F.floor((i - big * (size + 1)) / max(1, size))) + 1
    return out.withColumn("percent_rank", (F.col("rank") - 1) / max(1, n - 1)).withColumn("cume_dist", F.col("_upto") / n).withColumn("ntile", tile.cast("int")).drop("_pid", "_first", "_dense", "_upto", "_before", "pos")


def global_cumsum(df: DataFrame, keys, value: Column, out: str = "running", p: SortParams = SortParams()) -> DataFrame:
    """A running sum over all rows in key order: within partitions, plus what the partitions before have in total."""
    spec = KeySpec.of(keys)
    placed, _ = sorted_with_pid(df.withColumn("_v", value), spec, p)
    totals = placed.groupBy("_pid").agg(F.sum("_v").alias("_t"))  # one row for each partition
    before = totals.select("_pid", (F.sum("_t").over(Window.orderBy("_pid")) - F.col("_t")).alias("_before"))
    inside = F.sum("_v").over(Window.partitionBy("_pid").orderBy(*spec.order()).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return placed.withColumn("_in", inside).join(F.broadcast(before), "_pid").withColumn(out, F.col("_before") + F.col("_in")).drop("_v", "_pid", "_in", "_before")


def select_ranks(df: DataFrame, keys, ranks: list[int], p: SortParams = SortParams()) -> DataFrame:
    """The rows at some ranks (from 0): counts tell which buckets hold them, and only these are read again and sorted."""
    spec = KeySpec.of(keys)
    tree, equality, plan = plan_sort(df, spec, p)
    before, wanted = 0, []
    for c, size in enumerate(plan.sizes):
        inside = [r for r in ranks if before <= r < before + size]
        if inside:
            wanted.append((c, before, inside))
        before += size
    out = None
    for c, start, inside in wanted:
        bucket = (c + 1) // 2
        own = df.where(tree.inside(bucket, equality) if c % 2 == 0 else tree.keys.same(tree._values(tree.splitters.values[bucket - 1])))
        # a large bucket is distributed once more
        placed = sort_global(own, spec, p, rows=plan.sizes[c], pos="rank").where(F.col("rank").isin([r - start for r in inside]))
        one = placed.withColumn("rank", F.col("rank") + F.lit(start))
        out = one if out is None else out.unionByName(one)
    return df.limit(0).withColumn("rank", F.lit(0)) if out is None else out


def top_k(df: DataFrame, keys, k: int, offset: int = 0, p: SortParams = SortParams()) -> DataFrame:
    """Rows offset .. offset + k - 1 in key order, by sorting only the buckets that hold them; also for k too large for one task."""
    spec = KeySpec.of(keys)
    n = df.count()
    tree, equality, plan = plan_sort(df, spec, p, n)
    upto, last = 0, -1
    for c, size in enumerate(plan.sizes):
        last = c
        upto += size
        if upto >= offset + k:
            break
    bucket = (last + 1) // 2
    few = df.where(tree.keys.before(tree._values(tree.splitters.values[bucket]))) if bucket < len(tree.splitters) else df
    return sort_global(few, spec, p).where((F.col("pos") >= offset) & (F.col("pos") < offset + k))


def distinct_sorted(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """The first row of each run of equal keys; equal keys share a partition."""
    spec = KeySpec.of(keys)
    placed, _ = sorted_with_pid(df.select(*spec.names), spec, p)
    w = Window.partitionBy("_pid").orderBy(*spec.order())
    lagged = placed.select(*spec.names, F.row_number().over(w).alias("_i"), *[F.lag(n).over(w).alias(f"_b_{n}") for n in spec.names])
    return lagged.where((F.col("_i") == 1) | ~spec.same([F.col(f"_b_{n}") for n in spec.names])).select(*spec.names)


def sorted_group(df: DataFrame, keys, aggs: list[Column], p: SortParams = SortParams()) -> DataFrame:
    """Aggregation over runs that the distribution has put together."""
    spec = KeySpec.of(keys)
    tree, _, plan = plan_sort(df.select(*spec.names), spec, SortParams(**{**p.__dict__, "equality": False}))
    return distribute(df, tree, False, plan_of(df, tree, plan), p).groupBy("_pid", *spec.names).agg(*aggs).drop("_pid")
