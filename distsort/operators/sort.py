"""The distribution sort: sample, classify, count, plan, one exchange, local sorts, positions.

Rows move once.  What comes before the exchange reads key columns only: a sample of some keys for each partition, and one count for each class.  Buckets that the counts show
to be too large get more splitters from a sample of their own before anything moves, so that levels of recursion cost scans of keys and no exchange.  Keys
with many equal rows become classes of their own; these need no sorting and are spread over several partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.classify import SplitterTree, literal_array
from ..plans.keys import KeySpec, quoted
from ..plans.params import SortParams, level_plan
from ..plans.recursion import DistributionPlan, plan_partitions, plan_recursion
from ..plans.sampling import SplitterSet, dedupe_splitters, draw_sample, pick_splitters

_WITHIN = (1 << 33) - 1
#: Rows of a partition at least, where the number of partitions isn't given.
LEAST_ROWS = 2048


def sorted_sample(df: DataFrame, spec: KeySpec, k: int, rows: int, p: SortParams) -> list[tuple]:
    """Sample rows in order; they are few whatever the table's size, and the driver gets them anyway."""
    return _in_order(draw_sample(df, spec, p.alpha_for(rows) * k, p.seed, rows=rows).select(*spec.names), spec)


def _in_order(few: DataFrame, spec: KeySpec) -> list[tuple]:
    if spec.plainly_ordered(few):
        return sorted((tuple(r) for r in few.collect()), key=lambda r: spec.plain(r[-len(spec.keys) :]))
    return [tuple(r) for r in few.repartition(1).sortWithinPartitions(*spec.order()).collect()]


def splitters_of(df: DataFrame, spec: KeySpec, k: int, rows: int, p: SortParams) -> SplitterSet:
    return dedupe_splitters(pick_splitters(sorted_sample(df, spec, k, rows, p), k))


def leading_splitters(df: DataFrame, spec: KeySpec, k: int, rows: int, p: SortParams) -> tuple[KeySpec, SplitterSet]:
    """Splitters of the fewest leading keys that tell them all apart; rows that are equal in these share a bucket, and the local sort has all keys."""
    picked = pick_splitters(sorted_sample(df, spec, k, rows, p), k)
    for n in range(1, len(spec.keys) + 1):
        found = dedupe_splitters([v[:n] for v in picked])
        if not found.use_equality:
            return spec.prefix(n), found
    return spec, found


def class_counts(df: DataFrame, tree: SplitterTree, p: SortParams, equality: bool) -> list[int]:
    """Rows of each class; the scan reads key columns only."""
    cls = _classed(df.select(*dict.fromkeys(tree.keys.names)), tree, p, equality)
    sizes = [0] * (2 * tree.buckets)
    for c, n in cls.groupBy("_cls").count().collect():  # at most two rows a bucket
        sizes[c] = n
    return sizes


def _classed(df: DataFrame, tree: SplitterTree, p: SortParams, equality: bool) -> DataFrame:
    df = tree.with_bucket(df, "_bucket", p.backend)
    return tree.with_class(df, "_cls", "_bucket") if equality else df.withColumn("_cls", F.col("_bucket") * 2)


def plan_sort(df: DataFrame, keys, p: SortParams = SortParams(), rows: int | None = None) -> tuple[SplitterTree, bool, DistributionPlan]:
    """Splitters and plan for df.  Takes a job for the sample and one for the counts; more only if a bucket is too large."""
    spec = full = KeySpec.of(keys).validate(df)
    n = df.count() if rows is None else rows
    # a partition of fewer rows than this costs more to plan than to sort
    parts = p.partitions or min(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), max(1, -(-n // LEAST_ROWS)))
    # four buckets a partition in the end; the levels share them, so that no level has a needlessly large fan-out
    levels = level_plan(n, max(p.n0, n // (4 * parts)), p.k) if parts > 1 else []
    k = levels[0] if levels else 1
    found = SplitterSet((), False)
    if n > p.n0 and k > 1:
        spec, found = leading_splitters(df, spec, k, n, p)
    equality = found.use_equality if p.equality is None else p.equality
    tree = SplitterTree.build(df, spec, found)
    sizes = class_counts(df, tree, p, equality)
    for _ in range(p.most_levels - 1):
        limit = max(p.n0, p.beta * n / parts)
        if any(c % 2 == 0 and s > 2 * limit for c, s in enumerate(sizes)) and len(spec.keys) < len(full.keys):
            # rows that are equal in the leading keys make a bucket too large: all keys are taken from here on
            spec, found = full, splitters_of(df, full, k, n, p)
            equality = found.use_equality if p.equality is None else p.equality
            tree = SplitterTree.build(df, spec, found)
            sizes = class_counts(df, tree, p, equality)
        # what is over twice a partition's share is split by all workers again, equality classes never are
        doomed = plan_recursion(sizes, parts, 2 * p.beta, p.n0, frozenset(range(1, len(sizes), 2)))
        large = [c for c, what in enumerate(doomed) if what == "split"]
        if not large or len(tree.splitters) > 16 * max(p.k, parts):
            break
        more = deeper_splitters(df, tree, equality, large, sizes, limit, n, p)
        merged = _merge(df, spec, [*tree.splitters.values, *more])
        if len(merged) == len(tree.splitters):
            break
        equality = equality or p.equality is None and merged.use_equality
        tree = SplitterTree.build(df, spec, SplitterSet(merged.values, equality))
        sizes = class_counts(df, tree, p, equality)
    return tree, equality, plan_partitions(sizes, [c % 2 == 1 and len(spec.keys) == len(full.keys) for c in range(len(sizes))], parts)


def deeper_splitters(df: DataFrame, tree: SplitterTree, equality: bool, large: list[int], sizes: list[int], limit: float, n: int, p: SortParams) -> list[tuple]:
    """More splitters for all classes that are too large, from one sample that is dense enough for each: some rows for each partition, whatever n.

    The driver leaves out the other classes' rows: a filter on the class would be pushed below the walk, and each level names the one before many times."""
    names = tree.keys.names
    share = min(1.0, 3 * p.alpha_for(n) / limit)
    drawn = _classed(df.select(*dict.fromkeys(names)).sample(share, p.seed + 1), tree, p, equality)
    own: dict[int, list[tuple]] = {c: [] for c in large}
    for r in _in_order(drawn.select("_cls", *names), tree.keys):
        if r[0] in own:
            own[r[0]].append(r[1:])
    return [v for c in large for v in pick_splitters(own[c], max(2, min(p.k, int(2 * sizes[c] / limit))))]


def _merge(df: DataFrame, spec: KeySpec, values: list[tuple]) -> SplitterSet:
    """Sorted as Spark sorts; a driver list, of splitters only."""
    if spec.plainly_ordered(df):
        return dedupe_splitters(sorted(values, key=spec.plain))
    schema = df.select(*spec.names).schema
    rows = df.sparkSession.createDataFrame(values, schema).coalesce(1).orderBy(*spec.order()).collect()
    return dedupe_splitters([tuple(r) for r in rows])


def distribute(df: DataFrame, tree: SplitterTree, equality: bool, plan: DistributionPlan, p: SortParams = SortParams()) -> DataFrame:
    """df with _cls and _pid, every row in its partition: the one exchange."""
    rows = _classed(df, tree, p, equality)
    first, spread = (literal_array(list(x), T.IntegerType()) for x in (plan.first, plan.spread))
    every = ", ".join(quoted(f.name) for f in df.schema if f.dataType.typeName() not in ("map", "variant"))
    apart = f" + if(get(_spread, _cls) > 1, pmod(xxhash64({every}), get(_spread, _cls)), 0)" if max(plan.spread, default=1) > 1 else ""
    # never null, so that joins on it infer no filter that would repeat the walk
    pid = F.expr(f"cast(coalesce(get(_first, _cls){apart}, 0) as int)").alias("_pid")
    kept = [quoted(c) for c in rows.columns]
    return rows.select(*kept, first.alias("_first"), spread.alias("_spread"), pid).select(*kept, "_pid").repartitionById(plan.partitions, F.col("_pid"))


def sort_global(df: DataFrame, keys, p: SortParams = SortParams(), with_pos: bool = True, rows: int | None = None, pos: str = "pos") -> DataFrame:
    """df in key order over its partitions, with the position of every row (from 0).

    Rows of equal keys have some order among themselves; name a row id as last key for a total one."""
    spec = KeySpec.of(keys)
    tree, equality, plan = plan_sort(df, spec, p, rows)
    moved = distribute(df, tree, equality, plan, p).sortWithinPartitions(*spec.order())
    if not with_pos:
        return moved.drop("_bucket", "_cls", "_pid")
    return moved.withColumn(pos, partition_start(plan, moved) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).drop("_bucket", "_cls", "_pid")


def partition_start(plan: DistributionPlan, moved: DataFrame) -> Column:
    """The first position of a row's partition.  Partitions of a spread class are counted; all others follow from the plan."""
    starts = [0] * plan.partitions
    if any(s > 1 for s in plan.spread):
        for pid, n in moved.select("_pid").groupBy("_pid").count().collect():  # one row for each partition
            starts[pid] = n
    else:
        for f, n in zip(plan.first, plan.sizes):
            starts[f] += n
    at = 0
    for i, n in enumerate(starts):
        starts[i], at = at, at + n
    return F.get(literal_array(starts, T.LongType()), F.spark_partition_id())
