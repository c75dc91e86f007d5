"""What the distribution sort is compared with, each in its Spark form; all return df with `pos`."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import kernels
from ..functions.classify import SplitterTree, literal_array
from ..plans.keys import KeySpec, SortKey
from ..plans.params import SortParams
from ..plans.recursion import DistributionPlan, plan_partitions
from ..plans.sampling import SplitterSet, dedupe_splitters, pick_splitters
from ..sources.io import delete, fresh_path
from .presorted import probe_order
from .sort import _WITHIN, class_counts, distribute, partition_start, plan_sort, sort_global, splitters_of

#: Rows of a task of an array kernel, about: each is some hundred bytes of Python objects, and all of a task's are there at once.
KERNEL_ROWS = 1 << 17


def _parts(df: DataFrame, p: SortParams) -> int:
    return p.partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _placed(df: DataFrame, spec: KeySpec, found: SplitterSet, plan_of, p: SortParams) -> DataFrame:
    """One exchange by splitters and a plan, local sorts, positions."""
    tree = SplitterTree.build(df, spec, found)
    plan = plan_of(class_counts(df, tree, p, False))
    moved = distribute(df, tree, False, plan, p).sortWithinPartitions(*spec.order())
    return moved.withColumn("pos", partition_start(plan, moved) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).drop("_bucket", "_cls", "_pid")


def _one_each(sizes: list[int]) -> DistributionPlan:
    """Every bucket its own partition, as large as it came out."""
    return DistributionPlan(tuple(c // 2 for c in range(len(sizes))), (1,) * len(sizes), tuple(sizes))


def numbered(ordered: DataFrame) -> DataFrame:
    """Positions of a frame that is sorted over its partitions: written once with its places, as a second run might be cut elsewhere."""
    spark = ordered.sparkSession
    path = fresh_path(spark, "ordered")
    placed = ordered.withColumn("_at", F.monotonically_increasing_id())
    placed.write.parquet(path)
    back = spark.read.schema(placed.schema).parquet(path)
    pid = F.shiftright("_at", 33)
    sizes = back.groupBy(pid.alias("_p")).agg(F.count(F.lit(1)).alias("_n"))  # one row for each partition
    starts = sizes.select("_p", (F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).alias("_start"))
    return back.withColumn("_p", pid).join(F.broadcast(starts), "_p").withColumn("pos", F.col("_start") + F.col("_at").bitwiseAND(F.lit(_WITHIN))).drop("_p", "_at", "_start")


def oracle_samplesort(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """Copying branch-free samplesort: each row's bucket is stored, then rows are copied by it."""
    spec, spark = KeySpec.of(keys), df.sparkSession
    tree, equality, plan = plan_sort(df, spec, p)
    copy = tree.with_bucket(df, "_stored", p.backend)
    path = fresh_path(spark, "copy")
    copy.write.parquet(path)
    back = spark.read.schema(copy.schema).parquet(path)
    first = literal_array(list(plan.first), T.IntegerType())
    cls = tree.with_class(back, "_cls", "_stored") if equality else back.withColumn("_cls", F.col("_stored") * 2)
    moved = cls.withColumn("_pid", F.get(first, F.col("_cls"))).repartitionById(plan.partitions, F.col("_pid")).sortWithinPartitions(*spec.order())
    flat = DistributionPlan(plan.first, (1,) * len(plan.first), plan.sizes)
    return moved.withColumn("pos", partition_start(flat, moved) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).drop("_stored", "_cls", "_pid")


def copy_samplesort(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """One level, a bucket for each partition, rows copied to new space."""
    spec, n = KeySpec.of(keys), df.count()
    return _placed(df, spec, splitters_of(df, spec, _parts(df, p), n, p), _one_each, p)


def _two_way(df: DataFrame, spec: KeySpec, p: SortParams, of_sample: int) -> DataFrame:
    """Quicksort by levels: every part with several workers is split in two at a pivot of its own rows, and rows move to the workers of their side.

    of_sample 1: the pivot is one row and each side gets half of the workers; more: it is the median of so many, and workers go by the sides' rows.
    Parts of one worker are not moved by later levels: they wait where the last split found them."""
    spark, parts, names = df.sparkSession, _parts(df, p), df.columns
    at = lambda x, kind=T.IntegerType(): F.get(literal_array(x, kind), F.col("_part"))
    now, held, level, n = df.withColumn("_part", F.lit(0)), None, 0, df.count()
    going, ended, pieces = [(0, n, parts)], {}, []  # first position, rows, workers of each part; rows by first position; tables with what has ended in them
    if parts < 2 or n < 2:
        going, ended, pieces = [], {0: n}, [(now, [0])]
    while going:
        level += 1
        share = F.lit(1.0) if n < 64 * parts else F.least(F.lit(1.0), at([16.0 * of_sample / s for _, s, _ in going], T.DoubleType()))
        drawn: dict[int, list] = {i: [] for i in range(len(going))}
        for r in now.where(F.rand(p.seed + level) < share).select("_part", *spec.names).collect():  # some rows for each part
            drawn[r[0]].append(tuple(r)[1:])
        few = {i: sorted(rows[:of_sample], key=spec.plain) for i, rows in drawn.items()}
        pivots = [rows[len(rows) // 2] if rows else None for _, rows in sorted(few.items())]
        if known := [v for v in pivots if v is not None]:
            values = [at([(known[0] if v is None else v)[j] for v in pivots], df.schema[c].dataType) for j, c in enumerate(spec.names)]
            right = ~spec.before(values, [any(v[j] is None for v in known) for j in range(len(spec.names))])
            side = (right & at([int(v is not None) for v in pivots]).cast("boolean")).cast("int")
        else:
            side = F.lit(0)
        halves = now.withColumn("_side", side)
        counted = {(r[0], r[1]): r[2] for r in halves.groupBy("_part", "_side").count().collect()}  # two rows a part
        first, found, stuck = [], [], set()
        for i, (start, _, w) in enumerate(going):
            a, b = counted.get((i, 0), 0), counted.get((i, 1), 0)
            first.append(len(found))
            if not (a and b):  # one side has it all; another row may be a better pivot, but not a median
                if of_sample > 1 or level > 4 * parts.bit_length():
                    stuck.add(len(found))
                found.append((start, a + b, w))
                first[-1] -= not a  # all its rows are on the right
                continue
            left = w // 2 if of_sample == 1 else max(1, min(w - 1, round(w * a / (a + b))))
            found += [(start, a, left), (start + a, b, w - left)]
        halves = halves.withColumn("_part", at(first) + F.col("_side")).drop("_side")
        open_ = [w > 1 and s > 1 and i not in stuck for i, (_, s, w) in enumerate(found)]
        going = [x for x, more in zip(found, open_) if more]
        if not all(open_):
            ended |= {start: s for (start, s, _), more in zip(found, open_) if not more}
            pieces.append((halves, [-1 if more else start for (start, _, _), more in zip(found, open_)]))
        if going:
            number = [sum(open_[:i]) if more else -1 for i, more in enumerate(open_)]
            before = [sum(w for _, _, w in found[:i]) for i in range(len(found))]
            worker = (at(before) + F.pmod(F.monotonically_increasing_id(), at([w for _, _, w in found]))).cast("int")
            path = fresh_path(spark, "halves")
            moved = halves.withColumns({"_worker": worker, "_part": at(number)}).where(F.col("_part") >= 0)
            moved.repartitionById(parts, F.col("_worker")).drop("_worker").write.parquet(path)
            now = spark.read.schema(halves.schema).parquet(path)
            if held and all(open_):  # nothing is left in it
                delete(spark, held)
            held = path
    order = {start: i for i, start in enumerate(sorted(ended))}
    plan = DistributionPlan(tuple(range(len(order))), (1,) * len(order), tuple(ended[s] for s in order))
    whole = reduce(DataFrame.union, [x.withColumn("_part", at([order.get(s, -1) for s in starts])).where(F.col("_part") >= 0) for x, starts in pieces])
    moved = whole.repartitionById(plan.partitions, F.col("_part")).sortWithinPartitions(*spec.order())
    return moved.withColumn("pos", partition_start(plan, moved) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).select(*names, "pos")


def quicksort_unbalanced(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """Two-way splits at single rows; half of the workers go to each side, whatever its size."""
    return _two_way(df, KeySpec.of(keys), p, 1)


def quicksort_balanced(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """Two-way splits at medians of samples; workers go to the sides in proportion, by their counts."""
    return _two_way(df, KeySpec.of(keys), p, 9)


def task_quicksort(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """Looks first whether the input is sorted, and then only numbers it; else the balanced form."""
    spec = KeySpec.of(keys)
    state = probe_order(df, spec).first()["state"]
    return numbered(df) if state in ("sorted", "constant") else quicksort_balanced(df, spec, p)


def multiway_merge(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """Sorted runs first, splitters from regular samples of all runs, and each partition merges its pieces of the runs; rows are sorted once."""
    spec, spark, parts = KeySpec.of(keys), df.sparkSession, _parts(df, p)
    path, names = fresh_path(spark, "runs"), df.columns
    own = df.sortWithinPartitions(*spec.order()).withColumn("_at", F.monotonically_increasing_id())
    own.write.parquet(path)
    runs = spark.read.schema(own.schema).parquet(path)
    n = runs.count()
    # every so many rows of each run: a partition gets a share and what lies between samples of each run
    step = max(1, n // (4 * parts * parts))
    regular = [tuple(r) for r in runs.where(F.col("_at").bitwiseAND(F.lit(_WITHIN)) % step == step // 2).select(*spec.names).collect()]
    found = dedupe_splitters(pick_splitters(sorted(regular, key=spec.plain), parts))
    tree = SplitterTree.build(runs, spec, found)
    plan = _one_each(class_counts(runs, tree, p, False))
    moved = distribute(runs, tree, False, plan, p).drop("_bucket", "_cls", "_pid")

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(batches, arrow) if (batches := [b for b in batches if b.num_rows]) else None
        if table is None:
            return
        at = table.column("_at").to_numpy()
        values = [v for k in spec.keys for v in _comparable(table.column(k.name), k)]
        rows = list(zip(*[v.tolist() if isinstance(v, np.ndarray) else v for v in values], range(len(at))))
        order = np.argsort(at, kind="stable")  # runs one after another, each in its order
        cuts = np.flatnonzero(np.diff(at[order] >> 33)) + 1
        pieces = [[rows[i] for i in piece] for piece in np.split(order, cuts)]
        yield from table.take([r[-1] for r in kernels.merge_runs(pieces)]).drop_columns(["_at"]).combine_chunks().to_batches()

    arrow = to_arrow_schema(runs.schema)
    out = moved.mapInArrow(merged, df.schema)
    return out.withColumn("pos", _planned_start(plan) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).select(*names, "pos")


def _as_number(c: str, kind: T.DataType):
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(F.col(c).cast("timestamp")).cast("double")
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("double")
    if isinstance(kind, T.NumericType):
        return F.col(c).cast("double")
    raise TypeError(f"{c} has no digits")


def radix(df: DataFrame, keys, p: SortParams = SortParams(), levels: int = 4) -> DataFrame:
    """No comparison of keys decides a partition: digits of the first key, between its least and greatest value, do.

    A digit with over twice a partition's share is cut into digits of its own, `levels` times; the other keys are for local sorts."""
    spec, parts = KeySpec.of(keys), _parts(df, p)
    key = spec.keys[0]
    x = F.when(F.col(key.name).isNotNull(), F.coalesce(F.nanvl(_as_number(key.name, df.schema[key.name].dataType), F.lit(float("inf"))), F.lit(0.0)))
    rows = df.withColumn("_x", x if key.asc else -x)
    finite = F.when(F.abs("_x") < float("inf"), F.col("_x"))
    lo, hi, n = rows.agg(F.min(finite), F.max(finite), F.count(F.lit(1))).first()
    spans = [(lo or 0.0, hi if hi is not None else 0.0)]
    limit, wide = max(1, 2 * n // parts), []
    for level in range(levels):  # each level is one count of digits; a span is half open but for the last
        cuts = sorted({a + (b - a) * i / parts for a, b in spans for i in range(1, parts)} | set(wide))
        wide = [c for c in cuts if c == c]
        tree = SplitterTree(KeySpec.of(["_x"]), SplitterSet(tuple((c,) for c in wide), False), (T.DoubleType(),))
        sizes = class_counts(rows, tree, p, False)
        edges = [spans[0][0] if not level else low, *wide, high if level else spans[0][1]]
        low, high = edges[0], edges[-1]
        spans = [(edges[b], edges[b + 1]) for b in range(len(edges) - 1) if sizes[2 * b] > limit and edges[b + 1] > edges[b]]
        if not spans or max(b - a for a, b in spans) <= abs(high - low) * 2**-48:
            break
    # nulls are a digit of their own, in front of the first or behind the last
    end = len(wide) + 2
    digit = F.when(F.col("_x").isNull(), 0 if key.first else end - 1).otherwise(F.col("_digit") + (1 if key.first else 0)).cast("int")
    dealt = tree.with_bucket(rows, "_digit", p.backend).withColumn("_pid", digit).drop("_x", "_digit")
    counts = [0] * end
    for b, m in dealt.groupBy("_pid").count().collect():  # one row for each digit
        counts[b] = m
    packed = plan_partitions([c for m in counts for c in (m, 0)], [False] * (2 * end), parts)
    pid = F.get(literal_array(list(packed.first[::2]), T.IntegerType()), F.col("_pid"))
    moved = dealt.withColumn("_pid", F.coalesce(pid, F.lit(0))).repartitionById(packed.partitions, F.col("_pid")).sortWithinPartitions(*spec.order())
    return moved.withColumn("pos", partition_start(packed, moved) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN))).drop("_pid")


def spark_order_by(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    return numbered(df.orderBy(*KeySpec.of(keys).order()))


def window_sort(df: DataFrame, keys, p: SortParams = SortParams()) -> DataFrame:
    """All rows in one partition; there to be compared with, not to be used."""
    return df.withColumn("pos", F.row_number().over(Window.orderBy(*KeySpec.of(keys).order())) - 1)


def _planned_start(plan: DistributionPlan):
    """The first position of a row's partition, where no class is spread."""
    sizes = [0] * plan.partitions
    for f, s in zip(plan.first, plan.sizes):
        sizes[f] += s
    starts, at = [], 0
    for n in sizes:
        starts.append(at)
        at += n
    return F.get(literal_array(starts, T.LongType()), F.spark_partition_id())


def _comparable(column: pa.ChunkedArray, key: SortKey) -> list:
    """Lists of plain values, or arrays of numbers, that Python orders as the key wants it: one of ranks of nulls and NaN if there are any, and one of values, turned round if descending."""
    kind, ranks = column.type, None
    if pa.types.is_temporal(kind):
        column = column.cast(pa.int32() if kind.bit_width == 32 else pa.int64())
    elif pa.types.is_boolean(kind):
        column = column.cast(pa.int8())
    elif not (pa.types.is_integer(kind) or pa.types.is_floating(kind)):
        values = column.to_pylist()
        if key.asc and not column.null_count:
            return [values]
        return [[key.plain(v) for v in values]]
    null, nan = column.is_null(), pc.is_nan(column) if pa.types.is_floating(kind) else None
    if column.null_count or nan is not None and pc.any(nan).as_py():
        ranks = np.where(null.to_numpy(), 0 if key.first else 4, 2)
        if nan is not None:
            ranks[nan.fill_null(False).to_numpy()] = 3 if key.asc else 1
            column = pc.if_else(nan, 0.0, column)
        column = column.fill_null(0)
    if not key.asc:
        column = pc.negate(column) if pa.types.is_floating(column.type) else pc.bit_wise_not(column)
    return [*([ranks] if ranks is not None else []), column.to_numpy()]


def kernel_sort(df: DataFrame, keys, kernel: str, p: SortParams = SortParams()) -> DataFrame:
    """The distribution sort with an array kernel as each partition's local sort; keys in any direction, with nulls wherever they belong.

    There are more partitions than p asks for where these would have over KERNEL_ROWS rows."""
    spec, n = KeySpec.of(keys), df.count()
    if (least := -(-n // KERNEL_ROWS)) > _parts(df, p):
        p = replace(p, partitions=least)
    tree, equality, plan = plan_sort(df, spec, p, n)
    schema = df.schema

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        table = pa.Table.from_batches(parts)
        values = [v for k in spec.keys for v in _comparable(table.column(k.name), k)]
        yield from table.take(kernels.order_of(values, kernel)).combine_chunks().to_batches()

    moved = distribute(df, tree, equality, plan, p).drop("_bucket", "_cls", "_pid").mapInArrow(local, schema)
    if any(s > 1 for s in plan.spread):
        return numbered(moved)
    return moved.withColumn("pos", _planned_start(plan) + F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN)))


def sort_sequential(df: DataFrame, keys, kernel: str = "distribution") -> DataFrame:
    """One task, the array kernel; rows that one task can't hold are dealt out by their first distribution steps."""
    return kernel_sort(df, keys, kernel, SortParams(partitions=1))


def thin_sort(df: DataFrame, keys, rowid: list[str], p: SortParams = SortParams()) -> DataFrame:
    """For wide rows: key and row id are sorted, then the payload joins them by both; together they must name a row."""
    spec = KeySpec.of(keys)
    names = list(dict.fromkeys([*spec.names, *rowid]))
    thin = sort_global(df.select(*names), [*spec.keys, *[r for r in rowid if r not in spec.names]], p).select("pos", *[F.col(n).alias(f"_t_{n}") for n in names])
    same = F.lit(True)
    for n in names:
        same = same & F.col(n).eqNullSafe(F.col(f"_t_{n}"))
    return df.join(thin, same).drop(*[f"_t_{n}" for n in names])
