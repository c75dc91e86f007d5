"""Cost and balance measures, checks of results."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..catalog import query
from ..functions import metrics as M
from ..operators import blocks as B
from ..operators.sort import distribute, plan_sort, sort_global
from ..operators.verify import descents, same_multiset
from ..plans.params import SortParams
from ..sources.io import LINE_ID, load
from .methods import cte, line_blocks, line_keys, line_tree

#: What the cost models take for n: the rows of each part of lineitem.
_PARTS = "(select l_returnflag, l_linenumber, count(*) as n from lineitem group by l_returnflag, l_linenumber)"
_PART = ("l_returnflag", "l_linenumber", "n")


def line_parts(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_linenumber").groupBy("l_returnflag", "l_linenumber").agg(F.count(F.lit(1)).alias("n"))


@query(f"select l_returnflag, l_linenumber, n, round(n * 2 * (log2(256) + 1) + n * 16 / 4.0, 3)::double as comparisons from {_PARTS}")
def q_cost_comparisons(spark, d):
    return line_parts(spark, d).select(*_PART, F.round(M.comparisons(F.col("n"), 256, 2, 16, True), 3).alias("comparisons"))


@query(f"select l_returnflag, l_linenumber, n, (n * 8 * 6)::double as distribution, (n * 8 * 10.75)::double as copying from {_PARTS}")
def q_cost_io_volume(spark, d):
    return line_parts(spark, d).select(*_PART, M.io_volume(F.col("n"), 8).alias("distribution"), M.io_volume(F.col("n"), 8, 1, "copying").alias("copying"))


@query(f"select l_returnflag, l_linenumber, n, round(n / (32 * 8.0) * greatest(1.0, ln(greatest(n / 16.0, 1.0)) / ln(256)), 3)::double as transfers from {_PARTS}")
def q_cost_block_transfers(spark, d):
    return line_parts(spark, d).select(*_PART, F.round(M.block_transfers(F.col("n"), 32, 8, 256, 16), 3).alias("transfers"))


@query(f"select l_returnflag, l_linenumber, n, round(256 * 256 * 32 + ln(greatest(n / 16.0, 1.0)) / ln(256), 3)::double as with_stack, (256 * 256 * 32)::double as without from {_PARTS}")
def q_cost_extra_space(spark, d):
    return line_parts(spark, d).select(*_PART, F.round(M.extra_space(256, 256, 32, F.col("n"), 16), 3).alias("with_stack"), F.lit(float(M.extra_space(256, 256, 32, 0, 16, False))).alias("without"))


@query(f"select l_returnflag, l_linenumber, n, round(n * log2(greatest(n / 16.0, 2.0)) + n * 4, 3)::double as branchy, (n * 4)::double as branch_free from {_PARTS}")
def q_cost_branch_proxy(spark, d):
    return line_parts(spark, d).select(*_PART, F.round(M.branch_proxy(F.col("n")), 3).alias("branchy"), M.branch_proxy(F.col("n"), 16, "free").alias("branch_free"))


@query(f"with {cte()}, p as (select (slot >= delim and slot < delim + full_blocks) as ok from bl join dl on bl.bucket = dl.bucket) select count(*) as blocks, sum(ok::int)::bigint as skipped, sum((not ok)::int)::bigint as moves from p")
def q_cost_moves(spark, d):
    placed = B.blocks_in_place(line_blocks(spark, d), "l_extendedprice")
    return placed.agg(F.sum("blocks").alias("blocks"), F.sum("in_place").alias("skipped"), F.sum("to_move").alias("moves"))


@query(f"with {cte()} select (select count(*) from ks)::int as k, round(max(size) / avg(size), 6)::double as max_over_avg from sz")
def q_balance(spark, d):
    df = line_keys(spark, d)
    tree = line_tree(df)
    sizes = tree.with_bucket(df.select("l_extendedprice")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    return M.balance(sizes).select(F.lit(tree.buckets).alias("k"), F.round("max_over_avg", 6).alias("max_over_avg"))


@query("select l_discount as key, count(*) as n from lineitem group by l_discount having count(*) * 11 > (select count(*) from lineitem)")
def q_heavy_keys(spark, d):
    return M.heavy_keys(load(spark, d, "lineitem", "l_discount"), "l_discount", 11).withColumnRenamed("l_discount", "key")


@query("select 0::bigint as descents, 0::bigint as gaps")
def q_is_sorted(spark, d):
    return descents(sort_global(line_keys(spark, d), ["l_extendedprice", *LINE_ID]), ["l_extendedprice", *LINE_ID])


@query("select 0::bigint as only_first, 0::bigint as only_second")
def q_same_multiset(spark, d):
    df = line_keys(spark, d)
    return same_multiset(df, sort_global(df, ["l_extendedprice"]).drop("pos"))


@query("select l_returnflag, l_linenumber, n, x.cores, round(n / (0.01 * n + 0.99 * n / x.cores), 3)::double as speedup from (values (1), (2), (4), (8), (16), (32)) as x(cores), " + _PARTS)
def q_speedup_model(spark, d):
    """Speed-up of work on each part's rows of which a hundredth is sequential; measured ones come from bench.py."""
    cores = line_parts(spark, d).select(*_PART, F.explode(F.array(*[F.lit(c) for c in (1, 2, 4, 8, 16, 32)])).alias("cores"))
    return cores.select(*_PART, "cores", F.round(M.speedup(F.col("n"), 0.01 * F.col("n") + 0.99 * F.col("n") / F.col("cores")), 3).alias("speedup"))


@query("select count(*) as n, true as several, true as even from lineitem")
def q_partition_balance(spark, d):
    """What the production plan makes: all rows, whether about 8 partitions have some, and whether the largest has at most twice its share."""
    df = line_keys(spark, d)
    tree, equality, plan = plan_sort(df, ["l_extendedprice"], SortParams(partitions=8))
    dealt = distribute(df, tree, equality, plan).groupBy("_pid").agg(F.count(F.lit(1)).alias("n"))  # counted after the exchange
    return dealt.agg(F.sum("n").alias("n"), (F.count(F.lit(1)) >= 7).alias("several"), (F.max("n") * 8 <= F.sum("n") * 2).alias("even"))


_TABLE = "(select l_extendedprice as x from lineitem)"
_CUTS = [1000.0 * 2**i for i in range(7)]


def _measured(spark, d, f, schema):
    """f(values, cost) on one task's rows: kernels are for a task's share, not for a table."""
    from ..functions import kernels

    def run(batches):
        for batch in batches:
            values = batch.column(0).to_pylist()
            if values:
                yield f(kernels, values)

    return load(spark, d, "lineitem", "l_extendedprice").mapInArrow(run, schema)


@query(f"select count(*) as n, (count(*) * 3)::bigint as comparisons, count(*) as read_rows, count(*) as written_rows, {', '.join(f'sum((case when x < {c} then 1 else 0 end))::bigint as under_{i}' for i, c in enumerate(_CUTS))} from {_TABLE}")
def q_cost_measured_classification(spark, d):
    """Counters of the kernel's local classification into 8 buckets: three comparisons a row, whatever the input; one read and one write."""
    import pyarrow as pa

    names = ["n", "comparisons", "read_rows", "written_rows", *[f"under_{i}" for i in range(len(_CUTS))]]

    def one(kernels, values):
        cost, tree = kernels.Cost(), kernels.tree_of(_CUTS)
        _, _, counts, _ = kernels.flush_stripes(values, lambda x: kernels.classify(x, _CUTS, tree, cost), 8, 256, 2, cost)
        under = [sum(c[b] for c in counts for b in range(i + 1)) for i in range(len(_CUTS))]
        return pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (len(values), cost.comparisons, cost.read, cost.written, *under)], names)

    each = _measured(spark, d, one, ", ".join(f"{n} long" for n in names))
    return each.agg(*[F.sum(n).alias(n) for n in names])


@query("select m as method, true as sorted_, true as fewer_branches from (values ('distribution'), ('buffered')) as x(m)")
def q_cost_measured_branches(spark, d):
    """Branches on data of the kernels that avoid them beside those of the least branchy other one, on the table's rows in pieces of 4096."""
    import pyarrow as pa

    kept = ("distribution", "buffered", "quicksort", "dual_pivot", "introsort")

    def one(kernels, values):
        rows = []
        for i in range(0, len(values), 4096):
            want = sorted(values[i : i + 4096])
            for k in kept:
                cost = kernels.Cost()
                rows.append((k, kernels.KERNELS[k](values[i : i + 4096], cost=cost) == want, cost.branches))
        return pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows)], ["method", "right", "branches"])

    each = _measured(spark, d, one, "method string, right boolean, branches long").groupBy("method").agg(F.every("right").alias("sorted_"), F.sum("branches").alias("branches"))
    least = each.where(F.col("method").isin(list(kept[2:]))).agg(F.min("branches").alias("least"))
    return each.where(F.col("method").isin(list(kept[:2]))).join(F.broadcast(least)).select("method", "sorted_", (F.col("branches") < F.col("least")).alias("fewer_branches"))
