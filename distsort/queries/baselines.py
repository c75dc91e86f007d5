"""The algorithms compared with; all return the positions of the distribution sort and share its SQL."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import functions as F

from ..catalog import query
from ..operators import baselines as Z
from ..operators.presorted import probe_order
from ..operators.sort import sort_global
from ..operators.stackless import stackless_sort
from ..operators.verify import digests, run_of
from ..plans.params import SortParams
from ..sources.io import LINE_ID, freed, fresh_path, load, passing
from .methods import ID, line_keys, sorted_sql
from .workload import DESC_NULLS_SQL, MULTI_SQL, desc_nulls, multi

KEYS = ["l_extendedprice", *LINE_ID]
SQL = sorted_sql("lineitem", "l_extendedprice", "l_extendedprice", ID)

FORMS = {
    "oracle_samplesort": Z.oracle_samplesort,
    "buffered_quicksort": lambda df, keys: Z.kernel_sort(df, keys, "buffered"),
    "dual_pivot": lambda df, keys: Z.kernel_sort(df, keys, "dual_pivot"),
    "introsort": lambda df, keys: Z.kernel_sort(df, keys, "introsort"),
    "task_quicksort": Z.task_quicksort,
    "quicksort_unbalanced": Z.quicksort_unbalanced,
    "quicksort_balanced": Z.quicksort_balanced,
    "copy_samplesort": Z.copy_samplesort,
    "multiway_merge": Z.multiway_merge,
    "quicksort": lambda df, keys: Z.kernel_sort(df, keys, "quicksort"),
    "radix": Z.radix,
    "spark_order_by": Z.spark_order_by,
    "window_sort": Z.window_sort,
}
#: Other sorts that have to get directions and nulls right as well.
MORE = {
    "stackless": lambda df, keys: stackless_sort(df, keys, SortParams(partitions=4)),
    "stackless_kernel": lambda df, keys: Z.kernel_sort(df, keys, "stackless", SortParams(partitions=8)),
    "kernel_block_sort": lambda df, keys: Z.kernel_sort(df, keys, "distribution", SortParams(partitions=8)),
}


def _form(name):
    return lambda spark, d: FORMS[name](line_keys(spark, d), KEYS).select("pos", *KEYS)


def _form_of(name, table):
    def run(spark, d):
        df, keys = table(spark, d)
        return (FORMS | MORE)[name](df, keys).select("pos", *[k.name if hasattr(k, "name") else k.removeprefix("-") for k in keys])

    return run


for _n in FORMS:
    query(SQL, f"q_base_{_n}")(_form(_n))
for _n in FORMS | MORE:
    query(DESC_NULLS_SQL, f"q_desc_nulls_{_n}")(_form_of(_n, desc_nulls))
    query(MULTI_SQL, f"q_multi_{_n}")(_form_of(_n, multi))


@query(f"select * from (values {', '.join(f'({chr(39)}{n}{chr(39)}, 0::bigint)' for n in FORMS)}) as x(baseline, mismatches)")
def q_base_agree(spark, d):
    """For each baseline, positions whose key or row id differs from the distribution sort's.

    Baselines run two at a time, each with tables and shuffle files of its own that go when it is through.  Runs of positions are held against each other by their digests, and row by row where these differ."""
    df = line_keys(spark, d)
    path = fresh_path(spark, "own")
    with freed(spark), ThreadPoolExecutor(2) as pool:
        sort_global(df, KEYS).select("pos", *KEYS).write.parquet(path)  # sorted once for all
        own = spark.read.parquet(path)
        held = digests(own, KEYS)

        def differing(name: str) -> tuple[str, list, str | None]:
            """Runs of positions that differ, and where the baseline's rows in them are."""
            rows = fresh_path(spark, "other")
            with passing(spark):
                placed = FORMS[name](df, KEYS).select("pos", *KEYS)
                found = digests(placed, KEYS)
                if not (runs := [r for r in held.keys() | found.keys() if held.get(r) != found.get(r)]):
                    return name, [], None
                theirs = placed.join(_of_runs(spark, [(r,) for r in runs], "run long"), run_of("pos").eqNullSafe(F.col("run")), "left_semi")
                theirs.select(F.lit(name).alias("baseline"), "pos", F.struct(*KEYS).alias("other")).write.parquet(rows)
            return name, runs, rows

        # one task has all rows of window_sort: the others needn't wait for it
        unlike = [x for x in pool.map(differing, sorted(FORMS, key=lambda n: n != "window_sort")) if x[1]]
    mine = own.join(_of_runs(spark, [(n, r) for n, runs, _ in unlike for r in runs], "baseline string, run long"), run_of("pos") == F.col("run")).select("baseline", "pos", F.struct(*KEYS).alias("own"))
    theirs = spark.createDataFrame([], mine.withColumnRenamed("own", "other").schema)
    for _, _, rows in unlike:
        theirs = theirs.unionByName(spark.read.parquet(rows))
    wrong = mine.join(theirs, ["baseline", "pos"], "full").where(~F.col("other").eqNullSafe(F.col("own"))).groupBy("baseline").agg(F.count(F.lit(1)).alias("mismatches"))
    return spark.createDataFrame([(n,) for n in FORMS], "baseline string").join(wrong, "baseline", "left").select("baseline", F.coalesce("mismatches", F.lit(0).cast("long")).alias("mismatches"))


def _of_runs(spark, rows: list[tuple], schema: str):
    runs = spark.createDataFrame(rows, schema)
    return F.broadcast(runs) if len(rows) <= 200_000 else runs


@query(SQL)
def q_sort_sequential(spark, d):
    return Z.sort_sequential(line_keys(spark, d), KEYS).select("pos", *KEYS)


@query(SQL)
def q_kernel_block_sort(spark, d):
    return Z.kernel_sort(line_keys(spark, d), KEYS, "distribution", SortParams(partitions=8)).select("pos", *KEYS)


@query(SQL)
def q_stackless_sort(spark, d):
    return stackless_sort(line_keys(spark, d), KEYS, SortParams(partitions=4)).select("pos", *KEYS)


@query(SQL)
def q_stackless_kernel(spark, d):
    return Z.kernel_sort(line_keys(spark, d), KEYS, "stackless", SortParams(partitions=8)).select("pos", *KEYS)


@query(f"select row_number() over (order by l_extendedprice, {ID}) - 1 as pos, {ID}, l_extendedprice, l_quantity, l_returnflag from lineitem")
def q_thin_sort(spark, d):
    df = load(spark, d, "lineitem", *LINE_ID, "l_extendedprice", "l_quantity", "l_returnflag")
    return Z.thin_sort(df, ["l_extendedprice", *LINE_ID], LINE_ID)


_PROBE = [("orders", "o_orderkey", "o_orderkey"), ("orders", "o_totalprice", "o_orderkey"), ("part", "p_retailprice", "p_partkey"), ("events", "value", "event_id")]


@query(" union all ".join(f"select '{t}' as tbl, '{k}' as key, case when d = 0 and u = 0 then 'constant' when d = 0 then 'sorted' when u = 0 then 'reversed' else 'unsorted' end as state, d as descents from (select coalesce(sum((k < p)::int), 0)::bigint as d, coalesce(sum((k > p)::int), 0)::bigint as u from (select {k} as k, lag({k}) over (order by {i}) as p from {t}))" for t, k, i in _PROBE))
def q_probe_order(spark, d):
    out = None
    for t, k, i in _PROBE:
        one = probe_order(load(spark, d, t, *dict.fromkeys([k, i])), [k], i).select(F.lit(t).alias("tbl"), F.lit(k).alias("key"), "state", "descents")
        out = one if out is None else out.unionByName(one)
    return out
