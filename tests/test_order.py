"""Directions and nulls outside the one sort: probes, baselines, the stackless form; kernels against Python's sort."""

import random

import pytest
from pyspark.sql import functions as F

from distsort.functions import kernels as K
from distsort.operators import baselines as Z
from distsort.operators.blocks import RUN, numbered
from distsort.operators.presorted import probe_order
from distsort.operators.relational import asof_join, select_ranks
from distsort.operators.stackless import stackless_sort
from distsort.plans.keys import KeySpec, SortKey
from distsort.plans.params import SortParams

P = SortParams(partitions=3)


@pytest.mark.parametrize("sort", [Z.task_quicksort, stackless_sort, Z.multiway_merge, Z.quicksort_balanced, Z.quicksort_unbalanced, Z.radix], ids=lambda f: f.__name__)
def test_descending(spark, sort):
    df = spark.range(0, 3000, 1, 4).select((F.col("id") * 7919 % 3000).alias("x"))
    got = sort(df, ["-x"], P).orderBy("pos").collect()
    assert [(r.pos, r.x) for r in got] == [(i, 2999 - i) for i in range(3000)]


def test_probe_follows_the_keys(spark):
    up = spark.range(0, 100, 1, 3).select(F.col("id").alias("x"), F.col("id").cast("double").alias("d"), F.lit("s").alias("s"))
    state = lambda df, keys: tuple(probe_order(df, keys).first())
    assert state(up, ["x"]) == ("sorted", 0) and state(up, ["-x"]) == ("reversed", 99)
    assert state(up, ["s"]) == ("constant", 0) and state(up, ["s", "-x"]) == ("reversed", 99)
    odd = spark.createDataFrame([(None,), (1.0,), (float("inf"),), (float("nan"),)], "d double").coalesce(1)
    assert state(odd, ["d"]) == ("sorted", 0)
    assert state(odd, [SortKey("d", True, False)])[0] == "unsorted" and state(odd, [SortKey("d", False, True)])[0] == "unsorted"
    assert state(up.limit(0), ["x"]) == ("constant", 0)
    text = probe_order(up, ["x", "d"])._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning" not in text  # rows stay where they are


def test_plain_keys_sort_as_spark(spark):
    r = random.Random(5)
    values = [(r.choice([None, float("nan"), -0.0, 0.0, 1.5, -2.0, float("inf")]), r.choice([None, "", "a", "ä", "Z", "\U0001f600", "￿"]), i) for i in range(200)]
    df = spark.createDataFrame(values, "d double, s string, i int")
    for keys in (["d", "-s", "i"], [SortKey("d", False, True), SortKey("s", True, False), "i"]):
        spec = KeySpec.of(keys)
        assert [x.i for x in df.coalesce(1).orderBy(*spec.order()).collect()] == [v[2] for v in sorted(values, key=spec.plain)]


def test_partitioners_in_place():
    r = random.Random(6)
    for n in (0, 1, 129, 1000):
        for top in (1, 2, 1000):
            a = [r.randrange(top) for _ in range(n)]
            for part in (K._two_way, K._blockwise):
                x = list(a)
                m = part(x, 0, n, top // 2, K.Cost())
                assert sorted(x) == sorted(a) and all(v < top // 2 for v in x[:m]) and all(v >= top // 2 for v in x[m:])


def test_costs_stay_within_bounds():
    """No input makes the quicksorts quadratic: few values, sorted, reversed."""
    n = 4096
    inputs = [[i % 2 for i in range(n)], [1] * n, list(range(n)), list(range(n, 0, -1)), [i % 64 for i in range(n)]]
    for a in inputs:
        for name in ("quicksort", "buffered", "dual_pivot", "introsort", "distribution"):
            cost = K.Cost()
            assert K.KERNELS[name](list(a), cost=cost) == sorted(a)
            assert cost.comparisons < 4 * n * n.bit_length(), name


def test_numbers_of_runs_add_up(spark, monkeypatch):
    from distsort.operators import blocks

    monkeypatch.setattr(blocks, "RUN", 16)
    df = spark.range(500).select((F.col("id") % 3).alias("g"), (F.col("id") * 3 + 1).alias("at"))
    got = numbered(df, ["g"], "at", "n", 2000).collect()
    assert RUN > 16 and all(r.n == (r["at"] - 1) // 3 // 3 for r in got)


def test_frequent_by_of_asof(spark):
    r = random.Random(7)
    left = [(r.choice([1, 1, 1, 2]), r.randrange(5000), i) for i in range(400)]
    right = [(r.choice([1, 2]), t, t) for t in r.sample(range(5000), 60)]
    got = asof_join(spark.createDataFrame(left, "k int, t long, i int"), spark.createDataFrame(right, "k int, t long, v long"), "k", "t", "v", "last", P).collect()
    want = {i: max((v for k2, t2, v in right if k2 == k and t2 <= t), default=None) for k, t, i in left}
    assert {x.i: x["last"] for x in got} == want


def test_ranks_of_one_large_bucket(spark):
    df = spark.range(0, 20_000, 1, 4).select((F.col("id") * 7919 % 20_000).alias("x"))
    assert {(x.x, x["rank"]) for x in select_ranks(df, ["x"], [0, 9_999, 19_999], SortParams(partitions=2, k=2, most_levels=1)).collect()} == {(0, 0), (9_999, 9_999), (19_999, 19_999)}


def test_kernel_rows_are_bounded(spark, monkeypatch):
    """However few partitions are asked for, no task holds more rows than a kernel's Python objects have room for."""
    monkeypatch.setattr(Z, "KERNEL_ROWS", 500)
    df = spark.range(0, 6000, 1, 4).select((F.col("id") * 7919 % 6000).alias("x"))
    for sort in (lambda: Z.kernel_sort(df, ["-x"], "stackless", P), lambda: Z.sort_sequential(df, ["-x"])):
        got = sort().withColumn("p", F.spark_partition_id()).collect()
        assert sorted((r.pos, r.x) for r in got) == [(i, 5999 - i) for i in range(6000)]
        most = max(sum(r.p == q for r in got) for q in {r.p for r in got})
        assert most <= 1000


def test_kernel_keys_in_every_direction(spark):
    """Nulls, NaN, both zeros, the least long, dates, times, booleans and strings, as Spark's own sort has them."""
    import datetime as dt

    r = random.Random(8)
    pick = lambda *v: r.choice([None, *v])
    rows = [(pick(float("nan"), 0.0, -0.0, 1.5, float("-inf")), pick(-(2**63), 2**63 - 1, 0), pick(dt.date(1969, 1, 1), dt.date(2020, 1, 1)), pick(dt.datetime(1969, 1, 1), dt.datetime(2020, 1, 1)), pick(True, False), pick("", "a", "ä"), i) for i in range(300)]
    df = spark.createDataFrame(rows, "d double, l long, day date, t timestamp, b boolean, s string, i int").repartition(3)
    for c in ("d", "l", "day", "t", "b", "s"):
        for asc in (True, False):
            for first in (True, False):
                keys = [SortKey(c, asc, first), SortKey("i", asc)]
                want = [x.i for x in df.coalesce(1).orderBy(*KeySpec.of(keys).order()).collect()]
                assert [x.i for x in Z.kernel_sort(df, keys, "stackless", P).orderBy("pos").collect()] == want, (c, asc, first)


def test_agreement_sorts_its_own_order_once(spark, tiny, monkeypatch):
    """All baselines are held against one written order, and none differs from it."""
    from distsort.queries import baselines as Q

    monkeypatch.setattr(Q, "FORMS", {n: Q.FORMS[n] for n in ("radix", "quicksort")})
    out = Q.q_base_agree(spark, tiny)
    assert any("/own-" in f for f in out.inputFiles())
    assert sorted(map(tuple, out.collect())) == [("quicksort", 0), ("radix", 0)]


def test_agreement_counts_what_differs_and_leaves_nothing(spark, tiny, monkeypatch):
    """Positions that are swapped, missing, shifted or without a number are counted one by one; of all tables that were written, only those that the result reads are left."""
    from distsort.queries import baselines as Q
    from distsort.sources import io

    made = []

    def noted(s, label):
        made.append(io.fresh_path(s, label))
        return made[-1]

    monkeypatch.setattr(Z, "fresh_path", noted)
    pos, right = F.col("pos"), Q.FORMS["radix"]
    forms = {
        "swapped": lambda df, k: right(df, k).withColumn("pos", F.when(pos == 5, 4000).when(pos == 4000, 5).otherwise(pos).cast("long")),
        "missing": lambda df, k: right(df, k).where("pos <> 7"),
        "shifted": lambda df, k: right(df, k).withColumn("pos", pos + 1),
        "unnumbered": lambda df, k: right(df, k).withColumn("pos", F.expr("nullif(pos, 9L)")),
    }
    monkeypatch.setattr(Q, "FORMS", forms | {n: Q.FORMS[n] for n in ("window_sort", "quicksort_balanced", "oracle_samplesort", "multiway_merge", "spark_order_by")})
    out = Q.q_base_agree(spark, tiny)
    found = {r.baseline: r.mismatches for r in out.collect()}
    assert {n: m for n, m in found.items() if m} == {"swapped": 2, "missing": 1, "shifted": 6001, "unnumbered": 2} and len(found) == 9
    paths = [spark.sparkContext._jvm.org.apache.hadoop.fs.Path(x) for x in made]
    assert len(paths) > 4 and not any(x.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(x) for x in paths)


def test_digests_are_of_rows_and_their_positions(spark):
    """The same for positions of any integer type, another one where two rows or a null have changed places."""
    from distsort.operators.verify import digests

    rows = spark.range(0, 200_000, 1, 3).select(F.col("id").alias("pos"), (F.col("id") * 7 % 11).alias("a"), F.lit(None).cast("long").alias("b"))
    own = digests(rows, ["a", "b"])
    assert sorted(own) == [0, 1, 2, 3] and sum(x[0] for x in own.values()) == 200_000
    assert digests(rows.withColumn("pos", F.col("pos").cast("int")), ["a", "b"]) == own
    differ = lambda df: {r for r, x in digests(df, ["a", "b"]).items() if own[r] != x}
    at = F.col("pos") == 150_000
    assert differ(rows.select("pos", F.when(at, F.col("b")).otherwise(F.col("a")).alias("a"), F.when(at, F.col("a")).alias("b"))) == {2}
    assert differ(rows.withColumn("pos", F.when(at, 150_001).when(F.col("pos") == 150_001, 150_000).otherwise(F.col("pos")))) == {2}


def test_two_way_levels_leave_ended_parts(spark):
    """Parts that have one worker are not written again: of all rows, the levels wrote each anew until the last part had ended."""
    from distsort.sources import io

    df = spark.range(0, 20_000, 1, 4).select((F.col("id") * 7919 % 20_000).alias("x"))
    folder = io.shared_folder(spark)
    fs_of = lambda path: path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    for sort, rows in ((Z.quicksort_balanced, 20_000), (Z.quicksort_unbalanced, 20_000)):
        root = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        before = {str(x.getPath()) for x in fs_of(root).listStatus(root)} if fs_of(root).exists(root) else set()
        got = [r.x for r in sort(df, ["-x"], SortParams(partitions=5)).orderBy("pos").collect()]
        assert got == list(range(rows - 1, -1, -1))
        left = [p for p in (str(x.getPath()) for x in fs_of(root).listStatus(root)) if p not in before]
        assert any(spark.read.parquet(p).count() < rows for p in left)


def test_columns_of_kernels_in_every_direction():
    """Keys that kernels take as columns, with enough rows that segments are classified together: as Python sorts the rows' plain values."""
    import datetime as dt

    import numpy as np
    import pyarrow as pa

    r = random.Random(9)
    pick = lambda *v: [r.choice([None, *v]) for _ in range(1500)]
    columns = {
        "d": pa.array(pick(float("nan"), 0.0, -0.0, 1.5, float("-inf")), pa.float64()),
        "l": pa.array(pick(-(2**63), 2**63 - 1, 0), pa.int64()),
        "day": pa.array(pick(dt.date(1969, 1, 1), dt.date(2020, 1, 1)), pa.date32()),
        "b": pa.array(pick(True, False), pa.bool_()),
    }
    for names in (["d", "l"], ["l", "day"], ["b", "d"], ["day", "b"]):
        for asc in (True, False):
            for first in (True, False):
                keys = [SortKey(n, asc, first) for n in names]
                values = [v for k in keys for v in Z._comparable(pa.chunked_array([columns[k.name]]), k)]
                assert all(isinstance(v, np.ndarray) for v in values)
                plain = [tuple(k.plain(v) for k, v in zip(keys, row)) for row in zip(*(columns[n].to_pylist() for n in names))]
                want = sorted(range(1500), key=lambda i: (plain[i], i))  # noqa: B023
                assert K.order_of(values, "stackless") == K.order_of(values, "distribution") == want, (names, asc, first)
