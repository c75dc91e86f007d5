"""The distribution sort against Spark's and against plain lists; its plans."""

import math

import pytest
from pyspark.sql import functions as F

from distsort.functions.classify import SplitterTree
from distsort.operators import blocks as B
from distsort.operators.sort import plan_sort, sort_global
from distsort.operators.verify import descents, same_multiset
from distsort.plans.keys import KeySpec, SortKey
from distsort.plans.params import SortParams
from distsort.plans.sampling import SplitterSet
from distsort.sources import workloads as W


def plan_text(df):
    return df._jdf.queryExecution().toString()


@pytest.mark.parametrize("keys", [["x", "i"], ["-x", "i"], [SortKey("x", True, False), "i"], [SortKey("x", False, True), "-i"]])
def test_nulls_nan_infinities(spark, keys):
    values = [None, float("nan"), 0.0, -0.0, float("inf"), -float("inf"), 1.5, None, float("nan")] * 20
    df = spark.createDataFrame(list(enumerate(values)), "i int, x double").repartition(3)
    got = [r.i for r in sort_global(df, keys, SortParams(partitions=4, k=8)).orderBy("pos").collect()]
    want = [r.i for r in df.coalesce(1).orderBy(*KeySpec.of(keys).order()).collect()]
    assert got == want


@pytest.mark.parametrize("n", [0, 1, 5, 17])
def test_small(spark, n):
    df = spark.range(n).select((n - 1 - F.col("id")).alias("x"))
    assert [(r.pos, r.x) for r in sort_global(df, ["x"]).orderBy("pos").collect()] == [(i, i) for i in range(n)]


@pytest.mark.parametrize("name", W.NAMES)
def test_workloads(spark, name):
    df = W.make(spark, name, 3000, partitions=3)
    out = sort_global(df, ["key"], SortParams(partitions=5))
    assert tuple(descents(out, ["key"]).first()) == (0, 0)
    assert tuple(same_multiset(df, out.drop("pos")).first()) == (0, 0)


def test_strings_and_types(spark):
    df = spark.createDataFrame([("b", 1), ("", 2), ("ä", 3), (None, 4), ("a", 5), ("aa", 6), ("Z", 7)] * 5, "s string, i int")
    assert [r.s for r in sort_global(df, ["s", "i"], SortParams(partitions=3, k=4, n0=2)).orderBy("pos").collect()] == [r.s for r in df.coalesce(1).orderBy("s", "i").collect()]
    with pytest.raises(TypeError):
        KeySpec.of(["m"]).validate(spark.sql("select map('a', 1) as m"))


def test_equal_keys_are_spread(spark):
    df = spark.range(0, 4000, 1, 4).select(F.lit(1.0).alias("key"), "id")
    tree, equality, plan = plan_sort(df, ["key"], SortParams(partitions=4))
    assert equality and max(plan.spread) >= 4
    assert len({r[0] for r in sort_global(df, ["key"], SortParams(partitions=4)).select(F.spark_partition_id()).distinct().collect()}) >= 3


def test_one_exchange_of_rows(spark, tiny):
    df = spark.read.parquet(f"{tiny}/lineitem.parquet").select("l_extendedprice", "l_orderkey")
    text = sort_global(df, ["l_extendedprice", "l_orderkey"])._jdf.queryExecution().executedPlan().toString()
    assert text.count("Exchange") == 1 and "REPARTITION_BY_NUM" in text
    assert "l_comment" not in text and "ReadSchema: struct<l_orderkey:bigint,l_extendedprice:double>" in text.replace("l_extendedprice:double,l_orderkey:bigint", "l_orderkey:bigint,l_extendedprice:double")


@pytest.mark.parametrize("k", [1, 2, 3, 7, 16, 31])
def test_classifiers_agree(spark, k):
    df = spark.range(200).select((F.col("id") % 37).cast("double").alias("x"))
    tree = SplitterTree.build(df, ["x"], SplitterSet(tuple((float(v),) for v in range(1, k)), False))
    want = {v: sum(s <= v for s in range(1, k)) for v in range(37)}
    for method in ("chained", "case", "hof", "arrow", "rangejoin"):
        if method == "arrow" and k == 1:
            continue
        got = {r.x: r.bucket for r in tree.with_bucket(df, "bucket", method).distinct().collect()}
        assert got == want, method
    cls = {r.x: r.cls for r in tree.with_class(tree.with_bucket(df)).distinct().collect()}
    assert cls == {v: 2 * b - (1 <= v < k) for v, b in want.items()}


def test_blocks_of_the_worked_example(spark):
    a = [5, 1, 6, 2, 7, 3, 8, 4, 12, 1, 13, 2, 14, 3, 15, 4, 9]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(a)], "rnk long, key int")
    tree = SplitterTree.build(df, ["key"], SplitterSet(((4,), (9,)), False))
    s = B.local_classify(df, len(a), tree, 2, 2)
    got = {r.slot: (r.bucket, r.min_key, r.max_key) for r in B.flushed_blocks(s, "key").collect()}
    assert got == {0: (1, 5, 6), 1: (0, 1, 2), 2: (1, 7, 8), 4: (2, 12, 13), 5: (0, 1, 2), 6: (2, 14, 15)}
    d = sorted((r.bucket, r.start, r.delim, r.next_delim, r.full_blocks, r.overflow) for r in B.delimiters(s).collect())
    assert d == [(0, 0, 0, 3, 2, False), (1, 6, 3, 6, 2, False), (2, 12, 6, 9, 2, False)]
    assert sum(r.in_place for r in B.blocks_in_place(s, "key").collect()) == 2
    assert sum(r.moves for r in B.empty_compaction(s, "key").collect()) == 1
    assert math.isclose(min(r.min_room for r in B.flush_room(s, "key").collect()), 3)


def test_deeper_splitters_walk_once(spark, monkeypatch):
    """A filter on the class of a row is the whole walk again for each use of each level: the plan must not grow with a power of the depth."""
    from distsort.operators import sort as S
    from distsort.plans.keys import KeySpec

    df = spark.range(0, 4000, 1, 4).select((F.col("id") % 7).alias("a"), (F.col("id") * 7919 % 4000).alias("b"), F.col("id").alias("c"))
    spec, p, sizes = KeySpec.of(["a", "-b", "c"]), SortParams(partitions=8), []
    for k in (4, 16):
        found = S.splitters_of(df, spec, k, 4000, p)
        tree = S.SplitterTree.build(df, spec, found)
        counts = S.class_counts(df, tree, p, False)

        def seen(few, spec, inner=S._in_order):
            sizes.append(few._jdf.queryExecution().optimizedPlan().toString().count("coalesce("))
            return inner(few, spec)

        monkeypatch.setattr(S, "_in_order", seen)
        large = [c for c, n in enumerate(counts) if n]
        more = S.deeper_splitters(df, tree, False, large[:2], counts, 50, 4000, p)
        monkeypatch.undo()
        assert more and all(len(v) == 3 for v in more)
        edge = found.values[1]  # the first two classes end at the second splitter
        assert all(spec.plain(v) < spec.plain(edge) for v in more)
    assert 0 < sizes[0] and sizes[1] <= 3 * sizes[0], sizes
