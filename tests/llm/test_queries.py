"""Registered queries on the given tables: SQL where there is some, plain versions of the pipeline's law otherwise."""

import os
from collections import Counter

import duckdb
import pytest

import corpus_pipeline
from distsort.llm import registry
from distsort.llm.common import load, release, scratch

D = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_sql(spark, name):
    c = duckdb.connect()
    for f in os.listdir(D):
        c.execute(f"create view {f.split('.')[0]} as select * from read_parquet('{D}/{f}')")
    got, want = registry.queries()[name](spark, D).toPandas(), c.execute(registry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    one = lambda v: "" if v is None or v != v else f"{v:.9g}" if isinstance(v, float) else str(v)
    rows = lambda df: Counter(tuple(map(one, r)) for r in df[sorted(df.columns)].itertuples(index=False))
    assert rows(got) == rows(want)


def test_pipeline(spark):
    docs = load(spark, D, "documents")
    ids = lambda df: Counter(r[0] for r in df.select("doc_id").collect())
    before = ids(docs)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, D)
        if name != "sharding":
            assert out.columns == docs.columns
            now = ids(out)
            assert set(now) <= set(before) and now
            assert max(now.values()) == 1 or name == "mixing"
            before, docs = now, out
        else:
            assert ids(out) == before and {r.shard for r in out.select("shard").distinct().collect()} == set(range(24))


def test_release(spark):
    from distsort.llm.common import written

    written(spark.range(3), "x")
    folder = scratch(spark).removeprefix("file://")
    assert os.path.isdir(folder)
    release(spark)
    assert not os.path.exists(folder)
