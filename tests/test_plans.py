"""Parameters, splitters, plans: no Spark."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from distsort.functions import metrics
from distsort.plans.params import block_rows, level_plan, oversampling
from distsort.plans.recursion import pack_buckets, plan_partitions, plan_recursion
from distsort.plans.sampling import dedupe_splitters, pick_splitters


def test_block_rows():
    assert [block_rows(s) for s in (8, 16, 32, 100, 5000)] == [256, 128, 64, 16, 1]


@pytest.mark.parametrize("n,levels", [(1 << 17, [64, 64]), (60_000, [32, 32]), (600_000, [128, 128]), (1 << 30, [256, 256, 32, 32]), (16, []), (0, [])])
def test_level_plan(n, levels):
    assert level_plan(n) == levels


def test_splitters():
    assert pick_splitters([(i,) for i in range(1, 64)], 16) == [(4 * i,) for i in range(1, 16)]
    got = dedupe_splitters([(1,), (1,), (2,), (float("nan"),), (float("nan"),)])
    assert len(got) == 3 and got.use_equality
    assert not dedupe_splitters([(1,), (2,)]).use_equality
    assert pick_splitters([], 4) == []


def test_recursion():
    assert plan_recursion([500, 10, 300, 190], 4, 1.0, 16) == ["split", "base", "split", "pack"]
    assert plan_recursion([500, 10], 2, 1.0, 16, frozenset({0})) == ["skip", "base"]


@given(st.lists(st.integers(0, 1000), min_size=1, max_size=40), st.integers(1, 8))
@settings(max_examples=200, deadline=None)
def test_packing(sizes, workers):
    a, b = pack_buckets(sizes, workers), pack_buckets(sizes, workers, "lpt")
    assert a == sorted(a) and max(a + b) < workers
    loads = [sum(s for s, w in zip(sizes, b) if w == k) for k in range(workers)]
    assert max(loads) <= sum(sizes) / workers + max(sizes)
    plan = plan_partitions(sizes, [i % 2 == 1 for i in range(len(sizes))], workers)
    assert list(plan.first) == sorted(plan.first) and all(s >= 1 for s in plan.spread)
    taken = [p for f, s in zip(plan.first, plan.spread) if s > 1 for p in range(f, f + s)]
    assert len(taken) == len(set(taken))


def test_costs():
    n = 10**6
    assert metrics.io_volume(n, 8) == 48 * n
    assert metrics.io_volume(n, 8, 1, "copying") == 86 * n
    assert metrics.block_transfers(n, 32, 8, 256, 16) < metrics.block_transfers(n, 16, 8, 256, 16) < metrics.block_transfers(n, 16, 8, 16, 16)
    assert metrics.extra_space(256, 256, 8, n, 16, False) < metrics.extra_space(256, 256, 8, n, 16)
    assert metrics.branch_proxy(1 << 32) > 4 * metrics.branch_proxy(1 << 32, 16, "free")
    assert all(metrics.assumptions_hold(1 << 40, 256, 32, 8, 256, 1 << 20, 16, 8).values())
    assert oversampling(1 << 30) == 6
