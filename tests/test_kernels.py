"""Array kernels: results, the worked example, invariants of the permutation."""

import bisect

from hypothesis import given, settings
from hypothesis import strategies as st

from distsort.functions import kernels as K

EXAMPLE = [5, 1, 6, 2, 7, 3, 8, 4, 12, 1, 13, 2, 14, 3, 15, 4, 9]
ARRAYS = st.one_of(st.lists(st.integers(0, 3), max_size=90), st.lists(st.integers(-1000, 1000), max_size=90))


@given(ARRAYS)
@settings(max_examples=150, deadline=None)
def test_sorts(a):
    for name, sort in K.KERNELS.items():
        assert sort(list(a)) == sorted(a), name
    assert K.merge_runs([sorted(a[:30]), sorted(a[30:])]) == sorted(a)


@given(ARRAYS, st.sampled_from([1, 2, 4, 8]), st.integers(1, 4), st.booleans(), st.booleans(), st.data())
@settings(max_examples=250, deadline=None)
def test_partition(a, b, t, equality, skip, data):
    if not a:
        return
    cuts = sorted(set(data.draw(st.lists(st.sampled_from(a), max_size=6))))
    x = list(a)
    got = K.partition(x, cuts, b, t, equality, skip=skip, trace=True)
    assert sorted(x) == sorted(a)
    for c, (s, e) in enumerate(zip(got.starts, got.starts[1:])):
        for v in x[s:e]:
            bucket = bisect.bisect_right(cuts, v)
            assert c == (2 * bucket - (v in cuts) if equality else bucket)
    assert got.cost.waits <= len(got.counts)


def test_worked_example():
    cost, tree = K.Cost(), K.tree_of([4, 9])
    slots, left, counts, room = K.flush_stripes(EXAMPLE, lambda x: K.classify(x, [4, 9], tree, cost), 3, 2, 2, cost)
    assert counts == [[3, 5, 0], [3, 1, 5]]
    assert slots == [[5, 6], [1, 2], [7, 8], None, [12, 13], [1, 2], [14, 15], None, None]
    assert left == [[3, 3], [4, 4], [9]] and room >= 2
    x = list(EXAMPLE)
    got = K.partition(x, [4, 9], 2, 2)
    assert got.counts == [6, 6, 5] and got.starts == [0, 6, 12, 17]
    assert got.cost.skipped >= 2


def test_skipping_saves_moves():
    a = list(range(4096))
    with_, without = K.Cost(), K.Cost()
    K.partition(list(a), [1024, 2048, 3072], 16, 1, cost=with_)
    K.partition(list(a), [1024, 2048, 3072], 16, 1, cost=without, skip=False)
    assert with_.block_moves < without.block_moves


def test_branch_free_kernels_take_fewer_branches():
    import random

    a = [random.Random(3).random() for _ in range(5000)]
    a = [random.Random(i).random() for i in range(5000)]
    costs = {}
    for name in ("distribution", "buffered", "quicksort", "dual_pivot", "introsort"):
        costs[name] = K.Cost()
        K.KERNELS[name](list(a), cost=costs[name])
    assert max(costs["distribution"].branches, costs["buffered"].branches) < min(costs[n].branches for n in ("quicksort", "dual_pivot", "introsort"))


def test_gallop_and_cycles():
    s = [1, 1, 2, 5, 5, 9]
    assert [K.gallop_next_larger(s, x, 0) for x in (0, 1, 2, 5, 9)] == [0, 2, 3, 5, 6]
    ids = [2, 0, 1, 0, 2, 1]
    a = list("cabacb")
    starts = K.elementwise_permute(a, list(ids), 3)
    assert starts == [0, 2, 4, 6] and sorted(a[:2]) == ["a", "a"]


def test_classifier_counts_and_places():
    """The function of one row finds the bucket that a search of the splitters finds, and counts each level once a row."""
    import bisect

    from distsort.functions import kernels as K

    for splitters in ([5], [2, 4, 6], [1, 3, 5, 7, 9]):
        for equality in (False, True):
            cost, tree = K.Cost(), K.tree_of(splitters)
            place = K.classifier(splitters, tree, cost, equality)
            for x in range(12):
                b = bisect.bisect_right(splitters, x)
                assert place(x) == (2 * b - (b > 0 and splitters[b - 1] == x) if equality else b)
            assert cost.comparisons == 12 * (len(tree).bit_length() - 1 + equality)


def _calls(run) -> int:
    """Calls of functions that the interpreter makes."""
    import sys

    made = 0

    def count(frame, event, what):
        nonlocal made
        made += event in ("call", "c_call")

    sys.setprofile(count)
    try:
        run()
    finally:
        sys.setprofile(None)
    return made


def test_kernels_classify_rows_together():
    """What a task does for each row by itself decides its time: the kernels made 29 and 37 calls for each."""
    import random

    r = random.Random(8)
    rows = [(r.randrange(900) / 4, r.randrange(50), i) for i in range(20_000)]
    for name, most in (("distribution", 20), ("stackless", 28)):
        kernel = K.KERNELS[name]
        assert _calls(lambda: kernel(list(rows))) < most * len(rows), name  # noqa: B023


@given(st.lists(st.tuples(st.integers(-3, 3), st.integers(0, 40)), min_size=1, max_size=1500), st.sampled_from(["distribution", "stackless"]))
@settings(max_examples=60, deadline=None)
def test_columns_give_the_rows_order_and_costs(pairs, name):
    """Rows given as columns of numbers come out in the same order, by the same comparisons, branches and moves, as rows taken one by one."""
    import numpy as np

    columns = [np.array([x / 2 for x, _ in pairs]), np.array([y for _, y in pairs], dtype=np.int32)]
    rows = [(x / 2, y, i) for i, (x, y) in enumerate(pairs)]
    assert K.order_of(columns, name) == [x[-1] for x in sorted(rows)]
    one, together = K.Cost(), K.Cost()
    assert K.KERNELS[name](list(rows), cost=one) == K.KERNELS[name](list(rows), cost=together, bulk=K.Bulk(columns)) == sorted(rows)
    assert one == together


def test_order_of_columns_that_are_no_numbers():
    import numpy as np

    columns = [["b", "a", "b", "a"] * 200, np.arange(800) % 3]
    want = sorted(range(800), key=lambda i: (columns[0][i], columns[1][i], i))
    assert all(K.order_of(columns, name) == want for name in K.KERNELS)


def test_stackless_columns_take_no_row_by_itself():
    """Rows given as columns cost a pass over all buckets few calls, however many buckets there are: it was about 14 for each row."""
    import numpy as np

    r = np.random.default_rng(8)
    columns = [r.integers(0, 900, 20_000) / 4, r.integers(0, 50, 20_000)]
    found: list[int] = []
    assert _calls(lambda: found.extend(K.order_of(columns, "stackless"))) < 20_000
    assert found == np.lexsort(columns[::-1]).tolist()


def test_stackless_columns_of_all_kinds():
    """Wide and constant columns, infinities, both zeros, rows in any order, other fan-outs and blocks: the same order and costs as row by row."""
    import numpy as np

    r = np.random.default_rng(9)
    for n in (1, 2, 8, 9, 17, 200, 1500):
        kinds = [r.integers(-(2**63), 2**63 - 1, n), r.choice([-np.inf, np.inf, 0.0, -0.0, 1.5, -2.5], n), np.zeros(n), r.normal(size=n).astype(np.float32), r.integers(-5, 5, n).astype(np.int8), np.arange(n)[::-1].copy()]
        for columns in ([c] for c in kinds), ([kinds[1], kinds[0]], [kinds[4], kinds[1], kinds[0]], [kinds[2], kinds[4], kinds[3], kinds[5]]):
            for own in columns:
                rows = list(zip(*(c.tolist() for c in own), range(n)))
                mixed = [rows[i] for i in r.permutation(n)]
                for k, b, n0 in ((8, 4, 8), (3, 2, 4), (1, 1, 2)):
                    one, together = K.Cost(), K.Cost()
                    assert K.stackless_sort(list(mixed), k, b, n0, one) == K.stackless_sort(list(mixed), k, b, n0, together, K.Bulk(own)) == sorted(rows)
                    assert one == together


QUICK = ("quicksort", "introsort", "buffered", "dual_pivot")


def test_quicksort_columns_take_no_row_by_itself(monkeypatch):
    """Rows given as columns never go to the quicksorts that compare row by row, and cost a pass over all spans few calls, however many spans there are."""
    import numpy as np

    r = np.random.default_rng(8)
    columns = [r.integers(0, 900, 60_000) / 4, r.integers(0, 50, 60_000)]
    for name in QUICK:
        monkeypatch.setitem(K.KERNELS, name, None)
        found: list[int] = []
        assert _calls(lambda: found.extend(K.order_of(columns, name))) < 60_000, name  # noqa: B023
        assert found == np.lexsort(columns[::-1]).tolist()


def test_quicksort_columns_give_the_rows_order_and_costs():
    """By columns the quicksorts make the same comparisons, branches and moves as row by row, whatever the rows' order; too deep a recursion ends in heapsort in both."""
    import numpy as np

    r = np.random.default_rng(9)
    for n in (0, 1, 2, 16, 17, 40, 129, 200, 700, 3000):
        up = np.arange(n)
        for columns in ([r.integers(0, 40, n) / 4, r.integers(0, 5, n)], [r.normal(size=n)], [up], [up[::-1].copy()], [np.minimum(up, up[::-1])], [np.zeros(n)], [r.integers(-(2**63), 2**63 - 1, n), up]):
            rows = list(zip(*(c.tolist() for c in columns), range(n)))
            for name in QUICK:
                one, together = K.Cost(), K.Cost()
                order = K.PASSES[name](K.Bulk(columns), np.arange(n), together)
                assert [rows[i] for i in order.tolist()] == K.KERNELS[name](list(rows), cost=one) == sorted(rows), (name, n)
                assert one == together, (name, n)
            one, together = K.Cost(), K.Cost()
            order = K.quicksort_passes(K.Bulk(columns), np.arange(n), together, depth=2)
            assert [rows[i] for i in order.tolist()] == K.quicksort(list(rows), one, depth=2)
            assert one == together
