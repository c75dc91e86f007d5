"""Array forms of the methods, with counters: for one task's rows, for tests of invariants, and for cost measures.

Production sorts run in Spark's own sorter; these show block by block and comparison by comparison what the methods do."""

from __future__ import annotations

import bisect
import gc
import heapq
from dataclasses import dataclass, field
from itertools import accumulate
from operator import itemgetter
from random import Random

import numpy as np

EMPTY = None
#: Rows from which on a step over all of them is taken column by column; for fewer, calls of numpy cost more than they save.
BULK_ROWS = 192


@dataclass
class Cost:
    """What a kernel has done: comparisons, branches that hang on data, rows and blocks moved, rows read and written, waits."""

    comparisons: int = 0
    branches: int = 0
    row_moves: int = 0
    block_moves: int = 0
    skipped: int = 0
    waits: int = 0
    read: int = 0
    written: int = 0
    extra_rows: int = 0
    trace: list = field(default_factory=list)


# ---- small sorts and the quicksort family ------------------------------------------------------


def insertion_sort(a: list, lo: int = 0, hi: int | None = None, cost: Cost | None = None) -> list:
    moved = ended = 0  # each move follows a comparison, and one more ends a row's moves unless it has come to the front
    for i in range(lo + 1, len(a) if hi is None else hi):
        x, j = a[i], i
        while j > lo and x < a[j - 1]:
            a[j] = a[j - 1]
            j -= 1
        a[j] = x
        moved += i - j
        ended += j > lo
    if cost:
        cost.comparisons += moved + ended
        cost.branches += moved + ended
        cost.row_moves += moved
    return a


def _two_way(a: list, lo: int, hi: int, pivot, cost: Cost) -> int:
    """Rows that are less than pivot first; where the others begin.  Every comparison is a branch."""
    i, j = lo, hi - 1
    while True:
        while i <= j and a[i] < pivot:
            i += 1
            cost.comparisons += 1
            cost.branches += 1
        while i <= j and not a[j] < pivot:
            j -= 1
            cost.comparisons += 1
            cost.branches += 1
        if i >= j:
            return i
        a[i], a[j] = a[j], a[i]
        cost.row_moves += 2


def _blockwise(a: list, lo: int, hi: int, pivot, cost: Cost, block: int = 64) -> int:
    """The same in place: places of misplaced rows are added to two index buffers by the outcome of each comparison, none is branched on, and buffered rows are swapped in pairs."""
    left, right = [0] * block, [0] * block
    i, j = lo, hi  # what is not settled
    n_left = n_right = from_left = from_right = 0
    while j - i > 2 * block:
        if not n_left:
            from_left = 0
            for x in range(block):
                left[n_left] = x
                n_left += not a[i + x] < pivot
        if not n_right:
            from_right = 0
            for x in range(block):
                right[n_right] = x
                n_right += a[j - 1 - x] < pivot
        cost.comparisons += block * ((from_left == 0) + (from_right == 0))
        both = min(n_left, n_right)
        for x in range(both):
            u, v = i + left[from_left + x], j - 1 - right[from_right + x]
            a[u], a[v] = a[v], a[u]
        cost.row_moves += 2 * both
        cost.branches += 2  # whether a buffer is empty: once a block
        n_left, n_right, from_left, from_right = n_left - both, n_right - both, from_left + both, from_right + both
        if not n_left:
            i, from_left = i + block, 0
        if not n_right:
            j, from_right = j - block, 0
    return _gathered(a, i, j, lambda x: x < pivot, cost)


def _gathered(a: list, lo: int, hi: int, first, cost: Cost) -> int:
    """Rows that are to come first to the front, in place, by adding outcomes to the place that is written next."""
    at = lo
    for k in range(lo, hi):
        x = a[k]
        a[k], a[at] = a[at], x
        at += first(x)
    cost.comparisons += hi - lo
    cost.row_moves += hi - lo
    return at


def _median3(a: list, lo: int, hi: int):
    return sorted((a[lo], a[(lo + hi) // 2], a[hi - 1]))[1]


def quicksort(a: list, cost: Cost | None = None, n0: int = 16, part=_two_way, depth: int | None = None) -> list:
    """Two-way quicksort; with depth, heapsort takes over where recursion is too deep."""
    cost = cost or Cost()
    todo = [(0, len(a), depth)]
    while todo:
        lo, hi, left = todo.pop()
        if hi - lo <= n0:
            insertion_sort(a, lo, hi, cost)
            continue
        if left == 0:
            heap = a[lo:hi]
            heapq.heapify(heap)
            a[lo:hi] = [heapq.heappop(heap) for _ in range(hi - lo)]
            cost.comparisons += int(2 * (hi - lo) * max(1, (hi - lo).bit_length()))
            cost.branches += int((hi - lo) * max(1, (hi - lo).bit_length()))
            continue
        pivot = _median3(a, lo, hi)
        m = part(a, lo, hi, pivot, cost)
        if m in (lo, hi):  # nothing is less: rows equal to the pivot go first, and are done
            todo.append((_gathered(a, lo, hi, lambda x: not pivot < x, cost), hi, left))  # noqa: B023
            continue
        nxt = None if left is None else left - 1
        todo += [(lo, m, nxt), (m, hi, nxt)]
    return a


def introsort(a: list, cost: Cost | None = None) -> list:
    return quicksort(a, cost, depth=2 * max(1, len(a)).bit_length())


def buffered_quicksort(a: list, cost: Cost | None = None) -> list:
    return quicksort(a, cost, part=_blockwise)


def dual_pivot(a: list, cost: Cost | None = None, n0: int = 16) -> list:
    """Two pivots, three parts at each step, in place; rows between equal pivots are done.  Every comparison is a branch."""
    cost = cost or Cost()
    todo = [(0, len(a))]

    def less(x, y) -> bool:
        cost.comparisons += 1
        cost.branches += 1
        return x < y

    def swap(i: int, j: int) -> None:
        a[i], a[j] = a[j], a[i]
        cost.row_moves += 2

    while todo:
        lo, hi = todo.pop()
        if hi - lo <= n0:
            insertion_sort(a, lo, hi, cost)
            continue
        third = (hi - lo) // 3
        swap(lo, lo + third)
        swap(hi - 1, hi - 1 - third)
        if less(a[hi - 1], a[lo]):
            swap(lo, hi - 1)
        p, q = a[lo], a[hi - 1]
        low, at, high = lo + 1, lo + 1, hi - 2  # [lo + 1, low): under p; [low, at): from p to q; (high, hi - 1): over q
        while at <= high:
            if less(a[at], p):
                swap(at, low)
                low += 1
            elif less(q, a[at]):
                while at < high and less(q, a[high]):
                    high -= 1
                swap(at, high)
                high -= 1
                continue  # what came from there is looked at next
            at += 1
        swap(lo, low - 1)
        swap(hi - 1, high + 1)
        todo += [(lo, low - 1), (high + 2, hi)]
        if p < q:
            high += 1
            if 7 * (high - low) > 4 * (hi - lo):  # many rows may equal a pivot: these are done
                low = _gathered(a, low, high, lambda x: not p < x, cost)  # noqa: B023
                high = _gathered(a, low, high, lambda x: x < q, cost)  # noqa: B023
            todo.append((low, high))
    return a


def merge_runs(runs: list[list], cost: Cost | None = None) -> list:
    """All runs at once, by a heap of their next rows."""
    cost = cost or Cost()
    total = sum(map(len, runs))
    cost.comparisons += total * max(1, len(runs).bit_length())
    cost.extra_rows += total
    cost.row_moves += total
    return list(heapq.merge(*runs))


# ---- the quicksort family by columns ------------------------------------------------------------


def _spread(starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of the rows of some spans one after another, where each span begins among them, and whose they are."""
    off = np.cumsum(sizes) - sizes
    return np.repeat(starts - off, sizes) + np.arange(int(sizes.sum())), off, np.repeat(np.arange(len(sizes)), sizes)


def _settled(first: np.ndarray, off: np.ndarray, sizes: np.ndarray, always: bool) -> np.ndarray:
    """Where rows of spans come to lie when each span's rows are taken in turn, and one that is to come first is swapped with the first of those that aren't.

    always: the others are swapped with it as well, as `_gathered` does.  A row that isn't first is moved on whenever those in front reach its place: links from place to place, followed twice as far at each step."""
    n = len(first)
    count = np.concatenate([[0], np.cumsum(first)])
    base, end = count[off], np.repeat(off + sizes, sizes)
    start, of, many = np.repeat(off, sizes), np.repeat(base, sizes), np.repeat(count[off + sizes] - base, sizes)
    to, places = count[:-1] - of + start, np.arange(n)
    ahead, others, link = np.flatnonzero(first), np.flatnonzero(~first), places.copy()
    at = places - start
    if always:
        moved = np.flatnonzero((at > 0) & (at <= many))
        link[moved] = ahead[(of + at - 1)[moved]] + 1
        link = np.where(link < end, link, places)
        others = others[others + 1 < end[others]]  # a span's last row stays where it was put
        now = others + 1
    else:
        moved = np.flatnonzero(at < many)
        link[moved] = ahead[(of + at)[moved]]
        now = others
    while len(now) and not np.array_equal(further := link[now], now):
        now, link = further, link[link]
    to[others] = now
    return to


def _swapped(rows: np.ndarray, left: np.ndarray, right: np.ndarray, pairs: np.ndarray) -> None:
    """Swap rows of spans: each span's places on the left in order with those on the right in the other order; pairs: how many each has."""
    end = np.repeat(np.cumsum(pairs), pairs)
    back = right[end - 1 - (np.arange(len(left)) - np.repeat(np.cumsum(pairs) - pairs, pairs))]
    rows[left], rows[back] = rows[back], rows[left]


def _two_way_spans(rows: np.ndarray, less: np.ndarray, off: np.ndarray, sizes: np.ndarray, owner: np.ndarray, cost: Cost) -> np.ndarray:
    """`_two_way` of spans: rows on the wrong side are swapped in pairs from both ends, and each row is compared once."""
    few = np.bincount(owner[less], minlength=len(sizes))
    front = np.arange(len(rows)) - off[owner] < few[owner]
    left, right = np.flatnonzero(front & ~less), np.flatnonzero(~front & less)
    _swapped(rows, left, right, np.bincount(owner[left], minlength=len(sizes)))
    cost.comparisons += len(rows)
    cost.branches += len(rows)
    cost.row_moves += 2 * len(left)
    return few


def _blockwise_spans(rows: np.ndarray, less: np.ndarray, off: np.ndarray, sizes: np.ndarray, owner: np.ndarray, cost: Cost, block: int = 64) -> np.ndarray:
    """`_blockwise` of spans: what its buffers hold follows from how many misplaced rows each block has."""
    few = np.bincount(owner[less], minlength=len(sizes))
    count = np.concatenate([[0], np.cumsum(less)])
    pairs, low, high = np.zeros(len(sizes), np.int64), off.copy(), off + sizes
    for span in np.flatnonzero(sizes > 2 * block).tolist():
        n, lo = int(sizes[span]), int(off[span])
        steps = np.arange(0, n + 1, block)
        on_left, on_right = (block - np.diff(count[lo + steps])).tolist(), (-np.diff(count[lo + n - steps])).tolist()
        u = v = n_left = n_right = from_left = from_right = swaps = rounds = looked = 0
        while n - (u + v) * block > 2 * block:
            if not n_left:
                from_left, n_left = 0, on_left[u]
            if not n_right:
                from_right, n_right = 0, on_right[v]
            looked += (from_left == 0) + (from_right == 0)
            both = min(n_left, n_right)
            rounds, swaps = rounds + 1, swaps + both
            n_left, n_right, from_left, from_right = n_left - both, n_right - both, from_left + both, from_right + both
            if not n_left:
                u, from_left = u + 1, 0
            if not n_right:
                v, from_right = v + 1, 0
        pairs[span], low[span], high[span] = swaps, lo + u * block, lo + n - v * block
        cost.comparisons += block * looked
        cost.branches += 2 * rounds
        cost.row_moves += 2 * swaps
    # the first misplaced rows from both ends, as many as were swapped
    left, right = np.flatnonzero(~less), np.flatnonzero(less)
    of_left, of_right = owner[left], owner[right]
    before = np.cumsum(sizes - few) - (sizes - few)
    left = left[np.arange(len(left)) - before[of_left] < pairs[of_left]]
    right = right[np.cumsum(few)[of_right] - np.arange(len(right)) <= pairs[of_right]]
    _swapped(rows, left, right, pairs)
    less[left], less[right] = True, False
    places, start, _ = _spread(low, high - low)
    if len(places):
        to = _settled(less[places], start, high - low, True)
        rows[places[to]] = rows[places]
    cost.comparisons += len(places)
    cost.row_moves += len(places)
    return few


def quicksort_passes(bulk: Bulk, at: np.ndarray, cost: Cost | None = None, n0: int = 16, part=_two_way_spans, depth: int | None = None) -> np.ndarray:
    """`quicksort` by columns: a pass takes one step in all spans at once.  No two rows are equal, so a pivot, the median of three rows, always leaves rows on both sides."""
    cost = cost or Cost()
    starts, sizes = np.zeros(1, np.int64), np.array([len(at)])
    while True:
        small = sizes <= n0
        insert_spans(bulk, at, starts[small & (sizes > 1)], sizes[small & (sizes > 1)], cost)
        starts, sizes = starts[~small], sizes[~small]
        if not len(starts):
            return at
        if depth == 0:
            break
        x, y, z = at[starts], at[(2 * starts + sizes) // 2], at[starts + sizes - 1]
        xy, yz, xz = (bulk.less(i, bulk.columns, j) for i, j in ((x, y), (y, z), (x, z)))
        pivot = np.where(xy == yz, y, np.where(xy == xz, z, x))
        places, off, owner = _spread(starts, sizes)
        rows = at[places]
        few = part(rows, bulk.less(rows, [c[pivot] for c in bulk.columns], owner), off, sizes, owner, cost)
        at[places] = rows
        starts, sizes = np.stack([starts, starts + few], 1).ravel(), np.stack([few, sizes - few], 1).ravel()
        depth = None if depth is None else depth - 1
    for lo, n in zip(starts.tolist(), sizes.tolist()):  # too deep: heapsort
        heap = list(zip(*(c[at[lo : lo + n]].tolist() for c in bulk.columns)))
        heapq.heapify(heap)
        at[lo : lo + n] = [heapq.heappop(heap)[-1] for _ in range(n)]
        cost.comparisons += 2 * n * n.bit_length()
        cost.branches += n * n.bit_length()
    return at


def introsort_passes(bulk: Bulk, at: np.ndarray, cost: Cost | None = None) -> np.ndarray:
    return quicksort_passes(bulk, at, cost, depth=2 * max(1, len(at)).bit_length())


def buffered_passes(bulk: Bulk, at: np.ndarray, cost: Cost | None = None) -> np.ndarray:
    return quicksort_passes(bulk, at, cost, part=_blockwise_spans)


def dual_pivot_passes(bulk: Bulk, at: np.ndarray, cost: Cost | None = None, n0: int = 16) -> np.ndarray:
    """`dual_pivot` by columns: a pass takes one step in all spans at once.

    Rows over q on the left are swapped in pairs with others from the right, then rows under p come first among those on the left."""
    cost = cost or Cost()
    starts, sizes = np.zeros(1, np.int64), np.array([len(at)])
    while True:
        small = sizes <= n0
        insert_spans(bulk, at, starts[small & (sizes > 1)], sizes[small & (sizes > 1)], cost)
        starts, sizes = starts[~small], sizes[~small]
        if not len(starts):
            return at
        last, third = starts + sizes - 1, sizes // 3
        for i, j in ((starts, starts + third), (last, last - third)):
            at[i], at[j] = at[j], at[i]
        p, q = at[starts], at[last]
        turned = bulk.less(q, bulk.columns, p)
        p, q = np.where(turned, q, p), np.where(turned, p, q)
        places, off, owner = _spread(starts + 1, sizes - 2)
        rows, inner = at[places], sizes - 2
        under = bulk.less(rows, [c[p] for c in bulk.columns], owner)
        rest = np.flatnonzero(~under)
        over = np.zeros(len(rows), bool)
        over[rest] = ~bulk.less(rows[rest], [c[q] for c in bulk.columns], owner[rest])  # no row but q itself equals q
        kept = inner - np.bincount(owner[over], minlength=len(sizes))
        low = np.bincount(owner[under], minlength=len(sizes))
        front = np.arange(len(rows)) - off[owner] < kept[owner]
        left, right = np.flatnonzero(front & over), np.flatnonzero(~front & ~over)
        pairs = np.bincount(owner[left], minlength=len(sizes))
        _swapped(rows, left, right, pairs)
        _swapped(under, left, right, pairs)
        reached = inner.copy()  # how far the right pointer has come with the last pair
        paired = np.flatnonzero(pairs)
        reached[paired] = right[(np.cumsum(pairs) - pairs)[paired]] - off[paired]
        open_ = reached - kept  # rows over q between the pointers when the left one has passed all others
        among = np.flatnonzero(front)
        to = _settled(under[among], np.cumsum(kept) - kept, kept, False)
        rows[among[to]] = rows[among]
        at[places] = rows
        at[starts], at[last] = p, q
        for i, j in ((starts, starts + low), (last, starts + 1 + kept)):
            at[i], at[j] = at[j], at[i]
        middle = kept - low
        wide = np.flatnonzero(7 * middle > 4 * sizes)  # rows equal to a pivot would be gathered, but there are none: the last comes to the front
        for lo, n in zip((starts + 1 + low)[wide].tolist(), middle[wide].tolist()):
            at[lo : lo + n] = np.roll(at[lo : lo + n], 1)
        ended = open_ > 0
        compared = int((1 + low + 2 * middle + 2 * pairs + inner - reached + np.where(ended, open_ + 1, 0)).sum())
        cost.comparisons += compared + 2 * int(middle[wide].sum())
        cost.branches += compared
        cost.row_moves += int((8 + 2 * (turned + low + pairs + ended)).sum()) + 2 * int(middle[wide].sum())
        starts, sizes = np.stack([starts, starts + 1 + low, starts + kept + 2], 1).ravel(), np.stack([low, middle, inner - kept], 1).ravel()


# ---- distribution -------------------------------------------------------------------------------


def tree_of(splitters: list) -> list:
    leaves = 1 << len(splitters).bit_length() if (len(splitters) + 1) & len(splitters) else len(splitters) + 1
    full = list(splitters) + [splitters[-1]] * (leaves - 1 - len(splitters))
    tree, step = [None], leaves
    while step > 1:  # a level is every so many of them
        tree += full[step // 2 - 1 :: step]
        step //= 2
    return tree


def classify(x, splitters: list, tree: list, cost: Cost, equality: bool = False) -> int:
    """Bucket (or class) by arithmetic on outcomes of comparisons."""
    return classifier(splitters, tree, cost, equality)(x)


def classifier(splitters: list, tree: list, cost: Cost, equality: bool = False):
    """`classify` as a function of the row alone: the levels are as many for each row, so they are counted once a row."""
    leaves, most = len(tree), len(splitters)
    levels = range(leaves.bit_length() - 1)  # leaves are a power of two
    spent = len(levels) + equality

    def bucket(x) -> int:
        i = 1
        for _ in levels:
            i += i + (not x < tree[i])
        cost.comparisons += spent
        i -= leaves
        return i if i < most else most

    def with_equality(x) -> int:
        b = bucket(x)
        return 2 * b - (b > 0 and not splitters[b - 1] < x)

    return with_equality if equality else bucket


def places_of(rows: list, splitters: list, tree: list, equality: bool = False) -> list[int]:
    """What `classifier` says of each row, level by level for all rows."""
    leaves, most = len(tree), len(splitters)
    if most == 1:
        s = splitters[0]
        out = [not x < s for x in rows]
    else:
        out = [1] * len(rows)
        for _ in range(leaves.bit_length() - 1):
            out = [i + i + (not x < tree[i]) for i, x in zip(out, rows)]
        out = [i - leaves if i - leaves < most else most for i in out]
    return [2 * c - (c > 0 and not splitters[c - 1] < x) for c, x in zip(out, rows)] if equality else out


def packed(columns: list[np.ndarray]) -> list[np.ndarray]:
    """Columns of numbers as few columns of 64 bits that put rows in the same order: of each value its distance from the column's least, in no more bits than the largest takes.

    What a column has no room for goes on in the next."""
    out, used = [], 64
    for c in columns:
        if c.dtype.kind == "f":
            c = (c.astype(np.float64) + 0.0).view(np.int64)  # both zeros are one value
            c = c ^ (c >> 63 & (1 << 63) - 1)  # negative numbers the other way round
        c = c.astype(np.int64)
        least = int(c.min()) if len(c) else 0
        bits = (int(c.max()) - least).bit_length() if len(c) else 0
        far, room = c.view(np.uint64) - np.uint64(least % (1 << 64)), 64 - used
        if 0 < bits <= room:
            out[-1], used = out[-1] << bits | far, used + bits
        elif bits:
            if room:
                out[-1] = out[-1] << room | far >> (bits - room)
            out.append(far & (1 << bits - room) - 1)
            used = bits - room
    return out


class Bulk:
    """Steps over many rows at once, for rows that are tuples of numbers and of the row's number, the last to be compared; columns have the numbers, by the row's number."""

    def __init__(self, columns: list[np.ndarray]):
        self.columns = [*packed(columns), np.arange(len(columns[0]))]

    def less(self, at: np.ndarray, than: list[np.ndarray], which: np.ndarray) -> np.ndarray:
        """Whether rows come before those of a few others that they are held against: column by column, each for the rows that are equal up to there."""
        x, y = self.columns[0][at], than[0][which]
        out, tied = x < y, np.flatnonzero(x == y)
        for column, other in zip(self.columns[1:], than[1:]):
            if not len(tied):
                break
            x, y = column[at[tied]], other[which[tied]]
            out[tied] = x < y
            tied = tied[x == y]
        return out

    def places_of(self, rows: list, splitters: list, tree: list, equality: bool = False) -> np.ndarray:
        at = np.fromiter(map(itemgetter(-1), rows), np.int64, len(rows))
        nodes = np.array([0, *(x[-1] for x in tree[1:])])
        values, leaves, i = [c[nodes] for c in self.columns], len(tree), np.ones(len(at), np.int64)
        for _ in range(leaves.bit_length() - 1):
            i += i + ~self.less(at, values, i)
        out = np.minimum(i - leaves, len(splitters))
        if equality and splitters:
            own = np.array([x[-1] for x in splitters])  # no two rows are equal, so a splitter's class is its row
            out = 2 * out - ((out > 0) & (at == own[np.maximum(out - 1, 0)]))
        return out.astype(np.uint16) if len(splitters) < 1 << 15 else out  # short numbers are put in order without comparisons


    def largest(self, at: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Places of the largest row of each span of rows; no span is empty."""
        places, first = np.arange(len(at)), starts
        for column in self.columns:
            if len(places) == len(starts):
                break
            x = column[at[places]]
            held = x == np.repeat(np.maximum.reduceat(x, first), np.diff(first, append=len(x)))
            first = (np.cumsum(held) - held)[first]
            places = places[held]
        return places

    def marks(self, at: np.ndarray) -> np.ndarray:
        """Places of the rows that are larger than all rows before them."""
        places, group = np.arange(len(at)), np.zeros(len(at), np.int64)
        for depth, column in enumerate(self.columns):
            x = column[at[places]]
            if depth:  # the largest so far of each group of rows that are equal up to here, twice as far back at each step
                top, step, longest = x.copy(), 1, int(np.bincount(group).max(initial=0))
                while step < longest:
                    top[step:] = np.where(group[step:] == group[:-step], np.maximum(top[step:], top[:-step]), top[step:])
                    step *= 2
            else:
                top = np.maximum.accumulate(x)
            held = x == top
            places, x, group = places[held], x[held], group[held]
            new = np.ones(len(x), bool)
            new[1:] = (x[1:] != x[:-1]) | (group[1:] != group[:-1])
            if new.all():
                break
            group = np.cumsum(new) - 1
        return places


def sample_to_front(a: list, m: int, rng: Random) -> int:
    """Swap m random rows to the front, so that a sample needs no space of its own."""
    m = min(m, len(a))
    for i in range(m):
        j = rng.randrange(i, len(a))
        a[i], a[j] = a[j], a[i]
    return m


@dataclass
class Partitioned:
    starts: list[int]
    counts: list[int]
    cost: Cost


def stripes_of(n: int, b: int, t: int) -> list[int]:
    blocks = -(-n // b)
    return [min(n, b * (blocks * r // t)) for r in range(t)] + [n]


def flush_stripes(a: list, place, k: int, b: int, t: int, cost: Cost) -> tuple[list, list[list], list[list[int]], int]:
    """Local classification: the array as slots of blocks (None: empty), leftovers by bucket, counts by stripe, and the least room at a flush."""
    order, slots, left, counts, room = flush_places([place(x) for x in a], k, b, t, cost)
    rows = [a[i] for i in order]
    return [s and rows[s[1] : s[1] + b] for s in slots], [[x for at, m in parts for x in rows[at : at + m]] for parts in left], counts, room


def flush_places(places: list[int] | np.ndarray, k: int, b: int, t: int, cost: Cost) -> tuple[list[int] | np.ndarray, list, list[list[tuple[int, int]]], list[list[int]], int]:
    """The same for rows whose buckets are known: their places by stripe and bucket, blocks as bucket and beginning in that order, and leftovers as beginnings in it and rows.

    A bucket's buffer is written when one more of its rows comes and finds it full, so a stripe's blocks lie in the order of these rows."""
    n, bulk = len(places), isinstance(places, np.ndarray)
    slots: list = [EMPTY] * (-(-n // b))
    left: list[list[tuple[int, int]]] = [[] for _ in range(k)]
    orders, counts, room = [], [], n
    stripes = stripes_of(n, b, t)
    for start, end in zip(stripes, stripes[1:]):
        if bulk:
            own = places[start:end]
            order, count = np.argsort(own, kind="stable") + start, np.bincount(own, minlength=k).tolist()
        else:
            rows: list[list[int]] = [[] for _ in range(k)]
            for i, c in enumerate(places[start:end], start):
                rows[c].append(i)
            order, count = [i for x in rows for i in x], [len(x) for x in rows]
        at, first, bucket = start, [], []
        for c, m in enumerate(count):
            if m:
                full = (m - 1) // b
                first += range(at, at + full * b, b)
                bucket += [c] * full
                left[c].append((at + full * b, m - full * b))
                at += m
        if first:
            if bulk:
                blocks = np.array(first)
                found = order[blocks + (b - start)]
                by = np.argsort(found)
                slots[start // b : start // b + len(first)] = zip(np.array(bucket)[by].tolist(), blocks[by].tolist())
                room = min(room, int((found[by] - np.arange(start, start + len(first) * b, b)).min()))
            else:
                for to, (found, c, i) in enumerate(sorted((order[i + b - start], c, i) for c, i in zip(bucket, first)), start // b):
                    slots[to] = (c, i)
                    room = min(room, found - to * b)
            cost.block_moves += len(first)
        counts.append(count)
        orders.append(order)
    cost.read += n
    cost.written += n
    cost.extra_rows = max(cost.extra_rows, k * b * t)
    return orders[0] if t == 1 else np.concatenate(orders) if bulk else [i for x in orders for i in x], slots, left, counts, room


def permute_blocks(slots: list, delim: list[int], cost: Cost, workers: int = 1, skip: bool = True, trace: bool = False, spent: int = 0) -> dict[int, tuple]:
    """Blocks to their buckets' slots by read and write pointers, t workers in turn; overflow blocks come back by slot.

    A block names its bucket, and asking for it costs `spent` comparisons, those of classifying a row.  First each bucket's blocks are
    brought in front of its empty slots.  After each step all blocks left of a write pointer are their bucket's, and those from there
    to the read pointer are unprocessed."""
    k = len(delim) - 1
    outside: dict[int, tuple] = {}
    read, write, asked = [0] * k, list(delim[:k]), 0
    for i in range(k):
        if not (area := slots[delim[i] : delim[i + 1]]):
            read[i] = delim[i] - 1
            continue
        held = [x for x in area if x is not EMPTY]
        if held and len(held) < len(area):
            cost.block_moves += len(held) - area.index(EMPTY)
            slots[delim[i] : delim[i] + len(area)] = held + [EMPTY] * (len(area) - len(held))
        read[i] = delim[i] + len(held) - 1
    put = lambda s, block: slots.__setitem__(s, block) if s < len(slots) else outside.__setitem__(s, block)
    crossed = [False] * k

    def invariant():
        for i in range(k):
            for s in range(delim[i], write[i]):
                block = slots[s] if s < len(slots) else outside[s]
                assert block is not EMPTY and block[0] == i
            for s in range(write[i], read[i] + 1):
                assert slots[s] is not EMPTY
            for s in range(max(write[i], read[i] + 1), min(delim[i + 1], len(slots))):
                assert slots[s] is EMPTY

    primary = [r * k // workers for r in range(workers)]
    cycle, buffers = [0] * workers, [EMPTY] * workers
    active = list(range(workers))
    while active:
        for r in active:
            block = buffers[r]
            if block is EMPTY:
                while cycle[r] <= k:
                    p = primary[r]
                    at, last = write[p], read[p]
                    if skip:
                        while at <= last:
                            asked += 1
                            if slots[at][0] != p:
                                break
                            at += 1
                        cost.skipped += at - write[p]
                        write[p] = at
                    if at <= last:
                        block, slots[last] = slots[last], EMPTY
                        read[p] = last - 1
                        break
                    primary[r], cycle[r] = (p + 1) % k, cycle[r] + 1
                if block is EMPTY:
                    continue
            asked += 1
            d = block[0]
            s, last = write[d], read[d]
            if skip:
                while s <= last:
                    asked += 1
                    if slots[s][0] != d:
                        break
                    s += 1
                cost.skipped += s - write[d]
            write[d] = s + 1
            if s <= last:  # an unprocessed block is there: swap
                slots[s], buffers[r] = block, slots[s]
            else:  # an empty slot is there
                if not crossed[d]:
                    crossed[d] = True
                    cost.waits += 1
                put(s, block)
                buffers[r] = EMPTY
            cost.block_moves += 1
            if trace:
                invariant()
        active = [r for r in active if cycle[r] <= k or buffers[r] is not EMPTY]
    cost.comparisons += asked * spent
    return outside


def partition(a: list, splitters: list, b: int = 4, t: int = 1, equality: bool = False, cost: Cost | None = None, skip: bool = True, trace: bool = False, bulk: Bulk | None = None) -> Partitioned:
    """Partition a in place by splitters in the four steps, and return the buckets' starts.  With bulk, many rows are classified by their columns."""
    cost = cost or Cost()
    tree = tree_of(splitters) if splitters else [None]
    k = 2 * len(splitters) + 1 if equality else len(splitters) + 1
    n = len(a)
    spent = len(tree).bit_length() - 1 + equality  # comparisons of a row's classification, whoever asks for it
    cost.comparisons += n * spent
    places = bulk.places_of(a, splitters, tree, equality) if bulk and n >= BULK_ROWS else places_of(a, splitters, tree, equality)
    order, slots, left, by_stripe, room = flush_places(places, k, b, t, cost)
    assert room >= b or all(s is EMPTY for s in slots)
    counts = [sum(c) for c in zip(*by_stripe)] if t > 1 else by_stripe[0]
    starts = [0, *accumulate(counts)]
    delim = [-(-s // b) for s in starts]
    outside = permute_blocks(slots, delim, cost, t, skip, trace, spent) if any(slots) else {}
    # cleanup: blocks stay where they are, except what hangs over a bucket's end; gaps take leftovers
    begins: list[int] = []  # of pieces of the order, as they follow one another in the end
    sizes: list[int] = []
    asked = 0
    for i, before in enumerate(counts):
        spare, s, more = left[i], delim[i], 0
        if before <= b:  # no block, only what was left over
            for x, m in spare:
                begins.append(x)
                sizes.append(m)
            cost.row_moves += before
        else:
            more = (before - sum(m for _, m in spare)) // b
            held = [x for _, x in slots[s : s + more]]
            held += [outside[x][1] for x in range(max(s, len(slots)), s + more)]
            whole = [b] * more
            if more:
                before = s * b - starts[i]
                if (over := (s + more) * b - starts[i + 1]) > 0:
                    whole[-1] = b - over
                    spare = [*spare, (held[-1] + b - over, over)]
            behind = []
            for x, m in spare:
                cost.row_moves += m
                if before:
                    begins.append(x)
                    sizes.append(front := min(m, before))
                    before, x, m = before - front, x + front, m - front
                if m:
                    behind.append((x, m))
            begins += held
            sizes += whole
            for x, m in behind:
                begins.append(x)
                sizes.append(m)
        # each of its blocks is asked for its bucket, and so is the one behind them
        s += more
        asked += more + (slots[s] is not EMPTY if s < len(slots) else s in outside)
    cost.comparisons += asked * spent
    cost.read += n
    cost.written += n
    if isinstance(order, np.ndarray):
        size = np.array(sizes)
        ends = np.cumsum(size)
        out = order[np.repeat(np.array(begins) - ends + size, size) + np.arange(n)]
        a[:] = np.fromiter(a, object, n)[out].tolist()
    else:
        a[:] = [a[i] for x, m in zip(begins, sizes) for i in order[x : x + m]]
    return Partitioned(starts, counts, cost)


def distribution_sort(a: list, k: int = 16, b: int = 4, t: int = 1, n0: int = 16, seed: int = 1, cost: Cost | None = None, bulk: Bulk | None = None) -> list:
    """Recursive form on an array: partition, then each bucket; equality classes are done."""
    cost = cost or Cost()
    rng = Random(seed)
    todo = [(0, len(a))]
    while todo:
        lo, hi = todo.pop()
        if hi - lo <= n0:
            insertion_sort(a, lo, hi, cost)
            continue
        part = a[lo:hi]
        fan = min(k, max(2, (hi - lo) // n0))
        m = sample_to_front(part, 2 * fan - 1, rng)
        sample = sorted(part[:m])
        picked = [sample[min(m - 1, i * (m + 1) // fan - 1)] for i in range(1, fan)]
        distinct = sorted(set(picked))
        equality = len(distinct) < len(picked)
        got = partition(part, distinct, b, t, equality, cost, bulk=bulk)
        if not equality and max(got.counts) == hi - lo:  # no progress: splitters are rows, so their own classes make some
            equality = True
            got = partition(part, distinct, b, t, equality, cost, bulk=bulk)
        a[lo:hi] = part
        for c, (s, e) in enumerate(zip(got.starts, got.starts[1:])):
            if equality and c % 2:
                continue
            if e - s > 1:
                todo.append((lo + s, lo + e))
    return a


# ---- without a stack ----------------------------------------------------------------------------


def gallop_next_larger(a, x, lo: int) -> int:
    """The first place from lo on with a row larger than x, or the length: doubling steps, then halving.

    Everything from the first larger row on is larger than x."""
    n, step, at = len(a), 1, lo
    while at < n and not x < a[at]:
        lo = at + 1
        at += step
        step *= 2
    return bisect.bisect_right(a, x, lo, min(at, n)) if at > lo else lo


def _next_larger_marked(a: list, x, lo: int) -> int:
    """As above where rows from the first larger one on are buckets behind their largest rows."""
    n, step, at = len(a), 1, lo
    while at < n and not x < a[at]:
        lo = at + 1
        at += step
        step *= 2
    hi = min(at, n)
    while lo < hi:
        mid = (lo + hi) // 2
        if x < a[mid]:
            hi = mid
        else:
            lo = mid + 1
    return lo


_MASK = (1 << 64) - 1


def drawn_place(lo, size, m, j):
    """The place in a span of the j-th of m sample rows, one from each m-th part of it; spans draw without regard to what was drawn before.  Takes arrays of unsigned numbers as well."""
    x = (lo * 0x9E3779B97F4A7C15 + size * 0xC2B2AE3D27D4EB4F + j * 0x165667B19E3779F9) & _MASK
    x = ((x ^ x >> 29) * 0xBF58476D1CE4E5B9 & _MASK) >> 32
    return (j * size + x % size) // m


def stackless_sort(a: list, k: int = 8, b: int = 4, n0: int = 8, cost: Cost | None = None, bulk: Bulk | None = None) -> list:
    """No stack: each bucket's largest row stands first and marks it; the state is the span of the bucket at hand."""
    cost = cost or Cost()
    if bulk:
        at, rows = np.fromiter(map(itemgetter(-1), a), np.int64, len(a)), {x[-1]: x for x in a}
        a[:] = [rows[i] for i in stackless_passes(bulk, at, k, b, n0, cost).tolist()]
        return a
    lo, hi, n = 0, len(a), len(a)
    while lo < n:
        if hi - lo <= n0 or all(not a[lo] < x and not x < a[lo] for x in a[lo:hi]):
            insertion_sort(a, lo, hi, cost)
            lo = hi
        else:
            part, m = a[lo:hi], min(hi - lo, 2 * k)
            sample = sorted([part[drawn_place(lo, hi - lo, m, j)] for j in range(m)])
            cuts = sorted(set(sample[1::2]))
            if not any(x < cuts[0] for x in part):  # the least row cuts nothing off
                cuts = cuts[1:] or [max(part)]
            got = partition(part, cuts, b, 1, False, cost)
            for s, e in zip(got.starts, got.starts[1:]):
                if e - s > 1:
                    m = part.index(max(part[s:e]), s, e)
                    part[s], part[m] = part[m], part[s]
            a[lo:hi] = part
        if lo < n:
            hi = _next_larger_marked(a, a[lo], lo + 1)
    return a


def stackless_passes(bulk: Bulk, at: np.ndarray, k: int = 8, b: int = 4, n0: int = 8, cost: Cost | None = None) -> np.ndarray:
    """The same by columns: a pass takes one step in each bucket there is, and knows these from nothing but their marks, rows that are larger than all before them."""
    cost = cost or Cost()
    starts = np.zeros(min(1, len(at)), np.int64)
    while len(starts):
        sizes = np.diff(starts, append=len(at))
        small, large = (sizes > 1) & (sizes <= n0), sizes > n0
        insert_spans(bulk, at, starts[small], sizes[small], cost)
        if not large.any():
            break
        partition_spans(bulk, at, starts[large], sizes[large], k, b, cost)
        starts = bulk.marks(at)
    return at


def insert_spans(bulk: Bulk, at: np.ndarray, starts: np.ndarray, sizes: np.ndarray, cost: Cost) -> None:
    """`insertion_sort` of spans of rows: a row moves to the front past the larger ones before it, and back for each smaller one behind it."""
    for m in np.unique(sizes).tolist():
        places = starts[sizes == m][:, None] + np.arange(m)
        rows, (i, j) = at[places], np.tril_indices(m, -1)
        past = np.zeros((len(rows), m, m), np.int8)
        past[:, i, j] = bulk.less(rows[:, i].ravel(), bulk.columns, rows[:, j].ravel()).reshape(len(rows), -1)
        ahead = past.sum(2, dtype=np.int64)
        at[places - ahead + past.sum(1, dtype=np.int64)] = rows
        moved = int(ahead.sum())
        tried = moved + int((ahead < np.arange(m))[:, 1:].sum())
        cost.comparisons += tried
        cost.branches += tried
        cost.row_moves += moved


def partition_spans(bulk: Bulk, at: np.ndarray, starts: np.ndarray, sizes: np.ndarray, k: int, b: int, cost: Cost) -> None:
    """A step of `stackless_sort` in each of some spans of rows: splitters from a sample, the four steps of `partition`, and the largest row to each bucket's front."""
    spans, n = len(starts), int(sizes.sum())
    off = np.cumsum(sizes) - sizes  # the spans' rows one after another
    places = np.repeat(starts - off, sizes) + np.arange(n)
    rows = at[places]
    # splitters: every other row of the sample
    m = np.minimum(sizes, 2 * k)
    j = np.arange(2 * k)
    lo, size, of = (x.astype(np.uint64)[:, None] for x in (starts, sizes, m))
    sample = rows[off[:, None] + np.where(j < m[:, None], drawn_place(lo, size, of, j.astype(np.uint64)).astype(np.int64), 0)]
    absent = np.broadcast_to(j >= m[:, None], sample.shape)
    by = np.lexsort([*(c[sample].ravel() for c in reversed(bulk.columns)), absent.ravel(), np.repeat(np.arange(spans), 2 * k)])
    cuts, most = sample.ravel()[by].reshape(spans, -1)[:, 1::2], m // 2
    first = cuts[:, 0]
    cutting = np.minimum.reduceat(bulk.columns[0][rows], off) < bulk.columns[0][first]
    if not cutting.all():
        unsure = np.flatnonzero(~np.repeat(cutting, sizes))
        which = np.repeat(np.arange(spans), sizes)[unsure]
        less = bulk.less(rows[unsure], [c[first] for c in bulk.columns], which)
        cutting |= np.bincount(which[less], minlength=spans) > 0
    most = most - ~cutting  # the least row cuts nothing off
    if not (cut := most > 0).all():
        cuts[~cut, 0] = rows[bulk.largest(rows, off)[~cut]]
        most, cutting = np.maximum(most, 1), cutting | ~cut
    heap = np.array(tree_of(list(range((1 << k.bit_length()) - 1)))[1:])
    leaves = len(heap) + 1
    tree = np.zeros((spans, leaves), np.int64)
    tree[:, 1:] = np.take_along_axis(cuts, np.minimum(heap, most[:, None] - 1) + ~cutting[:, None], 1)
    spent = np.array([len(tree_of([0] * q)).bit_length() - 1 if q else 0 for q in range(k + 1)])[most]
    # classification
    values, base, i = [c[tree.ravel()] for c in bulk.columns], np.repeat(np.arange(spans) * leaves, sizes), np.ones(n, np.int64)
    for _ in range(leaves.bit_length() - 1):
        i += i + ~bulk.less(rows, values, base + i)
    bucket = np.minimum(i - leaves, np.repeat(most, sizes))
    order = np.argsort(bucket.astype(np.min_scalar_type(k)), kind="stable")  # short numbers are put in order without comparisons
    span = np.repeat(np.arange(spans).astype(np.min_scalar_type(spans)), sizes)
    order = order[np.argsort(span[order], kind="stable")]
    # buckets of all spans one after another, their rows as they lie in the order
    head = np.cumsum(most + 1) - (most + 1)
    owner = np.repeat(np.arange(spans), most + 1)
    counts = np.bincount(np.repeat(head, sizes) + bucket, minlength=len(owner))
    begin = np.cumsum(counts) - counts
    # blocks, in slots in the order in which their buffers were full
    full = np.maximum(counts - 1, 0) // b
    block_owner = np.repeat(np.arange(len(owner)), full)
    block = begin[block_owner] + b * (np.arange(len(block_owner)) - np.repeat(np.cumsum(full) - full, full))
    flushed = order[block + b]
    by = np.argsort(flushed)
    blocks = np.bincount(owner, full, spans).astype(np.int64)
    room = -(-sizes // b)
    slot0 = np.cumsum(room + 1) - (room + 1)
    nth = np.arange(len(by)) - np.repeat(np.cumsum(blocks) - blocks, blocks)
    assert (flushed[by] - np.repeat(off, blocks) - nth * b >= b).all()
    slots = np.full(int((room + 1).sum()), -1)
    slots[np.repeat(slot0, blocks) + nth] = by
    local = begin - off[owner]
    delim = slot0[owner] - (-local // b)
    stop = slot0[owner] - (-(local + counts) // b)
    if len(by):
        read = np.minimum(stop, np.maximum(delim, (slot0 + blocks)[owner])) - 1
        slots = permute_spans(slots, block_owner, delim, read, spent[owner], cost)
    # cleanup: a bucket's gap in front, its blocks, what is behind them; both take what was left over or hangs over its end
    held = np.repeat(delim - np.cumsum(full) + full, full) + np.arange(len(by))
    large = full > 0
    gap = np.where(large, (delim - slot0[owner]) * b - local, 0)
    over = np.where(large, np.maximum((delim + full - slot0[owner]) * b - local - counts, 0), 0)
    left, left_at = counts - full * b, begin + full * b
    over_at = np.zeros(len(owner), np.int64)
    over_at[large] = block[slots[(delim + full - 1)[large]]] + b - over[large]
    front = np.minimum(left, gap)
    front_over = np.minimum(over, gap - front)
    at_piece = np.cumsum(full + 4) - (full + 4)
    begins, lengths = np.zeros((2, int((full + 4).sum())), np.int64)
    own = np.repeat(at_piece + 2 - np.cumsum(full) + full, full) + np.arange(len(by))
    behind = at_piece + 2 + full
    begins[own], lengths[own] = block[slots[held]], b
    lengths[(behind - 1)[large]] -= over[large]
    for to, x, length in ((at_piece, left_at, front), (at_piece + 1, over_at, front_over), (behind, left_at + front, left - front), (behind + 1, over_at + front_over, over - front_over)):
        begins[to], lengths[to] = x, length
    rows = rows[order[np.repeat(begins - np.cumsum(lengths) + lengths, lengths) + np.arange(n)]]
    asked = full + (slots[delim + full] >= 0)
    cost.comparisons += int((spent * sizes).sum() + (spent[owner] * asked).sum())
    cost.block_moves += len(by)
    cost.row_moves += int((left + over).sum())
    cost.read += 2 * n
    cost.written += 2 * n
    cost.extra_rows = max(cost.extra_rows, int(most.max() + 1) * b)
    # marks
    front = begin[counts > 0]
    top = bulk.largest(rows, front)
    rows[front], rows[top] = rows[top], rows[front]
    at[places] = rows


def permute_spans(slots: np.ndarray, owner: np.ndarray, delim: np.ndarray, last: np.ndarray, spent: np.ndarray, cost: Cost) -> np.ndarray:
    """`permute_blocks` by one worker in each of some spans: slots have blocks' numbers, or -1, and owner names a block's bucket.

    A span's blocks lie in front of its empty slots, so none has to be brought there first."""
    todo = np.flatnonzero(delim <= last).tolist()
    slots, owner, write, read, spent = slots.tolist(), owner.tolist(), delim.tolist(), last.tolist(), spent.tolist()
    crossed = [False] * len(write)
    moves = skipped = total = 0
    for p in todo:
        asked = 0
        while True:
            s = w = write[p]
            r = read[p]
            while s <= r:
                asked += 1
                if owner[slots[s]] != p:
                    break
                s += 1
            skipped += s - w
            write[p] = s
            if s > r:
                break
            block, slots[r] = slots[r], -1
            read[p] = r - 1
            while True:
                asked += 1
                moves += 1
                d = owner[block]
                s = w = write[d]
                r = read[d]
                while s <= r:
                    asked += 1
                    if owner[slots[s]] != d:
                        break
                    s += 1
                skipped += s - w
                write[d] = s + 1
                if s > r:  # an empty slot is there
                    crossed[d] = True
                    slots[s] = block
                    break
                block, slots[s] = slots[s], block
        total += asked * spent[p]
    cost.block_moves += moves
    cost.skipped += skipped
    cost.waits += sum(crossed)
    cost.comparisons += total
    return np.array(slots)


def elementwise_permute(a: list, ids: list[int], k: int, cost: Cost | None = None) -> list[int]:
    """Rows to their buckets by following cycles, with the bucket of each row known beforehand; one move a row."""
    cost = cost or Cost()
    counts = [0] * k
    for i in ids:
        counts[i] += 1
    starts = [0]
    for c in counts:
        starts.append(starts[-1] + c)
    at = list(starts)
    for c in range(k):
        while at[c] < starts[c + 1]:
            i = at[c]
            d = ids[i]
            if d == c:
                at[c] += 1
            else:
                j = at[d]
                a[i], a[j], ids[i], ids[j] = a[j], a[i], ids[j], ids[i]
                at[d] += 1
                cost.row_moves += 1
    return starts


KERNELS = {"insertion": insertion_sort, "quicksort": quicksort, "introsort": introsort, "buffered": buffered_quicksort, "dual_pivot": dual_pivot, "distribution": distribution_sort, "stackless": stackless_sort}

#: Forms by columns, of kernels that have one for all of a task's rows.
PASSES = {"quicksort": quicksort_passes, "introsort": introsort_passes, "buffered": buffered_passes, "dual_pivot": dual_pivot_passes, "stackless": stackless_passes}


def order_of(columns: list, kernel: str) -> list[int]:
    """Places of the rows of some columns in the order that a kernel brings them to, equal rows by their places."""
    more = {"bulk": Bulk(columns)} if kernel in (*PASSES, "distribution") and all(isinstance(c, np.ndarray) for c in columns) else {}
    if more and kernel in PASSES:
        return PASSES[kernel](more["bulk"], np.arange(len(columns[0]))).tolist()
    rows = list(zip(*(c.tolist() if isinstance(c, np.ndarray) else c for c in columns), range(len(columns[0]))))
    collects = gc.isenabled()
    gc.disable()  # rows are plain values without cycles, and each search for these would walk through all rows
    try:
        return [r[-1] for r in KERNELS[kernel](rows, **more)]
    finally:
        if collects:
            gc.enable()
