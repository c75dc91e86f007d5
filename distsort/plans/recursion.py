"""Which buckets are split again, which are skipped, and who sorts the rest."""

from __future__ import annotations

from dataclasses import dataclass


def plan_recursion(sizes: list[int], workers: int, beta: float = 1.0, n0: int = 16, skip: frozenset[int] = frozenset()) -> list[str]:
    """For each bucket: split (all workers together), base (small enough), skip (an equality class) or pack (one worker)."""
    n = sum(sizes)
    return ["skip" if b in skip else "split" if s * workers >= beta * n and s >= n0 else "base" if s < n0 else "pack" for b, s in enumerate(sizes)]


def pack_buckets(sizes: list[int], workers: int, order: str = "contiguous", affinity: dict[int, int] | None = None) -> list[int]:
    """A worker for each bucket: neighbouring buckets together by their midpoints, the longest first to the least loaded, or where most of a bucket is already."""
    n = max(1, sum(sizes))
    if order == "contiguous":
        out, before = [], 0
        for s in sizes:
            out.append(min(workers - 1, (2 * before + s) * workers // (2 * n)))
            before += s
        return out
    out, load = [0] * len(sizes), [0] * workers
    share = -(-n // workers)
    for b in sorted(range(len(sizes)), key=lambda b: (-sizes[b], b)):
        liked = (affinity or {}).get(b)
        w = liked if liked is not None and load[liked] + sizes[b] <= 1.25 * share else min(range(workers), key=lambda w: (load[w], w))
        out[b] = w
        load[w] += sizes[b]
    return out


@dataclass(frozen=True)
class DistributionPlan:
    """For each class its first partition and how many partitions share it; the first position of each class."""

    first: tuple[int, ...]
    spread: tuple[int, ...]
    sizes: tuple[int, ...]

    @property
    def partitions(self) -> int:
        return max((f + s for f, s in zip(self.first, self.spread)), default=1)


def plan_partitions(sizes: list[int], equal: list[bool], partitions: int) -> DistributionPlan:
    """Contiguous classes to partitions of near equal size.  Equality classes need no order inside and so may be spread over several partitions of their own."""
    target = max(1, -(-sum(sizes) // partitions))
    first, spread, at, load = [], [], 0, 0
    for size, eq in zip(sizes, equal):
        if eq and size > target:
            at += 1 if load else 0
            parts = -(-size // target)
            first.append(at)
            spread.append(parts)
            at, load = at + parts, 0
            continue
        if load and load + size > target + target // 2:
            at, load = at + 1, 0
        first.append(at)
        spread.append(1)
        load += size
        if load >= target:
            at, load = at + 1, 0
    return DistributionPlan(tuple(first), tuple(spread), tuple(sizes))
