"""Tuning parameters, and what follows from them without data."""

from __future__ import annotations

import math
from dataclasses import dataclass


def block_rows(record_bytes: int, block_bytes: int = 2048) -> int:
    """Rows of a block: the largest power of two that fits, one at least."""
    return max(1, 2 ** math.floor(math.log2(block_bytes) - math.log2(record_bytes)))


def oversampling(n: int) -> int:
    """Sample rows for each bucket: a fifth of the binary logarithm of n, one at least."""
    return max(1, round(0.2 * math.log2(n))) if n > 1 else 1


def level_plan(n: int, n0: int = 16, k_max: int = 256) -> list[int]:
    """Fan-outs of the levels for n rows: k_max, but the last two levels share the bits that are left, so that final buckets don't become needlessly small."""
    bits, most, out = math.log2(n / n0) if n > n0 else 0.0, math.log2(k_max), []
    while bits > 0 and (levels := math.ceil(bits / most)) > 2:
        out.append(k_max)
        bits -= most
    if bits >= 1:
        out += [2 ** math.floor(bits / levels)] * levels
    return out


@dataclass(frozen=True)
class SortParams:
    k: int = 256
    alpha: int | None = None  # None: oversampling(n)
    beta: float = 1.0
    n0: int = 16
    block_bytes: int = 2048
    partitions: int | None = None  # None: spark.sql.shuffle.partitions
    seed: int = 7
    equality: bool | None = None  # None: only if the sample had duplicate splitters
    most_levels: int = 3
    backend: str = "chained"

    def alpha_for(self, n: int) -> int:
        return self.alpha or oversampling(n)
