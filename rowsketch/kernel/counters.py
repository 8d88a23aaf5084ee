"""Approximate item counts with fewer than ell counters.

A known item's counter grows; a new item takes a free counter.  As soon as all
ell counters are in use the least count is taken off every one, which frees
some.  ``shed`` sums what was taken off: an estimate is never too high and at
most ``shed`` too low, and ``ell * shed <= n``.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np


class CounterState:
    def __init__(self, ell: int):
        if ell < 1:
            raise ValueError("ell must be positive")
        self.ell = ell
        self.counts: dict = {}
        self.n = 0
        self.shed = 0

    def extend(self, items: Iterable) -> None:
        """One item after the other."""
        counts, ell = self.counts, self.ell
        for item in items:
            self.n += 1
            counts[item] = counts.get(item, 0) + 1
            if len(counts) >= ell:
                least = min(counts.values())
                self.shed += least
                counts = self.counts = {k: v - least for k, v in counts.items() if v > least}

    def add_counts(self, counts: dict, n: int | None = None, shed: int = 0) -> None:
        """Adds another summary, or exact counts of a batch: sum, then take the ell-th largest off all."""
        mine = self.counts
        for k, v in counts.items():
            mine[k] = mine.get(k, 0) + v
        self.n += sum(counts.values()) if n is None else n
        self.shed += shed
        if len(mine) >= self.ell:
            values = np.fromiter(mine.values(), np.int64, len(mine))
            cut = int(np.partition(values, len(values) - self.ell)[len(values) - self.ell])
            self.shed += cut
            self.counts = {k: v - cut for k, v in mine.items() if v > cut}

    def estimate(self, item) -> tuple[int, int]:
        """Bounds of an item's count."""
        low = self.counts.get(item, 0)
        return low, low + self.shed
