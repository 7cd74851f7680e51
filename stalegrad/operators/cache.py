"""The gradient cache: disjoint row intervals with the newest subgradient of each."""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass, field

import numpy as np


@dataclass
class Entry:
    lo: int
    hi: int
    version: int
    grad: np.ndarray | None = None


@dataclass
class Event:
    action: str  # insert, replace or reject
    evicted: list[tuple[int, int, int]] = field(default_factory=list)
    rows_covered: int = 0


class IntervalCache:
    """Sorted disjoint intervals with their running sum and row count.

    ``overlap='endpoint'`` is the ablation that only sees cached intervals with an
    end inside the arrival, and so counts rows of a containing interval twice.
    """

    def __init__(self, overlap: str = "intersect"):
        self.starts: list[int] = []
        self.entries: list[Entry] = []
        self.rows = 0
        self.total: np.ndarray | None = None
        self.overlap = overlap

    def overlapping(self, lo: int, hi: int) -> tuple[int, int]:
        """Slice of entries that share a row with [lo, hi]."""
        first = bisect_left(self.starts, lo)
        if first and self.entries[first - 1].hi >= lo:
            first -= 1
        last = bisect_left(self.starts, hi + 1)
        return first, max(first, last)

    def offer(self, lo: int, hi: int, version: int, grad: np.ndarray | None = None) -> Event:
        """Takes the arrival unless something it overlaps is as new; then it replaces all of that."""
        first, last = self.overlapping(lo, hi)
        hits = self.entries[first:last]
        if len(hits) == 1 and hits[0].lo == lo and hits[0].hi == hi and hits[0].version < version:
            return self._renew(hits[0], version, grad)
        if self.overlap == "endpoint":
            hits = [e for e in hits if lo <= e.lo <= hi or lo <= e.hi <= hi]
        if any(e.version >= version for e in hits):
            return Event("reject", rows_covered=self.rows)
        for e in hits:
            self.rows -= e.hi - e.lo + 1
            if e.grad is not None:
                self.total = self.total - e.grad
            at = self.entries.index(e, max(0, first - 1))
            del self.entries[at], self.starts[at]
        at = bisect_left(self.starts, lo)
        self.starts.insert(at, lo)
        self.entries.insert(at, Entry(lo, hi, version, grad))
        self.rows += hi - lo + 1
        if grad is not None:
            self.total = grad.copy() if self.total is None else self.total + grad
        return Event("replace" if hits else "insert", [(e.lo, e.hi, e.version) for e in hits], self.rows)

    def _renew(self, entry: Entry, version: int, grad: np.ndarray | None) -> Event:
        """The same interval again: its entry is changed in place, the lists stay as they are."""
        gone = (entry.lo, entry.hi, entry.version)
        if grad is not None:
            self.total = grad.copy() if self.total is None else self.total + grad - (0 if entry.grad is None else entry.grad)
        elif entry.grad is not None:
            self.total = self.total - entry.grad
        entry.version, entry.grad = version, grad
        return Event("replace", [gone], self.rows)

    def resum(self) -> None:
        """Exact sum again, against the drift of many small corrections."""
        grads = [e.grad for e in self.entries if e.grad is not None]
        self.total = np.sum(grads, axis=0) if grads else None

    def coverage(self, n: int) -> float:
        return self.rows / n

    def clear(self) -> None:
        self.starts, self.entries, self.rows, self.total = [], [], 0, None
