"""When a running count settles a test: exactly, by what the unseen rows could still do, or by an interval."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np

from sparkverdict.operators.confseq import BettingCS
from sparkverdict.plans.claims import Test, holds


def settle_deterministic(test: Test, seen: int, hits: int, size: int | None, exhausted: bool = False) -> bool | None:
    """The common verdict of all completions, None while they differ. Without a size any number of rows may follow."""
    if exhausted:
        size = seen
    if test.kind == "exists":
        return True if hits else (False if size == seen else None)
    if test.kind == "forall":
        return False if hits < seen else (True if size == seen else None)
    if test.kind == "share":
        if size is None:
            return None
        if not size:
            return False
        bar: Fraction = test.value * size
    else:
        bar = test.value
    least, most = hits, math.inf if size is None else hits + size - seen
    if test.op in ("==", "!="):
        at = holds("==", least, bar) if least == most else (None if least <= bar <= most and bar.denominator == 1 else False)
        return at if test.op == "==" or at is None else not at
    a, b = holds(test.op, least, bar), holds(test.op, most, bar)
    return a if a == b else None


def settle_interval(test: Test, size: int | None, lo: float, hi: float, eps: float) -> bool | None:
    """By an interval [lo, hi] of the share of hits. Equality has a relative tolerance; counts need the size. A universal claim
    has the tolerance only where the size is unknown: of a known number of rows a single miss makes it false."""
    if test.kind == "forall":
        return True if (lo >= 1 - eps if size is None else size * (1 - lo) < 1) else None
    if test.kind == "exists":
        return False if size is not None and size * hi < 1 else None
    if test.kind == "count":
        if size is None:
            return None
        lo, hi, bar = size * lo, size * hi, float(test.value)
        # integer comparisons with a strict side are comparisons with the next integer
        op, bar = {">": (">=", bar + 1), "<=": ("<", bar + 1)}.get(test.op, (test.op, bar))
    else:
        op, bar = test.op, float(test.value)
    if op == ">=":
        return True if lo >= bar else (False if hi < bar else None)
    if op == "<":
        return True if hi < bar else (False if lo >= bar else None)
    if op == ">":
        return True if lo > bar else (False if hi <= bar else None)
    if op == "<=":
        return True if hi <= bar else (False if lo > bar else None)
    low, high = bar * (1 - eps), bar * (1 + eps)
    inside = True if low <= lo and hi <= high else (False if hi < low or lo > high else None)
    return inside if op == "==" or inside is None else not inside


@dataclass
class Tally:
    """Bits in order; settles at the first bit that decides and ignores what follows."""

    test: Test
    size: int | None = None
    alpha: float | None = None  # None: no estimation
    eps: float = 0.05
    early: bool = True
    seen: int = 0
    hits: int = 0
    lo: float = 0.0
    hi: float = 1.0
    verdict: bool | None = None
    settled_by: str | None = None
    interval: BettingCS | None = field(default=None, repr=False)

    def __post_init__(self) -> None:
        if self.alpha is not None and self.early:
            self.interval = BettingCS(self.alpha, self.size)
        if self.early:
            self._check()

    @property
    def settled(self) -> bool:
        return self.verdict is not None

    def _check(self, exhausted: bool = False) -> None:
        found, by = settle_deterministic(self.test, self.seen, self.hits, self.size, exhausted), "exhausted" if exhausted else "bound"
        if found is None and self.interval is not None and self.seen:
            found, by = settle_interval(self.test, self.size, self.lo, self.hi, self.eps), "interval"
        if found is not None:
            self.verdict, self.settled_by = found, by

    def push(self, bits) -> int:
        """Takes bits until the test settles; returns how many it took."""
        bits = np.asarray(bits, bool)
        if self.settled or not len(bits):
            return 0
        bounds = self.interval.push(bits) if self.interval is not None else None
        for i, bit in enumerate(bits):
            self.seen += 1
            self.hits += int(bit)
            if bounds is not None:
                self.lo, self.hi = float(bounds[0][i]), float(bounds[1][i])
            if self.early:
                self._check()
                if self.settled:
                    return i + 1
        return len(bits)

    def close(self) -> bool:
        """End of input."""
        if not self.settled:
            self._check(exhausted=True)
        return bool(self.verdict)
