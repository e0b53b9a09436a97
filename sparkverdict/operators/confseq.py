"""Confidence sequences for the share of hits: intervals that hold at all times together with probability 1 - alpha.

For each candidate share two bettors start with a half each. One gains when hits are more frequent than the candidate says, the
other when they are rarer; stakes depend on earlier bits only. If the candidate is true their joint wealth is a
nonnegative martingale, so it ever reaches 1/alpha with probability at most alpha (Ville); candidates whose wealth got
there are dropped for good. Without replacement the fair odds of the next bit follow from what the candidate leaves for
the unseen rows, and candidates that the count rules out are dropped at once.
"""

from __future__ import annotations

import math

import numpy as np

GRID = 1001
CAP = 0.5
CHUNK = 256


class BettingCS:
    def __init__(self, alpha: float, size: int | None = None) -> None:
        self.alpha, self.size = alpha, size
        if size is not None and size <= GRID:
            self.counts = np.arange(size + 1, dtype=float)  # candidates are the possible counts
        elif size is not None:
            self.counts = np.unique(np.round(np.linspace(0, size, GRID)))
        else:
            self.counts = None
        self.m = self.counts / max(1, size) if size is not None else np.linspace(0, 1, GRID)
        self.gap = 0.0 if size is not None and size <= GRID else 1.0 / (GRID - 1)
        self.up, self.down = np.zeros_like(self.m), np.zeros_like(self.m)
        self.alive = np.ones(len(self.m), bool)
        self.seen = self.hits = 0
        self.spread = 0.25  # running sum for the variance, with one prior row
        self.lo, self.hi = 0.0, 1.0

    def push(self, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Intervals after each of the bits."""
        out = [self._push(np.asarray(bits[i : i + CHUNK], float)) for i in range(0, len(bits), CHUNK)]
        return (np.concatenate([o[0] for o in out]), np.concatenate([o[1] for o in out])) if out else (np.zeros(0), np.zeros(0))

    def _push(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(x)
        t = self.seen + np.arange(1, n + 1)
        before = self.hits + np.concatenate([[0.0], np.cumsum(x)[:-1]])
        mean = (0.5 + before) / t  # of the bits before t, with half a hit in one prior row
        after = (0.5 + before + x) / (t + 1)
        spread = self.spread + np.concatenate([[0.0], np.cumsum((x - after) ** 2)])
        var = spread[:-1] / t
        stake = np.sqrt(2 * math.log(2 / self.alpha) / (np.maximum(var, 1e-6) * t * np.log(t + 1)))[:, None]
        if self.size is None:
            odds = np.broadcast_to(self.m, (n, len(self.m)))
            possible = np.ones((n, len(self.m)), bool)
        else:
            left = self.size - (t - 1)
            odds = (self.counts[None, :] - before[:, None]) / np.maximum(left, 1)[:, None]
            now = before + x
            possible = (self.counts[None, :] >= now[:, None]) & (self.counts[None, :] <= (now + self.size - t)[:, None])
        fair = np.clip(odds, 1e-9, 1 - 1e-9)
        gain = x[:, None] - fair
        up = self.up + np.cumsum(np.log1p(np.minimum(stake, CAP / fair) * gain), axis=0)
        down = self.down + np.cumsum(np.log1p(-np.minimum(stake, CAP / (1 - fair)) * gain), axis=0)
        wealth = np.logaddexp(up, down) - math.log(2)
        # a candidate of share 0 or 1 is refuted by the first bit that contradicts it
        sure = ((self.m == 0)[None, :] & (np.cumsum(x) + self.hits > 0)[:, None]) | ((self.m == 1)[None, :] & (np.cumsum(1 - x) + self.seen - self.hits > 0)[:, None])
        alive = np.logical_and.accumulate((wealth < math.log(1 / self.alpha)) & possible & ~sure, axis=0) & self.alive
        self.up, self.down, self.alive = up[-1], down[-1], alive[-1]
        self.seen, self.hits, self.spread = self.seen + n, self.hits + x.sum(), spread[-1]
        some = alive.any(axis=1)
        first, last = alive.argmax(axis=1), len(self.m) - 1 - alive[:, ::-1].argmax(axis=1)
        # between grid points nothing is tested, so the interval reaches to the neighbours that are out
        lo = np.where(some, np.maximum(0, self.m[first] - np.where(first > 0, self.gap, 0)), np.nan)
        hi = np.where(some, np.minimum(1, self.m[last] + np.where(last < len(self.m) - 1, self.gap, 0)), np.nan)
        if not some.all():  # all candidates are out (an event of probability alpha): the last interval stays
            keep = np.flatnonzero(~some)[0]
            lo[keep:], hi[keep:] = (lo[keep - 1], hi[keep - 1]) if keep else (self.lo, self.hi)
        self.lo, self.hi = float(lo[-1]), float(hi[-1])
        return lo, hi


class ClassicalCI:
    """The normal interval of one fixed sample size, watched continuously; only a comparator."""

    def __init__(self, alpha: float, size: int | None = None, start: int = 30) -> None:
        from statistics import NormalDist

        self.z, self.start, self.seen, self.hits = NormalDist().inv_cdf(1 - alpha / 2), start, 0, 0.0

    def push(self, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        x = np.asarray(bits, float)
        t = self.seen + np.arange(1, len(x) + 1)
        p = (self.hits + np.cumsum(x)) / t
        half = self.z * np.sqrt(p * (1 - p) / t)
        self.seen, self.hits = self.seen + len(x), self.hits + x.sum()
        early = t < self.start
        return np.where(early, 0.0, np.maximum(0, p - half)), np.where(early, 1.0, np.minimum(1, p + half))


def bonferroni(alpha: float, operators: int, aggregates: int, groups: int) -> float:
    """Each interval's share of alpha where the number of groups is known."""
    return alpha / max(1, operators * aggregates * groups)


def geometric(alpha: float, operators: int, aggregates: int, arrival: int) -> float:
    """The share of the group that arrives as number 1, 2, ...; all shares add up to at most alpha. Late groups get 0."""
    return math.ldexp(alpha / max(1, operators * aggregates), -arrival)


def coverage(alpha: float, mean: float, rows: int, streams: int, size: int | None = None, seed: int = 0, classical: bool = False) -> float:
    """Share of seeded streams whose intervals ever miss the true share."""
    missed = 0
    for i in range(streams):
        rng = np.random.default_rng((seed, i))
        if size is None:
            bits, true = rng.random(rows) < mean, mean
        else:
            pool = np.zeros(size, bool)
            pool[: round(mean * size)] = True
            bits, true = rng.permutation(pool)[:rows], pool.mean()
        lo, hi = (ClassicalCI(alpha) if classical else BettingCS(alpha, size)).push(bits)
        missed += bool(((lo > true + 1e-12) | (hi < true - 1e-12)).any())
    return missed / streams


def refuted(alpha: float, bits: np.ndarray, mean: float, size: int | None = None, classical: bool = False) -> bool:
    """Whether the intervals of one stream ever miss the true share."""
    lo, hi = (ClassicalCI(alpha) if classical else BettingCS(alpha, size)).push(bits)
    return bool(((lo > mean + 1e-12) | (hi < mean - 1e-12)).any())


def truth_refuted(alpha: float | np.ndarray, bits: np.ndarray, mean: float | np.ndarray, size: int | None = None) -> np.ndarray:
    """Per stream (a row of bits) whether the bets against its own share ever reach 1/alpha, which is the only way in which
    an interval can miss it; all streams at once. `mean` and `alpha` may differ by stream; with a size the streams are drawn
    without replacement from that many rows, round(mean * size) of them hits."""
    x = np.asarray(bits, float)
    by_stream = lambda v: np.broadcast_to(np.asarray(v, float), len(x))[:, None]
    a, share = by_stream(alpha), by_stream(mean)
    t = np.arange(1, x.shape[1] + 1)
    before = np.cumsum(x, axis=1) - x
    squares = np.cumsum((x - (0.5 + before + x) / (t + 1)) ** 2, axis=1)
    var = (0.25 + np.concatenate([np.zeros((len(x), 1)), squares[:, :-1]], axis=1)) / t
    stake = np.sqrt(2 * np.log(2 / a) / (np.maximum(var, 1e-6) * t * np.log(t + 1)))
    odds = share if size is None else (np.round(share * size) - before) / np.maximum(size - (t - 1), 1)
    fair = np.clip(odds, 1e-9, 1 - 1e-9)
    up = np.cumsum(np.log1p(np.minimum(stake, CAP / fair) * (x - fair)), axis=1)
    down = np.cumsum(np.log1p(-np.minimum(stake, CAP / (1 - fair)) * (x - fair)), axis=1)
    return (np.logaddexp(up, down) - math.log(2) >= np.log(1 / a)).any(axis=1)


def streams_of(rng: np.random.Generator, streams: int, rows: int, mean: np.ndarray, size: int | None = None) -> np.ndarray:
    """Seeded bits, a stream a row: independent ones, or the first rows of a shuffled relation."""
    if size is None:
        return rng.random((streams, rows)) < mean[:, None]
    pools = np.arange(size)[None, :] < np.round(mean * size)[:, None]
    return rng.permuted(pools, axis=1)[:, :rows]


BUDGETS = ("known", "arrival", "none")


def budget_shares(alpha: float, budget: str, groups: int) -> list[float]:
    """Each group's share of alpha: 'known' (the number of groups is known), 'arrival' (it is not), 'none' (all of it)."""
    return {"known": [bonferroni(alpha, 1, 1, groups)] * groups, "arrival": [geometric(alpha, 1, 1, i + 1) for i in range(groups)], "none": [alpha] * groups}[budget]


def family_missed(alpha: float, budget: str, groups: int, rows: int, families: int, seed: int = 0, size: int | None = None) -> int:
    """Families of groups of which any group's own share is ever refuted. Budgets: 'known' (the number of groups is known),
    'arrival' (it is not), 'none' (each group has the whole alpha)."""
    rng = np.random.default_rng((seed, groups))
    shares = budget_shares(alpha, budget, groups)
    missed = 0
    for _ in range(families):
        mean = rng.random(groups)
        if size is not None:
            mean = np.round(mean * size) / size
        missed += bool(truth_refuted(np.asarray(shares), streams_of(rng, groups, rows, mean, size), mean, size).any())
    return missed
