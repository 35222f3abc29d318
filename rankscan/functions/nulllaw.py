"""The null law of a window's rank sum: the sum of w distinct integers drawn from 1..n, in several exact ways and by sampling.

Arrays run over the sums from the least, w(w+1)/2, to the greatest, w(2n-w+1)/2.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

MODES = ("tail", "mass", "upper", "lower", "two_sided")
#: Scores that an exact law gives alike to sums equally far from the mean.
SYMMETRIC = ("tail", "mass", "two_sided")


def least_sum(w: int) -> int:
    return w * (w + 1) // 2


def log10_binom(n: int, w: int) -> float:
    return (math.lgamma(n + 1) - math.lgamma(w + 1) - math.lgamma(n - w + 1)) / math.log(10)


@lru_cache(maxsize=None)
def partition_count(parts: int, largest: int, total: int) -> int:
    """Partitions of ``total`` into at most ``parts`` parts, none above ``largest``.

    An empty box holds the empty partition and no other. (A base that counts it only for total = parts = largest = 0 makes
    every count 0.)
    """
    if total < 0:
        return 0
    if parts == 0 or largest == 0:
        return int(total == 0)
    return partition_count(parts, largest - 1, total) + partition_count(parts - 1, largest, total - largest)


def law_by_memo(n: int, w: int) -> list[int]:
    return [partition_count(w, n - w, k) for k in range(w * (n - w) + 1)]


def law_by_product(n: int, w: int) -> list[int]:
    """Counts as the coefficients of a product of (1 - q^(n-w+i)) / (1 - q^i), in exact integers."""
    counts = np.zeros(w * (n - w) + 1, object)
    counts[0] = 1
    for i in range(1, w + 1):
        up = n - w + i
        if up < len(counts):
            counts[up:] = counts[up:] - counts[:-up].copy()
        for r in range(min(i, len(counts))):
            counts[r::i] = np.cumsum(counts[r::i])
    return counts.tolist()


def law_by_conditioning(n: int, w_max: int) -> list[np.ndarray]:
    """Masses for w = 0..w_max by growing the pool one number at a time; every term is positive, so nothing cancels."""
    # the least mass is 1 / C(n, w): beyond doubles the wider type's exponents hold it
    least = -log10_binom(n, min(w_max, n // 2))
    kind = np.float64 if least > -300 else np.longdouble
    if least < np.log10(np.finfo(kind).tiny):
        raise ValueError("masses of this n and w_max are below what the machine's floats hold")
    law = [np.ones(1, kind)] + [np.zeros(0, kind)] * w_max
    for pool in range(1, n + 1):
        fresh = [np.ones(1, kind)]
        for w in range(1, w_max + 1):
            if w > pool:
                fresh.append(np.zeros(0, kind))
                continue
            out = np.zeros(w * (pool - w) + 1, kind)
            if w < pool:
                out[: len(law[w])] += law[w] * ((pool - w) / pool)
            shift = pool - w  # the new number joins w - 1 others
            out[shift : shift + len(law[w - 1])] += law[w - 1] * (w / pool)
            fresh.append(out)
        law = fresh
    return law


def sampled_counts(n: int, w_max: int, draws: int, rng: np.random.Generator) -> list[np.ndarray]:
    """Histograms of rank sums for every w at once: each permutation's prefix sums are one draw for each w."""
    out = [np.zeros(w * (n - w) + 1, np.int64) for w in range(w_max + 1)]
    step = max(1, 2_000_000 // n)
    for a in range(0, draws, step):
        sums = np.cumsum(rng.permuted(np.tile(np.arange(1, n + 1), (min(step, draws - a), 1)), axis=1)[:, :w_max], axis=1)
        for w in range(1, w_max + 1):
            out[w] += np.bincount(sums[:, w - 1] - least_sum(w), minlength=len(out[w]))
    return out


def _log10(x: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore"):
        return np.log10(x).astype(float)


class Law:
    """Log10 scores of all windows up to w_max for one n; ``of`` gives a table over sums for each w."""

    def __init__(self, n: int, w_max: int, masses: list[np.ndarray], samples: int | None = None):
        self.n, self.w_max, self.samples = n, min(w_max, n), samples
        # an exact law is symmetric; so are its tails, to the last bit, if the rounding is made so too
        masses = [np.asarray(m) if np.asarray(m).dtype == np.longdouble else np.asarray(m, float) for m in masses]
        self.mass = masses if samples else [(m + m[::-1]) / 2 for m in masses]
        self.lower = [np.minimum(np.cumsum(m), 1.0) for m in self.mass]
        self.upper = [np.minimum(np.cumsum(m[::-1])[::-1], 1.0) for m in self.mass]

    @classmethod
    def exact(cls, n: int, w_max: int) -> Law:
        return cls(n, min(w_max, n), law_by_conditioning(n, min(w_max, n)))

    @classmethod
    def sampled(cls, n: int, w_max: int, samples: int, seed: int) -> Law:
        counts = sampled_counts(n, min(w_max, n), samples, np.random.default_rng(seed))
        return cls(n, min(w_max, n), [c / samples for c in counts], samples)

    def table(self, w: int, mode: str) -> np.ndarray:
        """Log10 score over sums; sums that no sample had are censored at one in ``samples``."""
        low, up = self.lower[w], self.upper[w]
        p = {"mass": self.mass[w], "lower": low, "upper": up, "tail": np.minimum(low, up), "two_sided": np.minimum(1, 2 * np.minimum(low, up))}[mode]
        return _log10(p if self.samples is None else np.maximum(p, 1 / self.samples))

    def tables(self, mode: str) -> list[np.ndarray]:
        return [np.zeros(1)] + [self.table(w, mode) for w in range(1, self.w_max + 1)]

    def critical(self, w: int, alpha: float) -> tuple[int | None, int | None]:
        """The greatest sum whose lower tail and the least whose upper tail is at most alpha."""
        low, up = np.flatnonzero(self.lower[w] <= alpha), np.flatnonzero(self.upper[w] <= alpha)
        return (int(low[-1]) + least_sum(w) if len(low) else None), (int(up[0]) + least_sum(w) if len(up) else None)


class LawTables:
    """Scores of all windows up to w_max for one n in one array. Where scores are symmetric about the mean sum (an exact
    law's masses and tails are) only the lower half is held, and sums above the mean are looked up by their mirror image."""

    def __init__(self, n: int, w_max: int, flat: np.ndarray, half: bool, samples: int | None = None):
        self.n, self.w_max, self.flat, self.half, self.samples = n, min(w_max, n), flat, half, samples
        w = np.arange(self.w_max + 1)
        self.last = w * (n - w)  # place of the greatest sum
        self.at = np.concatenate([[0], np.cumsum(self.last // 2 + 1 if half else self.last + 1)])
        self.shift = self.at[:-1] - w * (w + 1) // 2

    @classmethod
    def of(cls, n: int, tables: list[np.ndarray], half: bool = False, samples: int | None = None) -> LawTables:
        held = [x[: (len(x) + 1) // 2 if half else len(x)] for x in tables]
        return cls(n, len(tables) - 1, np.concatenate(held), half, samples)

    @classmethod
    def build(cls, n: int, w_max: int, mode: str = "tail", law: str = "exact", samples: int = 100_000, seed: int = 42) -> LawTables:
        one = Law.exact(n, w_max) if law == "exact" else Law.sampled(n, w_max, samples, seed)
        return cls.of(n, one.tables(mode), law == "exact" and mode in SYMMETRIC, one.samples)

    def scores(self, w, q: np.ndarray) -> np.ndarray:
        """Scores of rank sums q of windows of widths w."""
        if self.half:
            q = np.minimum(q, w * (self.n + 1) - q)
        return self.flat[self.shift[w] + q]

    def scores_or_inf(self, w, q: np.ndarray) -> np.ndarray:
        """The same for any sums: those that w numbers of 1..n cannot have score +inf."""
        least = w * (w + 1) // 2
        ok = (q >= least) & (q <= least + w * (self.n - w))
        return np.where(ok, self.scores(w, np.where(ok, q, least)), np.inf)


def min_width(n: int, alpha: float) -> int | None:
    """The least window whose most extreme sum has a mass of at most alpha."""
    return next((w for w in range(1, n // 2 + 1) if -log10_binom(n, w) <= math.log10(alpha)), None)


def required_samples(alpha: float, epsilon: float) -> int:
    return math.ceil(round(1 / (alpha * epsilon**2), 6))


def frequency_error(hits: float) -> float:
    return math.inf if hits <= 0 else hits**-0.5


def memo_cells(n: int, w_max: int) -> int:
    """Cells of the memo table that the recurrence may fill."""
    return w_max * n * (n * w_max - w_max * (w_max - 1) // 2)
