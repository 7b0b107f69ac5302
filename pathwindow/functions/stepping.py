"""Window width and cut choice: arithmetic on statistics that are small whatever the graph."""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class QuantileTable:
    """Edge weights at equally spaced shares; the last is the exact maximum."""

    values: tuple[float, ...]

    @property
    def wmax(self) -> float:
        return self.values[-1]

    def at(self, share: float) -> float:
        """The weight at a share, never zero: a zero falls back to the least positive entry."""
        k = min(len(self.values) - 1, max(0, int(share * (len(self.values) - 1))))
        if self.values[k] > 0:
            return self.values[k]
        return next((v for v in self.values[k:] if v > 0), 1.0)

    def share_below(self, w: float) -> float:
        return bisect_left(self.values, w) / max(1, len(self.values) - 1)


def open_degree(histogram: dict[int, int]) -> int:
    return sum(d * n for d, n in histogram.items())


def balance_degree(histogram: dict[int, int]) -> int:
    """The least degree d for which degrees below d and degrees from d on sum most equally."""
    total, below, best = open_degree(histogram), 0, (float("inf"), 0)
    for d in sorted(histogram):
        best = min(best, (abs(total - 2 * below), d))
        below += d * histogram[d]
    return best[1]


@dataclass(frozen=True)
class WindowChoice:
    width: float
    balance: int
    open_sum: int
    share: float


def choose_width(histogram: dict[int, int], two_m: int, table: QuantileTable, alpha: float = 3, beta: float = 0.9) -> WindowChoice:
    """How far the next window reaches: the weight that enough of the edges into the open part stay below."""
    total, balance = open_degree(histogram), balance_degree(histogram)
    if balance <= alpha:
        return WindowChoice(table.wmax, balance, total, 1.0)
    settle = min(beta, max(total, two_m - total) / two_m)
    share = 1 - (1 - settle) ** (1 / (settle * balance))
    return WindowChoice(table.at(share), balance, total, share)


@dataclass(frozen=True)
class Traversals:
    pushed: np.ndarray
    pulled: np.ndarray
    long: np.ndarray

    @property
    def profit(self) -> np.ndarray:
        return self.pushed - self.long - self.pulled


def estimate_traversals(x, degree_at_x, lo: float, hi: float, degree_at_lo: float, two_m: float, table: QuantileTable, by_quantiles: bool = False) -> Traversals:
    """Edges that would be pushed from [x, lo), pulled by the open part, and needed in the end, for cuts x.

    All lengths are first clipped to one maximum weight of reach. ``by_quantiles`` replaces the assumption of uniform
    weights by the table's shares.
    """
    wmax = table.wmax
    x = np.maximum(np.asarray(x, float), lo - wmax)
    near, far = np.minimum(hi, lo + wmax), np.minimum(hi, x + wmax)
    band = np.asarray(degree_at_x, float) - degree_at_lo
    reach = np.array([table.share_below(v) for v in np.atleast_1d(far - x)]).reshape(np.shape(x)) if by_quantiles else (far - x) / wmax
    pushed, pulled = (near - lo) * band / wmax, reach * degree_at_lo
    return Traversals(pushed, pulled, pulled * band / two_m)


def choose_cut(points: np.ndarray, degree_at: np.ndarray, lo: float, hi: float, degree_at_lo: float, two_m: float, table: QuantileTable, by_quantiles: bool = False) -> float:
    """The candidate below lo with the largest positive profit; lo if none has one."""
    held = points < lo
    if not held.any():
        return lo
    profit = estimate_traversals(points[held], degree_at[held], lo, hi, degree_at_lo, two_m, table, by_quantiles).profit
    best = int(np.argmax(profit))
    return float(points[held][best]) if profit[best] > 0 else lo


def cut_profit(x, degree_at_x, lo: float, hi: float, degree_at_lo: float, two_m: float, wmax: float):
    """The profit of a cut x for arrays or columns of candidates, uniform weights assumed (as in estimate_traversals)."""
    if isinstance(x, np.ndarray):
        reach, far = np.maximum(x, lo - wmax), np.minimum(hi, np.maximum(x, lo - wmax) + wmax)
    else:
        from pyspark.sql import functions as F

        reach = F.greatest(x, F.lit(lo - wmax))
        far = F.least(F.lit(hi), reach + wmax)
    band = degree_at_x - degree_at_lo
    pulled = (far - reach) * (degree_at_lo / wmax)
    return (min(hi, lo + wmax) - lo) * band / wmax - pulled * band / two_m - pulled
