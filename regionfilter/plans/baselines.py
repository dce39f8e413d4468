"""The designs that the region filter is compared with, on the same histogram and the same accounting."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from ..functions.formulas import LOG2E
from . import rates as R
from . import thresholds as T
from .planner import Plan, plan_of

GAMMAS = tuple(round(1.1 + 0.3 * i, 1) for i in range(131))  # 1.1 to 40.1


def ideal_bits(n: int, target: float) -> float:
    """The lower bound of any filter that knows nothing of its keys."""
    return n * math.log2(1 / target)


def standard(n: int, target: float) -> tuple[int, int]:
    """(bits, hashes) of one bit array for all keys."""
    want = math.log2(1 / target)
    return math.ceil(round(LOG2E * n * want, 6)), max(1, round(want))


@dataclass(frozen=True)
class TwoStage:
    """A front filter of all keys (``front`` rate, 1: none), a cut, and a backup filter of the keys below it."""

    cut: int
    front: float
    backup: float
    a_low: float
    b_low: float
    n: int
    target: float
    method: str

    @property
    def bits_per_key(self) -> float:
        return math.log2(1 / self.front) + (self.a_low * math.log2(1 / self.backup) if self.a_low > 0 else 0.0)

    @property
    def expected_rate(self) -> float:
        return self.front * (1 - self.b_low + self.b_low * (self.backup if self.a_low > 0 else 0.0))

    def as_regions(self, size: int, keys_low: int) -> Plan:
        """The plan of two regions that answers at the same rates with the same bits: below the cut the two filters
        act one after the other, so their rates multiply."""
        low = self.front * self.backup if self.a_low > 0 else 0.0
        return Plan((0, self.cut, size), (self.a_low, 1 - self.a_low), (self.b_low, 1 - self.b_low), (low, self.front), (keys_low, self.n - keys_low), self.target, self.method)


def regions_as_two_stages(plan: Plan) -> TwoStage:
    """The front and backup rates that act as a plan of two regions; it needs the lower region's rate not to pass
    the upper one's."""
    if plan.k != 2 or plan.rates[0] > plan.rates[1] + R.TOLERANCE:
        raise ValueError("only two regions, the upper one laxer, are a front and a backup filter")
    return TwoStage(plan.cuts[1], plan.rates[1], plan.rates[0] / plan.rates[1], plan.a[0], plan.b[0], plan.n, plan.target, "sandwich")


def _split(hist: T.Histogram):
    g, h = hist.below()
    return ((t, float(g[t]), float(h[t])) for t in range(1, hist.size))


def single(hist: T.Histogram, target: float, cut: int | None = None) -> TwoStage | None:
    """Scores from the cut on are accepted, the keys below have a backup filter. Without a cut all are tried.
    None if the non-keys above every cut alone pass the target."""
    best = None
    for t, a_low, b_low in _split(hist):
        if cut is not None and t != cut:
            continue
        room = target - (1 - b_low)
        if room <= 0 and a_low > 0 or b_low <= 0:
            continue
        p = TwoStage(t, 1.0, min(1.0, room / b_low) if a_low > 0 else 1.0, a_low, b_low, hist.n, target, "single")
        if a_low <= 0 and 1 - b_low > target:
            continue
        if best is None or round(p.bits_per_key, T.PLACES) < round(best.bits_per_key, T.PLACES):
            best = p
    return best


def sandwich(hist: T.Histogram, target: float, cut: int | None = None) -> TwoStage | None:
    """The best front and backup rates, in closed form for each cut. Where the front rate would pass 1 it is the
    single design; where the backup rate would, the front filter alone."""
    best = None
    for t, a_low, b_low in _split(hist):
        if cut is not None and t != cut:
            continue
        a_up, b_up = 1 - a_low, 1 - b_low
        if a_low <= 0 or b_low <= 0:
            continue
        backup = a_low * b_up / (b_low * a_up) if a_up > 0 else math.inf
        if backup >= 1 or b_up <= 0 and a_up <= 0:
            front, backup = target, 1.0
        else:
            front = target * a_up / b_up if b_up > 0 else math.inf
            if front > 1:
                front, room = 1.0, target - b_up
                if room <= 0:
                    continue
                backup = min(1.0, room / b_low)
        p = TwoStage(t, front, backup, a_low, b_low, hist.n, target, "sandwich")
        if best is None or round(p.bits_per_key, T.PLACES) < round(best.bits_per_key, T.PLACES):
            best = p
    return best


def sandwich_for_budget(hist: T.Histogram, bits: float) -> TwoStage | None:
    """The least rate in a number of bits. The backup's rate does not depend on the budget while the front filter
    takes part; what is left after the backup goes to the front. With less, the backup gets all."""
    per_key, best = bits / max(1, hist.n), None
    for t, a_low, b_low in _split(hist):
        a_up, b_up = 1 - a_low, 1 - b_low
        if a_low <= 0 or b_low <= 0 or a_up <= 0:
            continue
        backup = min(1.0, a_low * b_up / (b_low * a_up))
        spare = per_key - (a_low * math.log2(1 / backup) if backup > 0 else math.inf)
        front = 2.0**-spare if spare >= 0 else 1.0
        if spare < 0:
            backup = 2.0 ** (-per_key / a_low)
        p = TwoStage(t, front, backup, a_low, b_low, hist.n, 0.0, "sandwich")
        p = TwoStage(t, front, backup, a_low, b_low, hist.n, p.expected_rate, "sandwich")
        if best is None or p.target < best.target * (1 - 1e-12):
            best = p
    return best


def geometric_cuts(hist: T.Histogram, k: int, gamma: float) -> list[int]:
    """Cuts such that the non-key queries of a region are gamma times those of the next higher one."""
    _, h = hist.below()
    masses = np.array([gamma ** (k - r) for r in range(1, k + 1)])
    reach = np.cumsum(masses / masses.sum())[:-1]
    return T._spread([int(np.argmax(np.round(h, 12) >= round(float(x), 12))) for x in reach], hist.size)


def geometric_shared(hist: T.Histogram, k: int, target: float, gammas=GAMMAS, most_hashes: int = 40) -> Plan | None:
    """Geometric cuts; one array in which the number of hashes falls evenly from a region to the next higher one,
    to none at the top. Counted like ideal filters of rates 2 ** -hashes; the fewest bits within the target."""
    best = None
    for gamma in gammas:
        cuts = geometric_cuts(hist, k, gamma)
        a, b = hist.shares(cuts)
        for top in range(1, most_hashes + 1):
            hashes = [round(top * (k - 1 - r) / (k - 1)) if k > 1 else top for r in range(k)]
            rates = np.array([2.0**-x for x in hashes])
            if R.expected_rate(b, rates) <= target * (1 + 1e-12):
                size = round(R.size_per_key(a, rates), T.PLACES)
                if best is None or size < best[0]:
                    best = size, cuts, rates
                break
    return plan_of(hist, best[1], best[2], target, "geometric_shared") if best else None


def equal_mass_rates(b, target: float) -> np.ndarray:
    """Rates that give every region the same false-positive mass; regions that would pass 1 are pinned and what
    they leave is dealt to the others."""
    b, pinned = np.asarray(b, dtype=float), np.zeros(len(b), dtype=bool)
    while True:
        free = ~pinned
        if not free.any():
            return np.ones(len(b))
        rates = np.where(pinned, 1.0, max(0.0, target - b[pinned].sum()) / free.sum() / np.maximum(b, 1e-300))
        over = free & (rates > 1 + R.TOLERANCE)
        if not over.any():
            return np.minimum(rates, 1.0)
        pinned |= over


def geometric_separate(hist: T.Histogram, k: int, target: float, gammas=GAMMAS) -> Plan | None:
    """Geometric cuts; a filter for each region, all of the same false-positive mass; the best gamma."""
    best = None
    for gamma in gammas:
        cuts = geometric_cuts(hist, k, gamma)
        a, b = hist.shares(cuts)
        rates = equal_mass_rates(b, target)
        size = round(R.size_per_key(a, rates), T.PLACES)
        if best is None or size < best[0]:
            best = size, cuts, rates
    return plan_of(hist, best[1], best[2], target, "geometric_separate") if best else None


def geometric_shared_for_budget(hist: T.Histogram, k: int, bits: float, gammas=GAMMAS, most_hashes: int = 40) -> float | None:
    """The least expected rate of the one-array design within a number of bits."""
    best = None
    for gamma in gammas:
        a, b = hist.shares(geometric_cuts(hist, k, gamma))
        for top in range(most_hashes, 0, -1):
            rates = np.array([2.0 ** -(round(top * (k - 1 - r) / (k - 1)) if k > 1 else top) for r in range(k)])
            if R.size_per_key(a, rates) * hist.n <= bits * (1 + 1e-12):
                got = R.expected_rate(b, rates)
                best = got if best is None else min(best, got)
                break
    return best


def geometric_separate_for_budget(hist: T.Histogram, k: int, bits: float, gammas=GAMMAS) -> float:
    """The least target rate of the design of separate filters within a number of bits."""
    best = 1.0
    for gamma in gammas:
        a, b = hist.shares(geometric_cuts(hist, k, gamma))
        fits = lambda target: R.size_per_key(a, equal_mass_rates(b, target)) * hist.n <= bits  # noqa: E731, B023
        if not fits(best):
            continue  # no better than what is known
        low, high = 1e-12, best
        for _ in range(40):
            mid = math.sqrt(low * high)
            low, high = (low, mid) if fits(mid) else (mid, high)
        best = high
    return best


def at_budget(plan_at, bits: float) -> float:
    """The least target rate at which ``plan_at(target)`` takes at most ``bits``: bisection on the logarithm."""
    low, high = 1e-12, 1.0
    for _ in range(60):
        mid = math.sqrt(low * high)
        p = plan_at(mid)
        low, high = (low, mid) if p is not None and p.bits_per_key * p.n <= bits else (mid, high)
    return high


def uniform_rates(hist: T.Histogram, k: int, target: float) -> Plan:
    """Best cuts, but the target as every region's rate: what regions give without rates of their own."""
    cuts, _ = T.best_cuts(hist, k)
    return plan_of(hist, cuts, [target] * k, target, "uniform_rates")


def equal_cuts(hist: T.Histogram, k: int, target: float, by: str = "width") -> Plan:
    """Best rates on cuts of equal width or equal key share: what rates give without cuts of their own."""
    cuts = T.even_cuts(hist, k) if by == "width" else T.quantile_cuts(hist, k)
    return plan_of(hist, cuts, R.capped(*hist.shares(cuts), target), target, f"equal_{by}")
