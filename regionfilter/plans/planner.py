"""Planners: from a histogram to regions with rates and sizes."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from ..functions.formulas import LOG2E
from ..schemas import PLAN
from . import rates as R
from . import thresholds as T


@dataclass(frozen=True)
class Plan:
    """Regions [cuts[r], cuts[r+1]) with key shares, query shares, rates and key counts. ``model_bits`` is the size
    of the scorer; ``c`` the bits constant of the filter kind that sizes are counted with."""

    cuts: tuple[int, ...]
    a: tuple[float, ...]
    b: tuple[float, ...]
    rates: tuple[float, ...]
    n_keys: tuple[int, ...]
    target: float
    method: str = "region"
    model_bits: float = 0.0
    c: float = 1.0
    notes: tuple[str, ...] = field(default=())

    @property
    def k(self) -> int:
        return len(self.rates)

    @property
    def n(self) -> int:
        return sum(self.n_keys)

    @property
    def bits_per_key(self) -> float:
        return self.c * R.size_per_key(self.a, self.rates)

    @property
    def backup_bits(self) -> float:
        return self.n * self.bits_per_key

    @property
    def total_bits(self) -> float:
        return self.backup_bits + self.model_bits

    @property
    def expected_rate(self) -> float:
        return R.expected_rate(self.b, self.rates)

    @property
    def divergence(self) -> float:
        return T.divergence(self.a, self.b)

    def built(self, r: int, sizing: str = "formula") -> tuple[int, int]:
        """(bits, hashes) of region r's array; (0, 0) where nothing is stored. 'exact' sizing takes the least array
        whose rate by the standard formula, with a whole number of hashes, is at most the region's."""
        n, rate = self.n_keys[r], self.rates[r]
        if n == 0 or rate >= 1:
            return 0, 0
        want = math.log2(1 / max(rate, 1e-18))
        hashes = max(1, round(want))
        if sizing == "exact":
            return max(32, math.ceil(1 / (1 - (1 - rate ** (1 / hashes)) ** (1 / (hashes * n))))), hashes
        return max(32, math.ceil(round(LOG2E * n * want, 6))), hashes

    def rows(self, sizing: str = "formula") -> list[tuple]:
        return [(r + 1, self.cuts[r], self.cuts[r + 1], float(self.a[r]), float(self.b[r]), float(self.rates[r]), int(self.n_keys[r]), *self.built(r, sizing)) for r in range(self.k)]

    def frame(self, spark: SparkSession, sizing: str = "formula") -> DataFrame:
        return spark.createDataFrame(self.rows(sizing), PLAN)


def plan_of(hist: T.Histogram, cuts, rates, target: float, method: str) -> Plan:
    a, b = hist.shares(cuts)
    return Plan(tuple(cuts), tuple(a.tolist()), tuple(b.tolist()), tuple(float(x) for x in rates), tuple(int(x) for x in hist.keys_in(cuts)), target, method)


def relaxed(hist: T.Histogram, k: int, target: float) -> Plan:
    """Best cuts with relaxed rates; ``notes`` says if one passes 1, for then the plan is only a bound."""
    cuts, _ = T.best_cuts(hist, k)
    rates = R.relaxed(*hist.shares(cuts), target)
    p = plan_of(hist, cuts, rates, target, "relaxed")
    return p if relaxation_is_tight(p) else Plan(**{**p.__dict__, "notes": ("a rate passes 1",)})


def relaxed_then_cap(hist: T.Histogram, k: int, target: float, table: T.Table | None = None) -> Plan:
    """The cuts of the relaxed problem with the best rates that are at most 1."""
    table = table or T.dp_table(hist, k)
    cuts = table.cuts(hist.size, k)
    return plan_of(hist, cuts, R.capped(*hist.shares(cuts), target), target, "relax_cap")


def top_boundary(hist: T.Histogram, k: int, target: float, table: T.Table | None = None) -> Plan:
    """For every start of the top region, the best k - 1 regions below it; the smallest plan wins. Given the top
    region's share, the sum of terms below it is still what counts, so one table serves all starts."""
    if k == 1:
        return plan_of(hist, [0, hist.size], R.capped(*hist.shares([0, hist.size]), target), target, "region")
    table = table or T.dp_table(hist, k - 1)
    cuts, a, b = _all_starts(hist, table, k)
    rates = R.capped_many(a, b, target)
    best = int(np.argmin(np.round(R.sizes_per_key(a, rates), T.PLACES)))
    return plan_of(hist, cuts[best].tolist(), rates[best], target, "region")


def _all_starts(hist: T.Histogram, table: T.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cuts, key shares and query shares of k regions for every start of the top one, a row each."""
    starts = np.arange(k - 1, hist.size)
    cuts = np.zeros((len(starts), k + 1), dtype=int)
    cuts[:, k], cuts[:, k - 1] = hist.size, starts
    for j in range(k - 1, 1, -1):
        cuts[:, j - 1] = table.last[j][cuts[:, j]]
    g, h = hist.below()
    return cuts, np.diff(g[cuts], axis=1), np.diff(h[cuts], axis=1)


def exhaustive(hist: T.Histogram, k: int, target: float) -> Plan:
    """The best of all cut sets; for tests."""
    sized = ((round(R.size_per_key(hist.shares(c)[0], r := R.capped(*hist.shares(c), target)), T.PLACES), c, r) for c in T.exhaustive_cuts(hist, k))
    _, cuts, rates = min(sized, key=lambda x: (x[0], x[1]))
    return plan_of(hist, cuts, rates, target, "exhaustive")


def for_budget(hist: T.Histogram, k: int, bits: float, c: float = 1.0) -> Plan:
    """The least rate within a number of bits: the dual of ``top_boundary``, by the same search of the top region."""
    per_key = max(0.0, bits) / (c * max(1, hist.n))
    if k == 1:
        cuts, (x, y) = np.array([[0, hist.size]]), (z[None, :] for z in hist.shares([0, hist.size]))
    else:
        table = T.dp_table(hist, k)
        cuts, x, y = _all_starts(hist, table, k)
        whole = table.cuts(hist.size, k)
        ax, by = hist.shares(whole)
        cuts, x, y = np.vstack([whole, cuts]), np.vstack([ax, x]), np.vstack([by, y])
    rates = R.for_budget_many(x, y, per_key)
    got = (y * rates).sum(axis=1)
    best = int(np.flatnonzero(got <= got.min() * (1 + 1e-12))[0])
    return plan_of(hist, cuts[best].tolist(), rates[best], float(got[best]), "region")


def ratio_is_monotone(hist: T.Histogram) -> tuple[bool, int]:
    """Whether keys-to-queries never falls from a segment to the next higher, and how often it does; by products
    of counts, without a division."""
    kc, qc = np.array(hist.kc, dtype=object), np.array(hist.qc, dtype=object)
    used = [i for i in range(hist.size) if kc[i] or qc[i]]
    falls = sum(kc[j] * qc[i] < kc[i] * qc[j] for i, j in zip(used, used[1:]))
    return falls == 0, int(falls)


def relaxation_is_tight(plan: Plan) -> bool:
    """Whether no relaxed rate passes 1, so that the relaxed solution is the general one."""
    return bool(np.all(R.relaxed(plan.a, plan.b, plan.target) <= 1 + R.TOLERANCE))


def sweep_k(hist: T.Histogram, ks, target: float) -> list[Plan]:
    """A plan for each number of regions; one table serves them all."""
    table = T.dp_table(hist, max(ks))
    return [top_boundary(hist, k, target, table) for k in ks]


def pick_k(hist: T.Histogram, target: float, most: int = 25, enough: float = 0.95) -> int:
    """The least number of regions that saves ``enough`` of what ``most`` regions save."""
    most = min(most, hist.size)
    plans = sweep_k(hist, range(1, most + 1), target)
    plain = math.log2(1 / target)
    goal = enough * (plain - plans[-1].bits_per_key)
    return next(p.k for p in plans if plain - p.bits_per_key >= goal - 1e-12)


def worthwhile(plan: Plan) -> bool:
    """Whether the regions with the scorer take fewer bits than one plain filter."""
    return plan.total_bits < plan.c * plan.n * math.log2(1 / plan.target)


def plan_groups(hists: DataFrame, by: str, k: int, target: float, alpha: float = 0.5) -> DataFrame:
    """A plan for every group of (by, seg, kc, qc): one shuffle of histograms, no trip to the driver."""

    def one(key, rows: pd.DataFrame) -> Iterator[pd.DataFrame] | pd.DataFrame:
        rows = rows.sort_values("seg")
        p = top_boundary(T.Histogram(tuple(rows["kc"].tolist()), tuple(rows["qc"].tolist()), alpha), k, target)
        out = pd.DataFrame(p.rows(), columns=[f.split()[0] for f in PLAN.split(", ")])
        out.insert(0, by, key[0])
        return out

    return hists.groupBy(by).applyInPandas(one, f"{by} {dict(hists.dtypes)[by]}, {PLAN}")
