"""Cuts of the score axis that make the divergence of region shares largest.

The divergence of a set of regions is a sum with one term for each run of segments, so the best split of the
first e segments into j regions is the best split of some first b segments into j - 1 regions and the run [b, e).
One table of that holds the answer for every prefix and every number of regions; the planners share it.
It depends on the number of segments only, never on the data volume. ``best_cuts_sql`` is the same in DataFrames.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PLACES = 9  # values are compared at so many places; the smallest boundary wins a tie


@dataclass(frozen=True)
class Histogram:
    """Keys and non-key queries of each segment. ``alpha`` is added to every segment's queries, so that a segment
    without a sampled query does not count as free of them."""

    kc: tuple[int, ...]
    qc: tuple[int, ...]
    alpha: float = 0.5

    def __post_init__(self):
        if len(self.kc) != len(self.qc) or not self.kc:
            raise ValueError("a histogram needs as many key counts as query counts, and one at least")

    @property
    def size(self) -> int:
        return len(self.kc)

    @property
    def n(self) -> int:
        return int(sum(self.kc))

    def below(self) -> tuple[np.ndarray, np.ndarray]:
        """Shares of keys and of queries below each boundary 0..N."""
        k = np.concatenate([[0], np.cumsum(np.array(self.kc, dtype=float))])
        q = np.concatenate([[0], np.cumsum(np.array(self.qc, dtype=float) + self.alpha)])
        return k / max(k[-1], 1e-300), q / max(q[-1], 1e-300)

    def shares(self, cuts) -> tuple[np.ndarray, np.ndarray]:
        g, h = self.below()
        cuts = list(cuts)
        return np.diff(g[cuts]), np.diff(h[cuts])

    def keys_in(self, cuts) -> np.ndarray:
        return np.diff(np.concatenate([[0], np.cumsum(np.array(self.kc))])[list(cuts)])

    @classmethod
    def of(cls, frame: DataFrame, alpha: float = 0.5) -> Histogram:
        """From (seg, kc, qc) with one row for each segment: a bounded collect."""
        rows = sorted(frame.select("seg", "kc", "qc").collect())
        return cls(tuple(r["kc"] for r in rows), tuple(r["qc"] for r in rows), alpha)


def term(a, b):
    """a * log2(a / b): 0 without keys, infinite with keys and no queries."""
    a, b = np.asarray(a, dtype=float), np.asarray(b, dtype=float)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(a > 0, np.where(b > 0, a * np.log2(np.where(a > 0, a, 1) / np.where(b > 0, b, 1)), np.inf), 0.0)


def divergence(a, b) -> float:
    return float(np.sum(term(a, b)))


@dataclass(frozen=True)
class Table:
    """best[j][e]: largest divergence sum of the first e segments in j regions; last[j][e]: where the last begins."""

    best: np.ndarray
    last: np.ndarray
    #: how many runs of segments were weighed
    steps: int = 0

    def cuts(self, e: int, j: int) -> list[int]:
        out = [e]
        while j > 1:
            e = int(self.last[j][e])
            out.append(e)
            j -= 1
        return [0, *reversed(out)]


def dp_table(hist: Histogram, k: int) -> Table:
    if not 1 <= k <= hist.size:
        raise ValueError(f"{k} regions need as many segments; there are {hist.size}")
    g, h = hist.below()
    n = hist.size
    best, last = np.full((k + 1, n + 1), -np.inf), np.zeros((k + 1, n + 1), dtype=int)
    best[1, 1:] = term(g[1:], h[1:])
    steps = n
    for j in range(2, k + 1):
        for e in range(j, n + 1):
            b = np.arange(j - 1, e)
            value = best[j - 1, b] + term(g[e] - g[b], h[e] - h[b])
            at = int(np.argmax(np.round(value, PLACES)))
            best[j, e], last[j, e] = value[at], b[at]
            steps += len(b)
    return Table(best, last, steps)


def best_cuts(hist: Histogram, k: int) -> tuple[list[int], float]:
    """Boundaries 0 = c0 < ... < ck = N of the largest divergence, and that divergence."""
    t = dp_table(hist, k)
    return t.cuts(hist.size, k), float(t.best[k, hist.size])


def exhaustive_cuts(hist: Histogram, k: int):
    """All cut sets, for tests on few segments."""
    return ([0, *c, hist.size] for c in itertools.combinations(range(1, hist.size), k - 1))


def pair_terms(hist: DataFrame, alpha: float = 0.5) -> DataFrame:
    """(b, e, a_share, b_share, term) of every run of segments; N * (N + 1) / 2 rows."""
    run = Window.orderBy("seg").rowsBetween(Window.unboundedPreceding, 0)
    pre = hist.select((F.col("seg") + 1).alias("at"), F.sum("kc").over(run).cast("double").alias("k"), F.sum(F.col("qc") + F.lit(alpha)).over(run).alias("q"))
    pre = pre.unionByName(hist.sparkSession.createDataFrame([(0, 0.0, 0.0)], "at int, k double, q double"))
    total = pre.agg(F.max("k").alias("kt"), F.max("q").alias("qt"))
    lo, hi = pre.select(F.col("at").alias("b"), F.col("k").alias("k0"), F.col("q").alias("q0")), pre.select(F.col("at").alias("e"), F.col("k").alias("k1"), F.col("q").alias("q1"))
    share_a, share_b = (F.col("k1") - F.col("k0")) / F.col("kt"), (F.col("q1") - F.col("q0")) / F.col("qt")
    # segments are few whatever the data: this join is over boundaries, and its right side is broadcast
    pairs = lo.join(F.broadcast(hi), F.col("b") < F.col("e")).join(F.broadcast(total))
    return pairs.select("b", "e", share_a.alias("a_share"), share_b.alias("b_share")).withColumn("term", F.when(F.col("a_share") <= 0, F.lit(0.0)).otherwise(F.col("a_share") * F.log2(F.col("a_share") / F.col("b_share"))))


def dp_table_sql(hist: DataFrame, k: int, alpha: float = 0.5) -> DataFrame:
    """(e, j, best, last) by DataFrame joins, one for each further region."""
    pairs = pair_terms(hist, alpha).select("b", "e", "term")
    level = pairs.where("b = 0").select("e", F.lit(1).alias("j"), F.col("term").alias("best"), F.lit(0).alias("last"))
    out = level
    for j in range(2, k + 1):
        step = level.select(F.col("e").alias("b"), F.col("best").alias("before")).join(F.broadcast(pairs.where("b > 0")), "b")
        value = F.col("before") + F.col("term")
        pick = F.struct(F.round(value, PLACES).alias("r"), (-F.col("b")).alias("nb"), value.alias("v"))
        level = step.groupBy("e").agg(F.max(pick).alias("p")).select("e", F.lit(j).alias("j"), F.col("p.v").alias("best"), (-F.col("p.nb")).alias("last"))
        out = out.unionByName(level)
    return out


def quantile_cuts(hist: Histogram, k: int) -> list[int]:
    """Cuts at equal shares of the keys, one segment a region at least."""
    g, _ = hist.below()
    return _spread([int(np.argmax(g >= r / k - 1e-12)) for r in range(1, k)], hist.size)


def even_cuts(hist: Histogram, k: int) -> list[int]:
    return _spread([round(r * hist.size / k) for r in range(1, k)], hist.size)


def _spread(inner: list[int], n: int) -> list[int]:
    """Inner cuts made strictly increasing inside 0..n."""
    out, k = [0], len(inner) + 1
    for r, c in enumerate(inner, 1):
        out.append(min(max(c, out[-1] + 1), n - (k - r)))
    return [*out, n]
