"""False-positive rates of given regions.

a and b are the regions' shares of keys and of non-key queries. Without the bound of 1 the best rates are in
proportion to a / b. With it, regions whose rate would pass 1 are pinned there and the rest of the budget is
dealt again to the others, until none passes: ``capped``. As a pinned region takes less than its proportional
part, the others only gain, so the pinned ones are a prefix in the order of a / b: ``capped_sql`` finds that
prefix with window functions, for one plan or for many at once.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TOLERANCE = 1e-12


def relaxed(a, b, target: float) -> np.ndarray:
    """target * a / b, which may pass 1; 0 without keys; infinite with keys and no queries."""
    a, b = np.asarray(a, dtype=float), np.asarray(b, dtype=float)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(a > 0, target * a / b, 0.0)


def capped(a, b, target: float) -> np.ndarray:
    """The best rates that are at most 1 with sum(b * rate) <= target."""
    a, b = np.asarray(a, dtype=float), np.asarray(b, dtype=float)
    has, pinned = a > 0, (a > 0) & (b <= 0)
    while True:
        free = has & ~pinned
        if not free.any():
            return np.where(pinned, 1.0, 0.0)
        rates = np.where(free, max(0.0, target - b[pinned].sum()) / a[free].sum() * np.divide(a, b, out=np.zeros_like(a), where=b > 0), np.where(pinned, 1.0, 0.0))
        over = free & (rates > 1 + TOLERANCE)
        if not over.any():
            return np.minimum(rates, 1.0)
        pinned = pinned | over


def for_budget(a, b, bits_per_key: float) -> np.ndarray:
    """The rates of least sum(b * rate) with sum(a * log2(1 / rate)) <= bits_per_key."""
    a, b = np.asarray(a, dtype=float), np.asarray(b, dtype=float)
    has, pinned = a > 0, (a > 0) & (b <= 0)
    while True:
        free = has & ~pinned
        if not free.any():
            return np.where(pinned, 1.0, 0.0)
        level = (np.sum(a[free] * np.log2(b[free] / a[free])) - bits_per_key) / a[free].sum()
        rates = np.where(pinned, 1.0, 0.0)
        rates[free] = 2.0**level * a[free] / b[free]
        over = free & (rates > 1 + TOLERANCE)
        if not over.any():
            return np.minimum(rates, 1.0)
        pinned = pinned | over


def capped_many(a: np.ndarray, b: np.ndarray, target: float) -> np.ndarray:
    """``capped`` for every row of a and b at once: as many steps as a row has regions, at most."""
    has, pinned = a > 0, (a > 0) & (b <= 0)
    ratio = np.divide(a, b, out=np.zeros_like(a), where=b > 0)
    while True:
        free = has & ~pinned
        share = np.where(free, a, 0.0).sum(axis=1)
        room = np.maximum(0.0, target - np.where(pinned, b, 0.0).sum(axis=1))
        rates = np.where(free, np.divide(room, share, out=np.zeros_like(share), where=share > 0)[:, None] * ratio, np.where(pinned, 1.0, 0.0))
        over = free & (rates > 1 + TOLERANCE)
        if not over.any():
            return np.minimum(rates, 1.0)
        pinned = pinned | over


def for_budget_many(a: np.ndarray, b: np.ndarray, bits_per_key: float) -> np.ndarray:
    """``for_budget`` for every row of a and b at once."""
    has, pinned = a > 0, (a > 0) & (b <= 0)
    safe_a, safe_b = np.where(a > 0, a, 1.0), np.where(b > 0, b, 1.0)
    while True:
        free = has & ~pinned
        share = np.where(free, a, 0.0).sum(axis=1)
        given = np.where(free, a * np.log2(safe_b / safe_a), 0.0).sum(axis=1) - bits_per_key
        level = np.divide(given, share, out=np.zeros_like(share), where=share > 0)
        rates = np.where(free, np.exp2(level)[:, None] * safe_a / safe_b, np.where(pinned, 1.0, 0.0))
        over = free & (rates > 1 + TOLERANCE)
        if not over.any():
            return np.minimum(rates, 1.0)
        pinned = pinned | over


def sizes_per_key(a: np.ndarray, rates: np.ndarray) -> np.ndarray:
    """``size_per_key`` of every row."""
    with np.errstate(divide="ignore"):
        bits = np.where(a > 0, a * -np.log2(np.where(a > 0, rates, 1.0)), 0.0)
    return bits.sum(axis=1)


def size_per_key(a, rates) -> float:
    """sum(a * log2(1 / rate)): bits for each key with ideal filters; infinite if a region with keys has rate 0."""
    total = 0.0
    for share, rate in zip(a, rates, strict=True):
        if share > 0:
            if rate <= 0:
                return math.inf
            total += float(share) * math.log2(1 / float(rate))
    return total


def expected_rate(b, rates) -> float:
    return float(np.dot(b, rates))


def capped_sql(regions: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """``capped`` for every plan in (by..., region, a, b, target), with columns rate and pinned."""
    order = Window.partitionBy(*by).orderBy(F.desc("ratio"), F.desc("region"))
    rows = regions.withColumn("ratio", F.when(F.col("a") <= 0, F.lit(0.0)).when(F.col("b") <= 0, F.lit(float("inf"))).otherwise(F.col("a") / F.col("b")))
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("a_before", F.coalesce(F.sum("a").over(before), F.lit(0.0))).withColumn("b_before", F.coalesce(F.sum("b").over(before), F.lit(0.0)))
    # the share that would be left for each unit of a, were all before this region pinned
    rows = rows.withColumn("scale", F.when(1 - F.col("a_before") > 1e-15, F.greatest(F.lit(0.0), F.col("target") - F.col("b_before")) / (1 - F.col("a_before"))).otherwise(F.lit(0.0)))
    rows = rows.withColumn("free", (F.col("ratio") < float("inf")) & (F.col("scale") * F.col("ratio") <= 1 + TOLERANCE))
    all_ = Window.partitionBy(*by)
    first_free = F.max(F.when(F.col("free"), F.col("ratio"))).over(all_)
    scale = F.max_by("scale", F.when(F.col("free"), F.struct("ratio", "region"))).over(all_)
    pinned = first_free.isNull() | (F.col("ratio") > first_free)
    rows = rows.withColumn("pinned", pinned & (F.col("a") > 0)).withColumn("rate", F.when(F.col("a") <= 0, F.lit(0.0)).when(F.col("pinned"), F.lit(1.0)).otherwise(F.least(F.lit(1.0), scale * F.col("ratio"))))
    return rows.drop("ratio", "a_before", "b_before", "scale", "free")
