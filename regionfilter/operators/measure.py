"""Measures of plans, filters and scorers."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planner import Plan


def relaxed_bits(n: int, c: float, target: float, divergence: float) -> float:
    """Size of relaxed regions by the identity: c * n * (log2(1 / target) - divergence)."""
    return c * n * (math.log2(1 / target) - divergence)


def saved_bits(plan: Plan) -> float:
    """Bits saved against one plain filter of the same kind, the scorer counted."""
    return plan.c * plan.n * math.log2(1 / plan.target) - plan.total_bits


def answers(probed: DataFrame, *by: str) -> DataFrame:
    """(by..., n_queries, false_positives, rate, n_keys, false_negatives) from part and maybe; the rate is over the
    non-keys that took no part in training."""
    held = F.col("part") == "eval"
    q, fp = F.count_if(held), F.count_if(held & F.col("maybe"))
    return probed.groupBy(*by).agg(
        q.alias("n_queries"), fp.alias("false_positives"), F.when(q > 0, fp / q).alias("rate"),
        F.count_if(F.col("part") == "key").alias("n_keys"), F.count_if((F.col("part") == "key") & ~F.col("maybe")).alias("false_negatives"),
    )


def f1(scored: DataFrame, cut: float = 0.5) -> DataFrame:
    """One row: tp, fp, fn, precision, recall, f1 of score >= cut against is_key."""
    says, is_ = F.col("score") >= cut, F.col("is_key") == 1
    counts = scored.agg(F.count_if(says & is_).alias("tp"), F.count_if(says & ~is_).alias("fp"), F.count_if(~says & is_).alias("fn"))
    tp = F.col("tp")
    ratio = lambda x, y: F.when(y > 0, x / y)
    return counts.select("*", ratio(tp, tp + F.col("fp")).alias("precision"), ratio(tp, tp + F.col("fn")).alias("recall"), ratio(2 * tp, 2 * tp + F.col("fp") + F.col("fn")).alias("f1"))


def space_ratio(curve: DataFrame, of: str = "region") -> DataFrame:
    """(method, target, ratio): all bits of each method, its scorer's included, over those of one at the same target."""
    own = curve.where(F.col("method") == of).select("target", F.col("total_bits").alias("own"))
    return curve.join(own, "target").select("method", "target", (F.col("total_bits") / F.col("own")).alias("ratio"))


def dominated(curve: DataFrame) -> DataFrame:
    """The points of a curve that another point beats: fewer bits in all and no higher rate, or the other way round."""
    o = curve.select(F.col("total_bits").alias("bits2"), F.col("expected_rate").alias("rate2"))
    better = (F.col("bits2") <= F.col("total_bits")) & (F.col("rate2") <= F.col("expected_rate")) & ((F.col("bits2") < F.col("total_bits")) | (F.col("rate2") < F.col("expected_rate")))
    return curve.join(F.broadcast(o), better, "left_semi")  # a curve has one row for each method and target


def plateau(curve: DataFrame) -> DataFrame:
    """(target, saved, change): bits saved against the ideal filter as the target falls, and from target to target."""
    w = Window.orderBy(F.desc("target"))
    saved = F.col("ideal_bits") - F.col("backup_bits")
    return curve.select("target", saved.alias("saved"), (saved - F.lag(saved).over(w)).alias("change"))


def within_binomial(rate: float, target: float, queries: int, z: float = 3.0) -> bool:
    """Whether a measured rate is no more than z standard deviations above the target."""
    return rate <= target + z * math.sqrt(max(target * (1 - target), 1e-12) / max(1, queries))
