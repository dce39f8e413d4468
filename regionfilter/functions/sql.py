"""SQL access: scalar functions that the analyzer inlines, table functions, and an aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession

from pyspark.sql.functions import pandas_udf, udtf

from ..schemas import PLAN


def divergence_of(kc: pd.Series, qc: pd.Series) -> float:
    """Divergence of the shares of two count columns over a group, half a query added to each row."""
    from ..plans.thresholds import divergence

    q = qc + 0.5
    return divergence(kc / max(kc.sum(), 1e-300), q / q.sum())


class BestCuts:
    """best_cuts(TABLE(seg, kc, qc), k): the regions of largest divergence."""

    def __init__(self):
        self.rows, self.k = [], 1

    def eval(self, row, k: int):
        self.rows.append((row["seg"], row["kc"], row["qc"]))
        self.k = k

    def terminate(self):
        from regionfilter.plans import thresholds as T

        rows = sorted(self.rows)
        if rows:
            cuts, d = T.best_cuts(T.Histogram(tuple(r[1] for r in rows), tuple(r[2] for r in rows)), self.k)
            for r in range(self.k):
                yield r + 1, cuts[r], cuts[r + 1], d


class PlanRegions:
    """plan_regions(TABLE(seg, kc, qc), k, target): the plan of the top-boundary search."""

    def __init__(self):
        self.rows, self.k, self.target = [], 1, 0.01

    def eval(self, row, k: int, target: float):
        self.rows.append((row["seg"], row["kc"], row["qc"]))
        self.k, self.target = k, float(target)

    def terminate(self):
        from regionfilter.plans import planner
        from regionfilter.plans import thresholds as T

        rows = sorted(self.rows)
        if rows:
            yield from planner.top_boundary(T.Histogram(tuple(r[1] for r in rows), tuple(r[2] for r in rows)), self.k, self.target).rows()


SCALARS = {
    "kl_term": "(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN CASE WHEN a <= 0 THEN 0 WHEN b > 0 THEN a * log2(a / b) END",
    "seg_of": "(score DOUBLE, n INT) RETURNS INT RETURN CAST(least(n - 1, greatest(0, floor(least(greatest(coalesce(nanvl(round(score, 9), 0D), 0D), 0D), 1D) * n))) AS INT)",
    "ideal_bits": "(n BIGINT, rate DOUBLE) RETURNS DOUBLE RETURN CASE WHEN rate >= 1 OR n = 0 THEN 0 ELSE n * log2(1 / rate) END",
}


def register(spark: SparkSession) -> None:
    """kl_term, seg_of, ideal_bits; divergence_of; best_cuts and plan_regions, in this session."""
    for name, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("divergence_of", pandas_udf(divergence_of, "double"))
    spark.udtf.register("best_cuts", udtf(BestCuts, returnType="region int, seg_lo int, seg_hi int, divergence double"))
    spark.udtf.register("plan_regions", udtf(PlanRegions, returnType=PLAN))
