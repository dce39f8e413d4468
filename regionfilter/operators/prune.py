"""Semi-join reduction: a filter of a dimension's keys in front of a fact table's shuffle join."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..plans.planner import Plan
from .filters import probe


def reduce_join(fact: DataFrame, dim: DataFrame, filt: DataFrame, plan: Plan, how: str = "inner", **options) -> DataFrame:
    """fact (elem, seg, ...) joined to dim (elem, ...); rows that the filter rules out never reach the shuffle."""
    return probe(fact, filt, plan, **options).where("maybe").drop("region", "maybe").join(dim, "elem", how)
