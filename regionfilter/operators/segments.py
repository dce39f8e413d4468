"""Histograms over score segments: one pass, at most N rows from each task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.formulas import kl_term, seg_of
from ..schemas import require


def histogram(scored: DataFrame, n: int, weight: Column | None = None, keys: str = "part = 'key'", queries: str = "part = 'train'") -> DataFrame:
    """(seg, kc, qc), one row for each of the n segments, from rows with a score or a seg."""
    rows = scored if "seg" in scored.columns else scored.withColumn("seg", seg_of(F.col("score"), n))
    w = F.lit(1) if weight is None else weight
    counts = rows.groupBy("seg").agg(F.sum(F.when(F.expr(keys), 1).otherwise(0)).alias("kc"), F.sum(F.when(F.expr(queries), w).otherwise(0)).alias("qc"))
    every = scored.sparkSession.range(n).select(F.col("id").cast("int").alias("seg"))
    return every.join(counts, "seg", "left").select("seg", F.coalesce("kc", F.lit(0)).cast("bigint").alias("kc"), F.coalesce("qc", F.lit(0)).cast("bigint").alias("qc"))


def cumulate(hist: DataFrame) -> DataFrame:
    """hist with g and h: shares of keys and queries in segments up to each. A histogram has N rows, so its one
    window partition is bounded."""
    run, all_ = Window.orderBy("seg").rowsBetween(Window.unboundedPreceding, 0), Window.partitionBy()
    return hist.select("*", (F.sum("kc").over(run) / F.sum("kc").over(all_)).alias("g"), (F.sum("qc").over(run) / F.sum("qc").over(all_)).alias("h"))


def roll_up(hist: DataFrame, cuts: list[int], alpha: float = 0.0) -> DataFrame:
    """(region, seg_lo, seg_hi, n_keys, a, b) of the regions between cuts."""
    spark = require(hist, "seg", "kc", "qc").sparkSession
    regions = spark.createDataFrame([(r + 1, cuts[r], cuts[r + 1]) for r in range(len(cuts) - 1)], "region int, seg_lo int, seg_hi int")
    rows = hist.join(F.broadcast(regions), (F.col("seg") >= F.col("seg_lo")) & (F.col("seg") < F.col("seg_hi")))
    sums = rows.groupBy("region", "seg_lo", "seg_hi").agg(F.sum("kc").alias("n_keys"), F.sum(F.col("qc") + F.lit(alpha)).alias("q"))
    all_ = Window.partitionBy()
    return sums.select("region", "seg_lo", "seg_hi", "n_keys", (F.col("n_keys") / F.sum("n_keys").over(all_)).alias("a"), (F.col("q") / F.sum("q").over(all_)).alias("b"))


def divergence(regions: DataFrame) -> DataFrame:
    """One row: divergence of the bounded terms, and whether a region with keys has no queries."""
    return regions.agg(F.coalesce(F.sum(kl_term(F.col("a"), F.col("b"))), F.lit(0.0)).alias("divergence"), F.coalesce(F.bool_or((F.col("a") > 0) & (F.col("b") <= 0)), F.lit(False)).alias("unbounded"))


def seg_between(score: Column, edges: list[float]) -> Column:
    """Segment 0..len(edges) of a score: how many edges it has reached. Null and NaN fall in the lowest."""
    safe = F.coalesce(F.nanvl(F.round(score.cast("double"), 9), F.lit(0.0)), F.lit(0.0))
    return sum((F.when(safe >= F.lit(e), 1).otherwise(0) for e in sorted(edges)), F.lit(0)).cast("int")


def quantile_edges(scored: DataFrame, n: int) -> list[float]:
    """Edges 0 < e1 < ... < 1 at score quantiles: slices where the mass is. A bounded answer of one aggregation. With
    ``seg_between`` they take the place of equal slices; histograms and planners only see segments."""
    got = scored.agg(F.percentile_approx("score", [i / n for i in range(1, n)], 10_000).alias("q")).first()["q"] or []
    return sorted({round(float(x), 9) for x in got if 0 < x < 1})


def drift(old: DataFrame, new: DataFrame) -> DataFrame:
    """(variation, kl) between the query shares of two histograms; shares smoothed by half a query for kl."""
    both = old.select("seg", F.col("qc").alias("q1")).join(new.select("seg", F.col("qc").alias("q2")), "seg", "full").select("seg", F.coalesce("q1", F.lit(0)).alias("q1"), F.coalesce("q2", F.lit(0)).alias("q2"))
    all_ = Window.partitionBy()
    share = both.select(
        (F.col("q1") / F.sum("q1").over(all_)).alias("p1"), (F.col("q2") / F.sum("q2").over(all_)).alias("p2"),
        ((F.col("q1") + 0.5) / F.sum(F.col("q1") + 0.5).over(all_)).alias("s1"), ((F.col("q2") + 0.5) / F.sum(F.col("q2") + 0.5).over(all_)).alias("s2"),
    )
    return share.agg((F.sum(F.abs(F.col("p1") - F.col("p2"))) / 2).alias("variation"), F.sum(F.col("s2") * F.log2(F.col("s2") / F.col("s1"))).alias("kl"))
