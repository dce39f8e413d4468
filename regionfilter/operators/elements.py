"""Elements: distinct keys and non-keys, and their repeatable split.

A universe has (elem string, is_key int, features...). An element that is both is a key. A null element is never
a key and never stored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket
from ..schemas import require


def universe(df: DataFrame, *features: str) -> DataFrame:
    """One row for each element; key wins, features are the least of each."""
    require(df, "elem", "is_key", *features)
    return df.where(F.col("elem").isNotNull()).groupBy("elem").agg(F.max("is_key").cast("int").alias("is_key"), *(F.min(f).alias(f) for f in features))


def split(df: DataFrame, train_percent: int = 40) -> DataFrame:
    """df with part: 'key', or of the non-keys 'train' or 'eval' by a hash bucket of the element. Narrow."""
    require(df, "elem", "is_key")
    return df.withColumn("part", F.when(F.col("is_key") == 1, "key").when(bucket(F.col("elem"), "split") < train_percent, "train").otherwise("eval"))


def from_keys(keys: DataFrame, queries: DataFrame) -> DataFrame:
    """(elem, is_key, weight): distinct keys, and non-key queries with how often each is asked."""
    require(keys, "elem"), require(queries, "elem")
    k = keys.where("elem is not null").select("elem").distinct()
    q = queries.where("elem is not null").groupBy("elem").agg(F.count("*").alias("weight")).join(k, "elem", "left_anti")
    return k.select("elem", F.lit(1).alias("is_key"), F.lit(1).cast("bigint").alias("weight")).unionByName(q.select("elem", F.lit(0).alias("is_key"), "weight"))
