"""Workloads on the given tables: who is a key, and what a scorer may see.

Each gives (elem, is_key, c1, c2) with two small integer features, by rules that any SQL engine can repeat; some
give more features for the MLlib scorers. ``SQL`` holds the same rules in DuckDB's SQL.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.hashing import bucket, u60, u60_sql
from .operators import elements, scorers, segments
from .plans.thresholds import Histogram
from .sources.io import staged, table

CELLS = ("c1", "c2")
#: components of a vector in embeddings
VECTOR = 64
URL_COPIES, URL_NOISE = 40, (1, 2, 5, 10, 20, 50)


def line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weak signal: line items whose price is high for their quantity, with noise that depends on the discount."""
    t = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    elem = F.concat_ws("-", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    c1 = F.round(100 * F.col("l_discount")).cast("int")
    noise = bucket(elem, "noise", 1000) < 20 + 26 * c1
    c2 = F.least(F.lit(20), F.floor(F.col("l_extendedprice") / F.col("l_quantity") / 200)).cast("int")
    is_key = ((F.col("l_extendedprice") > 2000 * F.col("l_quantity")) != noise).cast("int")
    price = F.col("l_extendedprice") / F.col("l_quantity")
    return t.select(elem.alias("elem"), is_key.alias("is_key"), c1.alias("c1"), c2.alias("c2"), price.alias("price"), F.col("l_discount").alias("discount"), F.col("l_tax").alias("tax"))


def url(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strong signal: versions of page addresses; keys have a query and no www, with noise of six strengths."""
    t = table(spark, sf_dir, "pages", "url").where("url is not null").withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(URL_COPIES - 1))))
    elem, z = F.concat("url", F.lit("/v"), F.col("i").cast("string")), F.pmod(F.length("url") + F.col("i"), F.lit(6))
    rule = F.col("url").contains("?") & ~F.col("url").contains("://www")
    noise = bucket(elem, "noise", 1000) < F.element_at(F.array(*map(F.lit, URL_NOISE)), z + 1)
    shape = F.col("url").contains("?").cast("int") + 2 * F.col("url").contains("://www").cast("int") + 4 * F.col("url").startswith("https").cast("int")
    return t.select(elem.alias("elem"), (rule != noise).cast("int").alias("is_key"), shape.alias("c1"), z.cast("int").alias("c2"), "url")


def url_features(df: DataFrame) -> DataFrame:
    """The seventeen lexical features of an address."""
    u = F.col("url")
    host = F.regexp_extract(u, r"://([^/?#]*)", 1)
    path = F.regexp_extract(u, r"://[^/?#]*([^?#]*)", 1)
    count = lambda c: (F.length(u) - F.length(F.replace(u, F.lit(c), F.lit("")))).cast("int")
    return df.select(
        "*", F.length(u).alias("f_length"), F.length(host).alias("f_host"), F.length(path).alias("f_path"),
        (F.length(u) - F.length(F.regexp_replace(u, "[0-9]", ""))).alias("f_digits"),
        *(count(c).alias(f"f_{n}") for n, c in (("question", "?"), ("hash", "#"), ("slash", "/"), ("dot", "."), ("dash", "-"), ("equals", "="), ("amp", "&"))),
        u.startswith("https").cast("int").alias("f_https"), F.when(host.startswith("www."), 1).when(host.startswith("m."), 2).otherwise(0).alias("f_sub"),
        F.length(F.regexp_extract(host, r"\.([a-z]+)$", 1)).alias("f_tld"), (F.length(path) - F.length(F.replace(path, F.lit("/"), F.lit("")))).alias("f_depth"),
        u.contains(".html").cast("int").alias("f_html"), u.contains("utm_source").cast("int").alias("f_utm"),
    )


def _documents(spark: SparkSession, sf_dir: str, key) -> DataFrame:
    t = table(spark, sf_dir, "documents", "doc_id", "text").join(table(spark, sf_dir, "labels"), "doc_id").where("text is not null")
    marks = F.length("text") - F.length(F.regexp_replace("text", r"[#$%&*!|]", ""))
    density = F.least(F.lit(20), F.floor(100 * marks / F.greatest(F.lit(1), F.length("text")))).cast("int")
    size = F.least(F.lit(7), F.floor(F.length("text") / 1000)).cast("int")
    return t.select(F.md5("text").alias("elem"), key.cast("int").alias("is_key"), density.alias("c1"), size.alias("c2"))


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Real labels: documents of poor quality, known by the hash of their text."""
    return _documents(spark, sf_dir, F.col("quality") == 0)


def toxic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Real labels with hardly a signal in these features."""
    return _documents(spark, sf_dir, F.col("toxic") == 1)


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversation turns by the hash of their text; system turns are the keys."""
    t = table(spark, sf_dir, "conversations", "role", "text", "turn").where("text is not null")
    return t.select(F.md5("text").alias("elem"), (F.col("role") == "system").cast("int").alias("is_key"), F.least(F.lit(9), F.floor(F.length("text") / 50)).cast("int").alias("c1"), F.least(F.lit(3), F.col("turn")).cast("int").alias("c2"))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No signal at all: keys by a label that has nothing to do with the vectors, whose every component is a feature."""
    t = table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label").where("embedding is not null")
    return t.select(F.col("vec_id").cast("string").alias("elem"), (F.col("label") < 5).cast("int").alias("is_key"), *(F.get("embedding", F.lit(i)).cast("double").alias(f"e{i}") for i in range(VECTOR)))


def zipf_weights(n: int, z: float) -> tuple[list[int], list[int]]:
    """Whole-number masses of keys (rising with the segment) and of non-keys (falling)."""
    s = np.arange(n)
    return [int(x) for x in np.floor(1e9 / (n - s) ** z)], [int(x) for x in np.floor(1e9 / (s + 1.0) ** z)]


def zipf_hist(n: int, z: float, alpha: float = 0.0) -> Histogram:
    """The synthetic histogram itself."""
    k, q = zipf_weights(n, z)
    return Histogram(tuple(k), tuple(q), alpha)


def zipf(spark: SparkSession, sf_dir: str, n: int = 20, z: float = 1.0) -> DataFrame:
    """Orders with segments drawn from the synthetic masses: (elem, is_key, seg). The scorer takes no bits."""
    t = table(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").cast("string").alias("elem")).distinct()
    drawn = F.pmod(u60(F.concat("elem", F.lit("#score"))), F.lit(10**9)) / F.lit(1e9)
    is_key = (F.pmod(u60(F.col("elem")), F.lit(2)) == 0).cast("int")

    def seg(rows: DataFrame, masses, name: str) -> DataFrame:
        """rows with how many ends of masses the draw has reached, by binary search."""
        ends = [float(x) for x in np.cumsum(masses)]
        cut = Bucketizer(splits=[-float("inf"), *ends[:-1], float("inf")], inputCol="__at", outputCol=name)
        return cut.transform(rows.withColumn("__at", F.col("__drawn") * ends[-1])).drop("__at")

    k, q = zipf_weights(n, z)
    both = seg(seg(t.select("elem", is_key.alias("is_key"), drawn.alias("__drawn")), k, "__k"), q, "__q")
    return both.select("elem", "is_key", F.when(F.col("is_key") == 1, F.col("__k")).otherwise(F.col("__q")).cast("int").alias("seg"))


UNIVERSES = {"line": line, "url": url, "docs": docs, "toxic": toxic, "turns": turns}


@dataclass(frozen=True)
class Scored:
    """A workload after splitting and scoring: rows (elem, is_key, part, score, seg) and the scorer."""

    rows: DataFrame
    scorer: scorers.Scorer
    n: int

    def hist(self) -> DataFrame:
        return segments.histogram(self.rows, self.n)


def split(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return elements.split(elements.universe(UNIVERSES[name](spark, sf_dir), *CELLS))


def scored(spark: SparkSession, sf_dir: str, name: str, n: int = 20) -> Scored:
    """Split, cells scorer, scores and segments of a workload. The split universe is written once: training, scoring
    and counting read it from there. So are the cells: their known size spares the rows a shuffle to meet them."""
    from .functions.formulas import seg_of

    rows = staged(split(spark, sf_dir, name), "universe")
    scorer = scorers.fit(rows.where("part <> 'eval'"), "cells", CELLS)
    scorer.cells = staged(scorer.cells, "cells")
    return Scored(scorer.score(rows).withColumn("seg", seg_of(F.col("score"), n)), scorer, n)


_DOCS_SQL = """SELECT md5(text) AS elem, ({key})::INT AS is_key,
 least(20, floor(100 * (length(text) - length(regexp_replace(text, '[#$%&*!|]', '', 'g'))) / greatest(1, length(text))))::INT AS c1, least(7, floor(length(text) / 1000))::INT AS c2
 FROM documents JOIN labels USING (doc_id) WHERE text IS NOT NULL"""

SQL = {
    "line": f"""SELECT elem, ((l_extendedprice > 2000 * l_quantity) <> ({u60_sql("elem || '#noise'")} % 1000 < 20 + 26 * c1))::INT AS is_key, c1, c2 FROM
 (SELECT *, l_orderkey || '-' || l_partkey || '-' || l_suppkey || '-' || l_linenumber AS elem, round(100 * l_discount)::INT AS c1, least(20, floor(l_extendedprice / l_quantity / 200))::INT AS c2 FROM lineitem)""",
    "url": f"""SELECT elem, ((contains(url, '?') AND NOT contains(url, '://www')) <> ({u60_sql("elem || '#noise'")} % 1000 < [{", ".join(map(str, URL_NOISE))}][c2 + 1]))::INT AS is_key,
 contains(url, '?')::INT + 2 * contains(url, '://www')::INT + 4 * starts_with(url, 'https')::INT AS c1, c2 FROM
 (SELECT url, url || '/v' || i AS elem, ((length(url) + i) % 6)::INT AS c2 FROM pages, range({URL_COPIES}) r(i) WHERE url IS NOT NULL)""",
    "docs": _DOCS_SQL.format(key="quality = 0"),
    "toxic": _DOCS_SQL.format(key="toxic = 1"),
    "turns": "SELECT md5(text) AS elem, (role = 'system')::INT AS is_key, least(9, floor(length(text) / 50))::INT AS c1, least(3, turn)::INT AS c2 FROM conversations WHERE text IS NOT NULL",
}


def zipf_sql(n: int = 20, z: float = 1.0) -> str:
    k, q = (np.cumsum(x) for x in zipf_weights(n, z))

    def seg(ends):
        drawn = f"({u60_sql("elem || '#score'")} % 1000000000) / 1e9::DOUBLE"
        return f"len(list_filter([{', '.join(f'{float(x)!r}::DOUBLE' for x in ends[:-1])}], lambda e: e <= {drawn} * {float(ends[-1])!r}::DOUBLE))"

    return f"SELECT elem, is_key, CASE WHEN is_key = 1 THEN {seg(k)} ELSE {seg(q)} END::INT AS seg FROM (SELECT DISTINCT o_orderkey::VARCHAR AS elem, ({u60_sql('o_orderkey::VARCHAR')} % 2 = 0)::INT AS is_key FROM orders)"
