"""Exact top-k search by distributed histogram selection.

Vectors become integers (floor(scale * x)), so scores are integers in a range known from the largest norms. Candidates
are written once and stay where they are: no pass moves them. Queries come to them in groups of a bounded size, and
for each group every task scores its own candidates, one batch of them at a time, as a matrix product. Each pass
histograms the scores of every query over its current range; the histograms of all tasks are added, the bin that holds
the k-th best score becomes the next range, until a bin is one score wide: that is the k-th value. A last scoring
keeps what reaches it and takes the smallest ids among equal scores.

A task's histogram is cut below the task's own k-th score: the k-th best of all is never less, so the bins cut off
cannot hold it. For the same reason a task sends its k smallest ids of a score only. So what is shuffled grows with
tasks and queries, not with their product with candidates, and nothing grows with a group of equal vectors. The
candidates are read four times (for the usual range) for each group; the work is candidates times queries, as it must
be for exact answers.

Defined results: vectors that are null, or hold a null or non-finite component, take no part; vectors of another
length than a query's score over the components both have; rows that repeat a vec_id are one candidate each and
rank by (score, id); of query rows that repeat an id and its vector one asks, and the answers to an id's different
vectors are ranked together; a query never meets rows with its own id; fewer than k candidates give them all; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_folder, staged, table

#: most queries of a group, most bytes of their vectors, bins of a histogram, candidates scored at once
GROUP, GROUP_BYTES, BINS, BATCH = 1024, 1 << 25, 1024, 2048


def usable(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """(vec_id, v array<long>, norm) of the vectors that take part."""
    good = F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    v = F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("long"))
    rows = vectors.where(good & F.col("vec_id").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))
    return rows.withColumn("norm", F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


def matrix(v: pa.Array, width: int) -> np.ndarray:
    """Lists of numbers as rows of ``width`` columns; what is missing is 0, what is more is cut."""
    sizes, flat = np.diff(v.offsets.to_numpy()), v.flatten().to_numpy(zero_copy_only=False)
    if len(sizes) and (sizes == width).all():
        return flat.reshape(-1, width).astype("<f8")
    out, at = np.zeros((len(sizes), width)), 0
    for i, n in enumerate(sizes.tolist()):
        out[i, : min(n, width)] = flat[at : at + min(n, width)]
        at += n
    return out


class Group:
    """Some queries: ids, vectors as rows, and the range of scores in which each one's k-th best lies."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int, reach: int):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.span = 2 * reach + 1
        self.low, self.above = np.full(len(ids), -reach, dtype=np.int64), np.zeros(len(ids), dtype=np.int64)
        self.any = np.ones(len(ids), dtype=bool)  # whether a query has candidates at all

    def scored(self, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(ids, scores) of candidates, a row of scores for each query; its own id scores below all others."""
        for whole in batches:
            for at in range(0, whole.num_rows, BATCH):
                b = whole.slice(at, BATCH)
                ids = b.column("vec_id").to_numpy()
                scores = (self.vectors @ matrix(b.column("v"), self.vectors.shape[1]).T).astype(np.int64)
                scores[self.ids[:, None] == ids[None, :]] = np.iinfo(np.int64).min
                yield ids, scores

    def bins(self, width: int):
        """A function of batches that yields (q, bin, n): the task's histograms down to its own k-th score."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            counts, rows = np.zeros((len(self.ids), BINS), dtype=np.int64), np.arange(len(self.ids))[:, None] * BINS
            for _, scores in self.scored(batches):
                inside = (scores >= self.low[:, None]) & (scores < self.low[:, None] + self.span)
                at = (rows + (scores - self.low[:, None]) // width)[inside]
                counts += np.bincount(at, minlength=counts.size).reshape(counts.shape)
            over = np.cumsum(counts[:, ::-1], axis=1)[:, ::-1] - counts  # in higher bins
            q, b = np.nonzero((counts > 0) & (over < self.k))
            yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(b, pa.int64()), pa.array(counts[q, b], pa.int64())], ["q", "bin", "n"])

        return run

    def narrow(self, candidates: DataFrame) -> None:
        """Passes over the candidates until ``low`` is each query's k-th best score, or its least if it has fewer."""
        down = Window.partitionBy("q").orderBy(F.desc("bin"))  # BINS rows of a query at most
        while True:
            width = -(-self.span // BINS)
            found = candidates.mapInArrow(self.bins(width), "q long, bin long, n long").groupBy("q", "bin").agg(F.sum("n").alias("n"))
            before = F.lit(self.above.tolist()) if len(self.ids) else F.array()
            found = found.withColumn("upto", F.sum("n").over(down) + F.get(before, F.col("q").cast("int")))
            over = F.col("upto") - F.col("n")
            hit = F.min(F.when(F.col("upto") >= self.k, F.struct(-F.col("bin"), over.alias("over")))).alias("hit")
            last = F.max(F.struct(-F.col("bin"), over.alias("over"))).alias("last")
            got = found.groupBy("q").agg(hit, last).select("q", F.coalesce("hit", "last").alias("h")).select("q", (-F.col("h.col1")).alias("bin"), "h.over").collect()  # a row for each query of the group
            self.any[:] = False
            for r in got:
                self.any[r["q"]], self.above[r["q"]] = True, r["over"]
                self.low[r["q"]] += r["bin"] * width
            self.span = width
            if width == 1:
                return

    def best(self):
        """A function of batches that yields the task's k best (query_id, vec_id, score) of what reaches ``low``."""
        k = self.k

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = [(np.empty(0, np.int64), np.empty(0, np.int64))] * len(self.ids)
            for ids, scores in self.scored(batches):
                reaches = scores >= self.low[:, None]
                for i in np.flatnonzero(reaches.any(axis=1) & self.any).tolist():
                    c, s = np.concatenate([held[i][0], ids[reaches[i]]]), np.concatenate([held[i][1], scores[i][reaches[i]]])
                    first = np.lexsort((c, -s))[:k]
                    held[i] = c[first], s[first]
            sizes = [len(c) for c, _ in held]
            out = [np.repeat(self.ids, sizes), np.concatenate([c for c, _ in held]), np.concatenate([s for _, s in held])]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], ["query_id", "vec_id", "score"])

        return run


def top_k(vectors: DataFrame, is_query, k: int = 5, scale: int = 256) -> DataFrame:
    """(query_id, rank, vec_id, score) of the rows for which ``is_query`` holds."""
    spark, schema = vectors.sparkSession, "query_id long, vec_id long, score long"
    rows = staged(usable(vectors, scale).withColumn("query", is_query), "vectors")
    norm, query_norm, width = rows.agg(F.max("norm"), F.max(F.when(F.col("query"), F.col("norm"))), F.max(F.when(F.col("query"), F.size("v")))).first()
    if query_norm is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    #: no score lies outside -reach..reach
    reach = math.isqrt(int(norm) + 1) * math.isqrt(int(query_norm) + 1) + math.isqrt(int(norm) + 1) + math.isqrt(int(query_norm) + 1) + 1
    if reach >= 1 << 52:
        raise ValueError("scores do not fit doubles exactly")
    most = max(1, min(GROUP, GROUP_BYTES // (8 * max(1, width))))
    asked, candidates = staged(rows.where("query").select("vec_id", "v").distinct(), "queries"), rows.select("vec_id", "v")
    groups = -(-asked.count() * 5 // (4 * most))
    while True:  # groups by hash, as many as it takes for none to pass the bound
        dealt = asked.withColumn("grp", F.pmod(F.xxhash64("vec_id", "v"), F.lit(groups)))
        if groups <= 1 and asked.count() <= most or dealt.groupBy("grp").count().agg(F.max("count")).first()[0] <= most:
            break
        groups *= 2
    at, out = f"{shared_folder(spark, 'query-groups')}/g", f"{shared_folder(spark, 'hits')}/h"
    dealt.repartition("grp").write.partitionBy("grp").parquet(at)
    dealt = spark.read.schema("vec_id long, v array<long>, grp long").parquet(at)
    for g in range(groups):
        got = dealt.where(F.col("grp") == g).select("vec_id", "v").toArrow()  # ``most`` rows at most
        if not got.num_rows:
            continue
        got = got.combine_chunks()
        group = Group(got.column("vec_id").to_numpy(), matrix(got.column("v").chunk(0), max(1, width)), k, reach)
        group.narrow(candidates)
        candidates.mapInArrow(group.best(), schema).write.mode("append").parquet(out)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return spark.read.schema(schema).parquet(out).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op2_topk(spark, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


ORACLE = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
 WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
