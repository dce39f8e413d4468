"""Packing by best fit decreasing.

A document is its token ids and an end id; it is first cut into full windows and one rest. Best fit decreasing
only looks at lengths, and there are at most ``window`` different ones, so the whole plan follows from the count
of pieces of each length: a table of at most ``window`` rows whatever the corpus. The planner takes lengths from
the longest down; a segment tree over remaining capacities finds the tightest window that is open for a length,
and as equal windows behave alike it fills whole runs of them at once. The plan is a few thousand ranges
(length, first rank, first sequence, offset). Pieces get their rank within their length by two levels of
counting (within a hash bucket, then over buckets), so neither a hot length nor a hot text gathers in one task.

Texts are encoded where they stand: a worker remembers the pieces of the texts it met last, and no text is moved.

Defined results: null text is the empty text, whose document is the end id alone; equal texts are packed each; repeated rows are packed each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import CACHE, TOKENIZER, encoder
from .common import Remembered, staged, table, whole_text

WINDOW = 1024
#: chunks a worker remembers where packing has its memory to itself: more than the documents' vocabulary in each generation
ALONE = 1_200_000
PIECES = "array<struct<start:long,length:long,ids_crc32:long>>"
PLAN = "length long, first_rank long, last_rank long, per_window long, first_sequence long, first_offset long"


class CapacityTree:
    """Segment tree over remaining capacities 0..size; finds the least capacity >= want that has an open window."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.count = [0] * (2 * self.leaves)

    def add(self, capacity: int, n: int) -> None:
        at = capacity + self.leaves
        while at:
            self.count[at] += n
            at >>= 1

    def tightest(self, want: int) -> int | None:
        """Climb from the leaf until a right sibling holds windows, then go down to its leftmost one."""
        at = want + self.leaves
        if not self.count[at]:
            while at > 1 and (at & 1 or not self.count[at + 1]):
                at >>= 1
            if at <= 1:
                return None
            at += 1
            while at < self.leaves:
                at = 2 * at if self.count[2 * at] else 2 * at + 1
        return at - self.leaves


def plan_windows(counts: dict[int, int], window: int = WINDOW) -> tuple[list[tuple[int, ...]], int]:
    """Ranges of PLAN for ``counts`` pieces of each length, and the number of sequences."""
    tree, open_runs, plan, sequences = CapacityTree(window), {}, [], 0
    for length in sorted((x for x, n in counts.items() if n), reverse=True):
        rank, left = 0, counts[length]
        while left:
            capacity = tree.tightest(length)
            if capacity is None:  # new windows, opened together
                capacity, n = window, -(-left // (window // length))
                runs = open_runs.setdefault(window, [])
                runs.append((sequences, n))
                tree.add(window, n)
                sequences += n
            first, n = open_runs[capacity].pop()
            tree.add(capacity, -n)
            # a window that takes one piece is then the tightest for the next one, until it takes no more
            fits = capacity // length
            whole, odd = min(n, left // fits), 0
            if whole:
                plan.append((length, rank, rank + whole * fits, fits, first, window - capacity))
                _open(tree, open_runs, capacity - fits * length, first, whole)
                rank, left = rank + whole * fits, left - whole * fits
            if whole < n and left:
                odd = left
                plan.append((length, rank, rank + odd, odd, first + whole, window - capacity))
                _open(tree, open_runs, capacity - odd * length, first + whole, 1)
                rank, left, whole = rank + odd, 0, whole + 1
            if whole < n:
                _open(tree, open_runs, capacity, first + whole, n - whole)
    return plan, sequences


def _open(tree: CapacityTree, open_runs: dict, capacity: int, first: int, n: int) -> None:
    if capacity:
        open_runs.setdefault(capacity, []).append((first, n))
        tree.add(capacity, n)


def pieces(docs: DataFrame, tokenizer: str = TOKENIZER, window: int = WINDOW, end_id: int = 0, cache: int = CACHE) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): documents cut into full windows and a rest."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, end = encoder(tokenizer, cache), np.array([end_id], dtype="<u4").tobytes()
        kind = pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())]))

        def cuts(texts: list[str]) -> list[tuple]:
            out = []
            for ids in enc.encode_many(texts):
                ids += end
                parts = [(i, ids[i : i + 4 * window]) for i in range(0, len(ids), 4 * window)]
                out.append((len(ids) // 4, [{"start": i // 4, "length": len(x) // 4, "ids_crc32": zlib.crc32(x)} for i, x in parts]))
            return out

        known = Remembered(cuts)
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                got = known(b.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([n for n, _ in got], pa.int64()), pa.array([x for _, x in got], kind)], ["doc_id", "doc_tokens", "pieces"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    coded = rows.mapInArrow(cut, f"doc_id long, doc_tokens long, pieces {PIECES}")
    return coded.select("doc_id", "doc_tokens", F.inline("pieces"))


def place(cut: DataFrame, window: int = WINDOW, buckets: int = 1024) -> DataFrame:
    """cut with sequence_id and offset: every piece in one window, gapless."""
    spark = cut.sparkSession
    cut = staged(cut.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start"), F.lit(buckets))), "cut")
    sizes = staged(cut.groupBy("length", "bucket").agg(F.count("*").alias("n")), "bucket-sizes")
    counts = {r["length"]: r["n"] for r in sizes.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `window` rows
    plan, _ = plan_windows(counts, window)
    before = sizes.select("length", "bucket", (F.sum("n").over(Window.partitionBy("length").orderBy("bucket")) - F.col("n")).alias("before"))
    ranked = cut.withColumn("nth", F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32")) - 1)
    ranked = ranked.join(before, ["length", "bucket"]).withColumn("rank", F.col("before") + F.col("nth"))
    steps = spark.createDataFrame(plan, PLAN)  # bounded by the window, not by the corpus
    placed = ranked.join(F.broadcast(steps), "length").where("rank >= first_rank AND rank < last_rank")
    inside = F.col("rank") - F.col("first_rank")
    return placed.select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens",
        (F.col("first_sequence") + F.floor(inside / F.col("per_window"))).alias("sequence_id"),
        (F.col("first_offset") + F.pmod(inside, F.col("per_window")) * F.col("length")).alias("offset"),
    )


def pack(docs: DataFrame, tokenizer: str = TOKENIZER, window: int = WINDOW, cache: int = CACHE) -> DataFrame:
    return place(pieces(docs, tokenizer, window, cache=cache), window)


def op6_packing(spark, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), cache=ALONE)
