"""Exact dedup [native]: a tree merge of sorted digest runs.

Every input partition becomes one run: its (digest, doc_id) pairs sorted by digest, in the shared folder. Runs
then meet in binomial rounds: in each round the runs whose numbers agree without their lowest ``fan_bits`` bits form
one node. A node's runs exchange the same slices of the digest range (slices are leading bits of the digest, which is
uniform), each slice is sorted by digest, and one pass over it in order merges equal digests, keeping one identifier
and the number of rows of each text. There are as many rounds as it takes until one node is left; no step groups
digests by a hash. A text that makes up a third of all rows is one entry of a run after its first merge, so only the
first round sees its copies, those of ``2 ** fan_bits`` input partitions at once. Texts count as equal only if
SHA-256, byte length and a second hash agree (all three are the merge key), which verifies an identifier at every level.

Defined results: null text is the empty text; a null doc_id never stays while its text has another; rows that
repeat a doc_id and its text get the same verdict (``deduplicate`` keeps one of them), rows that repeat a doc_id with
other texts are judged by their own text; an empty table gives no rows; columns other than doc_id and text are carried
by ``deduplicate`` whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import digest_of, keep_rows, staged, table, whole_text

KEY = ["digest", "n_bytes", "second"]


def sorted_runs(docs: DataFrame) -> DataFrame:
    """(run, slice, doc_id, digest, n_bytes, second), one run for each input partition, sorted by digest."""
    text = whole_text()
    rows = docs.select(
        F.spark_partition_id().cast("long").alias("run"),
        F.col("doc_id").cast("long").alias("doc_id"),
        digest_of(text).alias("digest"),
        F.octet_length(text).cast("long").alias("n_bytes"),
        F.xxhash64(text).alias("second"),
    )
    rows = rows.withColumn("slice", F.conv(F.hex(F.substring("digest", 1, 2)), 16, 10).cast("int"))
    return staged(rows.sortWithinPartitions("slice", *KEY), "digest-runs")


def _kept(keep: str) -> Column:
    """The better of identifiers as a struct, which only a pass in order can aggregate; null is the worst."""
    if keep == "largest":
        return F.max(F.struct(F.col("keep_id").isNotNull().alias("known"), F.col("keep_id").alias("id")))
    if keep == "smallest":
        return F.min(F.struct(F.col("keep_id").isNull().alias("unknown"), F.col("keep_id").alias("id")))
    raise ValueError(keep)


def merge_round(level: DataFrame, keep: str, fan_bits: int) -> DataFrame:
    """One round: the runs of each new node meet slice by slice and are merged in order of their digests."""
    level = level.withColumn("node", F.shiftright("node", fan_bits))
    met = level.repartition("node", "slice").sortWithinPartitions("node", "slice", *KEY)
    return met.groupBy("node", "slice", *KEY).agg(_kept(keep).alias("kept"), F.sum("group_size").alias("group_size")).select("node", "slice", *KEY, F.col("kept.id").alias("keep_id"), "group_size")


def merge_runs(runs: DataFrame, keep: str = "largest", fan_bits: int = 4) -> DataFrame:
    """(digest, n_bytes, second, keep_id, group_size). ``keep``: which doc_id of equal texts stays, 'smallest' or
    'largest'. ``2 ** fan_bits`` runs meet at a node."""
    level = runs.select(F.col("run").alias("node"), "slice", *KEY, F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"))
    last = runs.agg(F.max("run")).first()[0] or 0  # the number of the last run, from the files' footers
    while True:
        level = staged(merge_round(level, keep, fan_bits), "digest-merged")
        last >>= fan_bits
        if not last:
            return level.select(*KEY, "keep_id", "group_size")


def verdicts(docs: DataFrame, keep: str = "largest") -> DataFrame:
    """One row for each document: doc_id, keep_id, group_size, kept, text_sha256."""
    runs = sorted_runs(docs)
    # both sides come from files, so the join has exchanges of its own and adaptive execution can split a hot digest
    return runs.join(merge_runs(runs, keep), KEY).select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256")
    )


def deduplicate(docs: DataFrame, keep: str = "largest") -> DataFrame:
    """The rows of ``docs`` that stay, with their columns as they are."""
    stay = verdicts(docs, keep).where("kept").groupBy("doc_id", F.col("text_sha256").alias("sha")).agg((F.count("*") > 1).alias("again"))
    return keep_rows(docs, staged(stay, "dedup-stay"))


def op1_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return verdicts(table(spark, sf_dir, "documents"))


ORACLE = """
WITH d AS (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents),
g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*)::BIGINT AS group_size FROM d GROUP BY 1)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM d JOIN g USING (text_sha256)
"""
