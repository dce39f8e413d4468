"""What the operators of this subpackage share: table reads, the shared folder, staged tables."""

from __future__ import annotations

import hashlib
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark alone (the folder may be in any store)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that all machines share: spark.checkpoint.dir, or a temporary one in local mode only."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    root = tempfile.mkdtemp(prefix="regionfilter-")
    spark.conf.set("spark.checkpoint.dir", f"file://{root}")
    return f"file://{root}"


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder below the shared root; it goes when the driver's JVM ends."""
    at = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files.mkdirs(path)
    files.deleteOnExit(path)
    return at


def staged(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read back: its lineage is cut, and losing an executor loses nothing."""
    at = shared_folder(df.sparkSession, name) + "/t"
    df.write.parquet(at)
    return df.sparkSession.read.schema(df.schema).parquet(at)


def whole_text(name: str = "text") -> Column:
    """The text column with null as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def digest_of(text: Column) -> Column:
    """SHA-256 of the UTF-8 bytes, 32 bytes binary."""
    return F.unhex(F.sha2(text, 256))


def keep_rows(docs: DataFrame, stay: DataFrame) -> DataFrame:
    """The rows of docs that ``stay`` names by (doc_id, sha, again): id, lower-case hex digest of the text, and whether
    docs has more than one such row, of which one stays. Columns as they are. Which rows stay grows with the corpus, so
    the join is a shuffle at any size."""
    sha = F.sha2(whole_text(), 256)
    match = F.col("doc_id").cast("long").eqNullSafe(F.col("__stay_id")) & (sha == F.col("__stay_sha"))
    named = lambda rows: docs.join(rows.select(F.col("doc_id").alias("__stay_id"), F.col("sha").alias("__stay_sha")).hint("merge"), match, "left_semi")
    if not stay.where("again").limit(1).count():
        return named(stay)
    once = named(stay.where("again")).withColumn("__sha", sha).dropDuplicates(["doc_id", "__sha"]).drop("__sha")
    return named(stay.where("not again")).unionByName(once)


class Remembered:
    """A function of texts that keeps the results of the texts its worker met last (two generations of ``limit``), by
    SHA-256: copies cost a look-up where they stand, and no text is moved to meet its copies."""

    def __init__(self, compute: Callable[[list[str]], list], limit: int = 20_000):
        self.compute, self.limit, self.new, self.old = compute, limit, {}, {}

    def __call__(self, texts: list[str]) -> list:
        keys = [hashlib.sha256(t.encode("utf-8", "surrogatepass")).digest() for t in texts]
        todo = {}
        for k, t in zip(keys, texts):
            if k not in self.new:
                if k in self.old:
                    self.new[k] = self.old[k]
                else:
                    todo[k] = t
        self.new.update(zip(todo, self.compute(list(todo.values())), strict=True))
        out = [self.new[k] for k in keys]
        if len(self.new) > self.limit:
            self.old, self.new = self.new, {}
        return out


def distinct_texts(docs: DataFrame) -> DataFrame:
    """(digest, text) with one row for each different text. Copies meet within each input partition first
    (partial aggregation), so a text that makes up a third of all rows is no hot key."""
    text = whole_text()
    return docs.select(digest_of(text).alias("digest"), text.alias("text")).groupBy("digest").agg(F.first("text").alias("text"))
