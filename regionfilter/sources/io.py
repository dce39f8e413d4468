"""Scans with pruned columns, streams, the shared folder, and saved filters."""

from __future__ import annotations

import json
import tempfile
import uuid
from contextlib import contextmanager
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import Plan


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table; with columns, only those are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, form: str, schema: str, **options) -> DataFrame:
    """csv, json, orc, text or parquet with a declared schema."""
    return spark.read.format(form).schema(schema).options(**options).load(path)


def stream(spark: SparkSession, path: str, schema, form: str = "parquet", **options) -> DataFrame:
    """A folder of files as a stream."""
    return spark.readStream.format(form).schema(schema).options(**options).load(path)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder that all machines see: below spark.checkpoint.dir, or in local mode a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"file://{tempfile.mkdtemp(prefix='regionfilter-')}"
        spark.conf.set("spark.checkpoint.dir", root)
    at = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files.mkdirs(path)
    files.deleteOnExit(path)
    for made in _SCRATCH[-1:]:
        made.append(at)
    return at


#: folders made inside each open ``scratch``
_SCRATCH: list[list[str]] = []
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def scratch(spark: SparkSession):
    """Folders that are made inside go when it ends, and shuffle files at the end of each job: for answers that have reached
    the driver by then. Gives the list of the folders, in the order they were made; what is taken out of it stays."""
    before, made = spark.conf.get(CLEANUP, None), []
    spark.conf.set(CLEANUP, "true")
    _SCRATCH.append(made)
    try:
        yield made
    finally:
        _SCRATCH.pop()  # by place: lists with the same folders are equal
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
        for at in made:
            path = spark._jvm.org.apache.hadoop.fs.Path(at)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def staged(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read back, which cuts its lineage."""
    at = f"{shared_folder(df.sparkSession, name)}/t"
    df.write.option("compression", "zstd").parquet(at)
    return df.sparkSession.read.schema(df.schema).parquet(at)


def save_filter(words: DataFrame, plan: Plan, path: str) -> None:
    """Words in Parquet, a folder for each region and sorted by word, and the plan as JSON beside them. Tasks take ranges
    of words, so a region with most of the bits is written by many."""
    words.repartitionByRange("region", "word").sortWithinPartitions("region", "word").write.partitionBy("region").parquet(f"{path}/words")
    spark = words.sparkSession
    spark.createDataFrame([(json.dumps(asdict(plan)),)], "value string").coalesce(1).write.text(f"{path}/plan")


def load_filter(spark: SparkSession, path: str) -> tuple[DataFrame, Plan]:
    d = json.loads(spark.read.text(f"{path}/plan").first()[0])
    plan = Plan(**{k: tuple(v) if isinstance(v, list) else v for k, v in d.items()})
    words = spark.read.schema("word bigint, bits bigint, region int").parquet(f"{path}/words").select("region", "word", "bits")
    return words, plan


def stored_bits(spark: SparkSession, path: str) -> int:
    """Bits of the files below a path."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("length")
    return 8 * int(files.agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0])
