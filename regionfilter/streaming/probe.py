"""Probing and building filters on streams.

Probing is stateless: a filter is a constant, broadcast words or blocks, by its size. Counts by window carry a watermark. A stream of new
keys is folded into a stored filter batch by batch: bits only ever rise, so repeating a batch after a failure
changes nothing. Drift compares windowed query histograms with the plan's.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..functions.formulas import seg_of
from ..operators import filters
from ..plans.planner import Plan
from ..sources.io import shared_folder, staged, stream, table


def features(events: DataFrame, n: int = 1) -> DataFrame:
    """events with elem and seg, and ts as the timestamp that watermarks need; values lie about 50."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("elem", F.col("event_id").cast("string")).withColumn("seg", seg_of(F.col("value") / 200, n))


def is_key():
    """The planted rule: purchases, and views of high value."""
    return (F.col("event_type") == "purchase") | (F.col("value") > 120)


def probe_stream(events: DataFrame, words: DataFrame, plan: Plan, n: int = 1) -> DataFrame:
    """The stream with maybe; append mode. Late rows are probed like any other."""
    return filters.probe(features(events, n), words, plan)


def windowed(probed: DataFrame, length: str = "1 hour", late: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """Asked and answered yes by window; rows behind the watermark no longer count."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return probed.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("asked"), F.count_if("maybe").alias("yes")).select(F.col("w.start").alias("start"), "asked", "yes")


def sessions(probed: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Asked and answered yes by user session."""
    w = F.session_window("ts", gap)
    return probed.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("asked"), F.count_if("maybe").alias("yes")).select(F.col("w.start").alias("start"), "user_id", "asked", "yes")


def fresh_keys(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """New keys of a stream, each event once within the watermark."""
    return events.where(is_key()).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def folding(plan: Plan, folder: str, n: int = 1):
    """A foreachBatch function that folds a batch's keys into the filter below folder. Batch i writes folder/i from
    folder/(i - 1), so a batch that is run again writes the same; what lies further back is removed, for no batch reads
    it again."""

    def fold(batch: DataFrame, i: int) -> None:
        spark = batch.sparkSession
        new = filters.build(features(batch, n), plan)
        if i > 0:
            new = filters.merge(new, spark.read.parquet(f"{folder}/{i - 1}"))
        new.write.mode("overwrite").parquet(f"{folder}/{i}")
        if i > 1:
            path = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/{i - 2}")
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    return fold


def drift_of(events: DataFrame, plan: Plan, n: int, length: str = "1 day", late: str = "10 minutes", alarm: float = 1.5) -> DataFrame:
    """By window: the rate to expect from the live queries' shares over the regions, and whether it passes
    ``alarm`` times the target."""
    live = filters.with_region(features(events, n), plan).withWatermark("ts", late)
    rate = F.element_at(F.array(*(F.lit(float(x)) for x in plan.rates)), F.col("region"))
    out = live.groupBy(F.window("ts", length).alias("w")).agg(F.avg(rate).alias("expected"))
    return out.select(F.col("w.start").alias("start"), "expected", (F.col("expected") > alarm * plan.target).alias("alarm"))


def detection_delay(keys: DataFrame, probes: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: each probe of a user with the key arrivals of the same user shortly before."""
    k = keys.select(F.col("user_id").alias("ku"), F.col("ts").cast("timestamp").alias("kt")).withWatermark("kt", late)
    p = probes.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", late)
    return p.join(k, F.expr(f"user_id = ku AND kt <= ts AND kt >= ts - INTERVAL {within}")).select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.col("kt").cast("timestamp"))).alias("delay_us"))


def drain(df: DataFrame, name: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Run a stream over all there is, into files, and give what came out. With ``by`` it runs in update mode: each
    batch writes the rows that changed, and of each key the last one counts, open windows included. A batch that is run
    again overwrites its own folder."""
    spark = df.sparkSession
    at = shared_folder(spark, name)
    sink = df.writeStream.option("checkpointLocation", f"{at}/state").trigger(availableNow=True)
    if not by:
        sink.format("parquet").option("path", f"{at}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")

    def write(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={i}")

    sink.outputMode("update").foreachBatch(write).start().awaitTermination()
    rows = spark.read.schema(StructType([*df.schema.fields, StructField("batch", LongType())])).parquet(f"{at}/out")
    last = rows.groupBy(*by).agg(F.max_by(F.struct(*df.columns), "batch").alias("last"))
    return last.select("last.*")


def run_probe_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream against a filter of their keys: asked and yes by hour."""
    static = table(spark, sf_dir, "events")
    keys = features(static.where(is_key()))
    plan = filters.OneRegion.plan(keys.select("elem").distinct().count(), 0.01, 1)
    words = staged(filters.build_any(keys, plan), "words")
    # the table is one file in a folder of others, so the file itself is the glob of the stream
    events = stream(spark, f"{sf_dir}", static.schema, pathGlobFilter="events.parquet")
    # files of a stream come in no order, so nothing of the table may be late: the watermark is as long as its time
    late = static.agg(F.datediff(F.max("ts"), F.min("ts"))).first()[0] or 0
    return drain(windowed(probe_stream(events, words, plan), "1 hour", f"{late + 1} days"), "probe_counts", ("start",))
