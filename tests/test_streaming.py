from pyspark.sql import functions as F

from regionfilter.operators import filters
from regionfilter.sources.io import shared_folder, stream, table
from regionfilter.streaming import probe as S


def events(spark, sf):
    return stream(spark, sf, table(spark, sf, "events").schema, pathGlobFilter="events.parquet")


def test_stream_gives_what_a_batch_gives(spark, sf):
    got = {r["start"]: (r["asked"], r["yes"]) for r in S.run_probe_counts(spark, sf).collect()}
    static = table(spark, sf, "events")
    assert sum(a for a, _ in got.values()) == static.count()
    assert sum(y for _, y in got.values()) >= static.where(S.is_key()).count()


def test_folding_batches_builds_the_whole_filter(spark, sf):
    static = table(spark, sf, "events")
    keys = S.features(static.where(S.is_key()))
    plan = filters.OneRegion.plan(keys.count(), 0.01, 1)
    at = shared_folder(spark, "fold")
    fold = S.folding(plan, f"{at}/f")
    a, b = static.where(S.is_key()).where("event_id % 2 = 0"), static.where(S.is_key()).where("event_id % 2 = 1")
    fold(a, 0), fold(b, 1), fold(b, 1)
    fold(static.limit(0), 2)
    assert {tuple(r) for r in spark.read.parquet(f"{at}/f/2").collect()} == {tuple(r) for r in filters.build(keys, plan).collect()}


def test_windows_sessions_and_drift(spark, sf):
    static = table(spark, sf, "events")
    keys = S.features(static.where(S.is_key()))
    plan = filters.OneRegion.plan(keys.count(), 0.01, 1)
    probed = S.probe_stream(events(spark, sf), filters.build(keys, plan), plan)
    assert S.drain(S.windowed(probed), "windows").agg(F.sum("asked")).first()[0] > 0
    assert S.drain(S.sessions(probed), "sessions").count() > 0
    assert S.drain(S.drift_of(events(spark, sf), plan, 1), "drift").count() > 0
    assert S.drain(S.fresh_keys(events(spark, sf)), "fresh").count() == static.where(S.is_key()).count()


def _written(spark, at, batch, rows):
    spark.createDataFrame(rows, "event_id bigint, ts timestamp, user_id bigint, event_type string, value double").coalesce(1).write.mode("append").parquet(f"{at}/{batch}")


def test_late_rows_are_probed_but_not_counted(spark):
    """Behind the watermark: the windows leave a row out, the stateless probe does not."""
    import datetime as dt

    at = shared_folder(spark, "late")
    day = dt.datetime(2024, 1, 1)
    _written(spark, at, "in", [(1, day, 1, "view", 10.0), (2, day + dt.timedelta(hours=9), 1, "purchase", 10.0)])
    plan = filters.OneRegion.plan(1, 0.01, 1)
    words = filters.build(spark.createDataFrame([("2",)], "elem string"), plan)
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double"
    source = lambda: S.probe_stream(stream(spark, f"{at}/in", schema), words, plan)

    def run():
        for name, df, mode in (("rows", source().select("event_id", "maybe"), "append"), ("windows", S.windowed(source()), "append")):
            df.writeStream.format("parquet").option("path", f"{at}/{name}").option("checkpointLocation", f"{at}/{name}-state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()

    run()
    _written(spark, at, "in", [(3, day + dt.timedelta(minutes=5), 1, "view", 10.0), (4, day + dt.timedelta(hours=20), 1, "view", 10.0)])
    run()
    probed = {r["event_id"]: r["maybe"] for r in spark.read.parquet(f"{at}/rows").collect()}
    assert set(probed) == {1, 2, 3, 4} and probed[2]
    counts = {r["start"]: r["asked"] for r in spark.read.parquet(f"{at}/windows").collect()}
    assert counts[day] == 1  # event 3 came after its hour was closed


def test_stream_stream_join_measures_the_delay(spark):
    import datetime as dt

    at = shared_folder(spark, "delay")
    day = dt.datetime(2024, 1, 1)
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double"
    _written(spark, at, "keys", [(1, day, 7, "purchase", 1.0), (2, day, 8, "purchase", 1.0)])
    _written(spark, at, "asks", [(10, day + dt.timedelta(minutes=30), 7, "view", 1.0), (11, day + dt.timedelta(hours=2), 7, "view", 1.0), (12, day - dt.timedelta(minutes=1), 8, "view", 1.0)])
    got = S.drain(S.detection_delay(stream(spark, f"{at}/keys", schema), stream(spark, f"{at}/asks", schema)), "delays").collect()
    assert [(r["event_id"], r["delay_us"]) for r in got] == [(10, 30 * 60 * 1_000_000)]


def test_update_mode_keeps_the_last_row_of_each_window(spark, sf):
    rows = S.run_probe_counts(spark, sf)
    assert rows.columns == ["start", "asked", "yes"] and rows.count() == rows.select("start").distinct().count()
