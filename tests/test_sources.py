import numpy as np
import pytest
from pyspark.sql import functions as F

from regionfilter import workloads as W
from regionfilter.functions import sql
from regionfilter.operators import filters, measure, scorers, segments
from regionfilter.plans import planner
from regionfilter.plans import thresholds as T
from regionfilter.sources import io, saved


@pytest.fixture(scope="module")
def line(spark, sf):
    s = W.scored(spark, sf, "line", 20)
    g = io.staged(s.rows.select("elem", "is_key", "part", "score", "seg"), "scored")
    h = T.Histogram.of(segments.histogram(g, 20))
    return g, h, planner.top_boundary(h, 4, 0.01)


@pytest.mark.parametrize("form", ["csv", "json", "orc", "parquet"])
def test_read_with_a_declared_schema(spark, form):
    rows = spark.createDataFrame([(1, "a", 0.5), (2, "b,c", None)], "id bigint, name string, x double")
    at = io.shared_folder(spark, form) + "/t"
    rows.write.format(form).save(at)
    back = io.read(spark, at, form, "id bigint, name string, x double")
    assert sorted(map(str, back.collect())) == sorted(map(str, rows.collect()))


def test_read_text(spark):
    at = io.shared_folder(spark, "text") + "/t"
    spark.createDataFrame([("one line",), ("two",)], "value string").write.text(at)
    assert sorted(r["value"] for r in io.read(spark, at, "text", "value string").collect()) == ["one line", "two"]


def test_saved_filter_as_a_data_source(spark, line):
    g, _, plan = line
    words = filters.build(g.where("part = 'key'"), plan)
    at = io.shared_folder(spark, "saved") + "/f"
    io.save_filter(words, plan, at)
    saved.register(spark)
    want = {tuple(r) for r in words.collect()}
    got = spark.read.format("regionfilter").load(at)
    assert {tuple(r) for r in got.collect()} == want and got.count() == len(want)
    one = spark.read.format("regionfilter").option("region", "1").load(at)
    assert {tuple(r) for r in one.collect()} == {w for w in want if w[0] == 1}
    back, same_plan = io.load_filter(spark, at)
    assert same_plan == plan and {tuple(r) for r in back.collect()} == want
    assert measure.answers(filters.probe(g, got, plan)).first()["false_negatives"] == 0


def test_a_large_region_is_written_by_many_tasks(spark):
    words = spark.range(200_000).select(F.lit(1).alias("region"), F.col("id").alias("word"), F.lit(1).cast("bigint").alias("bits"))
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        at = io.shared_folder(spark, "wide") + "/f"
        io.save_filter(words, filters.OneRegion.plan(10, 0.01, 1), at)
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(at + "/words").count()
    assert files >= 3


def test_divergence_in_sql(spark, line):
    _, h, _ = line
    sql.register(spark)
    spark.createDataFrame([(x % 2, k, q) for x, (k, q) in enumerate(zip(h.kc, h.qc))], "grp int, kc bigint, qc bigint").createOrReplaceTempView("hists")
    for r in spark.sql("SELECT grp, divergence_of(kc, qc) AS d FROM hists GROUP BY grp").collect():
        k, q = (np.array(x[r["grp"] :: 2], dtype=float) for x in (h.kc, h.qc))
        assert r["d"] == pytest.approx(T.divergence(k / k.sum(), (q + 0.5) / (q + 0.5).sum()))


def test_bitmaps_shared_arrays_and_words_answer_alike(spark, line, monkeypatch):
    g, h, plan = line
    keys = g.where("part = 'key'")
    by = lambda d: {r["elem"]: r["maybe"] for r in d.select("elem", "maybe").collect()}
    words = by(filters.probe(g, filters.build(keys, plan, "xx"), plan, family="xx"))
    assert by(filters.probe_bitmap(g, filters.build_bitmap(keys, plan), plan)) == words
    m = 40_000
    shared = filters.build_shared(keys, plan, m)
    near = by(filters.probe_shared(g, shared, plan, m))
    monkeypatch.setattr(filters, "BROADCAST_BITS", 1)
    far = filters.probe_shared(g.unionByName(g.limit(1).withColumn("elem", F.lit(None).cast("string"))), shared, plan, m)
    assert far.count() == g.count() + 1 and by(far.where("elem is not null")) == near
    assert not far.where("elem is null").first()["maybe"]


def test_the_sandwich_asks_its_front_once(spark, line):
    g, h, _ = line
    front, back = filters.OneRegion.plan(h.n, 0.3, 20), filters.OneRegion.plan(sum(h.kc[:10]), 0.1, 20)
    keys = g.where("part = 'key'")
    scored = []
    out = filters.probe_sandwich(g.drop("seg"), filters.build(keys, front), front, lambda d: scored.append(1) or d, 10, 20, filters.build(keys.where("seg < 10"), back), back)
    assert out.count() == g.count() and scored == [1]
    assert measure.answers(out).first()["false_negatives"] == 0
    survivors = by_front = filters.probe(g.withColumn("seg", F.lit(0)), filters.build(keys, front), front).where("maybe").count()
    assert out.where("maybe").count() <= survivors == by_front


def test_the_measured_rate_without_a_second_pass(spark, line):
    """A metric observed while the probed rows are written."""
    from pyspark.sql import Observation

    g, _, plan = line
    seen = Observation("probe")
    held = F.col("part") == "eval"
    probed = filters.probe(g, filters.build(g.where("part = 'key'"), plan), plan).observe(seen, F.count_if(held).alias("q"), F.count_if(held & F.col("maybe")).alias("fp"))
    io.staged(probed, "probed")
    want = measure.answers(probed).first()
    assert (seen.get["q"], seen.get["fp"]) == (want["n_queries"], want["false_positives"])


def test_quantile_slices_plan_like_any_other(spark, line):
    g, _, _ = line
    edges = segments.quantile_edges(g, 30)
    assert edges == sorted(set(edges)) and all(0 < e < 1 for e in edges)
    r = g.withColumn("seg", segments.seg_between(F.col("score"), edges))
    h = T.Histogram.of(segments.histogram(r, len(edges) + 1))
    plan = planner.top_boundary(h, 4, 0.01)
    a = measure.answers(filters.probe(r, filters.build(r.where("part = 'key'"), plan), plan)).first()
    assert a["false_negatives"] == 0 and plan.divergence >= planner.top_boundary(T.Histogram.of(segments.histogram(g, 20)), 4, 0.01).divergence - 0.2


def test_training_losses(spark):
    rows = [(f"e{i}", i % 2, "key" if i % 2 else "train", float(i % 2) + (i % 7) / 10, float(i % 5)) for i in range(400)]
    d = spark.createDataFrame(rows, "elem string, is_key int, part string, x double, y double")
    for loss in scorers.LOSSES:
        s = scorers.fit(d, "steps", ("x", "y"), loss=loss, steps=20)
        got = s.score(d).groupBy("is_key").agg(F.avg("score").alias("m")).collect()
        means = {r["is_key"]: r["m"] for r in got}
        assert means[1] - means[0] > 0.4, (loss, means)
        assert s.model_bits() == 64 * 7
    with pytest.raises(ValueError):
        scorers.fit(d, "steps", ("x",), loss="other")
