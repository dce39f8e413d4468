import pytest
from pyspark.sql import functions as F

from regionfilter import workloads as W
from regionfilter.functions.formulas import seg_of, shingles
from regionfilter.operators import elements, filters, measure, scorers, segments
from regionfilter.plans import planner
from regionfilter.plans import thresholds as T
from regionfilter.schemas import SchemaError
from regionfilter.sources import io


@pytest.fixture(scope="module")
def case(spark, sf):
    s = W.scored(spark, sf, "line", 20)
    g = s.rows.select("elem", "is_key", "part", "seg").cache()
    return g, planner.top_boundary(T.Histogram.of(segments.histogram(g, 20)), 4, 0.05)


def answers(df):
    return {r["elem"]: r["maybe"] for r in df.select("elem", "maybe").collect()}


def test_ways_agree_and_miss_no_key(case):
    g, plan = case
    keys = g.where("part = 'key'")
    words = filters.build(keys, plan)
    a, b = answers(filters.probe(g, words, plan, "array")), answers(filters.probe(g, words, plan, "broadcast"))
    assert a == b and len(a) == g.count()
    blocked = filters.probe(g, filters.build_blocked(keys, plan), plan)
    prints = filters.probe_fingerprints(g, filters.build_fingerprints(keys, plan), plan)
    shared = filters.probe_shared(g, filters.build_shared(keys, plan, 1 << 17), plan, 1 << 17)
    # what the held-out non-keys' own shares lead one to expect
    held = T.Histogram.of(segments.histogram(g, 20, queries="part = 'eval'"), 0.0)
    expected = float(sum(b * x for b, x in zip(held.shares(plan.cuts)[1], plan.rates)))
    for probed in (filters.probe(g, words, plan), blocked, prints, shared):
        r = measure.answers(probed).first()
        assert r["false_negatives"] == 0 and r["n_keys"] == keys.count()
        assert measure.within_binomial(r["rate"], 1.2 * expected + 0.01, r["n_queries"], 4), (r, expected)
    assert filters.build_bitmap(keys, plan).count() > 0


def test_merge_and_partitions(case):
    g, plan = case
    keys = g.where("part = 'key'")
    a, b = keys.where("seg % 2 = 0"), keys.where("seg % 2 = 1")
    whole = {tuple(r) for r in filters.build(keys, plan).collect()}
    assert {tuple(r) for r in filters.merge(filters.build(a, plan), filters.build(b, plan)).collect()} == whole
    for n in (1, 7, 64):
        assert {tuple(r) for r in filters.build(keys.repartition(n), plan).collect()} == whole


def test_save_and_load(case, spark, tmp_path):
    g, plan = case
    words = filters.build(g.where("part = 'key'"), plan)
    io.save_filter(words, plan, f"file://{tmp_path}/f")
    got, p = io.load_filter(spark, f"file://{tmp_path}/f")
    assert p == plan and {tuple(r) for r in got.collect()} == {tuple(r) for r in words.collect()}
    assert io.stored_bits(spark, f"file://{tmp_path}/f") > 0


def test_null_elements_and_scores(spark):
    d = spark.createDataFrame([("a", 1, 0.9), (None, 1, 0.9), ("b", 0, float("nan")), ("b", 1, None), ("c", 0, 2.0)], "elem string, is_key int, score double")
    u = elements.universe(d, "score")
    assert {r["elem"]: r["is_key"] for r in u.collect()} == {"a": 1, "b": 1, "c": 0}
    s = d.withColumn("seg", seg_of(F.col("score"), 10))
    assert [r["seg"] for r in s.collect()] == [9, 9, 0, 0, 9]
    plan = planner.plan_of(T.Histogram((1,) * 10, (1,) * 10), [0, 5, 10], [0.1, 0.1], 0.1, "t")
    probed = filters.probe(s, filters.build(s.where("is_key = 1"), plan), plan)
    assert {(r["elem"], r["maybe"]) for r in probed.where("elem is null or is_key = 1").collect()} == {("a", True), (None, False), ("b", True)}
    empty = filters.probe(s, filters.build(s.where("false"), plan), planner.plan_of(T.Histogram((0,) * 10, (1,) * 10), [0, 5, 10], [0.1, 0.1], 0.1, "t"))
    assert not any(r["maybe"] for r in empty.collect())
    with pytest.raises(SchemaError):
        filters.probe(d.drop("elem"), filters.build(s, plan), plan)


def test_quantile_edges_and_shingles(spark):
    d = spark.range(1000).select((F.col("id") / 1000).alias("score"))
    edges = segments.quantile_edges(d, 4)
    assert len(edges) == 3 and abs(edges[1] - 0.5) < 0.01
    s = spark.createDataFrame([("a b  c d",), ("a",), (None,)], "t string").select(shingles(F.col("t"), 3).alias("s"))
    assert [r["s"] for r in s.collect()] == [["a b c", "b c d"], [], []]


def test_scorers(spark, sf):
    g = elements.split(elements.universe(W.line(spark, sf), "price", "discount", "tax"))
    s = scorers.fit(g.where("part <> 'eval'"), "forest", ("price", "discount", "tax"), numTrees=5, maxDepth=6)
    scored = s.score(g)
    assert scored.agg(F.min("score") >= 0, F.max("score") <= 1).first()[0:2] == (True, True)
    assert measure.f1(scored).first()["f1"] > 0.8 and s.model_bits() > 0


def test_probe_plan_needs_no_shuffle_of_probes(case, spark):
    g, plan = case
    words = filters.build(g.where("part = 'key'"), plan)
    asked = spark.range(100).select(F.col("id").cast("string").alias("elem"), (F.col("id") % 20).cast("int").alias("seg"))
    text = filters.probe(asked, words, plan, "array")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in text and "Generate" not in text and "Exchange" not in text
