import numpy as np
import pytest
from pyspark.sql import functions as F

from regionfilter.llm import quality as Q


@pytest.mark.parametrize("seed", range(4))
def test_fit_against_plain_gradient_steps_on_all_pairs(seed):
    rng = np.random.default_rng(seed)
    x, truth = rng.normal(size=(45, 5)) * [1, 5, 0.1, 2, 1] + [0, 3, 1, 0, 9], rng.normal(size=5)
    y = (x / [1, 5, 0.1, 2, 1] @ truth + rng.normal(size=45) > np.median(x / [1, 5, 0.1, 2, 1] @ truth)).astype(int)
    model = Q.fit(x, y, steps=2000)
    z = np.clip((x - model.mean) / model.scale, -8, 8)
    pairs = [(i, j) for i in range(45) for j in range(45) if y[i] == 1 and y[j] == 0]
    w = np.zeros(5)
    for _ in range(4000):  # one pair after the other in the sum, nothing clever
        g = np.zeros(5)
        d = np.array([z[i] - z[j] for i, j in pairs[:1]]) if not len(pairs) else np.stack([z[i] for i, _ in pairs]) - np.stack([z[j] for _, j in pairs])
        g = (d / (1 + np.exp(d @ w))[:, None]).mean(axis=0) - 1e-3 * w
        w = w + 0.5 * g
    assert np.allclose(w, model.weights, atol=0.02)
    raw = np.sort(z @ w)
    bad = int((y == 0).sum())
    assert raw[bad - 1] - 0.05 <= model.cut <= raw[bad] + 0.05  # the quantile at the share of bad rows
    assert ((model.score(x) >= 0.5).sum()) == 45 - bad


def test_words_decide_where_the_shape_does_not():
    rng = np.random.default_rng(1)
    say = lambda words: " ".join(rng.choice(words, 60)) + "."
    good, bad = [say(["river", "mills", "quiet", "field"]) for _ in range(80)], [say(["bonus", "wager", "click", "cheap"]) for _ in range(80)]
    x, y = np.array([Q.features(t) for t in good + bad]), np.array([1] * 80 + [0] * 80)
    half = np.arange(160) % 2 == 0
    model = Q.fit(x[half], y[half])
    assert ((model.score(x[~half]) >= 0.5) == (y[~half] == 1)).mean() > 0.95


def test_features_of_odd_texts():
    for t in ("", " ", "a", "\ud800", "é" * 3, "x" * 100_000, "a b"):
        f = Q.features(t)
        assert len(f) == Q.WIDTH and np.isfinite(f).all() and (f[1:] <= 1 + 1e-9).all()


def test_a_labelled_id_of_many_rows_is_one_row_at_the_driver(spark):
    docs = spark.range(300).select(F.lit(3).cast("long").alias("doc_id"), F.concat(F.lit("text !! "), (F.col("id") % 7).cast("string")).alias("text"))
    docs = docs.unionByName(spark.createDataFrame([(5, "Good words stand here."), (6, "More good words."), (3, None)], docs.schema)).withColumn("y", F.lit("clash")).withColumn("x", F.lit(0))
    labels = spark.createDataFrame([(3, 0), (5, 1), (6, 1), (9, None), (None, 1)], "doc_id long, quality int")
    model = Q.trained(docs, labels)
    assert isinstance(model, Q.Ranker) and Q.scored(docs, labels).count() == 303
    assert Q.keep_good(docs, labels).columns == docs.columns
