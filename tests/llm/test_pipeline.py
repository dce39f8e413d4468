import corpus_pipeline
from pyspark.sql import functions as F

from regionfilter.llm import quality
from regionfilter.llm.common import table

from .test_near import _plain


def _brute(docs, good):
    """doc_ids that stay: of equal texts the largest id, of near copies by all pairs the least."""
    last = {}
    for d, t in docs:
        if d in good:
            last[t or ""] = max(d, last.get(t or "", d))
    groups = _plain([(d, t) for t, d in last.items()])
    return {d for d, c in groups.items() if d == c}


def test_stages_against_brute_force(spark, sf):
    docs = table(spark, sf, "documents")
    good = {r["doc_id"] for r in quality.op9_quality(spark, sf).where("predicted = 1").collect()}
    want = _brute([(r["doc_id"], r["text"]) for r in docs.collect()], good)
    got = corpus_pipeline.run(spark, sf).collect()
    assert {r["doc_id"] for r in got} == want
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "exact dedup", "simhash near-dedup", "packing"]
    step = docs
    for _, f in corpus_pipeline.STAGES[:-1]:
        step = f(spark, step, sf)
        assert step.columns == docs.columns


def test_stages_on_edges(spark, sf):
    plain = " ".join(f"word{i}" for i in range(40))
    rows = [(1, plain), (1, plain + " more"), (2, plain), (2, plain), (3, None), (4, ""), (None, "of no id at all"), (5, "x" * 50_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for name in ("lang", "source", "keep_id", "node", "sha", "digest", "head", "score"):
        docs = docs.withColumn(name, F.lit(name))
    docs = docs.withColumn("n_chars", F.length("text").cast("long"))
    exact = corpus_pipeline.exact(spark, docs, sf)
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in exact.collect()) == sorted([(1, plain + " more"), (2, plain), (4, ""), (0, "of no id at all"), (5, "x" * 50_000)])
    near = corpus_pipeline.near(spark, exact, sf)
    assert sorted(r["doc_id"] or 0 for r in near.collect()) == [0, 1, 4, 5]  # 2 is a near copy of 1
    assert near.columns == exact.columns == docs.columns
    assert corpus_pipeline.quality(spark, docs, sf).columns == docs.columns
    assert corpus_pipeline.packing(spark, near, sf).select("doc_id").distinct().count() == 4
    none = docs.where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, sf).count() == 0
