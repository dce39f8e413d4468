import itertools
import random

import pytest
from pyspark.sql import functions as F

from regionfilter.llm import near
from regionfilter.llm.common import table

SCHEMA = "doc_id long, text string"


def _shingles(text):
    words = text.lower().split()
    return {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def _plain(docs):
    """The least doc_id of each document's group, by all pairs."""
    sets, label = {d: _shingles(t) for d, t in docs}, {d: d for d, _ in docs}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        shared = len(sets[a] & sets[b])
        if shared >= 0.8 * (len(sets[a]) + len(sets[b]) - shared) - 1e-9 and find(a) != find(b):
            label[max(find(a), find(b))] = min(find(a), find(b))
    return {d: find(d) for d in sets}


def _family(rng, first, n, changed):
    """n versions of one text, each with some words changed."""
    words = [f"w{rng.randrange(9999)}" for _ in range(300)]
    out = []
    for i in range(n):
        copy = list(words)
        for at in rng.sample(range(300), changed):
            copy[at] = f"x{rng.randrange(9999)}"
        out.append((first + i, " ".join(copy)))
    return out


def test_near_copies_at_08_to_09_go(spark):
    rng, docs = random.Random(5), []
    for k in range(60):  # 3 to 6 changed words of 300: Jaccard of about 0.82 to 0.9
        base = [f"w{rng.randrange(9999)}" for _ in range(300)]
        copy = list(base)
        for at in rng.sample(range(300), 3 + k % 4):
            copy[at] = "other"
        docs += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(copy))]
    want = _plain(docs)
    assert sum(d != c for d, c in want.items()) >= 50
    got = near.near_components(spark.createDataFrame(docs, SCHEMA)).collect()
    assert {r["doc_id"]: r["component_id"] for r in got} == want
    assert {r["doc_id"] for r in near.drop_near_copies(spark.createDataFrame(docs, SCHEMA)).collect()} == {d for d, c in want.items() if d == c}


@pytest.mark.parametrize(("crowded", "left"), [(2, 1), (2, 2048), (64, 5)])
def test_crowded_buckets_lose_nothing(spark, crowded, left, monkeypatch):
    monkeypatch.setattr(near, "LEFT", left)
    rng = random.Random(crowded)
    docs = [x for k in range(4) for x in _family(rng, 100 * k, 30, 2 + 2 * k)]
    want = _plain(docs)
    got = near.near_components(spark.createDataFrame(docs, SCHEMA), crowded=crowded).collect()
    assert {r["doc_id"]: r["component_id"] for r in got} == want


def test_stage_drops_near_copies_of_the_given_table(spark, sf):
    import corpus_pipeline

    docs = corpus_pipeline.exact(spark, table(spark, sf, "documents"), sf)
    want = {d for d, c in _plain([(r["doc_id"], r["text"] or "") for r in docs.collect()]).items() if d == c}
    got = corpus_pipeline.near(spark, docs, sf)
    assert got.columns == docs.columns and {r["doc_id"] for r in got.collect()} == want and len(want) < docs.count()


def test_near_edges(spark):
    docs = spark.createDataFrame([(3, None), (2, " "), (5, "a b"), (None, "A  b"), (7, "a c"), (8, "x y z"), (None, "alone")], SCHEMA)
    got = sorted((r["doc_id"] or 0, r["text"] or "") for r in near.drop_near_copies(docs).collect())
    assert got == [(0, "alone"), (2, " "), (5, "a b"), (7, "a c"), (8, "x y z")]
    again = spark.createDataFrame([(1, "a b"), (1, "A b"), (1, "c d"), (4, "c d"), (4, "c d"), (None, "n"), (None, "N"), (None, "n")], SCHEMA)
    kept = near.drop_near_copies(again.withColumn("node", F.lit("clash")).withColumn("sha", F.lit(1)))
    assert kept.columns == ["doc_id", "text", "node", "sha"]
    assert sorted((r["doc_id"] or 0, r["text"].lower()) for r in kept.collect()) == [(0, "n"), (1, "a b"), (1, "c d")]
    assert near.near_components(docs.where("false")).count() == 0


def test_fingerprints_propose_pairs(spark, monkeypatch):
    """Without any band in common, near copies within two bits are still found by their fingerprints."""
    rng = random.Random(9)
    words = [f"w{rng.randrange(9999)}" for _ in range(4000)]
    own = near.fingerprint_of(near.shingle_set(" ".join(words)))
    copies = [" ".join([*words[:at], "other", *words[at + 1 :]]) for at in range(0, 4000, 50)]
    close = [t for t in copies if (near.fingerprint_of(near.shingle_set(t)) ^ own).bit_count() <= 2][:2]
    docs = list(enumerate([" ".join(words), *close]))
    assert len(docs) == 3
    monkeypatch.setattr(near, "_stars", lambda members, hubs, least: members.where("false").select(F.col("m.node").alias("a"), F.col("m.node").alias("b")))
    got = near.near_components(spark.createDataFrame(docs, SCHEMA), crowded=1 << 30).select("component_id").distinct().collect()
    assert [r[0] for r in got] == [0]


def test_late_links_are_no_more_than_a_forest():
    """All members of a group are linked to one another; what comes out leads to each once."""
    import numpy as np
    import pyarrow as pa

    grams = [np.unique(np.concatenate([np.arange(400), [1000 + i]])).astype("<u8").tobytes() for i in range(300)]
    table_ = pa.table({"node": pa.array(range(300), pa.int64()), "label": pa.array(range(300), pa.int64()), "grams": pa.array(grams, pa.binary())})
    up = {}
    first = near._against(table_.slice(0, 100), 0.8, up)
    assert sum(t.num_rows for t in first(iter(table_.slice(0, 100).to_batches()))) == 99
    rest = [(x, y) for t in first(iter(table_.to_batches())) for x, y in zip(*t.to_pydict().values())]
    assert len(rest) == 200
