import pytest

from regionfilter.operators import filters
from regionfilter.queries import methods, operators


@pytest.mark.parametrize("limits", [{"ARRAY_BITS": 1}, {"ARRAY_BITS": 1, "BROADCAST_BITS": 1}])
def test_queries_answer_above_the_limits(spark, sf, monkeypatch, limits):
    for name, value in limits.items():
        monkeypatch.setattr(filters, name, value)
    asked = methods.QUERIES["probe_counts_region"](spark, sf).collect()
    assert asked and sum(r["false_negatives"] for r in asked) == 0
    assert methods.QUERIES["false_negatives_all"](spark, sf).first()[0] == 0
    stream = operators.QUERIES["stream_probe_rows"](spark, sf).collect()
    assert sum(r["asked"] for r in stream) == spark.read.parquet(f"{sf}/events.parquet").count()
