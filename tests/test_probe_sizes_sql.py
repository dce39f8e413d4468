import pytest

from regionfilter.operators import filters
from regionfilter.queries import methods


@pytest.mark.parametrize("limits", [{"ARRAY_BITS": 1}, {"ARRAY_BITS": 1, "BROADCAST_BITS": 1}])
@pytest.mark.parametrize("name", ["probe_counts_region", "probe_counts_region_broadcast", "probe_counts_standard", "probe_counts_shared"])
def test_answers_of_the_sql_above_the_limits(spark, sf, same, monkeypatch, name, limits):
    for limit, value in limits.items():
        monkeypatch.setattr(filters, limit, value)
    same(methods.QUERIES[name](spark, sf), methods.ORACLES[name])
