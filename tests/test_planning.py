import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from regionfilter.operators import measure
from regionfilter.plans import baselines, kinds, planner
from regionfilter.plans import rates as R
from regionfilter.plans import thresholds as T
from regionfilter.workloads import zipf_hist

TOY = T.Histogram((1, 1, 2, 4, 8, 16, 32, 64), (64, 32, 16, 8, 4, 2, 1, 1), 0.0)
GOLDEN = [
    (0.001, 2, (0, 5, 8), 6.128623, 3.837161, (0, 5, 8), 6.128623),
    (0.001, 3, (0, 4, 6, 8), 5.646243, 4.319541, (0, 4, 6, 8), 5.646243),
    (0.001, 4, (0, 3, 5, 6, 8), 5.552292, 4.413492, (0, 3, 5, 6, 8), 5.552292),
    (0.01, 3, (0, 4, 6, 8), 2.324315, 4.319541, (0, 4, 6, 8), 2.324315),
    (0.1, 2, (0, 5, 8), 0.477087, 3.837161, (0, 4, 8), 0.290241),
    (0.1, 3, (0, 4, 6, 8), 0.290241, 4.319541, (0, 2, 4, 8), 0.227075),
    (0.1, 4, (0, 3, 5, 6, 8), 0.258042, 4.413492, (0, 2, 3, 4, 8), 0.211450),
    (0.3, 3, (0, 4, 6, 8), 0.123806, 4.319541, (0, 2, 3, 8), 0.056470),
]


@pytest.mark.parametrize("target,k,cuts,size,divergence,top_cuts,top_size", GOLDEN)
def test_golden(target, k, cuts, size, divergence, top_cuts, top_size):
    a, b = planner.relaxed_then_cap(TOY, k, target), planner.top_boundary(TOY, k, target)
    assert (a.cuts, round(a.bits_per_key, 6), round(a.divergence, 6)) == (cuts, size, divergence)
    assert (b.cuts, round(b.bits_per_key, 6)) == (top_cuts, top_size)
    assert round(planner.exhaustive(TOY, k, target).bits_per_key, 6) == top_size


def test_synthetic_scores_by_design():
    h = zipf_hist(1000, 1.0)
    sizes = [p.bits_per_key for p in (baselines.single(h, 0.01), baselines.sandwich(h, 0.01), planner.relaxed_then_cap(h, 5, 0.01), planner.top_boundary(h, 5, 0.01))]
    assert [round(x, 3) for x in sizes] == [3.306, 3.256, 2.244, 2.165]
    assert baselines.geometric_separate(h, 5, 0.01).bits_per_key > sizes[-1]
    assert [round(T.best_cuts(h, k)[1], 3) for k in (2, 3, 4, 5)] == [3.388, 4.275, 4.616, 4.779]
    assert 4 <= planner.pick_k(h, 0.001) <= 6


hists = st.integers(4, 10).flatmap(lambda n: st.tuples(st.lists(st.integers(0, 50), min_size=n, max_size=n), st.lists(st.integers(0, 50), min_size=n, max_size=n))).filter(lambda x: sum(x[0]) > 0)


@settings(max_examples=60, deadline=None)
@given(hists, st.integers(1, 4), st.sampled_from([0.001, 0.01, 0.1, 0.4]))
def test_properties(hist, k, target):
    h = T.Histogram(tuple(hist[0]), tuple(hist[1]), 0.5)
    a, b, e = planner.relaxed_then_cap(h, k, target), planner.top_boundary(h, k, target), planner.exhaustive(h, k, target)
    assert e.bits_per_key - 1e-6 <= b.bits_per_key <= a.bits_per_key + 1e-6
    for p in (a, b, e):
        assert p.expected_rate <= target + 1e-9 and all(0 <= x <= 1 for x in p.rates)
    assert max(T.divergence(*h.shares(c)) for c in T.exhaustive_cuts(h, k)) == pytest.approx(T.best_cuts(h, k)[1], abs=1e-8)
    assert a.divergence >= -1e-9
    if planner.relaxation_is_tight(a):
        assert a.bits_per_key == pytest.approx(measure.relaxed_bits(1, 1.0, target, a.divergence), abs=1e-9)
    if k < h.size:
        assert T.best_cuts(h, k + 1)[1] >= T.best_cuts(h, k)[1] - 1e-9
    if 0 < b.bits_per_key < math.inf:
        assert planner.for_budget(h, k, b.bits_per_key * h.n).expected_rate <= target * (1 + 1e-6)


def test_two_regions_are_a_sandwich():
    for target in (0.1, 0.01, 0.001):
        s, r = baselines.sandwich(TOY, target), planner.top_boundary(TOY, 2, target)
        assert r.bits_per_key == pytest.approx(s.bits_per_key, abs=1e-9)
        back = baselines.regions_as_two_stages(s.as_regions(TOY.size, int(sum(TOY.kc[: s.cut]))))
        assert (back.front, back.backup) == pytest.approx((s.front, s.backup))
        one = baselines.single(TOY, target)
        assert one is None or s.bits_per_key <= one.bits_per_key + 1e-9


def test_single_is_flagged_where_it_cannot_work():
    assert baselines.single(T.Histogram((1, 5), (5, 5), 0.0), 0.01) is None


def test_budget_inverts_target():
    h = zipf_hist(200, 1.0)
    p = planner.top_boundary(h, 5, 0.001)
    assert planner.for_budget(h, 5, p.bits_per_key * h.n).expected_rate == pytest.approx(0.001, rel=1e-9)


def test_edges():
    assert R.capped([0.0, 1.0], [0.5, 0.5], 0.1).tolist() == [0.0, 0.2]
    assert R.capped([0.5, 0.5], [1.0, 0.0], 0.1).tolist() == [0.1, 1.0]
    assert T.term(0.5, 0.0) == math.inf and T.term(0.0, 0.0) == 0
    with pytest.raises(ValueError):
        T.dp_table(TOY, 9)
    assert planner.top_boundary(TOY, 1, 0.01).rates == (0.01,)
    assert planner.top_boundary(TOY, 3, 1.0).bits_per_key == 0
    assert kinds.bits_per_key("standard", 0.5) == pytest.approx(1 / math.log(2))
    assert kinds.bits_per_key("cuckoo", 2**-8) > kinds.bits_per_key("ideal", 2**-8)
    assert planner.top_boundary(T.Histogram((0, 0, 0), (1, 1, 1)), 2, 0.1).bits_per_key == 0
    assert np.isclose(measure.relaxed_bits(10, 1.44, 0.01, 2.0), 14.4 * (math.log2(100) - 2))


def test_rates_do_not_depend_on_the_kind_of_filter():
    p = planner.top_boundary(TOY, 3, 0.01)
    q = planner.Plan(**{**p.__dict__, "c": 1.44})
    assert q.rates == p.rates and q.bits_per_key == pytest.approx(1.44 * p.bits_per_key)
