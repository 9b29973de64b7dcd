from __future__ import annotations

import math
import random

import pytest

from sepkey.functions import bounds


@pytest.mark.parametrize(("m", "tuples", "pairs"), [(13, 411, 13_000), (55, 1_739, 55_000), (372, 11_764, 372_000)])
def test_published_sample_sizes(m, tuples, pairs):
    assert bounds.tuple_sample_size(m, 0.001) == tuples
    assert bounds.pair_sample_size(m, 0.001) == pairs


@pytest.mark.parametrize(("m", "r"), [(5, 328), (6, 352), (11, 468), (13, 514), (55, 1451)])
def test_calibrated_sizes(m, r):
    assert bounds.tuple_sample_size(m, 0.001, "calibrated") == r


def test_scopes_need_fewer_tuples():
    every = bounds.tuple_sample_size(28, 0.001, "calibrated")
    assert bounds.tuple_sample_size(28, 0.001, "calibrated", scope="each") < bounds.tuple_sample_size(28, 0.001, "calibrated", largest=3) < every
    assert bounds.tuple_sample_size(28, 0.001, "calibrated", family=100) < every


def test_noncollision_equals_power_sums_and_simulation():
    hist = [(5, 2), (3, 4), (1, 20)]
    n = sum(a * k for a, k in hist)
    p2 = sum(a * a * k for a, k in hist)
    assert bounds.noncollision(hist, 2) == pytest.approx(1 - p2 / n**2)
    gamma = sum(k * bounds.pairs_of(a) for a, k in hist)
    assert bounds.noncollision(hist, 2, False) == pytest.approx(1 - gamma / bounds.pairs_of(n))
    balls = [i for i, (a, k) in enumerate([(a, 1) for a, k in hist for _ in range(k)]) for _ in range(a)]
    rng, hit, trials = random.Random(1), 0, 20_000
    for _ in range(trials):
        drawn = rng.sample(balls, 5)
        hit += len(set(drawn)) == 5
    p = bounds.noncollision(hist, 5, False)
    assert abs(hit / trials - p) < 5 * math.sqrt(p * (1 - p) / trials)


def test_replacement_ratio_is_bounded_in_the_regime():
    for n, m, r in ((60_000, 11, 348), (15_000, 13, 411)):
        assert n > bounds.least_rows(r, m)
        assert 0 < bounds.log_replacement_ratio(n, r) < m


def test_equal_groups_are_not_the_worst_profile():
    found = bounds.compare_profiles(1500, 0.001)
    assert found["equal"] == -math.inf and found["heavy"] > -60
    assert bounds.worst_profile(411, 0.001)["ka"] == 1
    finite = bounds.worst_profile(411, 0.001, rest=(math.inf, 1e4, 1e6))
    assert finite["log_miss"] == bounds.worst_profile(411, 0.001)["log_miss"]


def test_planted_miss_two_ways():
    n, c, r = 60_000, 1_899, 348
    assert bounds.planted_size(n, 0.001) == c and bounds.pairs_of(c) > 0.001 * bounds.pairs_of(n)
    assert bounds.planted_miss(n, c, r) == pytest.approx(bounds.noncollision([(c, 1), (1, n - c)], r, False))


def test_block_identity_and_thresholds():
    for t in range(2, 6):
        for k in range(1, 6):
            for u in range(k + 1):
                assert bounds.block_gamma(t, k, u) == bounds.block_gamma_by_groups(t, k, u)
        eps = bounds.decoder_eps(t)
        high, low = bounds.decoder_gap(t)
        assert high / low == pytest.approx((1 + eps) / (1 - eps))


def test_inequalities_of_the_analysis():
    for m in (2, 13, 372):
        u = bounds.final_union(m)
        assert u["per_set"] < u["per_set_bound"] and u["all_sets"] < u["all_sets_bound"]
    g = bounds.group_argument(4, 0.001, 13)
    assert g["expected"] >= 2 * g["needed"] * 0.999
    x = bounds.grid_detection(999, 20, int(math.sqrt(math.log(20) * 999)))
    assert x["in_regime"] and x["exact"] <= x["ceiling"] <= x["one_over_e"]
    assert bounds.sketch_bits_lower(11, 2, 0.1) < bounds.sketch_bits_upper(11, 2, 0.01, 0.1)
    assert bounds.counting_bound(3, 4, 5)["failure"] > 1 / 3
    assert bounds.sketch_pairs(11, 2, 0.01, 0.1) == 47_958
