"""Hand-worked numbers: a population of 12 rows in strata A (6), B (4) and C (2)."""

from __future__ import annotations

from math import isclose, isnan, sqrt

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from progressive_text.operators import allocate
from progressive_text.operators.estimate import GroupState, Moments, StratumDraws, finite, group_shares, normalised, random_share, stratified_filter, valid_mean, z, z_of
from progressive_text.operators.refine import merge_target
from progressive_text.operators.strata import strata_bounds

SIZES = {"A": 6, "B": 4, "C": 2}
STATES = [GroupState(6, 3, {"x": 2, "y": 1}), GroupState(4, 2, {"y": 2}), GroupState(2, 1, {"x": 1})]


def moments(values) -> Moments:
    out = Moments()
    for v in values:
        out += Moments(1, float(v), 0.0)
    return out


def test_quantiles():
    assert isclose(z(0.95), 1.95996398454005, abs_tol=1e-12)
    for k, want in ((2, 2.24140272760495), (3, 2.39397979981851), (4, 2.49770547441237), (10, 2.80703376834381)):
        assert isclose(z_of(0.95, k), want, abs_tol=1e-12)
    assert z_of(0.95, 3, literal_level=True) < 1


def test_allocation():
    assert allocate.proportional(SIZES, 6) == {"A": 3, "B": 2, "C": 1}
    left, weights = {"A": 3, "B": 2, "C": 1}, {"A": 4.0, "B": 0.0, "C": 0.0}
    assert allocate.share_out(weights, left, 3) == {"A": 3, "B": 0, "C": 0}
    assert allocate.share_out(weights, left, 3, 1) == {"A": 1, "B": 1, "C": 1}
    assert allocate.share_out(weights, left, 5) == {"A": 3, "B": 1, "C": 1}
    assert allocate.neyman(SIZES, {"A": 4 / 9, "B": 0, "C": 0}, 3, left, floor=0) == {"A": 3, "B": 0, "C": 0}
    assert allocate.proportional(SIZES, 0) == {"A": 0, "B": 0, "C": 0}
    assert allocate.proportional(SIZES, 100) == SIZES


def test_priority_breaks_ties_by_size_then_id():
    assert allocate.priority({"A": 2 / 3, "B": 0.0, "C": 1.0}, SIZES) == {"C": 1, "A": 2, "B": 3}
    assert allocate.priority({}, {"p": 1, "q": 2, "o": 1}) == {"q": 1, "o": 2, "p": 3}


def test_pooled_interval():
    mean, width = valid_mean(moments([10, 14, 18]))
    assert mean == 14 and isclose(width, 4.526342936304686)
    assert valid_mean(moments([5])) == (5.0, None) and valid_mean(Moments()) == (None, None)
    assert valid_mean(moments([1, 2]), population=2)[1] == 0


def test_stratified_count_and_exact_end():
    drawn = [StratumDraws(6, 3, moments([1, 1])), StratumDraws(4, 2, Moments()), StratumDraws(2, 1, moments([1]))]
    count, width = stratified_filter(drawn, "count")
    assert count == 6 and isclose(width, z(0.95) * sqrt(36 * 0.2 * (2 / 9)), rel_tol=1e-12) and isclose(width, 2.479180129218246)
    full = [StratumDraws(3, 3, moments([1, 2])), StratumDraws(2, 2, moments([9]))]
    assert stratified_filter(full, "avg") == (4.0, 0.0) and stratified_filter(full, "sum") == (12.0, 0.0) and stratified_filter(full, "count") == (3.0, 0.0)
    assert stratified_filter([StratumDraws(3, 1, Moments())], "avg") == (None, None)
    assert stratified_filter([StratumDraws(3, 0, Moments()), StratumDraws(3, 3, moments([1]))], "count")[1] is None


def test_state_and_shares():
    assert [s.dominant() for s in STATES] == ["x", "y", "x"]
    assert np.allclose([s.heterogeneity for s in STATES], [4 / 9, 0, 0])
    assert np.allclose([normalised(s.heterogeneity, 2) for s in STATES], [8 / 9, 0, 0]) and normalised(0.5, 1) == 0
    assert np.allclose([finite(6, 3), finite(4, 2), finite(2, 1)], [0.2, 1 / 3, 1.0]) and finite(1, 1) == 0 and finite(5, 5) == 0 and isnan(finite(5, 0))
    share, width, complete = group_shares(STATES, ["x", "y"])["x"]
    assert isclose(share, 0.5) and complete and isclose(width, 0.334128590925207)
    assert isclose(group_shares(STATES, ["x", "y"], form="printed")["x"][1], 0.136407426040315)
    own = group_shares([GroupState(6, 3, {"x": 2, "y": 1})], ["x", "y", "w"], scope="per_category")
    assert own["w"][1] == 0 < own["x"][1]
    assert group_shares([], ["x"])["x"] == (None, None, False)
    assert not group_shares([*STATES, GroupState(3, 0, {})], ["x", "y"])["x"][2]


def test_ties_and_unknown_labels():
    assert GroupState(4, 4, {"b": 2, "a": 2}).dominant() == "a"
    assert GroupState(4, 4, {}).dominant() is None and GroupState(4, 0, {}).heterogeneity == 0
    assert GroupState(10, 4, {"a": 2}).share("a") == 0.5  # two draws fell outside the domain


def test_strata_bounds():
    assert strata_bounds(15000, 3) == (29, 58) and strata_bounds(1, 3) == (1, 1) and strata_bounds(0, 3) == (1, 1)


def test_merge_target():
    means = {0: np.array([1.0, 0]), 1: np.array([0, 1.0]), 2: np.array([0.9, 0.1])}
    dominants = {0: "x", 1: "y", 2: "x"}
    away = np.array([0.05, 0.95])
    assert merge_target("y", away, 0, dominants, means) == 1
    assert merge_target("x", away, 0, dominants, means) == 2
    assert merge_target("z", away, 0, dominants, means) is None
    assert merge_target("z", away, 0, dominants, means, "nearest") == 1


def test_random_share_is_exact_at_the_end():
    assert random_share(3, 10, 10) == (0.3, 0.0) and random_share(0, 0, 5) == (None, None)


numbers = st.dictionaries(st.integers(0, 9), st.integers(0, 40), min_size=1)


@settings(max_examples=200, deadline=None)
@given(numbers, st.integers(0, 200), st.integers(0, 3), st.data())
def test_allocation_keeps_its_promises(capacity, n, floor, data):
    weights = {h: data.draw(st.floats(0, 100)) for h in capacity}
    got = allocate.share_out(weights, capacity, n, floor)
    assert sum(got.values()) == min(n, sum(capacity.values()))
    assert all(0 <= got[h] <= capacity[h] for h in capacity)
    if floor and n >= floor * len(capacity):
        assert all(got[h] >= min(floor, capacity[h]) for h in capacity)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.floats(-1e6, 1e6), min_size=2, max_size=40), st.integers(1, 39))
def test_moments_merge_like_numpy(values, cut):
    a = moments(values[:cut]) + moments(values[cut:])
    assert isclose(a.mean, np.mean(values), rel_tol=1e-9, abs_tol=1e-6)
    assert isclose(a.variance, np.var(values, ddof=1), rel_tol=1e-6, abs_tol=1e-3)


@settings(max_examples=100, deadline=None)
@given(st.dictionaries(st.sampled_from("abcd"), st.integers(0, 30), min_size=1))
def test_heterogeneity_is_bounded(counts):
    n = sum(counts.values())
    v = GroupState(100, n, counts).heterogeneity
    assert -1e-12 <= v <= 1 - 1 / 4 + 1e-12


def test_stratified_filter_is_unbiased_and_priority_means_are_not():
    """Draws by priority give strata unequal weight: the expanded mean stays right where the plain one does not."""
    rng = np.random.default_rng(0)
    strata = [(rng.normal(10, 1, 200), 0.9), (rng.normal(50, 1, 200), 0.3)]
    kept = [rng.random(200) < p for _, p in strata]
    truth = np.concatenate([v[k] for (v, _), k in zip(strata, kept, strict=True)]).mean()
    plain, expanded = [], []
    for _ in range(300):
        drawn, pooled = [], []
        for (v, _), k, m in zip(strata, kept, (100, 20), strict=True):
            at = rng.permutation(200)[:m]
            good = v[at][k[at]]
            pooled += [*good]
            drawn.append(StratumDraws(200, m, moments(good)))
        plain.append(np.mean(pooled))
        expanded.append(stratified_filter(drawn, "avg")[0])
    error = np.std(expanded) / sqrt(300)
    assert abs(np.mean(expanded) - truth) < 5 * error + 0.1
    assert abs(np.mean(plain) - truth) > 10 * error


def test_sums_of_whole_numbers_are_exact():
    """Count times mean is not: at large sums that shows in the sixth decimal of an estimate."""
    parts = [Moments(n, s / n, 0.0, float(s)) for n, s in ((49, 4973), (7, 611), (93, 9001), (41, 3))]
    held = sum(parts, Moments())
    assert held.sum == 4973 + 611 + 9001 + 3 and held.n == 190
    assert stratified_filter([StratumDraws(1_000_003, 200, held)], "sum")[0] == 1_000_003 * 14588.0 / 200
    assert valid_mean(held)[0] == 14588 / 190
    assert (held + Moments(2, 3.0)).known_sum is None and Moments(2, 3.0).sum == 6.0
