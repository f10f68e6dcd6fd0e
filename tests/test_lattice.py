import random
from math import comb

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pairlattice import lattice
from pairlattice.plans import bounds
from pairlattice.spec import EstimatorSpec, sub_values


@settings(max_examples=80, deadline=None)
@given(st.integers(1, 10), st.data())
def test_inversion_undoes_the_forward_system(d, data):
    s = data.draw(st.integers(1, d))
    x = {k: data.draw(st.integers(0, 10**6)) * 2 for k in range(s, d + 1)}
    n = data.draw(st.integers(0, 10**6))
    assert lattice.invert_moments(lattice.forward_moments(x, n, d, s), n, d, s) == x


def test_closed_form_is_the_recursion():
    y = {3: 500.0, 4: 90.0, 5: 30.0}
    x = lattice.invert_moments(y, 10, 5, 3)
    z = {k: v - comb(5, k) * 10 for k, v in y.items()}
    assert x == {k: sum(c * z[j] for a, j, c in lattice.inversion_matrix(5, 3) if a == k) for k in y}


def test_worked_system_has_the_coefficients_of_half_the_subvalues():
    d, s, r = 6, 4, 0.5
    assert [r * r * comb(j, k) for k in (6, 5, 4) for j in range(6, k - 1, -1)] == [0.25, 1.5, 0.25, 3.75, 1.25, 0.25]
    assert [r * comb(d, k) for k in (6, 5, 4)] == [0.5, 3.0, 7.5]
    x = {6: 2.0, 5: 138.0, 4: 1492.0}
    y = {k: r * comb(d, k) * 400 + r * r * sum(comb(j, k) * x[j] for j in range(k, 7)) for k in x}
    assert lattice.invert_sampled(y, {k: r * comb(d, k) * 400 for k in x}, d, s, r) == pytest.approx(x)


def test_scaling_higher_levels_twice_is_biased_below_ratio_one():
    x, n, d, s = {6: 200.0, 5: 138.0, 4: 1492.0}, 400, 6, 4
    sampled = lambda r: {k: r * comb(d, k) * n + r * r * sum(comb(j, k) * x[j] for j in range(k, 7)) for k in x}
    assert lattice.printed_recursion(sampled(1.0), n, d, s, 1.0) == pytest.approx(x)
    assert lattice.printed_recursion(sampled(0.5), n, d, s, 0.5)[4] > 1.2 * x[4]


def test_example_relation():
    x = lattice.invert_moments({3: 4, 2: 16}, 4, 3, 2)
    assert x == {3: 0, 2: 4}


def test_clamps():
    y, known = {3: 1.0, 2: 20.0}, {3: 4, 2: 12}
    assert lattice.invert_sampled(y, known, 3, 2)[3] == -3
    assert lattice.invert_sampled(y, known, 3, 2, clamp="final") == {3: 0, 2: 17}
    assert lattice.invert_sampled(y, known, 3, 2, clamp="cascade") == {3: 0, 2: 8}


@pytest.mark.parametrize("kw", [{"s": 0}, {"s": 6}, {"s": 3, "ratio": 0.0}, {"s": 3, "ratio": 1.5}, {"s": 3, "sampler": "x"}, {"s": 3, "null_policy": "never", "self_pairs": "expected"}, {"s": 3, "width": 0}])
def test_bad_options(kw):
    with pytest.raises(ValueError):
        EstimatorSpec(**kw).check(5)


def test_sizes_and_bounds():
    assert [sub_values(d, s) for d, s in ((5, 4), (5, 3), (6, 3), (8, 4), (10, 3))] == [6, 16, 42, 163, 968]
    assert bounds.sketch_bytes(6, 3, 1000, 3) == 48_000
    assert bounds.sample_size_for_bytes(48_000, 48) == 1000
    assert [bounds.variance_exact(d, s, r, 1) for d, s, r in ((5, 4, 1), (5, 3, 1), (6, 5, 0.5), (6, 4, 0.5), (6, 6, 0.5))] == [50, 600, 144, 2700, 2]
    assert bounds.variance_sketch(5, 4, 1, 1000, 15000, 15000) == pytest.approx(0.40334, abs=1e-4)
    assert bounds.min_sample_size(10_001) == 101
    assert bounds.ratio_for_budget(6, 3, 5)[3] == 0.25
    w, t = bounds.size_sketch(0.1, 0.05, 5, 4)
    assert w >= 8 * 50 / 0.01 - 1 and t % 2 == 1


def test_variance_falls_with_width_and_ratio():
    v = [bounds.variance_sketch(5, 4, r, w, 1000, 5000) for r, w in ((0.25, 100), (0.5, 100), (0.5, 1000), (1, 1000))]
    assert v == sorted(v, reverse=True)


def test_tab4_signs_of_four_keys_average_to_zero():
    from pairlattice.functions.hashing import coefficients, tab4_value

    rng = random.Random(1)
    keys = [rng.randrange(1 << 60) for _ in range(4)]
    total = 0
    for seed in range(4000):
        c = coefficients(seed, 0, "sign")
        p = 1
        for k in keys:
            p *= 1 if tab4_value(c, k) & 1 else -1
        total += p
    assert abs(total) < 4 * 4000**0.5
