import itertools
import math
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rankscan.functions import nulllaw as N


def enumerated(n, w):
    c = Counter(map(sum, itertools.combinations(range(1, n + 1), w)))
    return [c[k] for k in range(min(c), max(c) + 1)]


@pytest.mark.parametrize("n", range(1, 12))
def test_all_exact_ways_equal_enumeration(n):
    masses = N.law_by_conditioning(n, n)
    for w in range(1, n + 1):
        want = enumerated(n, w)
        assert N.law_by_memo(n, w) == N.law_by_product(n, w) == want
        assert np.allclose(masses[w], np.array(want) / math.comb(n, w), rtol=1e-12)


def test_worked_examples():
    assert N.law_by_product(6, 3) == [1, 1, 2, 3, 3, 3, 3, 2, 1, 1]
    assert N.law_by_product(4, 2) == [1, 1, 2, 1, 1]
    ways = N.law_by_product(30, 8)
    assert (len(ways), sum(ways), max(ways)) == (177, 5_852_925, 107_233)
    assert N.memo_cells(500, 50) == 594_375_000
    assert N.required_samples(1e-4, 0.1) == 10**6
    assert N.min_width(1000, 1e-8) == 3
    floor = N.Law.exact(1000, 3)
    assert 10 ** floor.table(3, "tail")[-1] == pytest.approx(1 / math.comb(1000, 3), rel=1e-9) == pytest.approx(6.0180e-9, rel=1e-4)
    assert floor.table(3, "mass")[-1] == pytest.approx(floor.table(3, "tail")[-1])


def test_a_base_of_only_the_empty_box_counts_nothing():
    def literal(parts, largest, total):
        if total < 0:
            return 0
        if parts == 0 or largest == 0:
            return int(parts == largest == total == 0)
        return literal(parts, largest - 1, total) + literal(parts - 1, largest, total - largest)

    assert [literal(3, 3, k) for k in range(10)] == [0] * 10 != N.law_by_memo(6, 3)


def test_stable_recursion_against_integers():
    law = N.law_by_conditioning(120, 30)
    for w in (1, 7, 30):
        exact = np.array([x / math.comb(120, w) for x in N.law_by_product(120, w)])
        assert np.allclose(law[w], exact, rtol=1e-12)


@given(st.integers(2, 40), st.data())
@settings(max_examples=30, deadline=None)
def test_moments_symmetry_and_tails(n, data):
    w = data.draw(st.integers(1, n))
    law = N.Law(n, w, N.law_by_conditioning(n, w))
    m = law.mass[w]
    phi = np.arange(len(m)) + N.least_sum(w)
    mean = w * (n + 1) / 2
    assert m.sum() == pytest.approx(1) and np.allclose(m, m[::-1])
    assert (m * phi).sum() == pytest.approx(mean)
    assert (m * (phi - mean) ** 2).sum() == pytest.approx(w * (n - w) * (n + 1) / 12, abs=1e-9)
    assert np.all(np.diff(law.lower[w]) >= -1e-15)
    lo, hi = law.critical(w, 0.05)
    assert all((law.lower[w] <= 0.05) == (phi <= (lo if lo is not None else -1)))
    assert hi is None or hi == w * (n + 1) - lo


def test_sampled_law_and_censoring():
    exact, mc = N.Law.exact(50, 10), N.Law.sampled(50, 10, 40_000, 1)
    for w in (3, 10):
        ok = exact.mass[w] >= 5e-3
        assert np.abs(mc.mass[w][ok] / exact.mass[w][ok] - 1).max() < 5 * N.frequency_error(40_000 * 5e-3)
        assert mc.table(w, "tail").min() >= -math.log10(40_000) - 1e-12
