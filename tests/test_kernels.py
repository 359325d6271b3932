"""The kernels against plain double loops, brute-force covers and the worked examples."""

import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from warpspan.functions import kernels as K

NORMS = [1, 2, 3, math.inf]


def plain_dtw(x, y, w, p):
    n, m = len(x), len(y)
    table = np.full((n + 1, m + 1), np.inf)
    table[0, 0] = 0
    for i in range(n):
        for j in range(m):
            if abs(i - j) <= w:
                c = abs(x[i] - y[j]) ** (1 if p == math.inf else p)
                best = min(table[i, j], table[i + 1, j], table[i, j + 1])
                table[i + 1, j + 1] = max(c, best) if p == math.inf else c + best
    return table[n, m]


def plain_cover(x, y, w, p):
    n = len(x)
    edges = [(i, j) for i in range(n) for j in range(n) if abs(i - j) <= w]
    best = math.inf
    for size in range(n, len(edges) + 1):
        for chosen in itertools.combinations(edges, size):
            if len({i for i, _ in chosen}) == n == len({j for _, j in chosen}):
                costs = [abs(x[i] - y[j]) ** (1 if p == math.inf else p) for i, j in chosen]
                best = min(best, max(costs) if p == math.inf else sum(costs))
    return best


series_pairs = st.integers(1, 9).flatmap(
    lambda n: st.tuples(*(st.lists(st.integers(-9, 9), min_size=n, max_size=n) for _ in range(2)), st.integers(0, n + 2), st.sampled_from(NORMS))
)


@settings(max_examples=150, deadline=None)
@given(series_pairs)
def test_chain_and_plain_versions(case):
    x, y, w, p = case
    a, b = np.array([x], float), np.array([y], float)
    d = K.dtw_pow(a, b, w, p)[0]
    assert d == plain_dtw(x, y, w, p)
    lo, hi = K.envelope(b, w)
    for i in range(len(y)):
        window = y[max(0, i - w) : i + w + 1]
        assert (lo[0, i], hi[0, i]) == (min(window), max(window))
    low, high, comparisons = K.envelope_by_queues(y, w)
    assert low == lo[0].tolist() and high == hi[0].tolist() and comparisons <= 3 * len(y)
    first, second = K.pass1_pow(a, lo, hi, p)[0], K.pass2_pow(a, b, lo, hi, min(w, len(y) - 1), p)[0]
    cover = K.ndtw_pow(x, y, w, p)
    slack = 1e-9
    assert first <= second + slack and second <= cover + slack and cover <= d + slack and d <= K.lp_pow(a, b, p)[0] + slack
    if p == 1:
        parts = [(0, len(x) // 2), (len(x) // 2, len(x))]
        sums, low, high = (K.piecewise_sums(m, parts) for m in (a, lo, hi))
        assert np.maximum(np.maximum(low - sums, sums - high), 0).sum() <= first + slack


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 3).flatmap(lambda n: st.tuples(*(st.lists(st.integers(-4, 4), min_size=n, max_size=n) for _ in range(2)), st.integers(0, 3), st.sampled_from(NORMS))))
def test_cover_and_generic_bound(case):
    x, y, w, p = case
    assert abs(K.ndtw_pow(x, y, w, p) - plain_cover(x, y, w, p)) < 1e-9
    assert abs(K.ndtw_pow(x, y, None, p) - K.ndtw_sorted_pow(x, y, p)) < 1e-9
    # Any admissible h splits the distance.
    a, b = np.array([x], float), np.array([y], float)
    lo, hi = K.envelope(b, w)
    for share in (0.0, 0.3, 1.0):
        h = a + share * (K.clamp(a, lo, hi) - a)
        parts = K.lp_pow(a, h, p)[0], K.ndtw_pow(h[0], y, w, p)
        assert K.ndtw_pow(x, y, w, p) >= (max(parts) if p == math.inf else sum(parts)) - 1e-9
        error = K.root(K.dtw_pow(a, b, w, p)[0], p) - K.root(K.lp_pow(a, h, p)[0], p)
        assert error <= K.root(K.lp_pow(h, b, p)[0], p) + 1e-9


def test_worked_examples():
    assert K.dtw_pow([[0, 1, 1, 0]], [[0, 1, 0, 0]], 1)[0] == 0
    assert K.lp_pow(np.array([[0.0, 1, 1, 0]]), np.array([[0.0, 1, 0, 0]]))[0] == 1
    path, cost = K.warping_path([0, 1, 1, 0], [0, 1, 0, 0], 1)
    left, right = K.aligned([0, 1, 1, 0], [0, 1, 0, 0], path)
    assert cost == 0 and left == right
    x, y = [[0, 0, 1, 0]], [[2, 3, 2, 2]]
    assert K.dtw_pow(x, y, None, 2)[0] == 17 and K.lp_pow(np.array(x), np.array(y), 2)[0] == 18
    assert K.dtw_pow([[5, 7, 6]], [[1, 2, 0]])[0] == 15 == K.ndtw_pow([5, 7, 6], [1, 2, 0])
    far = K.dtw_pow([[0, 0, 0]], [[0, 1, 1]])[0]
    assert far > K.dtw_pow([[0, 0, 0]], [[0, 0, 1]])[0] + K.dtw_pow([[0, 0, 1]], [[0, 1, 1]])[0]  # no metric
    lo, hi = K.envelope(np.array([[3, 1, 4, 1, 5]]), 1)
    assert hi.tolist() == [[3, 4, 4, 5, 5]] and lo.tolist() == [[1, 1, 1, 1, 1]]


def test_first_pass_depends_on_the_order():
    x, y = np.array([[0.0, 5, 0]]), np.array([[0.0, 0, 0]])
    there, back = K.pass1_pow(x, *K.envelope(y, 1))[0], K.pass1_pow(y, *K.envelope(x, 1))[0]
    assert (there, back) == (5, 0)


@pytest.mark.parametrize("n", [1, 2, 7, 40])
@pytest.mark.parametrize("form", ["random", "constant", "rising", "falling", "saw"])
def test_comparisons_and_band_extremes(n, form):
    rng = np.random.default_rng(n)
    y = {"random": rng.normal(size=n), "constant": np.ones(n), "rising": np.arange(n), "falling": -np.arange(n), "saw": np.arange(n) % 3}[form].astype(float)
    for w in (0, 1, n // 2, n - 1, n, 5 * n):
        lo, hi, comparisons = K.envelope_by_queues(y.tolist(), w)
        assert comparisons <= 3 * n
        if w >= n - 1:
            assert set(lo) == {y.min()} and set(hi) == {y.max()}
    x = rng.normal(size=n)
    assert np.isclose(K.dtw_pow(x, y, 0)[0], np.abs(x - y).sum())
    assert K.dtw_pow(x, y, n)[0] == K.dtw_pow(x, y, None)[0] == K.dtw_pow(x, y, n - 1)[0]
    wide = [K.dtw_pow(x, y, w)[0] for w in range(n)]
    assert all(a >= b - 1e-12 for a, b in zip(wide, wide[1:], strict=False))


def test_unequal_lengths_and_abandoning():
    assert K.dtw_pow([[1, 2, 3, 3]], [[1, 2, 3]], 2)[0] == 0
    assert K.dtw_pow([[1, 2, 3, 3, 3]], [[1, 2]], 2)[0] == math.inf
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(20, 100)).cumsum(axis=1), rng.normal(size=(1, 100)).cumsum(axis=1)
    lo, hi = K.envelope(y, 5)
    full = K.pass1_pow(x, lo, hi)
    part, read = K.abandoning_pass1(x, lo, hi, np.median(full))
    assert (part <= full + 1e-9).all() and ((part < np.median(full)) == (full < np.median(full))).all() and read <= x.size
    for p in (1, 2, math.inf):
        first, both = K.pass1_pow(x, lo, hi, p), K.pass2_pow(x, y, lo, hi, 5, p)
        assert np.allclose(K.abandoning_pass2(x, y, lo, hi, 5, first, np.inf, p, 7)[0], both)
        limit = np.median(both)
        part, read = K.abandoning_pass2(x, y, lo, hi, 5, first, limit, p, 7)
        assert (part <= both + 1e-9).all() and ((part < limit) == (both < limit)).all() and read < x.size


def test_paths_are_minimal_and_cheapest():
    rng = np.random.default_rng(3)
    for _ in range(40):
        n = int(rng.integers(1, 8))
        x, y = rng.integers(0, 4, n), rng.integers(0, 4, n)
        path, cost = K.warping_path(x, y, 2)
        rows, columns = [i for i, _ in path], [j for _, j in path]
        assert set(rows) == set(columns) == set(range(n))
        assert not any(rows.count(i) > 1 and columns.count(j) > 1 for i, j in path)
        assert cost == K.dtw_pow(x, y, 2)[0] == sum(abs(x[i] - y[j]) for i, j in path)


def test_errors():
    for bad in (lambda: K.check_norm(0.5), lambda: K.check_norm(0, bound=False), lambda: K.check_band(-1, 4)):
        with pytest.raises(ValueError):
            bad()
    assert K.check_norm(0.5, bound=False) == 0.5
