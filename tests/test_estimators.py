"""Algebra of the estimator with exact fractions, and by enumeration."""

from fractions import Fraction as Q
from itertools import product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from headcount.functions import estimators as E

PS = [Q(1, 10), Q(42, 100), Q(1, 2), Q(83, 100), Q(9, 10), Q(1)]


@pytest.mark.parametrize("p", PS)
def test_forward_and_back(p):
    true = {1: 100, 2: 50, 3: 20}
    seen = E.expected_histogram(true, p)
    assert E.recover_counts(seen, p) == true
    assert E.estimate(seen, p) == 170


@pytest.mark.parametrize("p", PS)
def test_general_weights_contain_the_published_ones(p):
    q = 1 - p
    w = E.component_weights(p, 6)
    assert w[:3] == [1, (2 * p - 1) / p, (1 - 6 * p * q**2) / (p**2 * (3 - 2 * p))]
    for k in range(1, 7):
        assert sum(x * y for x, y in zip(E.breakage(k, p), w, strict=False)) == 1


@pytest.mark.parametrize("p", PS)
def test_variance_by_enumeration_of_edge_subsets(p):
    q, w = 1 - p, E.component_weights(p)
    mean = square = Q(0)
    for kept in product((0, 1), repeat=3):
        chance = p ** sum(kept) * q ** (3 - sum(kept))
        value = {0: 3 * w[0], 1: w[0] + w[1], 2: w[2], 3: w[2]}[sum(kept)]
        mean += chance * value
        square += chance * value**2
    assert mean == 1
    assert square - 1 == E.variance(0, 1, p)
    assert p * w[1] ** 2 + q * 4 - 1 == E.variance(1, 0, p)


def test_published_numbers():
    assert round(float(E.variance(0, 1, 0.83)), 6) == 0.070024
    assert round(float(E.variance(1, 0, 0.83)), 6) == 0.204819
    p = 6.923e-6
    assert E.variance(0, 1, p) == pytest.approx(6_954_620_166, rel=1e-3)
    assert E.variance(1, 0, p) == pytest.approx(144_443, rel=1e-3)
    assert [round(float(E.component_weights(0.42, 5)[k]), 6) for k in (3, 4)] == [0.476583, 0.593402]
    contribution = lambda k, p: sum(x * (E.component_weights(p)[j] if j < 3 else 1) for j, x in enumerate(E.breakage(k, p)))
    assert [round(contribution(4, p), 4) for p in (0.42, 0.72, 0.83, 0.92)] == [1.2299, 1.0736, 1.0192, 1.0021]
    assert [round(E.connected_probability(4, p), 4) for p in (0.42, 0.72, 0.83, 0.92)] == [0.4393, 0.9115, 0.9794, 0.9979]


@given(st.floats(0.05, 0.98), st.floats(0, 1e6), st.floats(1, 1e6))
@settings(max_examples=50, deadline=None)
def test_variance_falls_with_p(p, n3, n2):
    assert E.variance_slope(n2, n3, p) < 0


def test_identities():
    assert E.variance(10, 5, 1) == 0
    assert E.estimate({1: 7, 2: 3, 5: 2}, 1) == 12
    assert E.estimate({1: 9}, 0.3) == 9
    assert E.similarity_at(E.retrieval_probability(0.7, 4, 25), 4, 25) == pytest.approx(0.7)


def test_rows_and_states(spark):
    from headcount.operators.observed import estimate_row

    h = spark.createDataFrame([(1, 900), (2, 60), (3, 10), (7, 2)], "size long, n long")
    ok = estimate_row(h, 0.83).first()
    assert ok["estimate"] == pytest.approx(float(E.estimate({1: 900, 2: 60, 3: 10, 7: 2}, 0.83)))
    c = E.recover_counts({1: 900, 2: 60, 3: 10}, 0.83)
    assert ok["variance"] == pytest.approx(E.variance(c[2], c[3], 0.83)) and ok["status"] == "ok"
    assert estimate_row(h, None).first()["status"] == "undefined"
    assert estimate_row(h, None).first()["estimate"] is None
    assert estimate_row(h, 0.3).first()["status"] == "low_p"
