import itertools
import math

import pytest

from cardest.experiments.metrics import empirical_cap, is_shattered, projections
from cardest.query import And, Clause, Not, Or, Query, QueryClass, classify, clause_count, to_nnf
from cardest.theory import capacity as K

EPS = DELTA = 0.05


@pytest.mark.parametrize(("m", "b", "d", "rows"), [(1, 1, 2, 1000), (1, 2, 4, 1400), (1, 3, 6, 1800), (1, 5, 10, 2600), (1, 8, 16, 3800), (2, 2, 31, 6800), (2, 3, 57, 12000), (2, 5, 117, 24000), (2, 8, 220, 44600), (5, 5, 294, 59400)])
def test_published_selection_dimensions(m, b, d, rows):
    # the published size for m=1, b=3 is 2800; its own formula gives 1800
    assert K.cap_select(m, b, "table") == d
    assert K.sample_size(d, EPS, DELTA) == rows


@pytest.mark.parametrize(("b", "d", "rows"), [(1, 4, 1400), (2, 16, 3800), (3, 36, 7800), (5, 100, 20600), (8, 256, 51800)])
def test_published_join_dimensions(b, d, rows):
    assert K.cap_join(2 * b, 2 * b, "table") == d
    assert K.sample_size(d, EPS, DELTA) == rows


def test_numeric_bounds():
    assert [K.cap_numeric(m, b) for m, b in ((1, 1), (1, 2), (1, 5), (2, 5))] == [3, 9, 39, 45]
    assert K.cap_numeric(1, 1, 2) == 11
    assert K.cap_numeric(2, 5, 2, free_pair=True) == 108


def test_inequality_of_boolean_closure_holds_with_three_and_fails_with_two():
    for d, h in itertools.product(range(2, 12), range(2, 12)):
        n = K.cap_boolean(d, h)
        assert d * h * math.log2(n) + 2 * h * math.log2(h) <= n
    n = 2 * 3 * 2 * math.log2(6)
    assert 3 * 2 * math.log2(n) + 4 > n


def test_formula_count_bound():
    for h in range(1, 10):
        assert K.boolean_shapes(h) <= h ** (2 * h)


def test_inverses():
    s = K.sample_size(31, 0.03, 0.1)
    assert K.eps_for_sample(s, 31, 0.1) <= 0.03
    assert K.delta_for_sample(s, 31, 0.03) <= 0.1 + 1e-9
    assert K.relative_sample_size(31, 0.1, 0.2, 0.05) > K.sample_size(31, 0.2, 0.05)
    assert K.sample_size(31, 0.05, 0.05, population=10) == 10


def test_best_bound_is_smallest():
    d, name = K.best_bound(QueryClass(2, 2, 5))
    assert name == "direct" and d == 108
    assert K.best_bound(QueryClass(1, 1, 1))[0] == 2


def test_intervals_shatter_two_points_not_three():
    points = [1, 2, 3]
    ranges = [frozenset(p for p in points if a <= p <= b) for a in range(5) for b in range(5)]
    assert is_shattered(ranges, frozenset([1, 2])) and not is_shattered(ranges, frozenset(points))
    assert empirical_cap(ranges, points) == 2
    assert len(projections(ranges, frozenset(points))) == K.growth(2, 3) == 7


def test_equalities_need_two_clauses():
    points = range(8)
    eq = [frozenset([p]) for p in points] + [frozenset(points) - {p} for p in points]
    half = [frozenset(p for p in points if p <= c) for c in range(-1, 9)] + [frozenset(p for p in points if p >= c) for c in range(-1, 9)]
    assert empirical_cap(half, list(points)) == 2
    assert empirical_cap(half + eq, list(points)) == 3 <= 2 * 1 + 1


def test_normal_forms():
    p = Not(And(Clause("a", "<", 1), Or(Clause("b", "=", 2), Clause("c", ">=", 3))))
    assert to_nnf(p) == Or(Clause("a", ">=", 1), And(Clause("b", "!=", 2), Clause("c", "<", 3)))
    assert clause_count(p) == 4
    q = Query({"x": "t", "y": "t"}, {"x": p, "y": Clause("d", "<=", 1)})
    assert classify([q]) == QueryClass(2, 4, 4)
    assert Query.from_json(q.to_json()) == q
    with pytest.raises(ValueError):
        Clause("a", "~", 1)
