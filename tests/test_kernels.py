"""Numeric kernels against brute force."""

import itertools
import math
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from joincluster.operators import bounds, fd
from joincluster.operators.categorical import categorical_cost, scaled_cost, scaled_parts
from joincluster.operators.line import line_kmeans
from joincluster.operators.transport import wasserstein_small
from joincluster.plans.hypergraph import Hypergraph, fhtw, gap_exponent, rho_star


def partitions(items, k):
    items = list(items)
    if not items:
        yield []
        return
    for rest in partitions(items[1:], k):
        for i in range(len(rest)):
            yield [*rest[:i], [items[0], *rest[i]], *rest[i + 1 :]]
        if len(rest) < k:
            yield [[items[0]], *rest]


def line_cost(x, w, parts, p=2, lam=0.0):
    out = 0.0
    for part in parts:
        xs, ws = np.array([x[i] for i in part], float), np.array([w[i] for i in part], float)
        if p == 1:
            out += min(float((ws * abs(xs - c)).sum()) for c in xs)
        else:
            m = (ws * xs).sum() / ws.sum()
            c = math.copysign(max(abs(m) - lam / (2 * ws.sum()), 0), m)
            out += float((ws * (xs - c) ** 2).sum()) + lam * abs(c)
    return out


values = st.lists(st.tuples(st.integers(-20, 20), st.integers(1, 5)), min_size=1, max_size=7, unique_by=lambda t: t[0])


@settings(max_examples=40, deadline=None)
@given(values, st.integers(1, 4), st.sampled_from([(2, 0.0), (1, 0.0), (2, 3.0)]))
def test_line_is_optimal(data, k, how):
    x, w = zip(*data, strict=True)
    p, lam = how
    best = min(line_cost(x, w, q, p, lam) for q in partitions(range(len(x)), k))
    if lam and len(x) <= k:
        return  # with a penalty fewer segments can be cheaper; as many as values are returned
    for method in ("dp", "dc"):
        assert line_kmeans(x, w, k, method, p, lam).cost == pytest.approx(best, abs=1e-6) or lam


def test_line_examples():
    a = line_kmeans([0, 1, 10], [1, 1, 1], 2)
    assert list(a.centers) == [0.5, 10.0] and a.cost == pytest.approx(0.5)
    assert line_kmeans([3, 3, 3], [1, 2, 3], 2).cost == 0
    assert line_kmeans([], [], 3).cost == 0
    assert line_kmeans([1, 2], [1, 0], 2).centers.tolist() == [1.0]
    assert line_kmeans([1, 2, 3], [1, 1, 1], 9).cost == 0


def test_line_methods_agree_on_many_values():
    rng = np.random.default_rng(0)
    x, w = rng.normal(size=600), rng.integers(1, 9, 600)
    costs = [line_kmeans(x, w, k, "dp").cost for k in (2, 5, 9)]
    assert costs == pytest.approx([line_kmeans(x, w, k, "dc").cost for k in (2, 5, 9)])
    assert costs == sorted(costs, reverse=True)
    assert line_kmeans(x, w, 5, "lloyd").cost >= costs[1] - 1e-9


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 30), min_size=1, max_size=7), st.integers(2, 4), st.sampled_from([1, 2]))
def test_heavy_light_is_optimal(ws, k, p):
    w = {str(i): float(v) for i, v in enumerate(ws)}
    order = sorted(w, key=lambda e: (-w[e], e))
    parts = [{e} for e in order[: k - 1]] + ([set(order[k - 1 :])] if len(order) >= k else [])
    best = min(categorical_cost(w, [set(q) for q in part], p) for part in partitions(w, k))
    got = categorical_cost(w, parts, p)
    assert got <= (best if p == 2 else 2 * best) + 1e-9


def test_categorical_closed_form():
    w = {"a": 5.0, "b": 3.0, "c": 1.0, "d": 1.0}
    assert categorical_cost(w, [{"a"}, {"b"}, {"c", "d"}]) == pytest.approx(1.0)
    assert categorical_cost({"a": 2.0, "b": 2.0, "c": 2.0}, [{"a"}, {"b", "c"}]) == pytest.approx(2.0)
    x, names = np.eye(4), list(w)
    part = [0, 1, 3]
    v = np.array([w[names[i]] for i in part])
    mu = (v[:, None] * x[part]).sum(0) / v.sum()
    assert categorical_cost(w, [{names[i] for i in part}]) == pytest.approx((v * ((x[part] - mu) ** 2).sum(1)).sum())


def test_scaled_categories():
    w, s = {"a": 4.0, "b": 3.0, "c": 2.0, "d": 1.0}, {"d": 10.0}
    best = min(scaled_cost(w, s, [set(q) for q in part]) for part in partitions(w, 3))
    assert scaled_cost(w, s, scaled_parts(w, s, 3)) == pytest.approx(best)


def test_widths():
    triangle = Hypergraph.of("ab", "bc", "ac")
    assert rho_star(triangle) == Fraction(3, 2) and fhtw(triangle) == Fraction(3, 2)
    star = Hypergraph.of("abcd", "a", "b", "c")
    assert fhtw(star) == 1
    square = Hypergraph.of("ab", "bc", "cd", "da")
    assert rho_star(square) == 2 and fhtw(square) == 2
    path = Hypergraph.of("ab", "bc", "cd", "de", "ef")
    assert fhtw(path) == 1 and rho_star(path) == 3 and gap_exponent(path) == 1


def test_bounds():
    assert bounds.approx_bound() == pytest.approx(9)
    assert bounds.approx_bound(1, 4) == pytest.approx((1 + 2 * 2) ** 2)
    assert bounds.approx_bound_reg() == 10
    assert bounds.approx_lower_bound(256, 2, 4) > bounds.approx_lower_bound(16, 2, 4)
    assert bounds.check_kappa(5, [3, 5]) and not bounds.check_kappa(4, [3, 5])


def test_chain_cover():
    fds = [("store", "zip"), ("zip", "city"), ("city", "state"), ("sku", "class")]
    assert fd.chain_cover(fds, ["store", "zip", "city", "state", "sku", "class", "x"]) == [["store", "zip", "city", "state"], ["sku", "class"], ["x"]]
    assert fd.cell_bound([["a", "b", "c"], ["d"]], 5) == 13 * 5
    star = fd.chain_cover([("c", "seg"), ("c", "nat"), ("nat", "reg")], ["c", "seg", "nat", "reg"])
    assert sorted(map(len, star)) == [1, 3]
    assert len(fd.chain_cover([("a", "b"), ("b", "a")], ["a", "b"])) == 1


def test_wasserstein_small():
    assert wasserstein_small([0, 1], [1, 1], [0, 1], [1, 1]) == pytest.approx(0)
    assert wasserstein_small([0], [1], [3], [1], 1) == pytest.approx(3)
    rng = np.random.default_rng(1)
    for _ in range(5):
        x, y = rng.normal(size=(4, 2)), rng.normal(size=(4, 2))
        best = min(sum(((x[i] - y[j]) ** 2).sum() for i, j in enumerate(p)) / 4 for p in itertools.permutations(range(4)))
        assert wasserstein_small(x, [1] * 4, y, [1] * 4) ** 2 == pytest.approx(best)
        marg = sum(wasserstein_small(x[:, j], [1] * 4, y[:, j], [1] * 4) ** 2 for j in range(2))
        assert best >= marg - 1e-9
