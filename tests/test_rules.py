"""Rules against brute force, in Python alone: what a node's bounds claim holds for all its members."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from treesieve import sqlface
from treesieve.functions import geometry as g
from treesieve.functions.expr import AnalysisError, E, abs_, case_, ceil_, col, evaluate, exp_, floor_, greatest_, least_, lit, negate, round_, sin_, sqrt_
from treesieve.functions.intervals import bounds, guards, tighten

X, Y = col("x"), col("y")
NUMBER = st.integers(-6, 6).map(float)
LEAF = st.one_of(st.just(X), st.just(Y), NUMBER.map(lit))
TERM = st.recursive(LEAF, lambda t: st.one_of(st.tuples(t, t).map(lambda p: p[0] + p[1]), st.tuples(t, t).map(lambda p: p[0] - p[1]), st.tuples(t, t).map(lambda p: p[0] * p[1]), st.tuples(t, t).map(lambda p: least_(*p)), st.tuples(t, t).map(lambda p: greatest_(*p)), t.map(lambda a: a * a), t.map(abs_), t.map(lambda a: -a), t.map(lambda a: sqrt_(abs_(a))), t.map(floor_), t.map(ceil_), t.map(round_), t.map(lambda a: a / 3.0), t.map(lambda a: a ** 2), t.map(lambda a: a % 4.0), t.map(sin_), st.tuples(t, t, t).map(lambda p: case_((p[0] < 1, p[1]), otherwise=p[2]))), max_leaves=8)
ATOM = st.tuples(TERM, TERM, st.sampled_from(["<", "<=", "=", "!="])).map(lambda p: E(p[2], (p[0], p[1])))
PREDICATE = st.recursive(ATOM, lambda p: st.one_of(st.tuples(p, p).map(lambda q: q[0] & q[1]), st.tuples(p, p).map(lambda q: q[0] | q[1]), p.map(negate)), max_leaves=4)


def env(name, side):
    return (col(f"{name}_lo", side), col(f"{name}_hi", side))


@settings(max_examples=300, deadline=None)
@given(PREDICATE, st.lists(st.tuples(NUMBER, NUMBER), min_size=1, max_size=8))
def test_guards_bracket_the_predicate(p, members):
    xs, ys = zip(*members, strict=True)
    node = {("x_lo", 0): min(xs), ("x_hi", 0): max(xs), ("y_lo", 0): min(ys), ("y_hi", 0): max(ys), ("x__nulls", 0): 0, ("y__nulls", 0): 0}
    always, maybe = guards(p, env, {("x", 0), ("y", 0)})
    truth = [evaluate(p, {("x", 0): a, ("y", 0): b}) for a, b in members]
    if any(t is True for t in truth):
        assert evaluate(maybe, node) in (True, None)
    if evaluate(always, node) is True:
        assert all(t is True for t in truth)


@settings(max_examples=150, deadline=None)
@given(TERM, st.lists(st.tuples(NUMBER, NUMBER), min_size=1, max_size=6))
def test_bounds_bracket_the_value(e, members):
    xs, ys = zip(*members, strict=True)
    node = {("x_lo", 0): min(xs), ("x_hi", 0): max(xs), ("y_lo", 0): min(ys), ("y_hi", 0): max(ys)}
    lo, hi = bounds(e, env)
    for a, b in members:
        v = evaluate(e, {("x", 0): a, ("y", 0): b})
        low, high = (None if x is None else evaluate(x, node) for x in (lo, hi))
        assert v is None or low is None or low <= v + 1e-9 * (1 + abs(v))
        assert v is None or high is None or v <= high + 1e-9 * (1 + abs(v))


def test_completed_square_is_tighter_and_sound():
    p = X * X - 4 * X + 3 <= 0
    always, _ = guards(tighten(p), env, set())
    node = {("x_lo", 0): 1.5, ("x_hi", 0): 2.5}
    assert evaluate(always, node) is True  # the naive rules can't tell here
    assert evaluate(guards(p, env, set())[0], node) is False
    for v in (0.5, 1.0, 2.0, 3.0, 3.5):
        assert evaluate(p, {("x", 0): v}) == evaluate(tighten(p), {("x", 0): v})


def test_nulls_and_unknown_columns():
    always, maybe = guards(X < 3, env, {("x", 0)})
    assert evaluate(always, {("x_hi", 0): 1, ("x_lo", 0): 0, ("x__nulls", 0): 2}) is False
    assert evaluate(maybe, {("x_lo", 0): None, ("x_hi", 0): None, ("x__nulls", 0): 2}) is True
    assert guards(X < 3, lambda n, s: (None, None), set()) == (lit(False), lit(True))
    assert negate(X < 3) == (X >= 3)
    with pytest.raises(AnalysisError):
        guards(X + 1, env, set())
    assert exp_(X) != exp_(Y)


CELLS = [(a, b) for a in range(3) for b in range(3) if a <= b]
BOXES = [(a, c, b, d) for a, b in CELLS for c, d in CELLS]
CORNERS = ("lx", "ly", "hx", "hy")


@pytest.mark.parametrize("name", ["contains", "covers", "disjoint", "intersects", "equals", "touches", "within"])
def test_geometric_rules_on_all_small_boxes(name):
    make = getattr(g, name)
    boxes = [g.Box((col("lx", s), col("ly", s)), (col("hx", s), col("hy", s))) for s in (0, 1)]
    rnd = random.Random(1)
    under = {v: [m for m in BOXES if v[0] <= m[0] and v[1] <= m[1] and m[2] <= v[2] and m[3] <= v[3]] for v in BOXES}
    node = lambda v, s: {(f"{c}_lo", s): v[i % 2] for i, c in enumerate(CORNERS)} | {(f"{c}_hi", s): v[2 + i % 2] for i, c in enumerate(CORNERS)}
    row = lambda m, s: {(c, s): m[i] for i, c in enumerate(CORNERS)}
    for u in rnd.sample(BOXES, 12):
        fixed = g.Box(u[:2], u[2:])
        for p in (make(fixed, boxes[0]), make(boxes[0], fixed)):
            lo, hi = bounds(p, env)
            for v in BOXES:
                sure, may = evaluate(lo, node(v, 0)), evaluate(hi, node(v, 0))
                for m in under[v]:
                    t = evaluate(p, row(m, 0))
                    assert (not t or may) and (t or not sure), (name, u, v, m)
    p = make(*boxes)
    lo, hi = bounds(p, env)
    for v, w in itertools.product(rnd.sample(BOXES, 8), repeat=2):
        n = node(v, 0) | node(w, 1)
        sure, may = evaluate(lo, n), evaluate(hi, n)
        for a, b in itertools.product(under[v], under[w]):
            t = evaluate(p, row(a, 0) | row(b, 1))
            assert (not t or may) and (t or not sure), (name, v, w, a, b)


def test_border_contact_and_point_volume():
    u = g.Box((0, 0), (4, 4))
    member = g.Box((col("lx"), col("ly")), (col("hx"), col("hy")))
    lo, _ = bounds(g.contains(u, member), env)
    v = {("lx_lo", 0): 0, ("ly_lo", 0): 1, ("hx_lo", 0): 0, ("hy_lo", 0): 1, ("lx_hi", 0): 2, ("ly_hi", 0): 2, ("hx_hi", 0): 2, ("hy_hi", 0): 2}
    assert evaluate(lo, v) is False
    assert evaluate(g.contains(u, member), {("lx", 0): 0, ("ly", 0): 1.5, ("hx", 0): 0, ("hy", 0): 1.5}) is False
    point = g.Box((1, 1), (1, 1))
    same = {(f"{c}_{e}", 0): 1 for c in CORNERS for e in ("lo", "hi")}
    assert evaluate(bounds(g.equals(point, member), env)[1], same) is True
    assert evaluate(bounds(g.within(point, member), env)[1], same) is True
    with pytest.raises(AnalysisError):
        g.contains(g.Ray((0, 0, 0), (0, 0, 1)), g.Sphere((0, 0, 0), 1))


def test_kernels():
    tri = g.Triangle((0.0, 0.0, 0.0), (1.0, 0.0, 0.0), (0.0, 1.0, 0.0))
    d = lambda *p: evaluate(g.distmin(g.Point(*p), tri), {})
    assert d(0.2, 0.2, 3.0) == pytest.approx(3) and d(-3.0, 0.0, 4.0) == pytest.approx(5) and d(1.0, 1.0, 0.0) == pytest.approx(0.5**0.5)
    ray = g.Ray((0.2, 0.2, -2.0), (0.0, 0.0, 1.0))
    assert evaluate(g.intersects(ray, tri), {}) is True and evaluate(g.distmin(ray, tri), {}) == 2
    assert evaluate(g.intersects(g.Ray((2.0, 2.0, -2.0), (0.0, 0.0, 1.0)), tri), {}) is False
    assert evaluate(g.intersects(tri, g.Triangle((0.2, 0.2, -1.0), (0.2, 0.2, 1.0), (5.0, 5.0, 1.0))), {}) is True
    assert evaluate(g.intersects(tri, g.Triangle((0.2, 0.2, 1.0), (0.2, 0.3, 1.0), (5.0, 5.0, 1.0))), {}) is False


def test_sql_text():
    p = sqlface.parse("abs(x) <= 10 AND NOT (y BETWEEN 1 AND 2 OR x IN (3, 4)) AND z IS NOT NULL AND s LIKE 'a%'")
    row = {("x", 0): 5, ("y", 0): 0, ("z", 0): 1, ("s", 0): "ab"}
    assert evaluate(p, row) is True and evaluate(p, row | {("x", 0): 3}) is False
    for bad in ("x <", "foo(x) < 1", "x < 1 1", "x LIKE '%a'"):
        with pytest.raises(AnalysisError):
            sqlface.parse(bad)
