"""What bounds on a node's members say about an expression over a member.

``bounds(e, env)`` gives two expressions over the node's metadata, a lower and an upper bound of e for
every member below the node. For a predicate these are ``always`` (if it holds, so does the
predicate, for all members) and ``maybe`` (if it fails, the predicate fails for all members). ``env``
gives the bounds of a column; None stands for no bound. Columns that ``env`` doesn't know are
uniform: one value for the whole node, as literals are.

Every rule is sound on its own, so are their compositions; correlated operands cost tightness only.
Algebraic rewrites that a rule makes (squares) are widened by a relative ``SLACK`` for rounding.
"""

from __future__ import annotations

from collections.abc import Callable

from .expr import E, FALSE, KERNELS, TRUE, AnalysisError, both, col, either, fn, greatest_, least_, lit, negate, substitute, walk

Pair = tuple["E | None", "E | None"]
Env = Callable[[str, int], "Pair | None"]
SLACK = 1e-12
MONOTONE = {"root", "exp", "floor", "ceil", "round", "year", "micros", "double", "sign"}
#: Rules for geometric predicates and metrics: name -> function (args, env) -> pair; see geometry.
GEOMETRIC: dict[str, Callable[[tuple[E, ...], Env], Pair]] = {}
USER: dict[str, Callable[[tuple[E, ...], Env], Pair]] = {}


def _both_known(*xs: E | None) -> bool:
    return all(x is not None for x in xs)


def _up(x: E | None) -> E | None:
    return None if x is None else x + fn("abs")(x) * SLACK


def _down(x: E | None) -> E | None:
    return None if x is None else x - fn("abs")(x) * SLACK


def _cmp(op: str, a: E | None, b: E | None, unknown: E) -> E:
    if a is None or b is None:
        return unknown
    if a.op == b.op == "lit" and a.value is not None and b.value is not None:
        return lit({"<": a.value < b.value, "<=": a.value <= b.value}[op])
    return E(op, (a, b))


def bounds(e: E, env: Env) -> Pair:
    memo: dict[E, Pair] = {}

    def go(x: E) -> Pair:
        if x not in memo:
            memo[x] = rule(x)
        return memo[x]

    def equal(a: Pair, b: Pair) -> Pair:
        same = both(_cmp("<=", a[1], b[0], FALSE), _cmp("<=", b[1], a[0], FALSE))
        meet = both(_cmp("<=", a[0], b[1], TRUE), _cmp("<=", b[0], a[1], TRUE))
        return same, meet

    def product(a: Pair, b: Pair) -> Pair:
        for one, two in ((a, b), (b, a)):
            if one[0] is not None and one[0] == one[1] and one[0].op == "lit":
                lo, hi = (two if one[0].value >= 0 else two[::-1])
                return (None if lo is None else lo * one[0]), (None if hi is None else hi * one[0])
        if not _both_known(*a, *b):
            return None, None
        ends = [x * y for x in a for y in b]
        return least_(*ends), greatest_(*ends)

    def square(a: Pair) -> Pair:
        if not _both_known(*a):
            return lit(0.0), None
        low, high = a[0] * a[0], a[1] * a[1]
        return _down(E("case", ((a[0] <= 0) & (lit(0) <= a[1]), lit(0.0), least_(low, high)))), _up(greatest_(low, high))

    def rule(x: E) -> Pair:
        op, args = x.op, x.args
        if op == "lit":
            return x, x
        if op == "col":
            known = env(*x.value)
            return (x, x) if known is None else known
        if op in GEOMETRIC:
            return GEOMETRIC[op](args, env)
        if op == "call":
            return USER[x.value.__name__](args, env) if getattr(x.value, "__name__", None) in USER else (FALSE, TRUE)
        if not any(y.op == "col" and env(*y.value) is not None for y in walk(x)) and op not in ("and", "or", "not"):
            return x, x  # uniform
        if op in ("and", "or"):
            join = both if op == "and" else either
            parts = [go(a) for a in args]
            return join(*(p[0] for p in parts)), join(*(p[1] for p in parts))
        if op == "not":
            lo, hi = go(args[0])
            return negate(hi), negate(lo)
        if op in ("<", "<="):
            a, b = map(go, args)
            return _cmp(op, a[1], b[0], FALSE), _cmp(op, a[0], b[1], TRUE)
        if op in ("=", "!="):
            same, meet = equal(*map(go, args))
            return (same, meet) if op == "=" else (negate(meet), negate(same))
        if op == "in":
            a, rest = go(args[0]), [go(b) for b in args[1:]]
            each = [equal(a, b) for b in rest]
            return either(*(s for s, _ in each)), either(*(m for _, m in each))
        if op == "prefix" and args[1].op == "lit":
            a, p = go(args[0]), args[1].value
            after = p[:-1] + chr(ord(p[-1]) + 1) if p else None
            if after is None:
                return FALSE, TRUE
            return both(_cmp("<=", lit(p), a[0], FALSE), _cmp("<", a[1], lit(after), FALSE)), both(_cmp("<=", lit(p), a[1], TRUE), _cmp("<", a[0], lit(after), TRUE))
        if op in ("null", "notnull"):
            if args[0].op != "col":
                return FALSE, TRUE
            name, side = args[0].value
            n, c = col(f"{name}__nulls", side), col("__rows", side)
            return (n.eq(c), lit(0) < n) if op == "null" else (n.eq(0), n < c)
        if op == "+":
            a, b = map(go, args)
            return (a[0] + b[0] if _both_known(a[0], b[0]) else None), (a[1] + b[1] if _both_known(a[1], b[1]) else None)
        if op == "-":
            if args[0] == args[1]:
                return lit(0), lit(0)
            a, b = map(go, args)
            return (a[0] - b[1] if _both_known(a[0], b[1]) else None), (a[1] - b[0] if _both_known(a[1], b[0]) else None)
        if op == "neg":
            lo, hi = go(args[0])
            return (None if hi is None else -hi), (None if lo is None else -lo)
        if op == "*":
            return square(go(args[0])) if args[0] == args[1] else product(*map(go, args))
        if op == "/":
            a, b = map(go, args)
            if b[0] is not None and b[0] == b[1] and b[0].op == "lit" and b[0].value:
                lo, hi = a if b[0].value > 0 else a[::-1]
                return (None if lo is None else lo / b[0]), (None if hi is None else hi / b[0])
            if not _both_known(*a, *b):
                return None, None
            apart = (lit(0) < b[0]) | (b[1] < 0)
            ends = [E("case", (apart, p / q, lit(None))) for p in a for q in b]
            return E("case", (apart, least_(*ends), lit(float("-inf")))), E("case", (apart, greatest_(*ends), lit(float("inf"))))
        if op == "pow" and args[1].op == "lit" and float(args[1].value).is_integer() and args[1].value > 0:
            n, a = int(args[1].value), go(args[0])
            if n % 2:
                return (None if a[0] is None else _down(E("pow", (a[0], args[1])))), (None if a[1] is None else _up(E("pow", (a[1], args[1]))))
            if not _both_known(*a):
                return lit(0.0), None
            low, high = (E("pow", (y, args[1])) for y in a)
            return _down(E("case", ((a[0] <= 0) & (lit(0) <= a[1]), lit(0.0), least_(low, high)))), _up(greatest_(low, high))
        if op == "abs":
            a = go(args[0])
            if not _both_known(*a):
                return lit(0), None
            low, high = fn("abs")(a[0]), fn("abs")(a[1])
            return E("case", ((a[0] <= 0) & (lit(0) <= a[1]), lit(0), least_(low, high))), greatest_(low, high)
        if op == "sqrt":  # of the members that have a root; guards ask whether all have
            lo, hi = go(args[0])
            return (None if lo is None else fn("root")(lo)), (None if hi is None else fn("root")(hi))
        if op in MONOTONE:
            lo, hi = go(args[0])
            return (None if lo is None else E(op, (lo,))), (None if hi is None else E(op, (hi,)))
        if op == "log":
            lo, hi = go(args[0])
            return (None if lo is None else E("case", (lit(0) < lo, E(op, (greatest_(lo, 1e-300),)), lit(float("-inf"))))), (None if hi is None else E("log", (greatest_(hi, 1e-300),)))
        if op in ("least", "greatest"):
            parts, f = [go(a) for a in args], fn(op)
            known = [[p[i] for p in parts if p[i] is not None] for i in (0, 1)]
            full = [len(k) == len(parts) for k in known]
            loose = 1 if op == "least" else 0  # the side on which one known argument is enough
            return tuple((f(*k) if len(k) > 1 else k[0]) if ok or (i == loose and k) else None for i, (k, ok) in enumerate(zip(known, full, strict=True)))  # type: ignore[return-value]
        if op == "case":
            guards, values = [go(a) for a in args[:-1:2]], [go(a) for a in (*args[1:-1:2], args[-1])]
            reach = [v for g, v in zip([*guards, (TRUE, TRUE)], values, strict=True) if g[1] != FALSE]
            los, his = [v[0] for v in reach], [v[1] for v in reach]
            pick = lambda f, xs: None if None in xs else f(*xs) if len(xs) > 1 else xs[0]
            return pick(least_, los), pick(greatest_, his)
        if op in ("sin", "cos"):
            return lit(-1.0), lit(1.0)
        if op == "%" and args[1].op == "lit":
            c = abs(args[1].value)
            a = go(args[0])
            return (lit(-c) if a[0] is None else E("case", (lit(0) <= a[0], lit(0), lit(-c)))), lit(c)
        return None, None

    return go(e)


def is_boolean(e: E) -> bool:
    return e.op in ("<", "<=", "=", "!=", "and", "or", "not", "in", "prefix", "null", "notnull") or e.op in GEOMETRIC and e.op not in ("distmin", "distmax") or e in (TRUE, FALSE) or e.op == "call"


def guards(p: E, env: Env, nullable: set[tuple[str, int]]) -> tuple[E, E]:
    """(always, maybe) of a predicate, safe where metadata are missing or values null: ``always`` also asks that
    no column it reads has nulls or NaN below the node."""
    if not is_boolean(p):
        raise AnalysisError(f"{p} is not a condition")
    lo, hi = bounds(p, env)
    nulls = [col(f"{n}__nulls", s).eq(0) for n, s in sorted(nullable)]
    # a root of a negative number is NaN, which is above all others: such nodes are neither taken nor pruned
    rootless = [_cmp("<", bounds(x.args[0], env)[0], lit(0), TRUE) for x in walk(p) if x.op == "sqrt"]
    if any(x != FALSE for x in rootless):
        lo, hi = both(FALSE if lo is None else lo, *map(negate, rootless)), either(TRUE if hi is None else hi, *rootless)
    always = FALSE if lo in (None, FALSE) else both(lo, *nulls)
    return E("coalesce", (always, FALSE)) if always not in (TRUE, FALSE) else always, E("coalesce", (hi, TRUE)) if hi not in (None, TRUE, FALSE) else (hi if hi is not None else TRUE)


def tighten(p: E) -> E:
    """Completes the square of a quadratic in one column with literal coefficients: where the naive rules
    would bound x*x and x apart, (x+b/2a)*(x+b/2a) is bounded as one."""

    def coefficients(e: E, x: E) -> tuple[float, float, float] | None:
        if e == x:
            return 0.0, 1.0, 0.0
        if e.op == "lit":
            return 0.0, 0.0, float(e.value)
        if e.op == "*" and e.args == (x, x):
            return 1.0, 0.0, 0.0
        parts = [coefficients(a, x) for a in e.args]
        if None in parts or e.op not in ("+", "-", "*", "neg"):
            return None
        if e.op == "neg":
            return tuple(-v for v in parts[0])  # type: ignore[return-value]
        (a, b, c), (d, f, g) = parts
        if e.op == "*":
            return (a * g, b * g, c * g) if d == f == 0 else (d * c, f * c, g * c) if a == b == 0 else None
        s = 1 if e.op == "+" else -1
        return a + s * d, b + s * f, c + s * g

    def go(e: E) -> E:
        if e.op in ("<", "<=", "=", "!="):
            names = {x for x in walk(e) if x.op == "col"}
            if len(names) == 1:
                x = next(iter(names))
                got = coefficients(e.args[0] - e.args[1], x)
                if got and got[0]:
                    a, b, c = got
                    t = x + b / (2 * a)
                    return E(e.op, (t * t * lit(a), lit(b * b / (4 * a) - c)))
            return e
        return E(e.op, tuple(go(a) for a in e.args), e.value) if e.op in ("and", "or", "not") else e

    return go(p)


__all__ = ["GEOMETRIC", "KERNELS", "USER", "bounds", "guards", "substitute", "tighten"]
