"""Expressions that the engine can analyse: immutable trees, equal by structure.

One tree serves three readers: ``to_column`` makes a Catalyst expression of it, ``intervals.bounds``
derives what a node's metadata say about it, and ``evaluate`` computes it in Python for tests.
Columns carry the side they come from: 0 is the indexed set (or the left one of a pair), 1 the right
one or the outer row of a probe.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class AnalysisError(ValueError):
    """A query that cannot be run, found before any job starts."""


@dataclass(frozen=True)
class E:
    op: str
    args: tuple = ()
    value: Any = None

    def _bin(self, op: str, other: Any, swap: bool = False) -> E:
        a, b = self, wrap(other)
        return E(op, (b, a) if swap else (a, b))

    __add__ = lambda s, o: s._bin("+", o)
    __radd__ = lambda s, o: s._bin("+", o, True)
    __sub__ = lambda s, o: s._bin("-", o)
    __rsub__ = lambda s, o: s._bin("-", o, True)
    __mul__ = lambda s, o: s._bin("*", o)
    __rmul__ = lambda s, o: s._bin("*", o, True)
    __truediv__ = lambda s, o: s._bin("/", o)
    __rtruediv__ = lambda s, o: s._bin("/", o, True)
    __mod__ = lambda s, o: s._bin("%", o)
    __pow__ = lambda s, o: s._bin("pow", o)
    __neg__ = lambda s: E("neg", (s,))
    __lt__ = lambda s, o: s._bin("<", o)
    __le__ = lambda s, o: s._bin("<=", o)
    __gt__ = lambda s, o: s._bin("<", o, True)
    __ge__ = lambda s, o: s._bin("<=", o, True)
    __and__ = lambda s, o: both(s, wrap(o))
    __or__ = lambda s, o: either(s, wrap(o))
    __invert__ = lambda s: negate(s)

    def eq(self, o: Any) -> E:
        return self._bin("=", o)

    def ne(self, o: Any) -> E:
        return self._bin("!=", o)

    def between(self, a: Any, b: Any) -> E:
        return (self >= a) & (self <= b)

    def isin(self, *values: Any) -> E:
        return E("in", (self, *map(wrap, values)))

    def is_null(self) -> E:
        return E("null", (self,))

    def not_null(self) -> E:
        return E("notnull", (self,))

    def startswith(self, prefix: str) -> E:
        return E("prefix", (self, wrap(prefix)))

    def __repr__(self) -> str:
        if self.op == "lit":
            return repr(self.value)
        if self.op == "col":
            return self.value[0] if self.value[1] == 0 else f"{self.value[0]}@{self.value[1]}"
        if len(self.args) == 2 and not self.op.isalpha():
            return f"({self.args[0]} {self.op} {self.args[1]})"
        return f"{self.op}({', '.join(map(repr, self.args))})"


TRUE, FALSE = E("lit", value=True), E("lit", value=False)


def lit(v: Any) -> E:
    return E("lit", value=v)


def col(name: str, side: int = 0) -> E:
    return E("col", value=(name, side))


def wrap(v: Any) -> E:
    return v if isinstance(v, E) else lit(v)


def both(*ps: E) -> E:
    """Conjunction, with constants folded."""
    ps = tuple(p for p in ps if p != TRUE)
    return FALSE if FALSE in ps else reduce(lambda a, b: E("and", (a, b)), ps) if ps else TRUE


def either(*ps: E) -> E:
    ps = tuple(p for p in ps if p != FALSE)
    return TRUE if TRUE in ps else reduce(lambda a, b: E("or", (a, b)), ps) if ps else FALSE


#: Comparisons under negation; both sides stay where they are.
OPPOSITE = {"<": ("<=", True), "<=": ("<", True), "=": ("!=", False), "!=": ("=", False)}


def negate(p: E) -> E:
    """Negation, pushed down to the atoms, so that a null atom never makes a condition true."""
    if p in (TRUE, FALSE):
        return FALSE if p == TRUE else TRUE
    if p.op == "not":
        return p.args[0]
    if p.op in ("and", "or"):
        return (either if p.op == "and" else both)(*map(negate, p.args))
    if p.op in OPPOSITE:
        op, swap = OPPOSITE[p.op]
        return E(op, p.args[::-1] if swap else p.args)
    if p.op in ("null", "notnull"):
        return E("notnull" if p.op == "null" else "null", p.args)
    return E("not", (p,))


def fn(name: str) -> Callable[..., E]:
    return lambda *args: E(name, tuple(map(wrap, args)))


abs_, sqrt_, round_, floor_, ceil_, exp_, log_, sign_, sin_, cos_, year_, micros_ = map(fn, ("abs", "sqrt", "round", "floor", "ceil", "exp", "log", "sign", "sin", "cos", "year", "micros"))
least_, greatest_, udf_ = fn("least"), fn("greatest"), fn("udf")


def case_(*branches: tuple[E, Any], otherwise: Any) -> E:
    return E("case", (*(wrap(x) for b in branches for x in b), wrap(otherwise)))


def walk(e: E):
    yield e
    for a in e.args:
        yield from walk(a)


def columns(e: E, side: int | None = None) -> set[str]:
    return {x.value[0] for x in walk(e) if x.op == "col" and side in (None, x.value[1])}


def substitute(e: E, to: dict[E, E]) -> E:
    return to[e] if e in to else e if not e.args else E(e.op, tuple(substitute(a, to) for a in e.args), e.value)


def sided(e: E, side: int) -> E:
    """The same expression over another side."""
    return E("col", value=(e.value[0], side)) if e.op == "col" else E(e.op, tuple(sided(a, side) for a in e.args), e.value)


BINARY: dict[str, Callable[[Column, Column], Column]] = {
    "+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: a / b, "%": lambda a, b: a % b,
    "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, "=": lambda a, b: a == b, "!=": lambda a, b: a != b, "and": lambda a, b: a & b, "or": lambda a, b: a | b,
    "pow": F.pow, "prefix": lambda a, b: F.startswith(a, b),
}
UNARY: dict[str, Callable[[Column], Column]] = {
    "neg": lambda a: -a, "not": lambda a: ~a, "abs": F.abs, "sqrt": F.sqrt, "root": lambda a: F.sqrt(F.greatest(a, F.lit(0.0))), "floor": F.floor, "ceil": F.ceil, "exp": F.exp, "log": F.log,
    "sign": F.signum, "sin": F.sin, "cos": F.cos, "year": F.year, "micros": lambda a: F.unix_micros(a.cast("timestamp")), "null": lambda a: a.isNull(), "notnull": lambda a: a.isNotNull(),
    "round": lambda a: F.round(a), "isnan": F.isnan, "double": lambda a: a.cast("double"),
}
KERNELS: dict[str, Callable[..., E]] = {}  # geometric predicates and metrics, by name: see geometry


def to_column(e: E, resolve: Callable[[str, int], Column]) -> Column:
    if e.op == "lit":
        return F.lit(e.value)
    if e.op == "col":
        return resolve(*e.value)
    if e.op in KERNELS:
        return to_column(KERNELS[e.op](*e.args), resolve)
    args = [to_column(a, resolve) for a in e.args]
    if e.op in BINARY:
        return BINARY[e.op](*args)
    if e.op in UNARY:
        return UNARY[e.op](*args)
    if e.op == "in":
        return args[0].isin(*args[1:])
    if e.op in ("least", "greatest"):
        return getattr(F, e.op)(*args)
    if e.op == "case":
        out = F.when(args[0], args[1])
        for i in range(2, len(args) - 1, 2):
            out = out.when(args[i], args[i + 1])
        return out.otherwise(args[-1])
    if e.op == "call":
        return e.value(*args)
    if e.op == "coalesce":
        return F.coalesce(*args)
    raise AnalysisError(f"no column for {e.op}")


def bind(df: DataFrame, e: E, resolve: Callable[[str, int], Column], name: str) -> DataFrame:
    """df with e as a further column. Terms that e repeats (geometry repeats most of its own) are columns of earlier
    projections, which the optimiser leaves apart as each is read more than once; so they are computed once and
    generated methods stay small. A filter on the new column would be pushed below them and undo that: aggregate or
    rank by it instead. Terms of conditional branches are computed for all rows, so user calls, conversions and
    divisions are bound only together with the condition that guards them."""
    index: dict[tuple, int] = {}
    nodes: list[tuple[str, Any, tuple[int, ...]]] = []
    refs: list[int] = []

    def intern(x: E) -> int:
        if x.op in KERNELS:
            return intern(KERNELS[x.op](*x.args))
        args = tuple(intern(a) for a in x.args)
        key = (x.op, type(x.value), x.value if x.op != "call" else id(x.value), args)
        if key not in index:
            index[key] = len(nodes)
            nodes.append((x.op, x.value, args))
            refs.append(0)
            for a in args:
                refs[a] += 1
        return index[key]

    top = intern(e)
    raises = [False] * len(nodes)
    layer = [0] * len(nodes)
    tmp = lambda i: f"_{name}_{i}"
    bound = set()
    for i, (op, _, args) in enumerate(nodes):
        raises[i] = op in ("call", "/", "%", "double") or any(raises[a] for a in (args[:1] if op == "case" else args))
        layer[i] = max((layer[a] + (a in bound) for a in args), default=0)
        if args and refs[i] > 1 and not raises[i]:
            bound.add(i)

    def made(i: int, here: bool = False) -> E:
        op, value, args = nodes[i]
        return E("col", value=(tmp(i), -1)) if i in bound and not here else E(op, tuple(made(a) for a in args), value)

    of = lambda c, side: F.col(c) if side == -1 else resolve(c, side)
    kept = df.columns
    for step in range(max((layer[i] + 1 for i in bound), default=0)):
        df = df.select("*", *[to_column(made(i, True), of).alias(tmp(i)) for i in sorted(bound) if layer[i] == step])
    return df.select(*[F.col(f"`{c}`") for c in kept], to_column(made(top), of).alias(name))


def kept(df: DataFrame, condition: Column) -> DataFrame:
    """Rows that satisfy a condition on columns that ``bind`` made. A number that the plan can't move stands between the two, so
    the condition is tested on the columns as they are."""
    return df.withColumn("_at", F.monotonically_increasing_id()).where(condition & (F.col("_at") >= 0)).drop("_at")  # a column that is read stays


def evaluate(e: E, row: dict[tuple[str, int], Any]) -> Any:
    """Value in Python; None where an argument is."""
    if e.op == "lit":
        return e.value
    if e.op == "col":
        return row[e.value]
    if e.op in KERNELS:
        return evaluate(KERNELS[e.op](*e.args), row)
    a = [evaluate(x, row) for x in e.args]
    if e.op in ("and", "or"):
        short = e.op == "or"
        return short if short in a else None if None in a else not short
    if e.op == "case":
        return next((a[i + 1] for i in range(0, len(a) - 1, 2) if a[i]), a[-1])
    if e.op in ("null", "notnull"):
        return (a[0] is None) == (e.op == "null")
    if e.op == "coalesce":
        return next((x for x in a if x is not None), None)
    if any(x is None for x in a):
        return None
    order = lambda x: (x != x, 0 if x != x else x)  # noqa: E731  NaN is the largest
    away = lambda x: math.copysign(math.floor(abs(x) + 0.5), x)
    table: dict[str, Callable[[], Any]] = {
        "+": lambda: a[0] + a[1], "-": lambda: a[0] - a[1], "*": lambda: a[0] * a[1], "/": lambda: a[0] / a[1] if a[1] else None, "%": lambda: math.fmod(a[0], a[1]), "pow": lambda: a[0] ** a[1],
        "<": lambda: order(a[0]) < order(a[1]), "<=": lambda: order(a[0]) <= order(a[1]), "=": lambda: a[0] == a[1], "!=": lambda: a[0] != a[1], "neg": lambda: -a[0], "not": lambda: not a[0], "abs": lambda: abs(a[0]),
        "sqrt": lambda: math.sqrt(a[0]) if a[0] >= 0 else math.nan, "root": lambda: math.sqrt(max(0.0, a[0])), "floor": lambda: math.floor(a[0]), "ceil": lambda: math.ceil(a[0]), "exp": lambda: math.exp(a[0]), "log": lambda: math.log(a[0]), "sign": lambda: (a[0] > 0) - (a[0] < 0),
        "sin": lambda: math.sin(a[0]), "cos": lambda: math.cos(a[0]), "round": lambda: away(a[0]), "in": lambda: a[0] in a[1:], "least": lambda: min(a), "greatest": lambda: max(a),
        "prefix": lambda: a[0].startswith(a[1]), "double": lambda: float(a[0]), "isnan": lambda: a[0] != a[0],
    }
    return table[e.op]()


def to_sql(e: E, names: dict[int, str]) -> str:
    """The expression in SQL that other engines run too; ``names`` gives each side's table alias."""
    if e.op == "lit":
        v = e.value
        if v is None:
            return "NULL"
        if isinstance(v, bool):
            return str(v).upper()
        if isinstance(v, float):
            return f"CAST('{v!r}' AS DOUBLE)"
        return str(v) if isinstance(v, int) else "'" + str(v).replace("'", "''") + "'"
    if e.op == "col":
        return f"{names[e.value[1]]}.{e.value[0]}"
    if e.op in KERNELS:
        return to_sql(KERNELS[e.op](*e.args), names)
    a = [to_sql(x, names) for x in e.args]
    if e.op in BINARY and e.op not in ("pow", "prefix"):
        return f"({a[0]} {'<>' if e.op == '!=' else e.op.upper()} {a[1]})"
    if e.op == "case":
        return "(CASE " + " ".join(f"WHEN {a[i]} THEN {a[i + 1]}" for i in range(0, len(a) - 1, 2)) + f" ELSE {a[-1]} END)"
    plain = {"neg": "(-{0})", "not": "(NOT {0})", "null": "({0} IS NULL)", "notnull": "({0} IS NOT NULL)", "prefix": "starts_with({0}, {1})", "sqrt": "(CASE WHEN {0} < 0 THEN CAST('NaN' AS DOUBLE) ELSE sqrt({0}) END)", "root": "sqrt(greatest({0}, 0))", "double": "CAST({0} AS DOUBLE)", "log": "ln({0})"}
    if e.op in plain:
        return plain[e.op].format(*a)
    if e.op == "in":
        return f"({a[0]} IN ({', '.join(a[1:])}))"
    return f"{e.op}({', '.join(a)})"
