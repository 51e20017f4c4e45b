"""Expressions over arrays, for what tasks compute in Python: values with a mask of what is null.

Only operators whose results are the same bits in NumPy as in Spark are known; ``known`` says whether an
expression has no others. NaN is above all numbers and equal to itself, a division by zero is null.
Arrays of both sides broadcast, so a side's own terms are computed once for each of its rows.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

from .expr import E, KERNELS

Value = tuple[Any, Any]  # values, and the mask of nulls or None where nothing is null
OPS = {"lit", "col", "+", "-", "*", "/", "<", "<=", "=", "!=", "and", "or", "not", "neg", "abs", "sqrt", "root", "sign", "null", "notnull", "isnan", "double", "in", "least", "greatest", "case", "coalesce"}
PLAIN = {"+": np.add, "-": np.subtract, "*": np.multiply, "neg": np.negative, "abs": np.abs, "sqrt": np.sqrt, "sign": lambda x: np.sign(np.float64(x)), "not": np.logical_not, "isnan": np.isnan, "double": np.float64}
NUMBERS = T.ByteType | T.ShortType | T.IntegerType | T.LongType | T.DoubleType


class Program:
    """An expression as steps, each term once."""

    def __init__(self, e: E):
        self.steps: list[tuple[str, Any, tuple[int, ...]]] = []
        index: dict[tuple, int] = {}
        seen: dict[int, tuple[E, int]] = {}

        def intern(x: E) -> int:
            if id(x) not in seen:
                if x.op in KERNELS:
                    at = intern(KERNELS[x.op](*x.args))
                else:
                    step = (x.op, x.value, tuple(intern(a) for a in x.args))
                    key = (x.op, type(x.value), repr(x.value), step[2])
                    if key not in index:
                        index[key] = len(self.steps)
                        self.steps.append(step)
                    at = index[key]
                seen[id(x)] = x, at
            return seen[id(x)][1]

        self.top = intern(e)
        last = {j: i for i, (_, _, args) in enumerate(self.steps) for j in args}
        self.free: list[list[int]] = [[] for _ in self.steps]
        for j, i in last.items():
            if j != self.top:
                self.free[i].append(j)

    def known(self) -> bool:
        plain = lambda v: v is None or isinstance(v, bool | int | float)
        return all(op in OPS and (op != "lit" or plain(v)) for op, v, _ in self.steps)

    def run(self, get: Callable[[str, int], Value]) -> Value:
        held: list[Any] = [None] * len(self.steps)
        with np.errstate(all="ignore"):
            for i, (op, value, args) in enumerate(self.steps):
                held[i] = get(*value) if op == "col" else _apply(op, value, [held[j] for j in args])
                for j in self.free[i]:
                    held[j] = None
        return held[self.top]

    def true(self, get: Callable[[str, int], Value]) -> Any:
        """Where a condition is true."""
        x, null = self.run(get)
        return x if null is None else x & ~null


def _any(*masks: Any) -> Any:
    masks = [m for m in masks if m is not None]
    return reduce(np.logical_or, masks) if masks else None


def _nan(x: Any) -> Any:
    """Where x is NaN; None if nowhere."""
    x = np.asarray(x)
    return np.isnan(x) if x.dtype.kind == "f" and np.isnan(x.sum()) else None


def _compared(op: str, a: Any, b: Any) -> Any:
    na, nb = _nan(a), _nan(b)
    if op == "<":
        x = a < b
        return x if nb is None else x | (nb & ~np.isnan(a))
    if op == "<=":
        x = a <= b
        return x if nb is None else x | nb
    x = a == b
    x = x if na is None or nb is None else x | (na & nb)
    return x if op == "=" else ~x


def _extreme(least: bool, args: list[Value]) -> Value:
    """Nulls are left out; NaN is the largest."""
    (x, null), *rest = args
    f = np.fmin if least else np.maximum
    for y, also in rest:
        both = f(x, y)
        if null is not None:
            both = np.where(null, y, both)
        if also is not None:
            both = np.where(also, x, both)
        x, null = both, (None if null is None or also is None else null & also)
    return x, null


def _apply(op: str, value: Any, args: list[Value]) -> Value:
    if op == "lit":
        return (np.float64(0), np.bool_(True)) if value is None else (np.bool_(value) if isinstance(value, bool) else np.int64(value) if isinstance(value, int) else np.float64(value), None)
    if op in ("null", "notnull"):
        null = np.bool_(False) if args[0][1] is None else args[0][1]
        return (null if op == "null" else ~null), None
    if op in ("least", "greatest"):
        return _extreme(op == "least", args)
    if op == "coalesce":
        x, null = args[-1]
        for y, also in args[-2::-1]:
            x, null = (y, None) if also is None else (np.where(also, x, y), None if null is None else also & null)
        return x, null
    if op == "case":
        x, null = args[-1]
        for at in range(len(args) - 3, -1, -2):
            (c, unknown), (y, also) = args[at], args[at + 1]
            c = c if unknown is None else c & ~unknown
            x = np.where(c, y, x)
            if null is not None or also is not None:
                null = np.where(c, False if also is None else also, False if null is None else null)
        return x, null
    if op in ("and", "or"):
        (x, n), (y, m) = args
        if n is None and m is None:
            return (x & y if op == "and" else x | y), None
        n, m = (np.bool_(False) if z is None else z for z in (n, m))
        x, y = x & ~n, y & ~m
        return (x & y, (n & m) | (n & y) | (m & x)) if op == "and" else (x | y, (n | m) & ~(x | y))
    null = _any(*(n for _, n in args))
    a = [x for x, _ in args]
    if op == "/":
        zero = np.asarray(a[1]) == 0
        return np.true_divide(a[0], a[1]), (_any(null, zero) if zero.any() else null)
    if op == "in":
        return reduce(np.logical_or, [_compared("=", a[0], b) for b in a[1:]]), null
    if op in ("<", "<=", "=", "!="):
        return _compared(op, *a), null
    if op == "root":
        return np.sqrt(np.maximum(a[0], 0.0)), null
    return PLAIN[op](*a), null


def numbers(column: pa.Array | pa.ChunkedArray) -> Value:
    """A column of numbers, 64 bits wide, and its nulls."""
    kind = pa.float64() if pa.types.is_floating(column.type) else pa.int64()
    null = column.is_null().to_numpy(zero_copy_only=False) if column.null_count else None
    return column.cast(kind).fill_null(0).to_numpy(**({} if isinstance(column, pa.ChunkedArray) else {"zero_copy_only": False})), null


def numeric(schema: T.StructType, names: set[str]) -> bool:
    return all(isinstance(schema[n].dataType, NUMBERS) for n in names)
