"""Conditions as SQL text, parsed to expressions that the engine can analyse.

Grammar: or, and, not, comparison (with BETWEEN, IN, IS NULL, LIKE 'prefix%'), sum, product, unary,
function call, column, number or string. In join conditions columns are ``l.name`` and ``r.name``.
"""

from __future__ import annotations

import re
from typing import Any

from pyspark.sql import DataFrame

from .functions.expr import AnalysisError, E, both, col, either, fn, lit, negate
from .operators.joins import dual_index_join
from .operators.tree import Tree
from .plans.query import Q

TOKEN = re.compile(r"\s*(?:(\d+\.?\d*(?:[eE][-+]?\d+)?|\.\d+)|('(?:[^']|'')*')|([A-Za-z_]\w*(?:\.\w+)?)|(<>|!=|<=|>=|[-+*/%(),<>=]))")
FUNCTIONS = {"abs", "sqrt", "round", "floor", "ceil", "exp", "log", "sign", "sin", "cos", "year", "least", "greatest", "pow"}


class Parser:
    def __init__(self, text: str):
        self.tokens: list[tuple[str, Any]] = []
        at = 0
        text = text.strip()
        while at < len(text):
            m = TOKEN.match(text, at)
            if not m:
                raise AnalysisError(f"cannot read {text[at:at + 20]!r}")
            number, string, name, sign = m.groups()
            self.tokens.append(("n", float(number) if re.search(r"[.eE]", number) else int(number)) if number else ("s", string[1:-1].replace("''", "'")) if string else ("w", name) if name else ("o", sign))
            at = m.end()
        self.at = 0

    def peek(self, *words: str) -> bool:
        if self.at >= len(self.tokens):
            return False
        kind, v = self.tokens[self.at]
        return kind in "wo" and str(v).upper() in words

    def take(self, *words: str) -> bool:
        if self.peek(*words):
            self.at += 1
            return True
        return False

    def need(self, word: str) -> None:
        if not self.take(word):
            raise AnalysisError(f"{word} expected")

    def parse(self) -> E:
        e = self.disjunction()
        if self.at < len(self.tokens):
            raise AnalysisError(f"{self.tokens[self.at][1]} is too much")
        return e

    def disjunction(self) -> E:
        e = self.conjunction()
        while self.take("OR"):
            e = either(e, self.conjunction())
        return e

    def conjunction(self) -> E:
        e = self.negation()
        while self.take("AND"):
            e = both(e, self.negation())
        return e

    def negation(self) -> E:
        return negate(self.negation()) if self.take("NOT") else self.comparison()

    def comparison(self) -> E:
        a = self.sum()
        for word, make in (("<=", lambda x, y: x <= y), (">=", lambda x, y: x >= y), ("<>", lambda x, y: x.ne(y)), ("!=", lambda x, y: x.ne(y)), ("<", lambda x, y: x < y), (">", lambda x, y: x > y), ("=", lambda x, y: x.eq(y))):
            if self.take(word):
                return make(a, self.sum())
        no = self.take("NOT")
        if self.take("BETWEEN"):
            low = self.sum()
            self.need("AND")
            out = a.between(low, self.sum())
        elif self.take("IN"):
            self.need("(")
            values = [self.sum()]
            while self.take(","):
                values.append(self.sum())
            self.need(")")
            out = a.isin(*values)
        elif self.take("LIKE"):
            kind, v = self.tokens[self.at]
            self.at += 1
            if kind != "s" or not re.fullmatch(r"[^%_]*%", v):
                raise AnalysisError("only LIKE 'prefix%' is known here")
            out = a.startswith(v[:-1])
        elif self.take("IS"):
            out = a.not_null() if self.take("NOT") else a.is_null()
            self.need("NULL")
        else:
            return a
        return negate(out) if no else out

    def sum(self) -> E:
        e = self.product()
        while self.peek("+", "-"):
            e = e + self.product() if self.take("+") else (self.need("-"), e - self.product())[1]
        return e

    def product(self) -> E:
        e = self.unary()
        while self.peek("*", "/", "%"):
            e = e * self.unary() if self.take("*") else e / self.unary() if self.take("/") else (self.need("%"), e % self.unary())[1]
        return e

    def unary(self) -> E:
        if self.take("-"):
            inner = self.unary()
            return lit(-inner.value) if inner.op == "lit" else -inner
        if self.take("("):
            e = self.disjunction()
            self.need(")")
            return e
        if self.at >= len(self.tokens):
            raise AnalysisError("the text ends too early")
        kind, v = self.tokens[self.at]
        self.at += 1
        if kind in "ns":
            return lit(v)
        if kind == "o":
            raise AnalysisError(f"{v} is not expected")
        if self.take("("):
            if v.lower() not in FUNCTIONS:
                raise AnalysisError(f"no function {v}")
            args = [self.sum()]
            while self.take(","):
                args.append(self.sum())
            self.need(")")
            return fn(v.lower())(*args)
        side, _, name = v.rpartition(".")
        return col(name, 1 if side.lower() == "r" else 0)


def parse(text: str) -> E:
    return Parser(text).parse()


def filter(tree: Tree, where: str) -> DataFrame:  # noqa: A001
    return Q(tree).filter(parse(where)).rows()


def agg(tree: Tree, what: str, where: str, name: str) -> DataFrame:
    """what: count(*), or sum, avg, min, max of an expression."""
    m = re.fullmatch(r"\s*(\w+)\s*\((.*)\)\s*", what)
    if not m:
        raise AnalysisError(f"cannot read {what!r}")
    q = Q(tree).filter(parse(where))
    return q.count(name) if m[2].strip() == "*" else q.reduce(m[1].lower(), parse(m[2]), name)


def join(left: Tree, right: Tree, on: str) -> DataFrame:
    return dual_index_join(left, right, parse(on))
