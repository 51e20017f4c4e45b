"""Set queries on one tree: filter, map and reductions, fused into one traversal.

A ``Q`` collects conditions and a projection; conditions after a map are rewritten to the stored
columns, so their bounds can be derived. A reduction ends the query: the traversal classifies nodes
level by level (take whole, descend, prune), taken nodes give their stored aggregate if there is one
and their rows otherwise, and rows of the leaves that were descended into are tested. The number of
levels is known, so all of it is one static plan; only min, argmin and top-k read one value back for
each level, the bound by which the next level is pruned.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.expr import FALSE, AnalysisError, E, both, col, columns, either, lit, negate, substitute, to_column, wrap
from ..functions.intervals import bounds, guards, is_boolean, tighten
from ..operators.tree import Agg, Forest, Tree, env_of

#: Leaf runs that are written into the scan's filter; beyond, leaves are joined.
MAX_RUNS = 200
#: Levels with at most so many nodes above the one below them are passed over: their guards cost less than a join.
START_NODES = 4096
#: What is folded into one at each step of a user-defined reduction.
FOLDS = 64
ROW = lambda name, side: F.col(name)


def node_guards(tree: Tree, p: E, side: int = 0) -> tuple[E, E]:
    """(always, maybe) of a condition on rows, over node metadata; NaN below a node forbids to prune by it."""
    used = columns(p, side) & set(tree.spec.bounds)
    always, maybe = guards(p, env_of(tree, side), {(n, side) for n in used})
    nan = [E("<", (lit(0), col(f"{n}__nan", side))) for n in sorted(used)]
    return always, either(maybe, *nan)


@dataclass
class Frontier:
    """Nodes that were reached, by level: taken whole, or leaves to test."""

    tree: Tree
    taken: list[tuple[int, DataFrame]]
    tested: DataFrame
    seen: list[tuple[int, DataFrame]]

    def leaves(self) -> DataFrame:
        """(leaf_id, whole)."""
        out = self.tested.select(F.col("node_id").alias("leaf_id"), F.lit(False).alias("whole"))
        for level, nodes in self.taken:
            u = self.tree.under(level)
            ids = F.col("node_id") if u == 1 else F.explode(F.sequence(F.col("node_id") * u, F.least((F.col("node_id") + 1) * u, F.lit(self.tree.n_leaves)) - 1))
            out = out.union(nodes.select(ids.alias("leaf_id"), F.lit(True).alias("whole")))
        return out


def classify(nodes: DataFrame, always: E, maybe: E, prefix=ROW) -> DataFrame:
    return nodes.withColumn("verdict", F.when(to_column(always, prefix), 2).when(to_column(maybe, prefix), 1).otherwise(0))


def descend(tree: Tree, p: E, prune: Any = None, whole: bool = False) -> Frontier:
    """prune(level, nodes, taken) -> nodes, for value bounds. The descent begins at the lowest level of few nodes, all of
    which it reads; with ``whole``, at the root, for counters."""
    always, maybe = node_guards(tree, p)
    taken, seen = [], []
    start = tree.height if whole else min((lv for lv in range(tree.height + 1) if tree.n_leaves <= START_NODES * tree.under(lv)), default=tree.height)
    nodes = tree.levels[start]
    for level in range(start, -1, -1):
        done = classify(nodes, always, maybe)
        seen.append((level, done))
        if always != FALSE:
            taken.append((level, done.where("verdict = 2")))
        down = done.where("verdict = 1")
        if prune is not None:
            down = prune(level, down, done.where("verdict = 2"))
        if level == 0:
            return Frontier(tree, taken, down, seen)
        parents = down.select(F.col("node_id").alias("_parent"))
        nodes = tree.levels[level - 1].join(parents, F.floor(F.col("node_id") / tree.spec.fanout) == F.col("_parent"), "left_semi")
    raise AssertionError


def fetch(tree: Tree, leaves: DataFrame, p: E) -> DataFrame:
    """Rows of the leaves, tested where a leaf isn't taken whole. Few runs of leaves become a filter on the
    clustered scan, many are joined."""
    runs = sorted(leaves.select("leaf_id", "whole").collect()) if tree.n_leaves <= MAX_RUNS * 64 else None
    test = to_column(p, ROW)
    if runs is not None:
        spans: list[list[Any]] = []
        for r in runs:
            if spans and spans[-1][1] == r["leaf_id"] - 1 and spans[-1][2] == r["whole"]:
                spans[-1][1] += 1
            else:
                spans.append([r["leaf_id"], r["leaf_id"], r["whole"]])
        if len(spans) <= MAX_RUNS:
            within = lambda xs: _any([F.col("leaf_id").between(a, b) for a, b, _ in xs])
            whole, part = [s for s in spans if s[2]], [s for s in spans if not s[2]]
            return tree.rows.where(within(spans)).where(within(whole) | test if part else F.lit(True)).drop("leaf_id")
    return tree.rows.join(leaves, "leaf_id").where(F.col("whole") | test).drop("leaf_id", "whole")


def _any(cs: list[Column]) -> Column:
    out = F.lit(False)
    for c in cs:
        out = out | c
    return out


@dataclass(frozen=True)
class Q:
    """A query over a tree. ``prune=False`` reads every row (the linear baseline), ``fuse=False`` writes the
    filter's rows before reducing them, ``stored=False`` ignores stored aggregates."""

    tree: Tree
    pred: E = lit(True)
    mapped: tuple[tuple[str, E], ...] = ()
    prune: bool = True
    fuse: bool = True
    stored: bool = True
    tight: bool = False

    def but(self, **kw) -> Q:
        return replace(self, **kw)

    def _to_stored(self, e: E) -> E:
        return substitute(e, {col(n): x for n, x in self.mapped})

    def filter(self, p: E) -> Q:
        p = self._to_stored(p)
        self.tree.check(p)
        if not is_boolean(p):
            raise AnalysisError(f"{p} is not a condition")
        return replace(self, pred=both(self.pred, p))

    def map(self, **exprs: E) -> Q:
        return replace(self, mapped=tuple((n, self._to_stored(wrap(e))) for n, e in exprs.items()))

    def _guide(self) -> E:
        """The condition that guards are derived from; rows are tested by the one that was given."""
        return both(self.pred, tighten(self.pred)) if self.tight else self.pred

    def rows(self) -> DataFrame:
        """Matching rows as stored."""
        if not self.prune:
            return self.tree.scan().where(to_column(self.pred, ROW))
        return fetch(self.tree, descend(self.tree, self._guide()).leaves(), self.pred)

    def select(self) -> DataFrame:
        rows = self.rows()
        return rows.select(*[to_column(e, ROW).alias(n) for n, e in self.mapped]) if self.mapped else rows

    def _value(self, e: E | str | None) -> E:
        return lit(1) if e is None else self._to_stored(col(e) if isinstance(e, str) else e)

    def reduce(self, kind: str, e: E | str | None = None, name: str | None = None) -> DataFrame:
        """One row: count, sum, avg, min, max, product, bit_and, bit_or, bit_xor, bool_and or bool_or of an expression."""
        value, name = self._value(e), name or kind
        self.tree.check(value)
        if kind == "avg":
            return self._average(value, name)
        f = {"count": F.count, "sum": F.sum, "min": F.min, "max": F.max, "product": F.product, "bit_and": F.bit_and, "bit_or": F.bit_or, "bit_xor": F.bit_xor, "bool_and": F.bool_and, "bool_or": F.bool_or}[kind]
        c = to_column(value, ROW)
        if not self.prune:
            return self.rows().agg(f(c).alias(name))
        if not self.fuse:
            from ..operators.tree import base_dir

            at = f"{base_dir(self.tree.rows.sparkSession)}/unfused-{time.time_ns()}"
            self.rows().write.parquet(at)
            return self.tree.rows.sparkSession.read.parquet(at).agg(f(c).alias(name))
        of = "" if kind == "count" else value.value[0] if value.op == "col" else None
        if not self.stored or of is None or kind not in ("count", "sum", "min", "max") or not self.tree.has(kind, of):
            return self.rows().agg(f(c).alias(name))
        front = descend(self.tree, self._guide())
        stored = f"agg__{kind}__{of}"
        tested = fetch(self.tree, front.tested.select(F.col("node_id").alias("leaf_id"), F.lit(False).alias("whole")), self.pred)
        parts = tested.agg(f(c).alias("v"))
        for _, nodes in front.taken:
            parts = parts.union(nodes.agg((F.sum if kind in ("count", "sum") else f)(stored).alias("v")))
        whole = parts.agg((F.sum if kind in ("count", "sum") else f)("v").alias(name))
        return whole.select(F.coalesce(name, F.lit(0).cast("long")).alias(name)) if kind == "count" else whole

    def _average(self, value: E, name: str) -> DataFrame:
        """Sum and number of values in one traversal; nodes taken whole give both if they are stored and the nulls of
        the column are counted."""
        c, of = to_column(value, ROW), value.value[0] if value.op == "col" else None
        sums = [F.sum(c).alias("s"), F.count(c).alias("n")]
        if not (self.prune and self.stored and self.fuse and of in self.tree.spec.bounds and self.tree.has("sum", of)):
            return self.rows().agg(F.avg(c).alias(name))
        front = descend(self.tree, self._guide())
        parts = fetch(self.tree, front.tested.select(F.col("node_id").alias("leaf_id"), F.lit(False).alias("whole")), self.pred).agg(*sums)
        for _, nodes in front.taken:
            parts = parts.union(nodes.agg(F.sum(Agg("sum", of).name).alias("s"), F.sum(F.col("__rows") - F.col(f"{of}__nulls") + F.col(f"{of}__nan")).alias("n")))
        return parts.agg((F.sum("s") / F.sum("n")).alias(name))

    def count(self, name: str = "n") -> DataFrame:
        return self.reduce("count", None, name)

    def user_reduce(self, zero: Any, combine: Any, value: E | str, kind: str = "double", name: str = "value") -> DataFrame:
        """A commutative and associative ``combine`` of Python values: each task folds its rows to one, ``FOLDS`` tasks fold
        these, and one task folds theirs."""
        import pandas as pd

        c = to_column(self._value(value), ROW).alias("v")

        def fold(frames):
            acc, some = zero, False
            for pdf in frames:
                for v in pdf["v"]:
                    acc, some = combine(acc, v), True
            if some:
                yield pd.DataFrame({"v": [acc]})

        partial = self.rows().select(c).mapInPandas(fold, f"v {kind}")
        for tasks in (FOLDS, 1):  # by a shuffle, so that the scan keeps its tasks
            partial = partial.repartition(tasks).mapInPandas(fold, f"v {kind}")
        return partial.select(F.col("v").alias(name))

    def _extreme(self, metric: E | str, largest: bool) -> tuple[DataFrame, E]:
        """Rows that can hold the extreme, found with value bounds: at each level the best bound that taken nodes
        prove is read back, and nodes that can't beat it are dropped."""
        m = self._value(metric)
        self.tree.check(m)
        lo, hi = bounds(m, env_of(self.tree, 0))
        near, far = (hi, lo) if largest else (lo, hi)  # the best that a node may hold, and what it holds at least
        sure = all(n in self.tree.spec.bounds for n in columns(m)) and near is not None
        best: list[Any] = []
        better = (lambda a, b: a >= b) if largest else (lambda a, b: a <= b)

        def cut(level: int, down: DataFrame, taken: DataFrame) -> DataFrame:
            if not sure:
                return down
            if far is not None:
                v = taken.where(both_not_null(m)).agg((F.max if largest else F.min)(to_column(far, ROW))).first()[0]
                if v is not None:
                    best.append(v)
            if best:
                b = (max if largest else min)(best)
                down = down.where(better(to_column(near, ROW), F.lit(b)) | to_column(near, ROW).isNull())
            return down

        def both_not_null(e: E) -> Column:
            out = F.lit(True)
            for n in columns(e):
                out = out & (F.col(f"{n}__nulls") == 0)
            return out

        front = descend(self.tree, self._guide(), cut)
        if sure and best:
            b = (max if largest else min)(best)
            front.taken = [(lv, t.where(better(to_column(near, ROW), F.lit(b)) | to_column(near, ROW).isNull())) for lv, t in front.taken]
        return fetch(self.tree, front.leaves(), self.pred), m

    def _stored_extreme(self, of: str, largest: bool, name: str) -> DataFrame:
        """The extreme of a column whose extreme is stored in the nodes: a node taken whole attains its stored value,
        and what can't beat the best so far is dropped, at each level, before any row is read."""
        f = F.max if largest else F.min
        stored = F.col(Agg("max" if largest else "min", of).name)
        best: list[Any] = []

        def cut(level: int, down: DataFrame, taken: DataFrame) -> DataFrame:
            v = taken.agg(f(stored)).first()[0]
            if v is not None and (not best or (v > best[0] if largest else v < best[0])):
                best[:] = [v]
            return down.where(stored > F.lit(best[0]) if largest else stored < F.lit(best[0])) if best else down.where(stored.isNotNull())

        front = descend(self.tree, self._guide(), cut)
        rows = fetch(self.tree, front.tested.select(F.col("node_id").alias("leaf_id"), F.lit(False).alias("whole")), self.pred).agg(f(of).alias("v"))
        if not best:
            return rows.select(F.col("v").alias(name))
        kind = self.tree.schema[of].dataType
        return rows.select((F.greatest if largest else F.least)("v", F.lit(best[0]).cast(kind)).alias(name))

    def min(self, metric: E | str, name: str = "value") -> DataFrame:
        m = self._value(metric)
        if self.prune and self.stored and m.op == "col" and self.tree.has("min", m.value[0]):
            return self._stored_extreme(m.value[0], False, name)
        rows, m = self._extreme(metric, False) if self.prune else (self.rows(), m)
        return rows.agg(F.min(to_column(m, ROW)).alias(name))

    def max(self, metric: E | str, name: str = "value") -> DataFrame:
        m = self._value(metric)
        if self.prune and self.stored and m.op == "col" and self.tree.has("max", m.value[0]):
            return self._stored_extreme(m.value[0], True, name)
        rows, m = self._extreme(metric, True) if self.prune else (self.rows(), m)
        return rows.agg(F.max(to_column(m, ROW)).alias(name))

    def topk(self, metric: E | str, k: int, tie: tuple[str, ...], largest: bool = False) -> DataFrame:
        """The k members of the smallest (largest) metric, ties by ``tie``. With k > 1 a taken node's bound counts
        for its first row only, so pruning waits for k of them."""
        rows, m = self._extreme(metric, largest) if self.prune and k == 1 else (self.rows(), self._value(metric))
        c = to_column(m, ROW)
        return rows.where(c.isNotNull()).orderBy(c.desc() if largest else c.asc(), *tie).limit(k)

    def argmin(self, metric: E | str, tie: tuple[str, ...]) -> DataFrame:
        return self.topk(metric, 1, tie)

    def argmax(self, metric: E | str, tie: tuple[str, ...]) -> DataFrame:
        return self.topk(metric, 1, tie, True)

    def any(self, p: E, name: str = "any") -> DataFrame:
        """Whether a member satisfies p; one taken node proves it without reading rows."""
        q = self.filter(p)
        if q.prune:
            front = descend(q.tree, q._guide())
            for _, nodes in front.taken:
                if not nodes.limit(1).isEmpty():
                    return q.tree.rows.sparkSession.range(1).select(F.lit(True).alias(name))
            return fetch(q.tree, front.leaves(), q.pred).limit(1).agg((F.count("*") > 0).alias(name))
        return q.rows().limit(1).agg((F.count("*") > 0).alias(name))

    def all(self, p: E, name: str = "all") -> DataFrame:
        return self.any(negate(self._to_stored(p)), name).select((~F.col(name)).alias(name))

    def explain(self) -> str:
        always, maybe = node_guards(self.tree, self._guide())
        return f"always: {always}\nmaybe:  {maybe}\nlevels: {self.tree.height + 1}, leaves: {self.tree.n_leaves}, rows: {self.tree.n}"

    def explain_analyze(self) -> DataFrame:
        """(level, taken, descended, pruned, rows_tested) of the traversal."""
        front = descend(self.tree, self._guide(), whole=True)
        out = None
        for level, nodes in front.seen:
            is_ = lambda v: F.sum((F.col("verdict") == v).cast("long"))
            tested = F.sum(F.when(F.col("verdict") == 1, F.col("__rows")).otherwise(0)) if level == 0 else F.lit(0).cast("long")
            row = nodes.agg(F.lit(level).alias("level"), F.coalesce(is_(2), F.lit(0)).alias("taken"), F.coalesce(is_(1), F.lit(0)).alias("descended"), F.coalesce(is_(0), F.lit(0)).alias("pruned"), F.coalesce(tested, F.lit(0)).alias("rows_tested"))
            out = row if out is None else out.union(row)
        return out


def over(forest: Forest, f) -> DataFrame:
    """Union of a query's rows over the members of a forest."""
    out = None
    for t in forest.members:
        part = f(Q(t))
        out = part if out is None else out.unionByName(part)
    return out


def prune_with(tree: Tree, maybe: Column, always: Column | None = None) -> list[DataFrame]:
    """The traversal with hand-written node conditions: nodes seen at each level, with their verdicts."""
    nodes, seen = tree.levels[-1], []
    for level in range(tree.height, -1, -1):
        done = nodes.withColumn("verdict", F.when(always if always is not None else F.lit(False), 2).when(maybe, 1).otherwise(0))
        seen.append(done)
        if level:
            parents = done.where("verdict = 1").select(F.col("node_id").alias("_parent"))
            nodes = tree.levels[level - 1].join(parents, F.floor(F.col("node_id") / tree.spec.fanout) == F.col("_parent"), "left_semi")
    return seen
