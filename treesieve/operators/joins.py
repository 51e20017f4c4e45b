"""Joins by tree: filters of products, pruned on one side or on both.

Single-index: outer rows carry the node they have reached; each level is one equi-join with the
node table below, and outer columns are uniform in the guards. Dual-index: pairs of nodes descend in
lockstep, an exhausted side stays where it is. The frontier is the work queue, so Spark spreads it;
leaves meet their rows by equality of the leaf number, where the optimiser may split skewed leaves.
Conditions on one side only go to that side's own nodes through the same guards.

Prefixes: columns of the left (outer) side are ``l_``..., of the right (inner) ``r_``... in the
frontier; results give them back under the caller's prefixes.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import Program, numeric
from ..functions.expr import FALSE, AnalysisError, E, bind, both, col, columns, either, kept, lit, to_column
from ..functions.intervals import bounds, guards, is_boolean
from . import blocks, pairs
from .tree import Tree

LEFT, RIGHT = "_l_", "_r_"


def _side(name: str, side: int) -> Column:
    return F.col(f"{LEFT if side == 0 else RIGHT}{name}")


def _named(df: DataFrame, prefix: str) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{prefix}{c}") for c in df.columns])


def _pair_guards(p: E, left: Tree | None, right: Tree | None) -> tuple[E, E]:
    """Guards of a condition on pairs where the given sides vary."""
    trees = {s: t for s, t in ((0, left), (1, right)) if t is not None}

    def env(name: str, side: int):
        if side not in trees:
            return None
        return (col(f"{name}_lo", side), col(f"{name}_hi", side)) if name in trees[side].spec.bounds else (None, None)

    used = {(n, s) for s, t in trees.items() for n in columns(p, s) & set(t.spec.bounds)}
    always, maybe = guards(p, env, used)
    return always, either(maybe, *(E("<", (lit(0), col(f"{n}__nan", s))) for n, s in sorted(used)))


def _check(p: E, left: list[str], right: list[str]) -> None:
    if not is_boolean(p):
        raise AnalysisError(f"{p} is not a condition")
    absent = columns(p, 0) - set(left) | columns(p, 1) - set(right)
    if absent:
        raise AnalysisError(f"no such column: {', '.join(sorted(absent))}")


def _verdict(always: E, maybe: E) -> Column:
    return F.when(to_column(always, _side), 2).when(to_column(maybe, _side), 1).otherwise(0)


def _out(df: DataFrame, left: list[str], right: list[str], prefixes: tuple[str, str]) -> DataFrame:
    return df.select(*[F.col(f"{LEFT}{c}").alias(f"{prefixes[0]}{c}") for c in left], *[F.col(f"{RIGHT}{c}").alias(f"{prefixes[1]}{c}") for c in right])


def _expand(tree: Tree, level: int, node: str) -> Column:
    """Leaf numbers below a node."""
    u = tree.under(level)
    return F.col(node) if u == 1 else F.explode(F.sequence(F.col(node) * u, F.least((F.col(node) + 1) * u, F.lit(tree.n_leaves)) - 1))


def probe(outer: DataFrame, tree: Tree, p: E) -> tuple[DataFrame, DataFrame]:
    """The descent of every outer row (side 0) into the tree (side 1): frontier rows at the leaves as
    (outer columns, leaf, whole), and per level what was seen (level, verdict)."""
    always, maybe = _pair_guards(p, None, tree)
    at = outer.withColumn("_node", F.lit(0).cast("long"))
    leaves, seen = None, None
    for level in range(tree.height, -1, -1):
        nodes = _named(tree.levels[level], RIGHT)
        met = at.join(nodes, F.col("_node") == F.col(f"{RIGHT}node_id")).withColumn("_v", _verdict(always, maybe))
        counted = met.select(F.lit(level).alias("level"), F.col("_v").alias("verdict"))
        seen = counted if seen is None else seen.union(counted)
        keep = [*outer.columns]
        if level == 0:
            done = met.where("_v > 0").select(*keep, F.col("_node").alias("_leaf"), (F.col("_v") == 2).alias("_whole"))
            leaves = done if leaves is None else leaves.union(done)
        else:
            if always != FALSE:
                whole = met.where("_v = 2").select(*keep, _expand(tree, level, "_node").alias("_leaf"), F.lit(True).alias("_whole"))
                leaves = whole if leaves is None else leaves.union(whole)
            # children of node n are n*F .. n*F+F-1; those beyond the last node find no partner
            kids = F.sequence(F.col("_node") * tree.spec.fanout, F.col("_node") * tree.spec.fanout + tree.spec.fanout - 1)
            at = met.where("_v = 1").select(*keep, F.explode(kids).alias("_node"))
    return leaves, seen


def _match(outer: DataFrame, tree: Tree, p: E) -> DataFrame:
    leaves, _ = probe(outer, tree, p)
    rows = _named(tree.rows, RIGHT)
    return leaves.join(rows, F.col("_leaf") == F.col(f"{RIGHT}leaf_id")).where(F.col("_whole") | to_column(p, _side))


def single_index_join(outer: DataFrame, tree: Tree, p: E, output: str = "flat", key: tuple[str, ...] = (), prefixes: tuple[str, str] = ("", "r_"), how: str = "inner", folds: dict[str, Callable[[Callable[[str], Column]], Column]] | None = None) -> DataFrame:
    """For each outer row the members that satisfy p. output: flat, or grouped (one row for each outer row,
    members in an array, empty where none match; key names the outer rows; with ``folds``, aggregates of a member's
    columns by name in the array's place, combined before the shuffle, null where none match). how: inner, or left, right and
    full to keep rows without a partner, in flat output; left and full need ``key``."""
    _check(p, outer.columns, tree.schema.names)
    left = _named(outer, LEFT)
    inner = tree.schema.names
    pairs = _match(left, tree, p)
    if output == "grouped" and folds:
        found = pairs.groupBy(*[F.col(f"{LEFT}{k}").alias(k) for k in key]).agg(*[f(lambda c: F.col(f"{RIGHT}{c}")).alias(n) for n, f in folds.items()])
        return outer.join(found, list(key), "left").select(*[F.col(c).alias(f"{prefixes[0]}{c}") for c in outer.columns], *folds)
    if output == "grouped":
        found = pairs.groupBy(*[f"{LEFT}{k}" for k in key]).agg(F.sort_array(F.collect_list(F.struct(*[F.col(f"{RIGHT}{c}").alias(c) for c in inner]))).alias("members"))
        found = found.select(*[F.col(f"{LEFT}{k}").alias(k) for k in key], "members")
        none = F.array().cast(found.schema["members"].dataType)
        return outer.join(found, list(key), "left").select(*[F.col(c).alias(f"{prefixes[0]}{c}") for c in outer.columns], F.coalesce("members", none).alias("members"))
    flat = _out(pairs, outer.columns, inner, prefixes)
    if how in ("left", "full"):
        lone = outer.join(pairs.select(*[F.col(f"{LEFT}{k}").alias(k) for k in key]).distinct(), list(key), "left_anti")
        flat = flat.unionByName(lone.select(*[F.col(c).alias(f"{prefixes[0]}{c}") for c in outer.columns]), allowMissingColumns=True)
    if how in ("right", "full"):
        # rows that are equal in all columns, nulls included, have the same partners
        met = pairs.select(*[F.col(f"{RIGHT}{c}") for c in inner]).distinct()
        same = F.lit(True)
        for c in inner:
            same = same & F.col(c).eqNullSafe(F.col(f"{RIGHT}{c}"))
        lone = tree.scan().join(met, same, "left_anti")
        flat = flat.unionByName(lone.select(*[F.col(c).alias(f"{prefixes[1]}{c}") for c in inner]), allowMissingColumns=True)
    return flat


def _in_tasks(outer: DataFrame, tree: Tree, *es: E) -> bool:
    """Whether tasks can compute the expressions over arrays."""
    return all(Program(e).known() and numeric(outer.schema, columns(e, 0)) and numeric(tree.schema, columns(e, 1)) for e in es)


def _fits(outer: DataFrame, tree: Tree, n: int) -> bool:
    return blocks.n_blocks(n, outer.sparkSession.sparkContext.defaultParallelism) * tree.n <= blocks.MOVED


def exists_join(outer: DataFrame, tree: Tree, p: E, key: tuple[str, ...], negate: bool = False) -> DataFrame:
    """Outer rows that have (or lack) a member that satisfies p. A node taken whole is a proof by itself; its
    rows are not read."""
    _check(p, outer.columns, tree.schema.names)
    if _in_tasks(outer, tree, p):
        maybe, n = _pair_guards(p, None, tree)[1], outer.count()
        if _fits(outer, tree, n):
            # every member counts as 0 and every leaf begins at 1, so a row is done with the first that is found
            found = blocks.best_members(outer, tree, lit(0.0), (), blocks.guard(maybe, lit(1.0)), p, 1, n).select(*[F.col(f"l_{k}").alias(k) for k in key]).distinct()
            return outer.join(found, list(key), "left_anti" if negate else "left_semi")
    leaves, _ = probe(_named(outer, LEFT), tree, p)
    names = [f"{LEFT}{k}" for k in key]
    proven = leaves.where("_whole").select(*names).distinct()
    rows = _named(tree.rows, RIGHT)
    open_ = leaves.where("not _whole").join(proven, names, "left_anti")
    tested = open_.join(rows, F.col("_leaf") == F.col(f"{RIGHT}leaf_id")).where(to_column(p, _side)).select(*names)
    found = proven.union(tested).distinct().select(*[F.col(n).alias(k) for n, k in zip(names, key, strict=True)])
    return outer.join(found, list(key), "left_anti" if negate else "left_semi")


def count_join(outer: DataFrame, tree: Tree, p: E, name: str = "n") -> DataFrame:
    """Outer rows that have members which satisfy p, and how many. In tasks, by ``blocks``, no pair leaves one; otherwise by the join
    of leaves."""
    _check(p, outer.columns, tree.schema.names)
    if _in_tasks(outer, tree, p):
        n = outer.count()
        if _fits(outer, tree, n):
            return blocks.count_members(outer, tree, p, *_pair_guards(p, None, tree), n, name).where(F.col(name) > 0)
    row = F.monotonically_increasing_id().alias("_row")
    found = _match(_named(outer.select("*", row), LEFT), tree, p).groupBy(f"{LEFT}_row", *[f"{LEFT}{c}" for c in outer.columns]).agg(F.count("*").alias(name))
    return found.select(*[F.col(f"{LEFT}{c}").alias(c) for c in outer.columns], name)


class Pairs:
    """The descent of two trees: pairs of leaves to test, pairs of nodes taken whole, counters."""

    def __init__(self, a: Tree, b: Tree, p: E, symmetric: bool = False):
        _check(p, a.schema.names, b.schema.names)
        self.a, self.b, self.p = a, b, p
        always, maybe = _pair_guards(p, a, b)
        at = a.rows.sparkSession.range(1).select(F.lit(0).cast("long").alias("_a"), F.lit(0).cast("long").alias("_b"))
        self.taken: list[tuple[int, int, DataFrame]] = []
        self.seen: list[tuple[int, DataFrame]] = []
        for step in range(max(a.height, b.height), -1, -1):
            i, j = min(step, a.height), min(step, b.height)
            na, nb = _named(a.levels[i], LEFT), _named(b.levels[j], RIGHT)
            met = at.join(na, F.col("_a") == F.col(f"{LEFT}node_id")).join(nb, F.col("_b") == F.col(f"{RIGHT}node_id")).withColumn("_v", _verdict(always, maybe))
            self.seen.append((step, met.select("_v", F.col(f"{LEFT}__rows").alias("ra"), F.col(f"{RIGHT}__rows").alias("rb"))))
            if always != FALSE:
                self.taken.append((i, j, met.where("_v = 2")))
            down = met.where("_v = 1").select("_a", "_b")
            if step == 0:
                self.leaves = down
                self.ended = met.where("_v > 0").select("_a", "_b", (F.col("_v") == 2).alias("_whole"))
                return
            ni, nj = min(step - 1, a.height), min(step - 1, b.height)
            kids = lambda c, go, f: F.sequence(F.col(c) * f, F.col(c) * f + f - 1) if go else F.array(F.col(c))
            at = down.select(F.explode(kids("_a", ni < i, a.spec.fanout)).alias("_a"), "_b").select("_a", F.explode(kids("_b", nj < j, b.spec.fanout)).alias("_b"))
            at = at.where((F.col("_a") * a.under(ni) < a.n_leaves) & (F.col("_b") * b.under(nj) < b.n_leaves))
            if symmetric:
                at = at.where("_a <= _b")

    def tested(self) -> DataFrame:
        """Row pairs of the leaf pairs, tested."""
        ra, rb = _named(self.a.rows, LEFT), _named(self.b.rows, RIGHT)
        return self.leaves.join(ra, F.col("_a") == F.col(f"{LEFT}leaf_id")).join(rb, (F.col("_b") == F.col(f"{RIGHT}leaf_id")) & to_column(self.p, _side))

    def rows(self, asked: tuple[list[str], list[str]] | None = None) -> DataFrame:
        """The pairs, with all columns of both sides or those asked for. Rows of leaves meet in tasks, by ``pairs``, where these can
        compute the condition; otherwise by joins."""
        of = asked or (self.a.schema.names, self.b.schema.names)
        names = [*[f"{LEFT}{c}" for c in of[0]], *[f"{RIGHT}{c}" for c in of[1]]]
        if all(of) and _in_tasks(self.a.rows, self.b, self.p):
            at = self.ended
            for i, j, nodes in self.taken:
                if (i, j) != (0, 0):
                    whole = nodes.select(_expand(self.a, i, "_a").alias("_a"), "_b").select("_a", _expand(self.b, j, "_b").alias("_b"))
                    at = at.union(whole.select("_a", "_b", F.lit(True).alias("_whole")))
            return pairs.of_leaves(self.a, self.b, at, self.p, of).toDF(*[f"{LEFT}{c}" for c in of[0]], *[f"{RIGHT}{c}" for c in of[1]])
        out = self.tested().select(*names)
        ra, rb = _named(self.a.rows, LEFT), _named(self.b.rows, RIGHT)
        for i, j, nodes in self.taken:
            whole = nodes.select(_expand(self.a, i, "_a").alias("_la"), "_b").select("_la", _expand(self.b, j, "_b").alias("_lb"))
            out = out.union(whole.join(ra, F.col("_la") == F.col(f"{LEFT}leaf_id")).join(rb, F.col("_lb") == F.col(f"{RIGHT}leaf_id")).select(*names))
        return out

    def count(self, name: str = "n", stored: bool = True) -> DataFrame:
        """Pairs, counted in the traversal: a pair of nodes taken whole counts by its row counts."""
        if not stored:
            return self.rows().agg(F.count("*").alias(name))
        if _in_tasks(self.a.rows, self.b, self.p):
            parts = pairs.of_leaves(self.a, self.b, self.leaves.withColumn("_whole", F.lit(False)), self.p, None).agg(F.sum("n").alias("v"))
        else:
            parts = self.tested().agg(F.count("*").alias("v"))
        for _, _, nodes in self.taken:
            parts = parts.union(nodes.agg(F.sum(F.col(f"{LEFT}__rows") * F.col(f"{RIGHT}__rows")).alias("v")))
        return parts.agg(F.coalesce(F.sum("v"), F.lit(0).cast("long")).alias(name))

    def counters(self) -> DataFrame:
        """(level, pairs, taken, descended, pruned, rows_tested); rows_tested counts row pairs at the last level."""
        out = None
        for level, met in self.seen:
            is_ = lambda v: F.coalesce(F.sum((F.col("_v") == v).cast("long")), F.lit(0)).alias
            tested = F.coalesce(F.sum(F.when(F.col("_v") == 1, F.col("ra") * F.col("rb"))), F.lit(0)) if level == 0 else F.lit(0).cast("long")
            row = met.agg(F.lit(level).alias("level"), F.count("*").alias("pairs"), is_(2)("taken"), is_(1)("descended"), is_(0)("pruned"), tested.alias("rows_tested"))
            out = row if out is None else out.union(row)
        return out


def dual_index_join(a: Tree, b: Tree, p: E, prefixes: tuple[str, str] = ("", "r_")) -> DataFrame:
    return _out(Pairs(a, b, p).rows(), a.schema.names, b.schema.names, prefixes)


def nested_join(a: DataFrame, b: DataFrame, p: E, prefixes: tuple[str, str] = ("", "r_"), out: tuple[list[str], list[str]] | None = None) -> DataFrame:
    """All pairs, then the condition: the baseline. ``out`` names the columns that are asked for, of both sides. Parts of both sides
    meet in tasks, by ``pairs``, where these can compute the condition; otherwise in Spark's nested loop."""
    _check(p, a.columns, b.columns)
    of = out or (a.columns, b.columns)
    if all(of) and Program(p).known() and numeric(a.schema, columns(p, 0)) and numeric(b.schema, columns(p, 1)):
        n, m = a.count(), b.count()
        if pairs.moved(n, m, a.sparkSession.sparkContext.defaultParallelism) <= blocks.MOVED:
            return pairs.all_pairs(a, b, p, of, n, m).toDF(*[f"{prefixes[0]}{c}" for c in of[0]], *[f"{prefixes[1]}{c}" for c in of[1]])
    return _out(_named(a, LEFT).join(_named(b, RIGHT), to_column(p, _side)), *of, prefixes)


def nearest(outer: DataFrame, tree: Tree, metric: E, key: tuple[str, ...], tie: tuple[str, ...], p: E | None = None, k: int = 1, prefixes: tuple[str, str] = ("", "r_"), name: str = "metric") -> DataFrame:
    """For each outer row the k members of the smallest metric among those that satisfy p (all without p).

    A first pass dives to one leaf for each row and takes its k-th best; the full pass leaves nodes that begin
    beyond it. Both are made in tasks, by ``blocks``, where the columns are numbers and the tree can be moved to every block
    of outer rows; otherwise level by level, linear in the levels, and nothing of a level is computed twice.
    """
    _check(both(p or lit(True)), outer.columns, tree.schema.names)
    left = _named(outer, LEFT)
    names = [f"{LEFT}{c}" for c in key]
    lo, _ = bounds(metric, lambda n, s: None if s == 0 else (col(f"{n}_lo", 1), col(f"{n}_hi", 1)) if n in tree.spec.bounds else (None, None))
    if lo is None:
        lo = lit(float("-inf"))
    maybe = _pair_guards(p, None, tree)[1] if p is not None else lit(True)
    if _in_tasks(outer, tree, metric, *([] if p is None else [p])):
        n = outer.count()
        if _fits(outer, tree, n):
            found = blocks.best_members(outer, tree, metric, tie, blocks.guard(maybe, lo), p, k, n)
            out = [F.col(f"l_{c}").alias(f"{prefixes[0]}{c}") for c in outer.columns] + [F.col(f"r_{c}").alias(f"{prefixes[1]}{c}") for c in tree.schema.names]
            return found.select(*out, F.col("m").alias(name), *([F.col("n").alias("rank")] if k > 1 else []))
    near = to_column(lo, _side)
    rows = _named(tree.rows, RIGHT)
    wanted = metric if p is None else E("case", (p, metric, lit(None)))

    def meet(at: DataFrame, level: int) -> DataFrame:
        nodes = _named(tree.levels[level], RIGHT)
        return at.join(nodes, F.col("_node") == F.col(f"{RIGHT}node_id")).where(to_column(maybe, _side)).withColumn("_near", near)

    def members(at: DataFrame) -> DataFrame:
        return bind(at.join(rows, F.col("_node") == F.col(f"{RIGHT}leaf_id")), wanted, _side, "_m")

    def kids(met: DataFrame) -> DataFrame:
        f = tree.spec.fanout
        return met.select(*left.columns, *(["_best"] if "_best" in met.columns else []), F.explode(F.sequence(F.col("_node") * f, F.col("_node") * f + f - 1)).alias("_node"))

    start = left.withColumn("_node", F.lit(0).cast("long"))
    # the dive: at each level the child that begins nearest; its leaf's k-th best is a bound that all may use
    dive = start
    for level in range(tree.height, -1, -1):
        met = meet(dive, level).withColumn("_first", F.struct(F.coalesce("_near", F.lit(float("inf"))).alias("near"), "_node"))
        first = met.groupBy(*names).agg(F.min("_first").alias("_first")).select(*names, F.col("_first._node").alias("_node")).join(left, names)
        dive = first if level == 0 else kids(first)
    if k == 1:
        kth = members(dive).groupBy(*names).agg(F.min("_m").alias("_best"))
    else:
        kth = members(dive).withColumn("_n", F.row_number().over(Window.partitionBy(*names).orderBy(F.col("_m").asc_nulls_last()))).where(F.col("_n") == k).select(*names, F.col("_m").alias("_best"))
    start = start.join(kth, names, "left")
    at = start
    for level in range(tree.height, -1, -1):
        met = meet(at, level)
        met = met.where(F.col("_best").isNull() | (F.col("_near") <= F.col("_best")))
        at = met if level == 0 else kids(met)
    # aggregates of structs and ranks sort their rows: only what the bound leaves goes there
    close = kept(members(at), F.col("_m").isNotNull() & (F.col("_best").isNull() | (F.col("_m") <= F.col("_best"))))
    if k == 1:
        order = F.struct("_m", *[f"{RIGHT}{t}" for t in tie])
        row = F.struct("_m", *[f"{RIGHT}{c}" for c in tree.schema.names])
        best = close.groupBy(*names).agg(F.min_by(row, order).alias("_row"))
        ranked = best.select(*names, "_row.*").join(left, names)
    else:
        ranked = close.withColumn("_n", F.row_number().over(Window.partitionBy(*names).orderBy(F.col("_m").asc_nulls_last(), *[f"{RIGHT}{t}" for t in tie]))).where(F.col("_n") <= k)
    out = [F.col(f"{LEFT}{c}").alias(f"{prefixes[0]}{c}") for c in outer.columns] + [F.col(f"{RIGHT}{c}").alias(f"{prefixes[1]}{c}") for c in tree.schema.names]
    return ranked.select(*out, F.col("_m").alias(name), *([F.col("_n").alias("rank")] if k > 1 else []))


def choose_side(a: Tree, b: Tree, p: E, sample: int = 200) -> dict[str, float]:
    """What the plans would test, from guards alone: row pairs of nested, dual, and of the single-index join with
    either side as outer, the latter extrapolated from a sample of outer rows."""
    dual = Pairs(a, b, p).counters().agg(F.sum("rows_tested")).first()[0] or 0
    costs = {"nested": float(a.n * b.n), "dual": float(dual)}
    for name, outer, tree, q in (("single_right", a, b, p), ("single_left", b, a, swap(p))):
        n = outer.n
        part = outer.scan().limit(sample)
        leaves, _ = probe(_named(part, LEFT), tree, q)
        costs[name] = leaves.where("not _whole").count() * tree.spec.leaf_rows * n / max(1, min(sample, n))
    return costs


def swap(p: E) -> E:
    """The condition with its sides exchanged."""
    return E("col", value=(p.value[0], 1 - p.value[1])) if p.op == "col" else E(p.op, tuple(map(swap, p.args)), p.value)


