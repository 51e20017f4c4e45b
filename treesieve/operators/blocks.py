"""The best members of a tree for blocks of outer rows, each block in one task.

Outer rows are dealt to blocks; every block meets the tree's rows in the order of its leaves, a run of leaves
at a time. A task derives the runs' node metadata, asks a guard which leaves an outer row can use and where
they begin, tests the leaf that begins nearest, and then those that begin within what it proved. No pair
of a row and a leaf leaves a task, so nothing of the descent is shuffled or sorted; what moves are the
tree's rows, once for each block. The size of the blocks grows with the outer side, up to a bound that
a task can hold.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.arrays import Program, Value, numbers
from ..functions.expr import E, columns
from .tree import Tree

Columns = dict[str, Value]
#: (outer columns as a column of values, node metadata as a row) -> which leaves are to be met, and where they begin.
Guard = Callable[[Columns, Columns], tuple[Any, Any]]
#: Rows of a block and of a run of leaves, cells of what a guard computes at once, members that are tested at once.
BLOCK, RUN, CELLS, TESTED = 65_536, 65_536, 1 << 17, 1 << 15
#: How many of its nearest leaves a row meets at first, before the rest that its bound leaves.
ROUNDS = (1, 4, 16)
#: Rows of a tree that are moved to blocks at most.
MOVED = 1 << 30


def n_blocks(n: int, cores: int) -> int:
    """Enough for all cores, none beyond what a task holds."""
    return max(1, -(-n // BLOCK), min(4 * cores, -(-n // 64)))


def runs(columns: Columns, leaf: np.ndarray, names: tuple[str, ...]) -> tuple[np.ndarray, np.ndarray, Columns]:
    """Where each leaf begins, its size, and its metadata."""
    starts = np.flatnonzero(np.concatenate([[True], leaf[1:] != leaf[:-1]]))
    sizes = np.diff(np.append(starts, len(leaf)))
    out: Columns = {"__rows": (sizes, None)}
    for n in names:
        x, null = columns[n]
        floating = x.dtype.kind == "f"
        nan = np.isnan(x) if floating else np.zeros(len(x), bool)
        gone = nan if null is None else nan | null
        low, high = (-np.inf, np.inf) if floating else (np.iinfo(np.int64).min, np.iinfo(np.int64).max)
        missing, nans = (np.add.reduceat(m.astype(np.int64), starts) for m in (gone, nan))
        absent = missing == sizes if (missing == sizes).any() else None
        out[f"{n}_lo"] = np.minimum.reduceat(np.where(gone, high, x), starts), absent
        out[f"{n}_hi"] = np.maximum.reduceat(np.where(gone, low, x), starts), absent
        out[f"{n}__nulls"], out[f"{n}__nan"] = (missing, None), (nans, None)
    return starts, sizes, out


def guard(maybe: E | None, near: E | None) -> Guard:
    """What conditions and bounds that were derived say, as a guard."""
    may, begin = (None if e is None else Program(e) for e in (maybe, near))

    def of(outer: Columns, nodes: Columns) -> tuple[Any, Any]:
        get = lambda name, side: outer[name] if side == 0 else nodes[name]
        at = -np.inf
        if begin is not None:
            at, null = begin.run(get)
            at = at if null is None else np.where(null, -np.inf, at)
        return (True if may is None else may.true(get)), at

    return of


class Best:
    """What is known of a block: its rows, and for each the best members so far."""

    def __init__(self, outer: pa.Table, names: list[str], k: int):
        self.outer, self.k = outer, k
        self.columns = {n: numbers(outer.column(f"l_{n}")) for n in names}
        self.bound = np.full(outer.num_rows, np.inf)
        self.row, self.m, self.members = np.empty(0, np.int64), np.empty(0), None

    def add(self, row: np.ndarray, m: np.ndarray, members: pa.Table, tie: tuple[str, ...]) -> None:
        if self.members is not None:
            row, m, members = np.concatenate([self.row, row]), np.concatenate([self.m, m]), pa.concat_tables([self.members, members])
        table = pa.table({"row": row, "m": m, **{f"t{i}": members.column(f"r_{t}") for i, t in enumerate(tie)}})
        order = pc.sort_indices(table, [(c, "ascending") for c in table.column_names], null_placement="at_start").to_numpy()
        row = row[order]
        first = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else np.empty(0, np.int64)
        place = np.arange(len(row)) - np.repeat(first, np.diff(np.append(first, len(row))))
        kept = order[place < self.k]
        self.row, self.m, self.members = row[place < self.k], m[kept], members.take(pa.array(kept))
        full = np.flatnonzero(place[place < self.k] == self.k - 1)
        self.bound[self.row[full]] = self.m[full]


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices start, start+1, ... of every run, one run after another."""
    before = np.cumsum(lengths) - lengths
    return np.arange(int(lengths.sum()), dtype=np.int64) + np.repeat(starts - before, lengths)


def meet(best: Best, inner: pa.Table, bounded: tuple[str, ...], used: list[str], tie: tuple[str, ...], of: Guard, metric: Program, p: Program | None) -> None:
    """A block meets a run of leaves."""
    columns = {n: numbers(inner.column(f"r_{n}")) for n in used}
    starts, sizes, nodes = runs(columns, inner.column("leaf_id").to_numpy(), bounded)
    nodes = {n: (x[None, :], None if null is None else null[None, :]) for n, (x, null) in nodes.items()}
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def tested(rows: np.ndarray, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, member, metric) of the members of leaves that have a metric and satisfy p."""
        out, ends, at = [], np.cumsum(sizes[leaves]), 0
        while at < len(rows):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + TESTED, side="right")))
            i, j = np.repeat(rows[at:to], sizes[leaves[at:to]]), ragged(starts[leaves[at:to]], sizes[leaves[at:to]])
            at = to

            def get(name: str, side: int, i: np.ndarray = i, j: np.ndarray = j) -> Value:
                (x, null), where = (best.columns[name], i) if side == 0 else (columns[name], j)
                return x[where], None if null is None else null[where]

            if p is not None:
                ok = np.flatnonzero(np.broadcast_to(p.true(get), i.shape))
                i, j = i[ok], j[ok]
            m, null = metric.run(lambda name, side, i=i, j=j: get(name, side, i, j))
            m = np.broadcast_to(np.asarray(m, float), i.shape)
            if null is not None:
                ok = np.flatnonzero(~np.broadcast_to(null, i.shape))
                i, j, m = i[ok], j[ok], m[ok]
            bound = best.bound[i]
            ok = np.flatnonzero((m <= bound) | np.isnan(bound) | (bound == np.inf))
            out.append((i[ok], j[ok], m[ok]))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))  # type: ignore[return-value]

    step = max(1, CELLS // len(starts))
    for at in range(0, best.outer.num_rows, step):
        rows = np.arange(at, min(at + step, best.outer.num_rows))
        shape = (len(rows), len(starts))
        some = {n: (x[rows, None], None if null is None else null[rows, None]) for n, (x, null) in best.columns.items()}
        keep, near = of(some, nodes)
        keep = np.array(np.broadcast_to(keep, shape))
        near = np.broadcast_to(np.asarray(near, float), shape)
        near = np.where(np.isnan(near), -np.inf, near)

        def within(keep: np.ndarray = keep, near: np.ndarray = near, rows: np.ndarray = rows) -> np.ndarray:
            bound = best.bound[rows]
            return keep & ((near <= bound[:, None]) | np.isnan(bound)[:, None])

        for most in (*ROUNDS, len(starts)):
            left = within()
            if most < len(starts):
                nearest = np.argpartition(np.where(left, near, np.inf), most - 1, axis=1)[:, :most]
                which, place = np.nonzero(np.take_along_axis(left, nearest, axis=1))
                leaves = nearest[which, place]
            else:
                which, leaves = np.nonzero(left)
            if not len(which):
                break
            i, j, m = tested(rows[which], leaves)
            found.append((i, j, m))
            keep[which, leaves] = False
            # the k-th best of a round, if it is a number, is a bound
            order = np.lexsort((m, i))
            at_row = np.flatnonzero(np.concatenate([[True], i[order][1:] != i[order][:-1]])) if len(i) else np.empty(0, np.int64)
            kth = order[at_row[np.diff(np.append(at_row, len(i))) >= best.k] + best.k - 1]
            kth = kth[~np.isnan(m[kth])]
            best.bound[i[kth]] = np.fmin(best.bound[i[kth]], m[kth])
    if not found:
        return
    i, j, m = (np.concatenate(x) for x in zip(*found, strict=True))
    bound = best.bound[i]
    ok = np.flatnonzero((m <= bound) | np.isnan(bound) | (bound == np.inf))
    if len(ok):
        best.add(i[ok], m[ok], inner.take(pa.array(j[ok])).drop_columns("leaf_id"), tie)


def best_members(outer: DataFrame, tree: Tree, metric: E, tie: tuple[str, ...], of: Guard, p: E | None, k: int, n: int) -> DataFrame:
    """(l_ columns of outer, r_ columns of the tree, m, n): for each of the n outer rows the k members of the least metric among those that
    satisfy p, the smaller tie first."""
    names = sorted(columns(metric, 0) | (columns(p, 0) if p is not None else set()))
    used = sorted(columns(metric, 1) | (columns(p, 1) if p is not None else set()))
    bounded, program, condition = tuple(c for c in used if c in tree.spec.bounds), Program(metric), None if p is None else Program(p)
    rows, lefts, rights = dealt(outer, tree, n)
    schema = T.StructType([*(T.StructField(c, rows.schema[c].dataType) for c in (*lefts, *rights)), T.StructField("m", T.DoubleType()), T.StructField("n", T.IntegerType())])

    def ended(best: Best) -> Iterator[pa.RecordBatch]:
        if best.members is None:
            return
        first = np.flatnonzero(np.concatenate([[True], best.row[1:] != best.row[:-1]]))
        place = np.arange(len(best.row)) - np.repeat(first, np.diff(np.append(first, len(best.row)))) + 1
        o = best.outer.take(pa.array(best.row))
        arrays = [*(o.column(c) for c in lefts), *(best.members.column(c) for c in rights), pa.array(best.m), pa.array(place.astype(np.int32))]
        yield from pa.table(arrays, names=[*lefts, *rights, "m", "n"]).combine_chunks().to_batches()

    met = lambda best, inner: meet(best, inner, bounded, used, tie, of, program, condition)
    return rows.mapInArrow(lambda batches: by_block(batches, lefts, rights, lambda mine: Best(mine, names, k), met, ended), schema)


def dealt(outer: DataFrame, tree: Tree, n: int) -> tuple[DataFrame, list[str], list[str]]:
    """The rows of both sides by block (q), the outer ones (l_ columns) before the tree's (r_ columns), which come by leaf."""
    blocks = n_blocks(n, outer.sparkSession.sparkContext.defaultParallelism)
    left = outer.select(*[F.col(c).alias(f"l_{c}") for c in outer.columns]).withColumn("q", (F.monotonically_increasing_id() % blocks).cast("int")).withColumn("side", F.lit(0))
    inner = tree.rows.select(*[F.col(c).alias(f"r_{c}") for c in tree.schema.names], "leaf_id")
    right = inner.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("side", F.lit(1))
    rows = left.unionByName(right, allowMissingColumns=True)
    return rows.repartition("q").sortWithinPartitions("q", "side", "leaf_id"), [f"l_{c}" for c in outer.columns], [f"r_{c}" for c in tree.schema.names]


def by_block(batches: Iterator[pa.RecordBatch], lefts: list[str], rights: list[str], begin: Callable[[pa.Table], Any], met: Callable[[Any, pa.Table], None], ended: Callable[[Any], Iterator[pa.RecordBatch]]) -> Iterator[pa.RecordBatch]:
    """What a block has found once it has met the tree, a run of leaves at a time."""
    now, state, mine, held = None, None, [], []

    def flush() -> Iterator[pa.RecordBatch]:
        if state is None:
            return
        if held:
            met(state, pa.Table.from_batches(held).combine_chunks())
        yield from ended(state)

    for batch in batches:
        at = batch.column("q").to_numpy() * 2 + batch.column("side").to_numpy()
        cuts = [0, *(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), len(at)] if len(at) else [0]
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            q, side, part = int(at[i]) // 2, int(at[i]) % 2, batch.slice(i, j - i)
            if q != now:
                yield from flush()
                now, state, mine, held = q, None, [], []
            if side == 0:
                mine.append(part.select(lefts))
            elif mine:
                state = begin(pa.Table.from_batches(mine).combine_chunks()) if state is None else state
                held.append(part.select([*rights, "leaf_id"]))
                if sum(x.num_rows for x in held) >= RUN:
                    met(state, pa.Table.from_batches(held).combine_chunks())
                    held = []
    yield from flush()


def by_key(batches: Iterator[pa.RecordBatch], key: str, met: Callable[[list[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Iterator[pa.RecordBatch]:
    """What ``met`` makes of the rows of each key, in batches that are sorted by it."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        q = batch.column(key).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(q[1:] != q[:-1]) + 1).tolist(), len(q)] if len(q) else [0]
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            if held and held[-1].column(key)[0].as_py() != q[i]:
                yield from met(held)
                held = []
            held.append(batch.slice(i, j - i))
    if held:
        yield from met(held)


class Counts:
    """The rows of a block, and how many members each has found."""

    def __init__(self, outer: pa.Table, names: list[str]):
        self.outer, self.columns = outer, {n: numbers(outer.column(f"l_{n}")) for n in names}
        self.n = np.zeros(outer.num_rows, np.int64)


def count_members(outer: DataFrame, tree: Tree, p: E, always: E, maybe: E, n: int, name: str) -> DataFrame:
    """The n outer rows and how many members satisfy p with each. Leaves where all do count by their sizes."""
    names, used = sorted(columns(p, 0)), sorted(columns(p, 1))
    bounded, condition, all_, some_ = tuple(c for c in used if c in tree.spec.bounds), Program(p), Program(always), Program(maybe)
    rows, lefts, rights = dealt(outer, tree, n)
    schema = T.StructType([*(T.StructField(c, rows.schema[f"l_{c}"].dataType) for c in outer.columns), T.StructField(name, T.LongType())])

    def met(state: Counts, inner: pa.Table) -> None:
        members = {c: numbers(inner.column(f"r_{c}")) for c in used}
        starts, sizes, nodes = runs(members, inner.column("leaf_id").to_numpy(), bounded)
        ends = starts + sizes
        step = max(1, CELLS // len(starts))
        for at in range(0, inner_rows := state.outer.num_rows, step):
            part = slice(at, min(at + step, inner_rows))
            mine = {c: (x[part, None], None if null is None else null[part, None]) for c, (x, null) in state.columns.items()}
            get = lambda c, side: mine[c] if side == 0 else tuple(None if z is None else z[None, :] for z in nodes[c])  # noqa: E731, B023
            shape = (part.stop - part.start, len(starts))
            whole, maybe_ = (np.broadcast_to(g.true(get), shape) for g in (all_, some_))
            state.n[part] += whole @ sizes
            # a leaf is tested against all rows that can use it: no member is gathered
            open_ = maybe_ & ~whole
            for leaf in np.flatnonzero(open_.any(axis=0)):
                i = np.flatnonzero(open_[:, leaf])
                run = slice(starts[leaf], ends[leaf])

                def cell(c: str, side: int, i: np.ndarray = i, run: slice = run) -> Value:
                    x, null = (mine[c] if side == 0 else members[c])  # noqa: B023
                    return (x[i], None if null is None else null[i]) if side == 0 else (x[None, run], None if null is None else null[None, run])

                state.n[part.start + i] += np.broadcast_to(condition.true(cell), (len(i), int(sizes[leaf]))).sum(axis=1)

    def ended(state: Counts) -> Iterator[pa.RecordBatch]:
        yield from pa.table([*(state.outer.column(c) for c in lefts), pa.array(state.n)], names=schema.names).combine_chunks().to_batches()

    return rows.mapInArrow(lambda batches: by_block(batches, lefts, rights, lambda mine: Counts(mine, names), met, ended), schema)
