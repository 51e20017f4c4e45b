"""Pairs of rows, tested in tasks.

All pairs: both sides are dealt to parts, and every part of one side meets every part of the other in one task. Pairs of
leaves, as a descent leaves them: runs of the left tree's leaves meet the right leaves that they are paired with. Every pair is
tested by the condition as given, a tile of arrays at a time. Pairs leave a task as one row for each right row and run, with
its left rows in an array that the JVM explodes, so what is moved and converted is one value a pair.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.arrays import Program, numbers, numeric
from ..functions.expr import E, KERNELS, columns
from . import blocks
from .blocks import Columns, by_key, ragged
from .tree import Tree

#: Pairs of a tile (their arrays stay in a core's cache), left rows of it, pairs that leave a task at once.
TILE, WIDTH, PAIRS_AT_ONCE = 1 << 16, 1 << 14, 1 << 18
#: Pairs of a tile whose arrays are made anew: below what the allocator maps.
MADE = 1 << 13
#: Rows of a part of the right side, rows of a run of left leaves.
PART, RUN = 1 << 17, 1 << 15
#: Pairs for which a task is begun, rows of a run of left leaves at least.
WORK, LEAST = 1 << 24, 1 << 11
FAST = {"+": "add", "-": "subtract", "*": "multiply", "neg": "negative", "abs": "absolute", "<": "less", "<=": "less_equal", "=": "equal", "!=": "not_equal", "and": "logical_and"}

COMPARED = ("less", "equal", "not_equal", "logical_and")


def expanded(e: E) -> E:
    """Geometric predicates and metrics written out. The driver does it: workers don't know them."""
    return expanded(KERNELS[e.op](*e.args)) if e.op in KERNELS else E(e.op, tuple(map(expanded, e.args)), e.value) if e.args else e


def conjuncts(p: E) -> list[E]:
    return [y for x in p.args for y in conjuncts(x)] if p.op == "and" else [p]


def places(mask: np.ndarray) -> np.ndarray:
    """Where a mask without gaps is true; eight cells at once where few are."""
    even = mask.size // 8 * 8
    words = np.flatnonzero(mask[:even].view(np.uint64))
    if len(words) * 16 > mask.size:
        return np.flatnonzero(mask)
    i, j = np.nonzero(mask[:even].reshape(-1, 8)[words])
    return np.concatenate([words[i] * 8 + j, np.flatnonzero(mask[even:]) + even])


class Conjunct:
    """One condition on pairs. Where no value is null or not finite, and none can become so, plain array functions are the same as
    ``Program`` with its masks; one-sided terms are computed once for each row."""

    def __init__(self, e: E):
        self.e, self.program = e, Program(e)
        self.terms: tuple[list[E], list[E]] = [], []
        self.lines: dict[str, str] = {}
        top, made = self._source(e), {f: getattr(np, f) for f in FAST.values()}
        if top:
            for name, shared in (("fast", False), ("lean", True)):
                exec(f"def {name}(l, r, o):\n{self._body(shared)}    return {top}", made)  # noqa: S102
        self.fast: Callable[..., np.ndarray] | None = made.get("fast")
        self.lean: Callable[..., np.ndarray] | None = made.get("lean")
        self.programs = tuple([Program(t) for t in side] for side in self.terms)

    def _source(self, e: E) -> str | None:
        """The name of a term, each made once."""
        if e.op == "lit":
            return f"({e.value!r})" if isinstance(e.value, int | float) and not isinstance(e.value, bool) and np.isfinite(e.value) else None
        sides = [bool(columns(e, s)) for s in (0, 1)]
        if sides != [True, True]:
            at = 0 if sides[0] else 1
            if not any(sides) or e.op in ("<", "<=", "=", "!=", "and", "or", "not", "null", "notnull", "isnan", "in"):
                return None
            if e not in self.terms[at]:
                self.terms[at].append(e)
            return f"{'lr'[at]}[{self.terms[at].index(e)}]"
        if e.op not in FAST:
            return None
        parts = [self._source(a) for a in e.args]
        return None if None in parts else self.lines.setdefault(f"{FAST[e.op]}({', '.join(parts)})", f"t{len(self.lines)}")  # type: ignore[arg-type]

    def _body(self, shared: bool) -> str:
        """Terms go into arrays of the tile before: new ones would be mapped anew by the system each time. ``shared``: where all terms
        have one type, those that are used up are written over, and what is held fits a core's cache."""
        lines = [(name, term, set(re.findall(r"\bt\d+\b", term))) for term, name in self.lines.items()]
        last = {t: k for k, (_, _, used) in enumerate(lines) for t in used}
        at: dict[str, int] = {}
        free: list[int] = []
        out = ""
        for k, (name, term, used) in enumerate(lines):
            if shared:
                free += [at[t] for t in sorted(used) if last[t] == k]
            at[name] = free.pop() if free and not term.startswith(COMPARED) else k
            out += f"    o[{at[name]}] = {name} = {term[:-1]}, out=o[{at[name]}])\n"
        return out

    def side(self, at: int, values: Columns, n: int) -> tuple[list[np.ndarray], float] | None:
        """A side's terms and the largest magnitude among them, if none is null or not finite."""
        if self.fast is None:
            return None
        out, most = [], 0.0
        for program in self.programs[at]:
            x, null = program.run(lambda name, _: values[name])
            if null is not None and np.any(null):
                return None
            x = np.ascontiguousarray(np.broadcast_to(x, n))
            size = max(abs(float(x.min())), abs(float(x.max()))) if n else 0.0
            if not np.isfinite(size):
                return None
            out, most = [*out, x], max(most, size)
        return out, most

    def safe(self, most: float) -> bool:
        """Whether sums and products of terms up to this magnitude are finite numbers."""

        def size(e: E) -> float:
            if e.op == "lit":
                return abs(float(e.value))
            if not (columns(e, 0) and columns(e, 1)):
                return most
            a = [size(x) for x in e.args]
            return a[0] * a[1] if e.op == "*" else sum(a)

        return size(self.e) < 1e300


class Rows:
    """A side's columns and the terms that conditions have of them."""

    def __init__(self, terms: list[tuple[list[np.ndarray], float] | None], values: Columns, n: int, of: tuple[Rows, Any] | None = None):
        self.terms, self._values, self.n, self.of = terms, values, n, of

    @property
    def values(self) -> Columns:
        if self.of is not None:
            whole, at = self.of
            self._values, self.of = {c: (x[at], None if null is None else null[at]) for c, (x, null) in whole.values.items()}, None
        return self._values

    def taken(self, at: np.ndarray | slice) -> Rows:
        terms = [None if t is None else ([x[at] for x in t[0]], t[1]) for t in self.terms]
        return Rows(terms, {}, len(range(*at.indices(self.n))) if isinstance(at, slice) else len(at), (self, at))


class Condition:
    """A condition on pairs, as its conjuncts; the one that fewest pairs of a first tile satisfy is asked first."""

    def __init__(self, p: E, counted: bool = False):
        # where all pairs are asked for everything, terms that conjuncts share are made once
        whole = Conjunct(expanded(p))
        self.all = [whole] if counted and whole.fast else [Conjunct(e) for e in conjuncts(expanded(p))]
        self.order: list[int] = []
        self.held: dict[tuple[int, int], np.ndarray] = {}

    def rows(self, at: int, values: Columns, n: int) -> Rows:
        return Rows([c.side(at, values, n) for c in self.all], values, n)

    def _arrays(self, k: int, n: int, w: int) -> list:
        """A conjunct's arrays for n right rows and w left ones, kept from tile to tile."""
        terms = list(self.all[k].lines)
        if n * w > TILE:
            return [None] * len(terms)
        out = []
        for i, term in enumerate(terms):
            if (k, i) not in self.held:
                self.held[k, i] = np.empty(TILE, bool if term.startswith(COMPARED) else float)
            out.append(self.held[k, i][: n * w].reshape(n, w))
        return out

    def _asked(self, left: Rows, right: Rows) -> list[tuple[Callable[[slice], np.ndarray], Callable[[np.ndarray, np.ndarray], np.ndarray]]]:
        """For each conjunct what tests a slice of right rows with all left rows, and what tests single pairs."""
        out = []
        for k, (c, l, r) in enumerate(zip(self.all, left.terms, right.terms, strict=True)):
            if l is not None and r is not None and c.safe(max(l[1], r[1])):
                ls, rs, none = l[0], [x[:, None] for x in r[0]], [None] * len(c.lines)
                one, held = all(x.dtype == np.float64 for x in (*l[0], *r[0])), {}

                def tile(some: slice, k: int = k, c: Conjunct = c, ls: list = ls, rs: list = rs, one: bool = one, held: dict = held) -> np.ndarray:
                    n = some.stop - some.start
                    if n not in held:
                        held.clear()
                        held[n] = self._arrays(k, n, left.n) if one else [None] * len(c.lines)
                    return (c.lean if one else c.fast)(ls, [x[some] for x in rs], held[n])  # type: ignore[misc]

                single = lambda i, j, f=c.fast, ls=ls, rs=r[0], none=none: f([x[i] for x in ls], [x[j] for x in rs], [*none])
            else:

                def tile(some: slice, c: Conjunct = c) -> np.ndarray:  # type: ignore[misc]
                    cut = lambda v, at: tuple(None if z is None else z[at] for z in v)
                    got = c.program.true(lambda n, s: cut(left.values[n], (None, slice(None))) if s == 0 else cut(right.values[n], (some, None)))
                    return np.broadcast_to(got, (some.stop - some.start, left.n))

                def single(i: np.ndarray, j: np.ndarray, c: Conjunct = c) -> np.ndarray:
                    cut = lambda v, at: tuple(None if z is None else z[at] for z in v)
                    return np.broadcast_to(c.program.true(lambda n, s: cut(left.values[n], i) if s == 0 else cut(right.values[n], j)), i.shape)

            out.append((tile, single))
        if not self.order:
            step = slice(0, min(right.n, max(1, TILE // left.n)))
            self.order = sorted(range(len(out)), key=lambda k: np.count_nonzero(out[k][0](step)))
        return [out[k] for k in self.order]

    def count(self, left: Rows, right: Rows) -> int:
        """How many pairs satisfy it."""
        if not left.n or not right.n:
            return 0
        step, asked, total = max(1, TILE // left.n), self._asked(left, right), 0
        for at in range(0, right.n, step):
            mask = None
            for tile, _ in asked:
                got = tile(slice(at, min(at + step, right.n)))
                mask = got if mask is None else np.logical_and(mask, got)
            total += int(np.count_nonzero(mask))
        return total

    def met(self, left: Rows, right: Rows) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """Of right rows from a first one on: how many left rows each meets, and which."""
        if not left.n or not right.n:
            return
        w, step = left.n, max(1, TILE // left.n)
        asked = self._asked(left, right)
        for at in range(0, right.n, step):
            some = slice(at, min(at + step, right.n))
            mask, found = None, None
            for tile, single in asked:
                if found is not None:
                    found = found[single(found % w, at + found // w)]
                else:
                    got = tile(some)
                    mask = got if mask is None else mask & got
                    n = np.count_nonzero(mask)
                    if not n:
                        break
                    if n * 16 < mask.size:
                        found = places(np.ascontiguousarray(mask).reshape(-1))
            else:
                found = places(np.ascontiguousarray(mask).reshape(-1)) if found is None else found
                if len(found):
                    n = some.stop - at
                    counts = np.diff(np.searchsorted(found, np.arange(n + 1) * w)) if n > 1 else np.array([len(found)])
                    yield at, counts, found - np.repeat(np.arange(n) * w, counts) if n > 1 else found


def _packed(table: pa.Table, names: list[str]) -> pa.Array:
    """The columns as one array of values, or of structs."""
    arrays = [table.column(c).combine_chunks() for c in names]
    arrays = [a.chunk(0) if isinstance(a, pa.ChunkedArray) and a.num_chunks == 1 else a for a in arrays]
    return arrays[0] if len(arrays) == 1 else pa.StructArray.from_arrays(arrays, names)


class Sent:
    """Right rows with the left rows that they meet, in batches."""

    def __init__(self, lefts: list[str], rights: list[str]):
        self.lefts, self.rights = lefts, rights
        self.rows: list[np.ndarray] = []
        self.counts: list[np.ndarray] = []
        self.left: list[np.ndarray] = []
        self.n = 0

    def add(self, rows: np.ndarray, counts: np.ndarray, left: np.ndarray) -> bool:
        self.rows.append(rows)
        self.counts.append(counts)
        self.left.append(left)
        self.n += len(left)
        return self.n >= PAIRS_AT_ONCE

    def batch(self, left: pa.Array, right: pa.Table) -> Iterator[pa.RecordBatch]:
        if not self.n:
            return
        rows, counts, which = (np.concatenate(x) for x in (self.rows, self.counts, self.left))
        some = np.flatnonzero(counts)
        offsets = np.concatenate([[0], np.cumsum(counts[some])]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(offsets), left.take(pa.array(which)))
        at = pa.array(rows[some])
        yield pa.RecordBatch.from_arrays([*(right.column(c).take(at).combine_chunks() for c in self.rights), lists], names=[*self.rights, "lefts"])
        self.__init__(self.lefts, self.rights)  # type: ignore[misc]


def _sent_schema(rows: DataFrame, lefts: list[str], rights: list[str]) -> T.StructType:
    kinds = [rows.schema[c].dataType for c in lefts]
    held = kinds[0] if len(lefts) == 1 else T.StructType([T.StructField(c, k) for c, k in zip(lefts, kinds, strict=True)])
    return T.StructType([*(T.StructField(c, rows.schema[c].dataType) for c in rights), T.StructField("lefts", T.ArrayType(held))])


def _exploded(sent: DataFrame, lefts: list[str], rights: list[str]) -> DataFrame:
    if len(lefts) == 1:
        return sent.select(F.explode("lefts").alias(lefts[0]), *rights)
    return sent.select(F.explode("lefts").alias("__l"), *rights).select(*[F.col(f"__l.{c}").alias(c) for c in lefts], *rights)


def _sides(a: DataFrame, b: DataFrame, p: E, out: tuple[list[str], list[str]]) -> tuple[list[str], list[str], list[str], list[str]]:
    """Columns that conditions use, with those that are asked for: of the left side and of the right."""
    used = [sorted(columns(p, s)) for s in (0, 1)]
    return used[0], used[1], [c for c in a.columns if c in {*used[0], *out[0]}], [c for c in b.columns if c in {*used[1], *out[1]}]


def parts(n: int, m: int, cores: int) -> tuple[int, int]:
    """How many parts each side is dealt to: enough tasks for all cores to end at about the same time, none beyond what a task holds, and
    none that is over before it is worth a task."""
    tasks = max(1, min(32 * cores, n * m // WORK))
    i = max(1, -(-n // blocks.BLOCK), min(4 * cores, tasks))
    return i, max(1, -(-m // PART), min(8, tasks // i))


def moved(n: int, m: int, cores: int) -> int:
    """Rows that meet, each once for every part of the other side."""
    i, j = parts(n, m, cores)
    return n * j + m * i


def dealt_to(keys: int) -> int:
    """Partitions for so many keys of work: their number is kept, as tasks are long for what they read."""
    return min(1000, 2 * keys)


def all_pairs(a: DataFrame, b: DataFrame, p: E, out: tuple[list[str], list[str]], n: int, m: int) -> DataFrame:
    """The pairs of n left and m right rows that satisfy p, as (l_ columns, r_ columns) that are asked for. All pairs are tested."""
    use_l, use_r, of_l, of_r = _sides(a, b, p, out)
    i, j = parts(n, m, a.sparkSession.sparkContext.defaultParallelism)
    mine = (F.monotonically_increasing_id() % F.lit(i)).cast("int")
    theirs = (F.monotonically_increasing_id() % F.lit(j)).cast("int")
    left = a.select(*[F.col(c).alias(f"l_{c}") for c in of_l], mine.alias("__p")).withColumn("q", F.explode(F.sequence(F.col("__p") * j, F.col("__p") * j + (j - 1)))).drop("__p")
    right = b.select(*[F.col(c).alias(f"r_{c}") for c in of_r], theirs.alias("__p")).withColumn("q", F.explode(F.sequence(F.col("__p"), F.col("__p") + F.lit((i - 1) * j), F.lit(j)))).drop("__p")
    rows = left.withColumn("side", F.lit(0)).unionByName(right.withColumn("side", F.lit(1)), allowMissingColumns=True)
    lefts, rights = [f"l_{c}" for c in out[0]], [f"r_{c}" for c in out[1]]
    condition = Condition(p)

    def met(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every = pa.Table.from_batches(held).combine_chunks()
        side = every.column("side").to_numpy()
        l, r = (every.filter(pa.array(side == s)).combine_chunks() for s in (0, 1))
        inner = condition.rows(1, {c: numbers(r.column(f"r_{c}")) for c in use_r}, r.num_rows)
        mine, sent = _packed(l, lefts), Sent(lefts, rights)
        whole = condition.rows(0, {c: numbers(l.column(f"l_{c}")) for c in use_l}, l.num_rows)
        for at in range(0, l.num_rows, WIDTH):
            for first, counts, which in condition.met(whole.taken(slice(at, at + WIDTH)), inner):
                if sent.add(np.arange(first, first + len(counts)), counts, which + at):
                    yield from sent.batch(mine, r)
        yield from sent.batch(mine, r)

    found = rows.repartition(dealt_to(i * j), "q").sortWithinPartitions("q").mapInArrow(lambda batches: by_key(batches, "q", met), _sent_schema(rows, lefts, rights))
    return _exploded(found, lefts, rights)


def of_leaves(a: Tree, b: Tree, at: DataFrame, p: E, out: tuple[list[str], list[str]] | None) -> DataFrame:
    """``at`` has pairs of leaves (_a, _b) and whether they are taken whole (_whole). Their pairs of rows that satisfy p, as (l_
    columns, r_ columns) that are asked for, or without such: how many there are, as rows of n."""
    use_l, use_r, of_l, of_r = _sides(a.scan(), b.scan(), p, out or ([], []))
    # the right rows of a leaf come as one row, once for each run of left leaves that the leaf is paired with
    run = max(1, LEAST // a.spec.leaf_rows, min(RUN // a.spec.leaf_rows, a.n_leaves // (8 * a.rows.sparkSession.sparkContext.defaultParallelism)))
    met_by = at.groupBy(F.floor(F.col("_a") / run).cast("long").alias("q"), "_b").agg(F.collect_list(F.struct("_a", "_whole")).alias("with"))
    leaf = b.rows.groupBy(F.col("leaf_id").alias("_b")).agg(F.collect_list(F.struct(*[F.col(c).alias(f"r_{c}") for c in of_r], F.lit(0).cast("byte").alias("__"))).alias("members"))
    right = met_by.join(leaf, "_b").select("q", F.lit(1).alias("side"), F.col("_b").alias("leaf"), "with", "members")
    left = a.rows.select(F.floor(F.col("leaf_id") / run).cast("long").alias("q"), F.lit(0).alias("side"), F.col("leaf_id").alias("leaf"), *[F.col(c).alias(f"l_{c}") for c in of_l])
    rows = left.unionByName(right, allowMissingColumns=True).repartition(dealt_to(-(-a.n_leaves // run)), "q").sortWithinPartitions("q", "side", "leaf")
    lefts, rights = ([f"{s}_{c}" for c in cs] for s, cs in zip("lr", out or ([], []), strict=True))
    condition = Condition(p, out is None)

    def of_run(held: list[pa.RecordBatch], mine: list[Any]) -> Iterator[pa.RecordBatch]:
        """Right leaves of a run, a batch at a time, meet its left rows."""
        test, (l, own, starts, sizes, first) = condition, mine
        packed, total = (_packed(l, lefts) if out else None), 0
        for batch in held:
            with_, members = batch.column("with"), batch.column("members")
            pairs, inner = with_.flatten(), members.flatten()
            r = pa.table({f"r_{c}": inner.field(f"r_{c}") for c in of_r} | {"__": inner.field("__")})
            theirs = test.rows(1, {c: numbers(r.column(f"r_{c}")) for c in use_r}, r.num_rows)
            ends, r_ends = (np.concatenate([[0], np.cumsum(x.value_lengths().to_numpy())]) for x in (with_, members))
            leaves, whole, sent = pairs.field("_a").to_numpy() - first, pairs.field("_whole").to_numpy(zero_copy_only=False), Sent(lefts, rights)
            for k in range(batch.num_rows):
                some, taken = leaves[ends[k]:ends[k + 1]], whole[ends[k]:ends[k + 1]]
                j0, j1 = r_ends[k], r_ends[k + 1]
                if taken.any():
                    i = ragged(starts[some[taken]], sizes[some[taken]])
                    if out is None:
                        total += len(i) * int(j1 - j0)
                    else:
                        for j in range(j0, j1):
                            if sent.add(np.array([j]), np.array([len(i)]), i):
                                yield from sent.batch(packed, r)
                    some = some[~taken]
                if len(some):
                    i = ragged(starts[some], sizes[some])
                    right_rows = theirs.taken(slice(j0, j1))
                    for x in range(0, len(i), WIDTH):
                        mine_ = i[x:x + WIDTH]
                        if out is None:
                            total += test.count(own.taken(mine_), right_rows)
                            continue
                        for at_, counts, which in test.met(own.taken(mine_), right_rows):
                            if sent.add(np.arange(j0 + at_, j0 + at_ + len(counts)), counts, mine_[which]):
                                yield from sent.batch(packed, r)
            if out is not None:
                yield from sent.batch(packed, r)
        if out is None:
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, left_rows, mine = None, [], None
        for batch in batches:
            key = batch.column("q").to_numpy() * 2 + batch.column("side").to_numpy()
            cuts = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)] if len(key) else [0]
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                q, side, part = int(key[i]) // 2, int(key[i]) % 2, batch.slice(i, j - i)
                if q != now:
                    now, left_rows, mine = q, [], None
                if side == 0:
                    left_rows.append(part.select(["leaf", *[f"l_{c}" for c in of_l]]))
                    continue
                if mine is None:
                    l = pa.Table.from_batches(left_rows).combine_chunks()
                    leaf_of = l.column("leaf").to_numpy()
                    first = int(leaf_of[0])
                    sizes = np.bincount(leaf_of - first)
                    own = condition.rows(0, {c: numbers(l.column(f"l_{c}")) for c in use_l}, l.num_rows)
                    mine, left_rows = [l, own, np.cumsum(sizes) - sizes, sizes, first], []
                yield from of_run([part], mine)

    if out is None:
        return rows.mapInArrow(task, "n long")
    schema = a.rows.select(*[F.col(c).alias(f"l_{c}") for c in out[0]]), b.rows.select(*[F.col(c).alias(f"r_{c}") for c in out[1]])
    fields = T.StructType([*schema[0].schema.fields, *schema[1].schema.fields])
    kinds = [f.dataType for f in schema[0].schema.fields]
    held = kinds[0] if len(kinds) == 1 else T.StructType([T.StructField(c, k) for c, k in zip(lefts, kinds, strict=True)])
    sent_schema = T.StructType([*(fields[c] for c in rights), T.StructField("lefts", T.ArrayType(held))])
    return _exploded(rows.mapInArrow(task, sent_schema), lefts, rights)



class Least:
    """The rows of a block, and for each the least value of a metric and the smallest id that has it. NaN is above all numbers."""

    def __init__(self, outer: pa.Table, names: list[str]):
        self.outer, self.columns = outer, {n: numbers(outer.column(f"l_{n}")) for n in names}
        n = outer.num_rows
        self.some, self.m, self.id = np.zeros(n, bool), np.full(n, np.nan), np.zeros(n, np.int64)

    def meet(self, inner: pa.Table, names: list[str], metric: Program) -> None:
        columns_, ids = {n: numbers(inner.column(f"r_{n}")) for n in names}, inner.column("r_id").to_numpy()
        width, step = min(MADE, len(ids)), max(1, MADE // len(ids))
        for at in range(0, self.outer.num_rows, step):
            rows = slice(at, min(at + step, self.outer.num_rows))
            for j in range(0, len(ids), width):
                self._tile(rows, slice(j, j + width), columns_, ids[j:j + width], metric)

    def _tile(self, rows: slice, members: slice, inner: Columns, ids: np.ndarray, metric: Program) -> None:
        cut = lambda v, at: tuple(None if z is None else z[at] for z in v)
        m, null = metric.run(lambda n, s: cut(self.columns[n], (rows, None)) if s == 0 else cut(inner[n], (None, members)))
        m = np.broadcast_to(np.asarray(m, float), (rows.stop - rows.start, len(ids)))
        if null is not None:
            null = np.broadcast_to(null, m.shape)
            m = np.where(null, np.nan, m)
        least = np.fmin.reduce(m, axis=1)
        # of NaN, a row has none but where all else is null
        none = np.isnan(least)
        there = ~none if null is None else ~null.all(axis=1)
        there = there | none if null is None else there
        now, known = self.m[rows], self.some[rows]
        for k in np.flatnonzero(there & (~known | (least <= now) | (np.isnan(now) & known))):
            same = (np.isnan(m[k]) if none[k] else m[k] == least[k])
            if none[k] and null is not None:
                same = same & ~null[k]
            best, i = int(ids[same].min()), rows.start + k
            less = not self.some[i] or least[k] < self.m[i] or (np.isnan(self.m[i]) and not none[k])
            if less or ((least[k] == self.m[i] or (none[k] and np.isnan(self.m[i]))) and best < self.id[i]):
                self.some[i], self.m[i], self.id[i] = True, least[k], best

    def ended(self) -> Iterator[pa.RecordBatch]:
        """One row for each id: rows that share one are in one block."""
        at = np.flatnonzero(self.some)
        found = pa.table([self.outer.column("l_id").take(pa.array(at)), pa.array(self.id[at]), pa.array(self.m[at])], names=["id", "r_id", "m"])
        found = found.sort_by([(c, "ascending") for c in ("id", "m", "r_id")])
        ids = found.column("id").to_numpy()
        first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]])) if len(ids) else np.empty(0, np.int64)
        yield from found.take(pa.array(first)).combine_chunks().to_batches()


def least_in_tasks(outer: DataFrame, inner: DataFrame, metric: E) -> bool:
    """Whether tasks can compute the metric, and its ids are numbers."""
    return Program(metric).known() and numeric(outer.schema, columns(metric, 0)) and numeric(inner.schema, columns(metric, 1)) and all(isinstance(df.schema["id"].dataType, T.LongType) for df in (outer, inner))


def least_parts(n: int, cores: int) -> int:
    return max(1, -(-n // blocks.BLOCK), min(16 * cores, -(-n // 64)))


def least(outer: DataFrame, inner: DataFrame, metric: E, n: int) -> DataFrame:
    """(id, r_id, m): for each of the n outer rows the least metric of all pairs, and the smallest id of the inner rows that have it."""
    use_l, use_r = (sorted(columns(metric, s)) for s in (0, 1))
    count = least_parts(n, outer.sparkSession.sparkContext.defaultParallelism)
    left = outer.where("id IS NOT NULL").select(F.col("id").alias("l_id"), *[F.col(c).alias(f"l_{c}") for c in use_l if c != "id"], F.pmod(F.hash("id"), F.lit(count)).alias("q"), F.lit(0).alias("side"))
    right = inner.where("id IS NOT NULL").select(F.col("id").alias("r_id"), *[F.col(c).alias(f"r_{c}") for c in use_r if c != "id"], F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("q"), F.lit(1).alias("side"), F.lit(0).alias("leaf_id"))
    rows = left.unionByName(right, allowMissingColumns=True)
    lefts, rights, program = [c for c in rows.columns if c.startswith("l_")], [c for c in rows.columns if c.startswith("r_")], Program(metric)
    schema = T.StructType([T.StructField("id", rows.schema["l_id"].dataType), T.StructField("r_id", T.LongType()), T.StructField("m", T.DoubleType())])
    dealt = rows.repartition(dealt_to(count), "q").sortWithinPartitions("q", "side")
    return dealt.mapInArrow(lambda batches: blocks.by_block(batches, lefts, rights, lambda mine: Least(mine, use_l), lambda best, r: best.meet(r, use_r, program), Least.ended), schema)
