"""What tree plans are held against: scans, nested loops, index probes, the sort-based inequality join, grids."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.expr import E, bind, to_column
from . import blocks, pairs
from .blocks import by_key, ragged
from .tree import Tree

ROW = lambda name, side: F.col(name)


def scan(df: DataFrame, p: E) -> DataFrame:
    return df.where(to_column(p, ROW))


def grid_join(a: DataFrame, b: DataFrame, x: str, y: str, dx: float, dy: float, ids: tuple[str, str]) -> DataFrame:
    """Pairs within dx and dy: rows are dealt to cells of that size, the left side to its cell and the right one
    to the nine around; equal cells meet. A pair meets once, as the left row has one cell."""
    cell = lambda c, w: F.floor(F.col(c) / w).cast("long")
    left = a.select(*[F.col(c).alias(f"a_{c}") for c in (ids[0], x, y)], cell(x, dx).alias("i"), cell(y, dy).alias("j"))
    around = lambda c, w: F.explode(F.sequence(cell(c, w) - 1, cell(c, w) + 1))
    right = b.select(*[F.col(c).alias(f"b_{c}") for c in (ids[1], x, y)], around(x, dx).alias("i")).select("*", F.explode(F.sequence(F.floor(F.col(f"b_{y}") / dy).cast("long") - 1, F.floor(F.col(f"b_{y}") / dy).cast("long") + 1)).alias("j"))
    return left.join(right, ["i", "j"]).where((F.abs(F.col(f"a_{x}") - F.col(f"b_{x}")) <= dx) & (F.abs(F.col(f"a_{y}") - F.col(f"b_{y}")) <= dy)).drop("i", "j")


def index_probe_join(a: DataFrame, b: DataFrame, x: str, y: str, dx: float, dy: float, ids: tuple[str, str]) -> DataFrame:
    """The index-nested-loop of a row store with an ordered index on (bucket of x, y): equal buckets of x meet, a row's run of near
    y is found by binary search, and what it holds is tested. A task holds the rows of one bucket."""
    bucket = F.floor(F.col(x) / dx).cast("long")
    some = F.col(x).isNotNull() & F.col(y).isNotNull()
    row = lambda ident: [F.col(ident).alias("id"), F.col(x).alias("x"), F.col(y).alias("y")]
    left = a.where(some).select(bucket.alias("q"), F.lit(1).alias("side"), *row(ids[0]))
    right = b.where(some).select(F.explode(F.sequence(bucket - 1, bucket + 1)).alias("q"), F.lit(0).alias("side"), *row(ids[1]))
    rows = left.union(right)

    def met(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every = pa.Table.from_batches(held).combine_chunks()
        side = every.column("side").to_numpy()
        u, v = (every.column(c).cast(pa.float64(), safe=False).to_numpy() for c in ("x", "y"))
        own, outer = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        own = own[np.argsort(v[own], kind="stable")]
        # a little wider than asked; the condition itself is tested on the columns as they are
        wide = lambda w, at: w + 1e-9 * (abs(w) + np.abs(at))
        starts = np.searchsorted(v[own], v[outer] - wide(dy, v[outer]), side="left")
        runs = np.searchsorted(v[own], v[outer] + wide(dy, v[outer]), side="right") - starts
        ends = np.cumsum(runs)
        at = 0
        while at < len(outer):
            before = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, before + PAIRS_AT_ONCE, side="right")))
            i, j = np.repeat(outer[at:to], runs[at:to]), own[ragged(starts[at:to], runs[at:to])]
            ok = np.abs(u[i] - u[j]) <= wide(dx, u[i])
            pair = [every.column(c).take(pa.array(k[ok])).combine_chunks() for k in (i, j) for c in ("id", "x", "y")]
            yield pa.RecordBatch.from_arrays(pair, names=names)
            at = to

    names = [f"{s}_{c}" for s, ident in zip("ab", ids, strict=True) for c in (ident, x, y)]
    kinds = {"id": rows.schema["id"].dataType, "x": rows.schema["x"].dataType, "y": rows.schema["y"].dataType}
    schema = T.StructType([T.StructField(n, k) for n, k in zip(names, [*kinds.values()] * 2, strict=True)])
    near = rows.repartition("q").sortWithinPartitions("q").mapInArrow(lambda batches: by_key(batches, "q", met), schema)
    return near.where((F.abs(F.col(f"a_{x}") - F.col(f"b_{x}")) <= dx) & (F.abs(F.col(f"a_{y}") - F.col(f"b_{y}")) <= dy))


#: Rows of a range bucket of the sort-based join, and pairs that leave a task at once.
BUCKET_ROWS, PAIRS_AT_ONCE = 16_384, 1 << 18


def inequality_join(a: DataFrame, b: DataFrame, first: str, second: str, ident: str, buckets: int = 16) -> DataFrame:
    """Pairs with a.first < b.first and a.second > b.second, sort-based: rows are dealt to range buckets of ``first``;
    of two buckets in order, whole pairs satisfy the first condition, and a sort by ``second`` gives each row
    its partners as a run. A row meets only buckets that have a smaller ``second``. A task holds the rows of one bucket, and
    their pairs leave it in batches. ``buckets`` is the least number of them. Returns (a_id, b_id)."""
    buckets = max(buckets, b.count() // BUCKET_ROWS)
    cuts = b.select(F.percentile_approx(F.col(first).cast("double"), [i / buckets for i in range(1, buckets)], 10_000)).first()[0] or []
    place = F.aggregate(F.lit(sorted(set(cuts))).cast("array<double>"), F.lit(0), lambda n, c: n + (F.col(first).cast("double") > c).cast("int"))
    columns = [F.col(ident).cast("long").alias("id"), F.col(first).cast("double").alias("u"), F.col(second).cast("double").alias("v"), place.alias("p")]
    some = F.col("u").isNotNull() & F.col("v").isNotNull()
    left, right = a.select(*columns).where(some), b.select(*columns).where(some).withColumn("q", F.col("p"))
    reach = right.groupBy("q").agg(F.min("v").alias("low"))
    left = left.withColumn("q", F.explode(F.sequence(F.col("p"), F.lit(buckets)))).join(reach, "q").where("v > low")
    rows = left.select("q", F.lit(1).alias("side"), "id", "u", "v", "p").union(right.select("q", F.lit(0), "id", "u", "v", "p"))

    def met(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        side, ids, u, v, p, q = (np.concatenate([x.column(c).to_numpy(zero_copy_only=False) for x in held]) for c in ("side", "id", "u", "v", "p", "q"))
        own = np.flatnonzero(side == 0)
        own = own[np.argsort(v[own], kind="stable")]
        outer = np.flatnonzero(side == 1)
        runs = np.searchsorted(v[own], v[outer], side="left")
        ends = np.cumsum(runs)
        at = 0
        while at < len(outer):
            before = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, before + PAIRS_AT_ONCE, side="right")))
            x = np.repeat(outer[at:to], runs[at:to])
            y = own[ragged(np.zeros(to - at, np.int64), runs[at:to])]
            ok = (p[x] < q[x]) | (u[y] > u[x]) | (np.isnan(u[y]) & ~np.isnan(u[x]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[x[ok]]), pa.array(ids[y[ok]])], names=["a_id", "b_id"])
            at = to

    return rows.repartition("q").sortWithinPartitions("q").mapInArrow(lambda batches: by_key(batches, "q", met), "a_id long, b_id long")


def pushdown(df: DataFrame, p: E) -> str:
    """The comparisons of a condition that the Parquet scan gets, as the plan prints them."""
    plan = df.where(to_column(p, ROW))._jdf.queryExecution().executedPlan().toString()
    found = re.search(r"PushedFilters: \[([^\]]*)\]", plan)
    return ", ".join(sorted(x for x in re.split(r",\s*(?=[A-Z])", found[1] if found else "") if x and not x.startswith("IsNotNull")))


def box_overlaps(a: DataFrame, b: DataFrame, cell: float) -> DataFrame:
    """Collisions by hand: boxes (id, lx, ly, lz, hx, hy, hz) are dealt to the cells of the x axis that they span; a
    pair counts in the cell where its overlap begins."""
    spans = lambda df, s: df.select(*[F.col(c).alias(f"{s}_{c}") for c in ("id", "lx", "ly", "lz", "hx", "hy", "hz")]).withColumn("c", F.explode(F.sequence(F.floor(F.col(f"{s}_lx") / cell), F.floor(F.col(f"{s}_hx") / cell))))
    met = spans(a, "a").join(spans(b, "b"), "c")
    for d in "xyz":
        met = met.where((F.col(f"a_l{d}") <= F.col(f"b_h{d}")) & (F.col(f"b_l{d}") <= F.col(f"a_h{d}")))
    return met.where(F.col("c") == F.floor(F.greatest("a_lx", "b_lx") / cell)).select("a_id", "b_id")


BOUND = "_r_"


def _least(met: DataFrame) -> DataFrame:
    """The best member of each outer row, the smallest id among equals. An aggregate of numbers is hashed, one of structs would sort all
    pairs; so the least value comes first, and ids of the pairs that have it in a second pass over the pairs."""
    best = met.groupBy(F.col("_l_id").alias("id")).agg(F.min("m").alias("m")).where("m is not null")
    again = met.join(best.select(F.col("id").alias("_l_id"), F.col("m").alias("_least")), "_l_id")
    ids = again.groupBy(F.col("_l_id").alias("id")).agg(F.min(F.when(F.col("m") == F.col("_least"), F.col(f"{BOUND}id"))).alias("r_id"))
    return ids.join(best, "id").select("id", "r_id", "m")


def _by_hand(outer: DataFrame, tree: Tree, guard: blocks.Guard, metric: E) -> DataFrame:
    """The traversal that a hand-written program makes, in tasks: leaves that the guard doesn't keep, or that begin beyond what
    another leaf of the row proves, are left."""
    found = blocks.best_members(outer, tree, metric, ("id",), guard, None, 1, outer.count())
    return found.select(F.col("l_id").alias("id"), F.col("r_id"), "m")


def _corners(nodes: blocks.Columns, axis: str) -> tuple[np.ndarray, np.ndarray]:
    at = [f"{v}{axis}" for v in "abc"]
    return np.minimum.reduce([nodes[f"{c}_lo"][0] for c in at]), np.maximum.reduce([nodes[f"{c}_hi"][0] for c in at])


def closest_point(points: DataFrame, tree: Tree, metric: E) -> DataFrame:
    """For each point (id, px, py, pz) the closest triangle of a tree over corners (ax .. cz): distances to a
    leaf's box, written out. Returns (id, r_id, m)."""

    def guard(outer: blocks.Columns, nodes: blocks.Columns) -> tuple[bool, np.ndarray]:
        near = 0.0
        for d in "xyz":
            lo, hi = _corners(nodes, d)
            p = outer[f"p{d}"][0]
            gap = np.maximum(np.maximum(lo - p, p - hi), 0.0)
            near = near + gap * gap
        return True, np.sqrt(near) * (1 - 1e-12)

    return _by_hand(points, tree, guard, metric)


def closest_hit(rays: DataFrame, tree: Tree, metric: E) -> DataFrame:
    """For each ray (id, ox .. dz) the triangle that it hits first: leaves whose box the ray meets, by slabs written out."""

    def guard(outer: blocks.Columns, nodes: blocks.Columns) -> tuple[np.ndarray, np.ndarray]:
        into, out, speed = 0.0, np.inf, 0.0
        with np.errstate(all="ignore"):
            for d in "xyz":
                lo, hi = _corners(nodes, d)
                o, v = outer[f"o{d}"][0], outer[f"d{d}"][0]
                a, b, still = (lo - o) / v, (hi - o) / v, v == 0
                first, last = np.minimum(a, b), np.maximum(a, b)
                if still.any():
                    first, last = np.where(still, np.where((lo <= o) & (o <= hi), 0.0, np.inf), first), np.where(still, np.inf, last)
                into, out, speed = np.maximum(into, first), np.minimum(out, last), speed + v * v
            return ~(into * (1 - 1e-12) > out * (1 + 1e-12)), into * np.sqrt(speed) * (1 - 1e-9)

    return _by_hand(rays, tree, guard, metric)


def brute_nearest(outer: DataFrame, inner: DataFrame, metric: E) -> DataFrame:
    """All pairs, the best of each outer row: what the traversals are to beat. Pairs are made in tasks, by ``pairs``, where these can compute the
    metric; otherwise as rows. Returns (id, r_id, m)."""
    if pairs.least_in_tasks(outer, inner, metric):
        n = outer.count()
        if pairs.least_parts(n, outer.sparkSession.sparkContext.defaultParallelism) * inner.count() <= blocks.MOVED:
            return pairs.least(outer, inner, metric, n)
    left, right = (df.select(*[F.col(c).alias(f"{p}{c}") for c in df.columns]) for df, p in ((outer, "_l_"), (inner, BOUND)))
    return _least(bind(left.crossJoin(right), metric, lambda name, s: F.col(f"{'_l_' if s == 0 else BOUND}{name}"), "m"))
