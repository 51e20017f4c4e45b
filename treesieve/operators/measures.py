"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.expr import to_column
from ..plans.query import ROW, Q, descend, node_guards
from .tree import Tree


@dataclass
class Measured:
    seconds: float
    runs: list[float]
    build_s: float = 0.0
    timed_out: bool = False


def measure(make: Callable[[], DataFrame], runs: int = 7, limit_s: float = 30.0, build_s: float = 0.0) -> Measured:
    """Mean of the runs without the fastest and the slowest; a run beyond the limit ends the series."""
    took: list[float] = []
    for _ in range(runs):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
        if took[-1] > limit_s:
            return Measured(took[-1], took, build_s, True)
    inner = sorted(took)[1:-1] if len(took) > 2 else took
    return Measured(sum(inner) / len(inner), took, build_s)


def speedup(a: Measured, b: Measured) -> float:
    """How many times faster b is than a."""
    return a.seconds / b.seconds


def mean_ratio(pairs: list[tuple[Measured, Measured]]) -> float:
    return sum(speedup(a, b) for a, b in pairs) / len(pairs)


def slope(points: list[tuple[float, float]]) -> float:
    """Power with which the second value grows with the first, by least squares of logarithms."""
    xs, ys = [math.log(x) for x, _ in points], [math.log(max(y, 1e-9)) for _, y in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)


def lowering_ms(q: Q) -> float:
    """Time to derive the guards of a query."""
    began = time.perf_counter()
    node_guards(q.tree, q._guide())
    return 1000 * (time.perf_counter() - began)


def tightness(q: Q) -> DataFrame:
    """One row: how many leaves were descended into, in how many of these a row matches (their share is the precision of
    ``maybe``), rows of leaves all of whose rows match, and how many of them were taken whole (the recall of ``always``)."""
    front = descend(q.tree, q._guide())
    leaves = front.leaves()
    truth = q.tree.rows.groupBy("leaf_id").agg(F.sum(F.coalesce(to_column(q.pred, ROW).cast("int"), F.lit(0))).alias("k"), F.count("*").alias("n"))
    j = truth.join(leaves, "leaf_id", "left")
    return j.agg(
        F.sum((~F.col("whole")).cast("long")).alias("descended"), F.sum((~F.col("whole") & (F.col("k") > 0)).cast("long")).alias("productive"),
        F.sum(F.when(F.col("k") == F.col("n"), F.col("n")).otherwise(0)).alias("all_true_rows"), F.sum(F.when(F.col("whole"), F.col("n")).otherwise(0)).alias("taken_rows"),
        F.sum(F.when(F.col("whole").isNull(), F.col("k")).otherwise(0)).alias("missed_rows"), F.sum(F.when(F.col("whole"), F.col("n") - F.col("k")).otherwise(0)).alias("wrong_rows"),
    )


def selectivity(q: Q) -> DataFrame:
    return q.count("k").select("k", F.lit(q.tree.n).alias("n"), (F.col("k") / F.lit(max(1, q.tree.n))).alias("share"))


def index_bytes(tree: Tree) -> tuple[int, int]:
    """Bytes of node metadata and of rows."""
    jvm, conf = tree.rows.sparkSession._jvm, tree.rows.sparkSession._jsc.hadoopConfiguration()
    size = lambda at: (p := jvm.org.apache.hadoop.fs.Path(at)).getFileSystem(conf).getContentSummary(p).getLength()
    return sum(size(f"{tree.path}/level-{i}") for i in range(len(tree.levels))), size(f"{tree.path}/rows")
