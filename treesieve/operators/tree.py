"""Trees over DataFrames: what they store, how they are built, and the handle that queries use.

A tree is its rows in clustered Parquet, each with the dense number of its leaf, and one small table
of node metadata for each level. Node n of level l holds leaves n*F^l .. (n+1)*F^l - 1, so a subtree
is a range of leaf numbers and a parent is a division. Building costs one range shuffle and, level
by level, an aggregation of the level below.
"""

from __future__ import annotations

import json
import math
import tempfile
import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.expr import AnalysisError, E, col, columns, to_column

#: Rows that the recursive median builder takes at most: it sorts once for each level of a binary split.
MEDIAN_ROWS = 2_000_000


@dataclass(frozen=True)
class Agg:
    """A stored partial aggregate: count, sum, min or max of a column."""

    kind: str
    of: str = ""

    @property
    def name(self) -> str:
        return f"agg__{self.kind}__{self.of}"


@dataclass(frozen=True)
class TreeSpec:
    """bounds: columns with an interval in every node. order: columns that cluster the rows (default: bounds).
    method: sort, tile, zorder, hilbert (two columns) or median."""

    bounds: tuple[str, ...]
    aggs: tuple[Agg, ...] = ()
    order: tuple[str, ...] = ()
    method: str = "sort"
    leaf_rows: int = 1024
    fanout: int = 16
    tight: bool = True
    layout: str = "own"  # or "packed": a node's row also has its children's metadata

    @staticmethod
    def interval(name: str, *aggs: Agg, **kw) -> TreeSpec:
        return TreeSpec((name,), aggs, **kw)

    @staticmethod
    def boxes(bounds: tuple[str, ...], *aggs: Agg, **kw) -> TreeSpec:
        return TreeSpec(bounds, aggs, **({"method": "zorder"} | kw))


def base_dir(spark: SparkSession) -> str:
    """Where trees are kept unless a path is given: the folder that the cluster shares; a temporary one only
    where the session names none."""
    at = spark.conf.get("spark.checkpoint.dir", None) or getattr(base_dir, "own", None)
    if not at:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the cluster shares, or give paths")
        at = base_dir.own = tempfile.mkdtemp(prefix="trees-")  # type: ignore[attr-defined]
    return at


def _ranks(df: DataFrame, names: tuple[str, ...], bits: int) -> list[Column]:
    """Each column scaled to 0 .. 2^bits-1 over its range."""
    got = df.agg(*[f(F.col(n).cast("double")).alias(f"{k}{i}") for i, n in enumerate(names) for k, f in (("a", F.min), ("b", F.max))]).first()
    out = []
    for i, n in enumerate(names):
        lo, hi = got[f"a{i}"] or 0.0, got[f"b{i}"] or 0.0
        width = (hi - lo) or 1.0
        out.append(F.coalesce(F.least(F.lit((1 << bits) - 1), F.floor((F.col(n).cast("double") - lo) / width * (1 << bits)).cast("int")), F.lit(0)))
    return out


def _zorder(ranks: list[Column], bits: int) -> Column:
    out = F.lit(0).cast("long")
    for b in range(bits):
        for i, r in enumerate(ranks):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(r, b).bitwiseAND(1).cast("long"), b * len(ranks) + i))
    return out


def _hilbert(x: Column, y: Column, bits: int) -> Column:
    """Places on the curve, a batch of rows at a time; a fold over the bits in Spark is interpreted row by row."""

    @F.pandas_udf("long", F.PandasUDFType.SCALAR)
    def place(x, y):
        x, y = (c.to_numpy("int64") for c in (x, y))
        d = x * 0
        for b in range(bits - 1, -1, -1):
            side = 1 << b
            rx, ry = (x & side > 0).astype("int64"), (y & side > 0).astype("int64")
            d = d + side * side * ((3 - ry) * rx + ry * (1 - rx))
            x, y = x & (side - 1), y & (side - 1)
            flip = (ry == 0) & (rx == 1)
            x, y = x + flip * (side - 1 - 2 * x), y + flip * (side - 1 - 2 * y)
            turned = ry == 0
            x, y = x + turned * (y - x), y + turned * (x - y)
        import pandas as pd

        return pd.Series(d)

    return place(x.cast("long"), y.cast("long"))


def _clustered(df: DataFrame, spec: TreeSpec) -> list[Column]:
    """Sort key of the rows."""
    names = spec.order or spec.bounds
    if spec.method == "sort":
        return [F.col(n) for n in names]
    if spec.method == "zorder":
        bits = min(10, 62 // len(names))
        return [_zorder(_ranks(df, names, bits), bits)]
    if spec.method == "hilbert":
        return [_hilbert(*_ranks(df, names[:2], 10), 10)]
    if spec.method == "tile":
        slabs = max(1, math.isqrt(max(1, df.count() // spec.leaf_rows)))
        cuts = df.select(F.percentile_approx(F.col(names[0]).cast("double"), [i / slabs for i in range(1, slabs)] or [0.5], 10_000)).first()[0] or []
        slab = sum(((F.col(names[0]).cast("double") > c).cast("int") for c in cuts), F.lit(0))
        return [slab, *(F.col(n) for n in names[1:])]
    raise AnalysisError(f"no builder {spec.method}")


def _median(df: DataFrame, spec: TreeSpec, n: int) -> DataFrame:
    """Halves every group at the median of its widest dimension until groups fit a leaf."""
    if n > MEDIAN_ROWS:
        raise AnalysisError(f"the median builder takes at most {MEDIAN_ROWS} rows; use sort, tile or zorder")
    names = spec.order or spec.bounds
    out = df.withColumn("__g", F.lit(0).cast("long"))
    for _ in range(max(0, math.ceil(math.log2(max(1, n / spec.leaf_rows))))):
        group = Window.partitionBy("__g")
        spread = [F.coalesce(F.max(F.col(x).cast("double")).over(group) - F.min(F.col(x).cast("double")).over(group), F.lit(0.0)) for x in names]
        widest = F.greatest(*spread) if len(spread) > 1 else spread[0]
        key = F.coalesce(*[F.when(s == widest, F.col(x).cast("double")) for s, x in zip(spread, names, strict=True)])
        out = out.withColumn("__k", key).withColumn("__h", F.ntile(2).over(group.orderBy("__k"))).withColumn("__g", F.col("__g") * 2 + F.col("__h") - 1).drop("__k", "__h")
    return out


@dataclass
class Tree:
    """Handle of a built tree."""

    spec: TreeSpec
    rows: DataFrame  # with leaf_id
    levels: list[DataFrame]  # leaf level first; the last has one node
    n: int
    n_leaves: int
    path: str
    build_s: float = 0.0
    schema: T.StructType = field(default_factory=T.StructType)

    @property
    def height(self) -> int:
        return len(self.levels) - 1

    def scan(self) -> DataFrame:
        return self.rows.drop("leaf_id")

    def under(self, level: int) -> int:
        """Leaves below a node of a level."""
        return self.spec.fanout**level

    def has(self, kind: str, of: str = "") -> bool:
        return Agg(kind, of) in self.spec.aggs or kind == "count" and Agg("count") in self.spec.aggs

    def check(self, e: E, side: int = 0) -> None:
        absent = columns(e, side) - set(self.schema.names)
        if absent:
            raise AnalysisError(f"no such column: {', '.join(sorted(absent))}")


def _floating(kind: T.DataType) -> bool:
    return isinstance(kind, T.DoubleType | T.FloatType)


def _leaf_stats(spec: TreeSpec, schema: T.StructType) -> list[Column]:
    out = [F.count("*").alias("__rows")]
    for n in spec.bounds:
        c = F.col(n)
        if _floating(schema[n].dataType):
            nan = F.isnan(c)
            real = F.when(~nan, c)
            out += [F.min(real).alias(f"{n}_lo"), F.max(real).alias(f"{n}_hi"), F.sum((c.isNull() | nan).cast("long")).alias(f"{n}__nulls"), F.sum(nan.cast("long")).alias(f"{n}__nan")]
        else:
            out += [F.min(c).alias(f"{n}_lo"), F.max(c).alias(f"{n}_hi"), F.sum(c.isNull().cast("long")).alias(f"{n}__nulls"), F.sum(F.lit(0).cast("long")).alias(f"{n}__nan")]
    return out + [{"count": lambda a: F.count("*"), "sum": lambda a: F.sum(a.of), "min": lambda a: F.min(a.of), "max": lambda a: F.max(a.of)}[a.kind](a).alias(a.name) for a in spec.aggs]


def _node_stats(spec: TreeSpec) -> list[Column]:
    out = [F.sum("__rows").alias("__rows")]
    for n in spec.bounds:
        out += [F.min(f"{n}_lo").alias(f"{n}_lo"), F.max(f"{n}_hi").alias(f"{n}_hi"), F.sum(f"{n}__nulls").alias(f"{n}__nulls"), F.sum(f"{n}__nan").alias(f"{n}__nan")]
    return out + [{"count": F.sum, "sum": F.sum, "min": F.min, "max": F.max}[a.kind](a.name).alias(a.name) for a in spec.aggs]


def build(df: DataFrame, spec: TreeSpec, path: str | None = None) -> Tree:
    """Builds a tree of df's rows. The rows are written twice: once where the range shuffle puts them, which
    fixes their order for good, and once with their leaf numbers."""
    import time

    began = time.time()
    spark = df.sparkSession
    for n in (*spec.bounds, *spec.order):
        if n not in df.columns:
            raise AnalysisError(f"no such column: {n}")
    path = path or f"{base_dir(spark)}/tree-{uuid.uuid4().hex}"
    if spec.method == "median":
        keyed, keys = _median(df, spec, df.count()), [F.col("__g")]
    else:
        keyed, keys = df, _clustered(df, spec)
    placed = keyed.select(*[F.col(c) for c in df.columns], *[k.alias(f"__k{i}") for i, k in enumerate(keys)])
    order = [f"__k{i}" for i in range(len(keys))]
    placed.repartitionByRange(*order).sortWithinPartitions(*order).drop(*order).withColumn("__at", F.monotonically_increasing_id()).write.parquet(f"{path}/placed")
    fixed = spark.read.parquet(f"{path}/placed")
    part, inside = F.shiftright("__at", 33), F.col("__at").bitwiseAND((1 << 33) - 1)
    sizes = sorted((r["p"], r["n"]) for r in fixed.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())  # one row a partition
    before, offsets = 0, []
    for p, n in sizes:
        offsets.append((p, before))
        before += n
    of = spark.createDataFrame(offsets or [(0, 0)], "__p long, __before long")
    leafed = fixed.join(F.broadcast(of), part == F.col("__p")).withColumn("leaf_id", F.floor((F.col("__before") + inside) / spec.leaf_rows).cast("long")).select(*df.columns, "leaf_id")
    leafed.write.parquet(f"{path}/rows")
    drop(spark, f"{path}/placed")
    return _finish(spark.read.parquet(f"{path}/rows"), df.schema, spec, path, before, began)


def _finish(rows: DataFrame, schema: T.StructType, spec: TreeSpec, path: str, n: int, began: float) -> Tree:
    import time

    spark = rows.sparkSession
    level, levels, nodes = rows.groupBy(F.col("leaf_id").alias("node_id")).agg(*_leaf_stats(spec, schema)), [], max(1, math.ceil(n / spec.leaf_rows))
    count = nodes
    while True:
        at = f"{path}/level-{len(levels)}"
        level.coalesce(max(1, count // 100_000 + 1)).write.parquet(at)
        levels.append(spark.read.parquet(at))
        if count == 1:
            break
        count = math.ceil(count / spec.fanout)
        level = levels[-1].groupBy(F.floor(F.col("node_id") / spec.fanout).cast("long").alias("node_id")).agg(*_node_stats(spec))
    tree = Tree(spec, rows, levels, n, nodes, path, time.time() - began, T.StructType([f for f in rows.schema.fields if f.name != "leaf_id"]))
    spark.createDataFrame([(json.dumps({"bounds": spec.bounds, "aggs": [(a.kind, a.of) for a in spec.aggs], "order": spec.order, "method": spec.method, "leaf_rows": spec.leaf_rows, "fanout": spec.fanout, "n": n, "levels": len(levels)}),)], "manifest string").coalesce(1).write.text(f"{path}/manifest")
    return tree


def read_index(spark: SparkSession, path: str) -> Tree:
    m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    spec = TreeSpec(tuple(m["bounds"]), tuple(Agg(*a) for a in m["aggs"]), tuple(m["order"]), m["method"], m["leaf_rows"], m["fanout"])
    rows = spark.read.parquet(f"{path}/rows")
    return Tree(spec, rows, [spark.read.parquet(f"{path}/level-{i}") for i in range(m["levels"])], m["n"], max(1, math.ceil(m["n"] / spec.leaf_rows)), path, schema=T.StructType([f for f in rows.schema.fields if f.name != "leaf_id"]))


def drop(spark: SparkSession, path: str) -> None:
    """Deletes a folder, wherever Spark keeps it."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@dataclass
class Forest:
    """Trees of what came in at different times; a query's answer is the union over them."""

    members: list[Tree]

    def append(self, df: DataFrame) -> Forest:
        return Forest([*self.members, build(df, self.members[0].spec)])

    def compact(self) -> Forest:
        whole = self.members[0].scan()
        for t in self.members[1:]:
            whole = whole.unionByName(t.scan())
        return Forest([build(whole, self.members[0].spec)])

    def save(self, path: str, version: int) -> None:
        """Writes which trees belong to a version; a version that is there already is an error. Spark marks the folder
        last, so a writer that was lost leaves nothing that ``load`` reads."""
        spark = self.members[0].rows.sparkSession
        listed = json.dumps([t.path for t in self.members])
        spark.createDataFrame([(listed,)], "manifest string").coalesce(1).write.text(f"{path}/v{version:012d}")

    @staticmethod
    def versions(spark: SparkSession, path: str) -> list[int]:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        marked = fs.globStatus(spark._jvm.org.apache.hadoop.fs.Path(f"{path}/v*/_SUCCESS")) if fs.exists(at) else None
        return sorted(int(s.getPath().getParent().getName()[1:]) for s in marked or ())

    @staticmethod
    def load(spark: SparkSession, path: str, version: int | None = None) -> Forest:
        version = Forest.versions(spark, path)[-1] if version is None else version
        return Forest([read_index(spark, p) for p in json.loads(spark.read.text(f"{path}/v{version:012d}").first()[0])])


def env_of(tree: Tree, side: int):
    """Bounds of the columns of one side's node; columns of other sides are uniform."""

    def env(name: str, at: int):
        if at != side:
            return None
        return (col(f"{name}_lo", side), col(f"{name}_hi", side)) if name in tree.spec.bounds else (None, None)

    return env


def resolver(prefix: dict[int, str]):
    return lambda name, side: F.col(f"{prefix.get(side, '')}{name}")


__all__ = ["Agg", "Forest", "Tree", "TreeSpec", "build", "env_of", "read_index", "resolver", "to_column"]
