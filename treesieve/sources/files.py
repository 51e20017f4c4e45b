"""Tables in files, and a tree as a source of Spark SQL.

``tree_source`` registers the format ``treesieve``: comparisons with literals that Spark pushes down
are held against leaf metadata, one partition is made for each run of leaves that survive, and Spark
still tests every row.
"""

from __future__ import annotations

import base64
import operator
import pickle
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import TimestampType


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def round_trip(df: DataFrame, kind: str, path: str) -> DataFrame:
    """df written to a format and read again."""
    writer, reader = df.write, df.sparkSession.read.schema(df.schema)
    if kind == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    writer.format(kind).save(path)
    return reader.format(kind).load(path)


def by_leaf_bucket(df: DataFrame, path: str, leaves: int = 64) -> None:
    """Rows of a tree (with leaf_id) as Parquet folders of so many leaves each."""
    df.withColumn("leaf_bucket", F.floor(F.col("leaf_id") / leaves)).write.partitionBy("leaf_bucket").parquet(path)


class Run(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


COMPARE = {GreaterThan: operator.gt, GreaterThanOrEqual: operator.ge, LessThan: operator.lt, LessThanOrEqual: operator.le}


class TreeReader(DataSourceReader):
    def __init__(self, schema, path: str, leaves: list[dict]):
        self.schema, self.path, self.leaves, self.wanted = schema, path, leaves, [True] * len(leaves)

    def pushFilters(self, filters: list[Filter]):  # noqa: N802
        for f in filters:
            kind = type(f)
            if (kind in COMPARE or kind is EqualTo) and len(f.attribute) == 1 and f"{f.attribute[0]}_lo" in (self.leaves[0] if self.leaves else {}):
                name = f.attribute[0]
                for i, leaf in enumerate(self.leaves):
                    lo, hi = leaf[f"{name}_lo"], leaf[f"{name}_hi"]
                    if lo is None or leaf[f"{name}__nan"]:
                        continue
                    ok = lo <= f.value <= hi if kind is EqualTo else COMPARE[kind](hi if kind in (GreaterThan, GreaterThanOrEqual) else lo, f.value)
                    self.wanted[i] &= ok
            yield f  # Spark tests the rows

    def partitions(self):
        runs: list[Run] = []
        for leaf, ok in zip(self.leaves, self.wanted, strict=True):
            if ok:
                n = leaf["node_id"]
                if runs and runs[-1].last == n - 1:
                    runs[-1] = Run(runs[-1].first, n)
                else:
                    runs.append(Run(n, n))
        return runs or [Run(0, -1)]

    def read(self, partition: Run) -> Iterator:
        import pyarrow.dataset as ds
        from pyspark.sql.pandas.types import to_arrow_schema

        names = [f.name for f in self.schema.fields]
        data = ds.dataset(self.path, format="parquet")
        found = data.to_table(columns=names, filter=(ds.field("leaf_id") >= partition.first) & (ds.field("leaf_id") <= partition.last))
        yield from found.cast(to_arrow_schema(self.schema)).to_batches()  # Spark writes timestamps of another unit than it reads


class TreeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "treesieve"

    def schema(self):
        return self.options["rows_schema"]

    def reader(self, schema):
        return TreeReader(schema, self.options["rows"], pickle.loads(base64.b64decode(self.options["leaves"])))


def tree_source(spark: SparkSession, path: str, most_leaves: int = 100_000) -> DataFrame:
    """A saved tree as a source with filter pushdown, for trees on a file system that workers can open. The leaf
    table is sent with the scan, so trees with more leaves than the limit are refused; use Q for them."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TreeSource)
    rows, leaves = spark.read.parquet(f"{path}/rows").drop("leaf_id"), spark.read.parquet(f"{path}/level-0")
    if leaves.count() > most_leaves:
        raise ValueError(f"more than {most_leaves} leaves")
    timed = [f.name for f in leaves.schema.fields if isinstance(f.dataType, TimestampType)]  # collected without a zone, pushed down with one
    listed = [r.asDict() | {n: r[n].astimezone() for n in timed if r[n] is not None} for r in leaves.orderBy("node_id").collect()]
    local = f"{path}/rows".removeprefix("file://")
    return spark.read.format("treesieve").option("rows", local).option("rows_schema", ", ".join(f"`{n}` {t}" for n, t in rows.dtypes)).option("leaves", base64.b64encode(pickle.dumps(listed)).decode()).load()
