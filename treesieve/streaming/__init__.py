"""Streams: probing a tree, windows, joins of streams, running extremes, and index upkeep."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.expr import E
from ..operators.joins import single_index_join
from ..operators.tree import Forest, Tree, drop


def read_stream(spark: SparkSession, like: DataFrame, path: str, files_a_batch: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def probe_stream(stream: DataFrame, tree: Tree, p: E) -> DataFrame:
    """Stream-static single-index join: every level is an equi-join with a static table, so the plan streams."""
    return single_index_join(stream, tree, p)


def windowed(stream: DataFrame, time: str, late: str, width: str, slide: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Counts by tumbling or sliding windows; rows behind the watermark are dropped."""
    return stream.withWatermark(time, late).groupBy(F.window(time, width, slide or width), *keys).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, time: str, late: str, gap: str, keys: tuple[str, ...]) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap), *keys).agg(F.count("*").alias("n"))


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, late: str, before: str) -> DataFrame:
    """Rows of two streams with equal keys, the right one at most ``before`` earlier."""
    a, b = left.withWatermark(time, late).alias("a"), right.withWatermark(time, late).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} AND b.{time} <= a.{time} AND b.{time} >= a.{time} - INTERVAL {before}"))


def running_extremes(stream: DataFrame, key: str, metric: str, member: str) -> DataFrame:
    """Per key the smallest and largest metric so far and the members that have them."""
    return stream.groupBy(key).agg(F.min(metric).alias("low"), F.max(metric).alias("high"), F.min_by(member, metric).alias("argmin"), F.max_by(member, metric).alias("argmax"))


def keep_index(stream: DataFrame, start: Forest, checkpoint: str, each: Callable[[Forest], None] = lambda f: None, compact_at: int = 8) -> tuple[StreamingQuery, Callable[[], Forest]]:
    """Appends every micro-batch to a forest; from ``compact_at`` members on they are merged into one tree. Each batch
    leaves a version of the forest, named by its number, beside the checkpoint: a restart goes on from the newest
    one, and a batch that is run again finds its version and adds nothing."""
    spark, at = stream.sparkSession, f"{checkpoint}-forest"

    def newest() -> Forest:
        return Forest.load(spark, at) if Forest.versions(spark, at) else start

    held = [newest()]

    def upkeep(batch: DataFrame, number: int) -> None:
        if number in Forest.versions(spark, at):
            held[0] = newest()
            return
        if not batch.isEmpty():
            grown = held[0].append(batch)
            held[0] = grown.compact() if len(grown.members) >= compact_at else grown
        drop(spark, f"{at}/v{number:012d}")  # what a lost writer may have begun
        held[0].save(at, number)
        each(held[0])

    q = stream.writeStream.foreachBatch(upkeep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    return q, lambda: held[0]


def drain(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now, into a table in memory."""
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)
