"""Near copies: texts whose sets of word shingles have a Jaccard similarity of at least ``LEVEL``.

The first links are those of SimHash fingerprints over the same shingles, by the deletion variants of
``simhash``; each is verified by the shingles. At a similarity of 0.8, fingerprints of 64 bits differ
in some 3 to 11 bits, more than a radius that can be indexed by wildcards. The links beyond it
come from MinHash: ``BANDS`` keys a set, each of ``ROWS`` minima. Two sets of similarity s share a key with
probability 1 - (1 - s^ROWS)^BANDS, that is all but 3 in a million at 0.8 and more above. What shares a key
is compared in its minima first, a byte of each: fewer than ``ALIKE`` of 96 agree at 0.8 with a probability
of 1 in 50,000. The rest is verified by its shingles, as hashes of 32 bits: that one of n shingles
meets one of m others by chance has probability n m / 2^32.

A key's members are not compared in all pairs. First one member of each bucket leads: it is compared with
all others and leaves. Buckets whose members are then of one component are done, so a large group of near
copies costs one comparison a member. What remains shares keys without being linked. Buckets of at most
``SMALL`` members are compared in pairs. The members of larger ones are joined by a complete prefix filter
instead: with a set's shingles in order of rareness, the first that two similar sets of n and m have in common
has at most n - o shingles before it in the one and m - o in the other, o being the overlap that they need. Copies that differ by
a few words begin with shingles of their own, so many copies that are not similar enough meet nothing.

Results: equal sets of shingles are one row throughout; a text without words has the empty set and
is a copy of its like; fewer than ``width`` words are one shingle; a component's id is the smallest
doc_id in it (null only if all are null); a text of any length is hashed whole, by one task; further
columns are not read; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import components, durable, list_array, released, texts, written
from .simhash import links, majority, shingle_hashes

WIDTH, LEVEL, BANDS, ROWS, ALIKE = 5, 0.8, 24, 4, 60
#: Members of a bucket that are compared in pairs once its leader has left, parts of a member's comparisons in a join.
SMALL, SALTS = 16, 64
#: Classes of sizes: a set's partners have sizes of some 450 / SIZES per cent steps, which join keys name.
SIZES = 32
#: Up to so many sets, the rows that are verified are sent to where the shingles lie; beyond, shingles are shuffled to them.
SENT = 200_000


@lru_cache(maxsize=4)
def orders(n: int) -> tuple[np.ndarray, np.ndarray]:
    odd, flip = np.random.default_rng(11).integers(0, 1 << 63, (2, n), dtype=np.int64).astype(np.uint64)
    return odd | np.uint64(1), flip


def minima(shingles: np.ndarray, n: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """The least of each of n * rows hashes of a set's members."""
    odd, flip = orders(n * rows)
    least = np.full(n * rows, np.uint64((1 << 64) - 1))
    for at in range(0, len(shingles), 1024):
        x = (shingles[at : at + 1024, None] ^ flip) * odd
        least = np.minimum(least, (x ^ (x >> np.uint64(32))).min(axis=0))
    return least


def bands(least: np.ndarray, n: int = BANDS) -> np.ndarray:
    """Keys of a set by its minima."""
    return np.array([xxhash.xxh64_intdigest(part.tobytes(), i) for i, part in enumerate(least.reshape(n, -1))], np.uint64).view(np.int64)


def shingle_sets(docs: DataFrame, width: int = WIDTH, seed: int = 42) -> DataFrame:
    """(doc_id, id, n, fp, keys, sketch, shingles) for each row of docs: a hash of its set, the set's size, the
    fingerprint of its shingles, bands (none of the empty set), a byte of each minimum, and members."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches, rows=256):
            every = [shingle_hashes(t, width, seed) for t in found]
            fps = np.array([majority(h) for h in every], np.uint64).view(np.int64)
            sets = [np.unique(h) for h in every]
            ids = np.array([xxhash.xxh64_intdigest(s.tobytes()) for s in sets], np.uint64).view(np.int64)
            least = [minima(s) for s in sets]
            narrow = [np.unique((s >> np.uint64(32)).astype(np.uint32)) for s in sets]
            members = list_array(pa.array(np.concatenate(narrow).view(np.int32)), np.array([len(s) for s in narrow]))
            keys = list_array(pa.array(np.concatenate([bands(x) if len(s) else np.empty(0, np.int64) for x, s in zip(least, sets, strict=True)])), np.array([BANDS if len(s) else 0 for s in sets]))
            sketch = pa.array([x.astype(np.uint8).tobytes() for x in least], pa.binary())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(ids), pa.array([len(s) for s in sets], pa.int32()), pa.array(fps), keys, sketch, members], names=["doc_id", "id", "n", "fp", "keys", "sketch", "shingles"])
        released()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, id long, n int, fp long, keys array<long>, sketch binary, shingles array<int>")


def alike(pairs: DataFrame, one: DataFrame, least: int = ALIKE) -> DataFrame:
    """Those of the pairs (a, b) whose minima agree often enough."""
    sketches = one.select("id", "sketch")
    both = pairs.join(sketches.withColumnsRenamed({"id": "a", "sketch": "x"}), "a").join(sketches.withColumnsRenamed({"id": "b", "sketch": "y"}), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in ("x", "y"))
            ok = pa.array((x == y).sum(axis=1) >= least)
            yield pa.RecordBatch.from_arrays([batch.column(c).filter(ok) for c in ("a", "b")], names=["a", "b"])

    return both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def verified(pairs: DataFrame, sets: DataFrame, level: float = LEVEL) -> DataFrame:
    """Those of the pairs (a, b) that are similar. A set with many partners meets them in parts."""

    salted = pairs.withColumn("salt", F.xxhash64("b") % SALTS)
    left = salted.select("a", "salt").distinct().join(sets.select(F.col("id").alias("a"), F.col("shingles").alias("x")), "a")
    both = salted.join(left, ["a", "salt"]).join(sets.select(F.col("id").alias("b"), F.col("shingles").alias("y")), "b")
    counted = both.select("a", "b", F.size(F.array_intersect("x", "y")).alias("common"), (F.size("x") + F.size("y")).alias("of"))
    return counted.where(F.col("common") >= level * (F.col("of") - F.col("common")) - 1e-9).select("a", "b")


def prefix_pairs(sets: DataFrame, level: float = LEVEL) -> DataFrame:
    """(a, b), a < b: all pairs of the sets (id, root, shingles) with different roots that can be similar, by the first shingle that
    they have in common: rare ones come first. The key names the classes of both sizes."""
    each = sets.select("id", "root", F.size("shingles").alias("n"), F.explode("shingles").alias("s"))
    often = each.groupBy("s").agg(F.count("*").alias("often"))
    place = F.row_number().over(Window.partitionBy("id").orderBy("often", "s"))
    size_class = lambda c: F.floor(F.log(c) * SIZES).cast("int")
    # with p shingles before the common one, at most n - p are shared, and similar sets share level / (1 + level) of n + m
    placed = each.join(often, "s").withColumn("most", F.floor((F.col("n") - place + 1) * ((1 + level) / level) - F.col("n") + 1e-6).cast("int"))
    low, high = F.greatest(F.ceil(F.col("n") * level - 1e-6), F.lit(1)), F.least(F.col("most"), F.floor(F.col("n") / level + 1e-6))
    keyed = placed.where(low <= high).select("s", "id", "root", "n", "most", size_class(F.col("n")).alias("own"), F.explode(F.sequence(size_class(low), size_class(high))).alias("other"))
    x = keyed.toDF("s", "id_a", "root_a", "n_a", "most_a", "own", "other")
    y = keyed.toDF("s", "id_b", "root_b", "n_b", "most_b", "other", "own")
    met = x.join(y, ["s", "own", "other"]).where("id_a < id_b AND root_a <> root_b AND n_b <= most_a AND n_a <= most_b")
    return met.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")).distinct()


def similar(keyed: DataFrame, one: DataFrame, each: DataFrame, level: float = LEVEL, small: int = SMALL) -> DataFrame:
    """(node, root): components of the links between the sets of ``one`` (id, fp, sketch, row), whose fingerprints link or
    that share a key. keyed (key, id, n), distinct; row names the row of each (row, shingles) that has a set."""

    def shingles(ids: DataFrame) -> DataFrame:
        needed = written(ids.join(one.select("id", "row"), "id"))
        few = needed.limit(SENT + 1).count() <= SENT
        return each.select("row", "shingles").join(F.broadcast(needed) if few else needed, "row").drop("row")

    def check(pairs: DataFrame) -> DataFrame:
        return durable(verified(pairs, shingles(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()).select("id", "shingles"), level))

    # one set stands for a fingerprint; the others that have it are linked to it
    of = written(one.groupBy("fp").agg(F.min("id").alias("first"), F.count("*").alias("sets")))
    near = links(of.select("fp")).toDF("u", "v")
    firsts = of.select("fp", "first")
    near = near.join(firsts.toDF("u", "a"), "u").join(firsts.toDF("v", "b"), "v").select("a", "b")
    same = one.join(of.where("sets > 1"), "fp").where("id <> first").select(F.col("first").alias("a"), F.col("id").alias("b"))
    tested = written(near.union(same).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    found = check(tested)

    # each bucket's leader is compared with the others, whatever the links so far
    sizes_fit = lambda n, m: F.least(n, m) >= level * F.greatest(n, m) - 1e-9
    shared = written(keyed.groupBy("key").agg(F.count("*").alias("_n"), F.min(F.struct("id", "n")).alias("lead")).where("_n > 1"))
    met = keyed.join(shared.select("key", "lead"), "key").where("id <> lead.id").where(sizes_fit(F.col("n"), F.col("lead.n")))
    pairs = written(met.select(F.col("lead.id").alias("a"), F.col("id").alias("b")).distinct().join(tested, ["a", "b"], "left_anti"))
    found, tested = found.union(check(written(alike(pairs, one)))), tested.union(pairs)
    roots = durable(components(found))

    # buckets that still have several components, without their leaders
    left = keyed.join(shared.select("key", F.col("lead.id").alias("_lead")), "key").where("id <> _lead")
    named = written(left.join(roots, left.id == roots.node, "left").select("key", "id", "n", F.coalesce("root", "id").alias("root")))
    several = written(named.groupBy("key").agg(F.min("root").alias("_a"), F.max("root").alias("_b"), F.count("*").alias("_n")).where("_a <> _b").select("key", "_n"))
    if several.isEmpty():
        return roots
    rest = named.join(several, "key")
    few = rest.where(F.col("_n") <= small).select("key", "id", "n", "root")
    other = few.toDF("key", "b", "m", "other")
    met = few.join(other, "key").where("id < b AND root <> other").where(sizes_fit(F.col("n"), F.col("m")))
    pairs = met.select(F.col("id").alias("a"), "b")
    many = written(rest.where(F.col("_n") > small).select("id", "root").distinct())
    if not many.isEmpty():
        pairs = pairs.union(prefix_pairs(shingles(many), level))
    pairs = written(pairs.distinct().join(tested, ["a", "b"], "left_anti"))
    found = found.union(check(written(alike(pairs, one))))
    return durable(components(found))


def classes(docs: DataFrame, width: int = WIDTH, level: float = LEVEL) -> DataFrame:
    """(doc_id, component_id) for each row of docs."""
    each = written(shingle_sets(docs, width).withColumn("row", F.monotonically_increasing_id()))
    one = written(each.groupBy("id").agg(F.min("doc_id").alias("least"), *(F.first(c).alias(c) for c in ("n", "fp", "keys", "sketch")), F.min("row").alias("row")))
    roots = similar(one.select(F.explode("keys").alias("key"), "id", "n").distinct(), one, each, level)
    of = written(one.join(roots, one.id == roots.node, "left").select("id", "least", F.coalesce("root", "id").alias("root")))
    low = of.groupBy("root").agg(F.min("least").alias("component_id"))
    named = of.join(low, "root").select("id", "component_id")
    return each.select("doc_id", "id").join(named, "id").select("doc_id", "component_id")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component: the one with the smallest id (of rows that repeat it, one; rows
    without an id can't be told apart and all stay)."""
    docs = docs.select("doc_id", "text", "lang", "source", "n_chars")
    keep = classes(docs).where("doc_id = component_id").select("doc_id").distinct()
    kept = docs.join(keep, "doc_id", "left_semi")
    lone = docs.where("doc_id is null")
    one = kept.withColumn("_n", F.row_number().over(Window.partitionBy("doc_id").orderBy("text", "lang", "source", "n_chars"))).where("_n = 1").drop("_n")
    return one.unionByName(lone)
