"""SimHash near-duplicates through deletion-variant signatures.

Fingerprints of 64 bits link at ``radius`` = 2 or fewer differing bits. Cut into two segments of 32
bits, two linked fingerprints have a segment in which they differ by at most one bit; of that
segment they then share the variant that wildcards this bit (or any, if they are equal there). So
each distinct fingerprint is indexed under its 2 x 32 one-wildcard variants, rows meet by equality
of variants, and what meets is verified.

A bucket holds fingerprints that agree on all but the bits in which they may differ: 33 bits at
first. A bucket of at most ``BUCKET`` members is verified whole, and leaves a link from each member
to the smallest of its component, not every pair. A larger one goes to the next level: its free
bits are again cut into two and wildcarded, which leaves 17 or 18 free bits, and then 9 or 10. Distinct
values with 10 free bits number at most 1024, so the last level has no large bucket and no link is
lost.

Exact copies share a fingerprint and are one row throughout. Links become components by rounds of
joins; nothing but counts reaches the driver.

Results: a text without words (null too) has fingerprint zero and links like any other; fewer than
``width`` words are one shingle; repeated rows are each returned; a component's id is the smallest
doc_id in it (null only if all are null); an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, durable, table, texts

BUCKET = 512
ONES = np.uint64(0x0101010101010101)


def shingle_hashes(text: bytes, width: int = 3, seed: int = 42) -> np.ndarray:
    words = text.lower().split()
    if not words:
        return np.empty(0, np.uint64)
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([digest(joined, seed)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[: len(words) - width + 1]
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts.tolist(), ends[width - 1 :].tolist())], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """Bits that are set in over half of the hashes. Bit b+8j of a hash is bit 0 of byte j after a shift
    by b, so that bytes are added up side by side, 255 hashes at a time."""
    n = len(hashes)
    if n == 0:
        return 0
    counts = np.zeros((8, 8), np.int64)
    cuts = np.arange(0, n, 255)
    for b in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(b)) & ONES, cuts)
        counts[b] = lanes.view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    set_bits = counts.T.ravel() * 2 > n  # bit 8j+b
    return int(np.packbits(set_bits, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp) for each row of docs, fp a long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            fp = np.array([majority(shingle_hashes(t, width, seed)) for t in found], np.uint64)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(fp.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, fp long")


def _pieces(bits: list[int]) -> tuple[list[int], list[int]]:
    return bits[: (len(bits) + 1) // 2], bits[(len(bits) + 1) // 2 :]


def _mask(bits: list[int]) -> int:
    m = sum(1 << b for b in bits)
    return m - (1 << 64) if m >> 63 else m


def variants(level: int) -> tuple[list[tuple[int, int]], list[int], list[list[int]]]:
    """Of each variant, with how the variants of the level before are numbered: (number of the variant
    that it refines, mask of the bits that its members agree on)."""
    free = [list(range(64))]
    out: list[tuple[int, int]] = [(-1, 0)]
    for _ in range(level):
        nxt, masks = [], []
        for parent, bits in enumerate(free):
            for kept, rest in (_pieces(bits), _pieces(bits)[::-1]):
                for wild in kept:
                    left = [*rest, wild]
                    nxt.append(left)
                    masks.append((parent, _mask(sorted(set(range(64)) - set(left)))))
        free, out = nxt, masks
    return out, [m for _, m in out], free


def linked(fps: np.ndarray, radius: int = 2) -> np.ndarray:
    """For each of a few sorted distinct fingerprints, the position of the smallest of its component."""
    n = len(fps)
    root = np.arange(n)
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= radius
    while True:
        low = np.where(near, root[None, :], n).min(axis=1)
        low = low[low]
        if (low == root).all():
            return root
        root = low


def _verify(df: DataFrame, last: bool, bucket: int) -> DataFrame:
    """df (key, var, fp), sorted by key in each partition -> links (a, b), or (var, fp) of buckets that
    are too large (b null). A partition is read as a stream; at most a bucket and a batch are held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.empty(0, np.int64)] * 3
        large: int | None = None  # the key of a bucket whose rows stream by
        a, b, var = [], [], []

        def close(key: np.ndarray, v: np.ndarray, fp: np.ndarray) -> None:
            nonlocal large
            if not len(key):
                return
            cut = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            size = np.diff(np.append(cut, len(key)))
            for at, n in zip(cut[size > 1].tolist(), size[size > 1].tolist()):
                if (n > bucket and not last) or key[at] == large:
                    continue
                f = np.sort(fp[at : at + n].view(np.uint64))
                root = linked(f)
                moved = np.flatnonzero(root != np.arange(n))
                if len(moved):
                    a.append(f[moved].view(np.int64))
                    b.append(f[root[moved]].view(np.int64))
            big = np.repeat((size > bucket) & (not last), size) | (key == large if large is not None else False)
            if big.any():
                var.append((v[big], fp[big]))

        def out() -> pa.RecordBatch:
            v = np.concatenate([x[0] for x in var]) if var else np.empty(0, np.int64)
            f = np.concatenate([x[1] for x in var]) if var else np.empty(0, np.int64)
            x = np.concatenate(a) if a else np.empty(0, np.int64)
            y = np.concatenate(b) if b else np.empty(0, np.int64)
            a.clear(), b.clear(), var.clear()
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([x, f])), pa.array(np.concatenate([y, v])), pa.array(np.concatenate([np.zeros(len(x), bool), np.ones(len(f), bool)]))], names=["a", "b", "large"])

        for batch in batches:
            now = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
            key, v, fp = (np.concatenate([h, x]) for h, x in zip(held, now, strict=True))
            if not len(key):
                continue
            start = int(np.searchsorted(key, key[-1]))
            close(key[:start], v[:start], fp[:start])
            if key[-1] != large:
                large = None
            if not last and (len(key) - start > bucket or key[-1] == large):
                large = int(key[-1])
                close(key[start:], v[start:], fp[start:])
                start = len(key)
            held = [key[start:], v[start:], fp[start:]]
            if a or var:
                yield out()
        close(*held)
        yield out()

    return df.mapInArrow(run, "a long, b long, large boolean")


def links(fps: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp) with the components that links make."""
    rows, found = fps.select(F.lit(0).cast("long").alias("var"), "fp"), None
    for level in (1, 2, 3):
        keyed = _keyed(rows, level).repartition("key").sortWithinPartitions("key")
        done = durable(_verify(keyed, level == 3, bucket))
        edges = done.where("not large").select("a", "b")
        found = edges if found is None else found.union(edges)
        over = done.where("large")
        if level == 3 or over.isEmpty():
            return found.distinct()
        rows = over.select(F.col("b").alias("var"), F.col("a").alias("fp"))
    raise AssertionError


def _keyed(rows: DataFrame, level: int) -> DataFrame:
    """(key, var, fp): each row under all variants that refine its own. The key is a hash of variant and
    agreed bits; buckets that collide are verified like any other."""
    all_of, masks, _ = variants(level)
    if level == 1:
        table_of: Column = F.array(*[F.lit(m).cast("long") for m in masks])
        out = rows.select(F.posexplode(table_of).alias("i", "m"), "fp").select(F.col("i").cast("long").alias("var"), "m", "fp")
    else:
        of = rows.sparkSession.createDataFrame([(p, i, m) for i, (p, m) in enumerate(all_of)], "p long, i long, m long")
        out = rows.join(F.broadcast(of), F.col("var") == F.col("p")).select(F.col("i").alias("var"), "m", "fp")  # a table of fixed size
    return out.select(F.xxhash64("var", F.col("fp").bitwiseAND(F.col("m"))).alias("key"), "var", "fp")


def classes(docs: DataFrame, width: int = 3, seed: int = 42, bucket: int = BUCKET) -> DataFrame:
    """(doc_id, fp, component_id) for each row of docs."""
    each = durable(fingerprints(docs, width, seed))
    distinct = durable(each.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(links(distinct.select("fp"), bucket))
    of = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    low = of.groupBy("root").agg(F.min("least").alias("component_id"))
    named = of.join(low, "root").select(F.col("fp").alias("_fp"), "component_id")
    return each.join(named, F.col("fp") == F.col("_fp")).select("doc_id", "fp", "component_id")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classes(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
