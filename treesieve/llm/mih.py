"""Exact k nearest neighbours of binary codes in Hamming distance, by incremental multi-index hashing.

A code of 64 bits is cut into four segments of 16, each with a table of its own. If two codes differ
in at most 4r+j bits, some segment differs in at most r bits, or one of the first j+1 in at most r
(the others in less): so after segment tables 0..j were probed up to radius r and the rest up to
r-1, every code within 4r+j is known. A query grows its radii segment by segment and stops once its
k-th verified distance is within what is covered.

Equal codes are one entry with a count and its k smallest ids, so a code that a third of all rows
carry is one row. Distinct codes are dealt into blocks of a bounded size by hash, queries likewise,
and each pair of blocks is searched in one task; a query's best k of all blocks are its answer.

Results: ties go to the smaller id; a query is among its own neighbours; with fewer than k rows all
are returned; a row without id or vector is neither searched nor found, and a row that repeats id
and code counts once; components beyond 64 don't count, missing or NaN ones give bit 0.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import durable, ragged, table

BITS, SEGMENTS, WIDTH = 64, 4, 16
K, QUERY_EVERY, BLOCK_ROWS, BLOCK_QUERIES = 10, 20, 1 << 16, 256


def binary_codes(df: DataFrame, ident: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, code): bit i of code tells whether component i is above zero."""
    bit = lambda v, i: F.when((v > 0) & ~F.isnan(v), F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))
    bits = F.transform(F.slice(vector, 1, BITS), lambda v, i: F.coalesce(bit(v, i), F.lit(0).cast("long")))
    code = F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))
    return df.where(F.col(ident).isNotNull() & F.col(vector).isNotNull()).select(F.col(ident).cast("long").alias("id"), code.alias("code")).distinct()


@lru_cache(maxsize=None)
def masks(radius: int) -> np.ndarray:
    return np.array([sum(1 << b for b in bits) for bits in combinations(range(WIDTH), radius)], np.int64)


class Tables:
    """The four segment tables of a block of distinct codes."""

    def __init__(self, codes: np.ndarray):
        self.codes = codes
        parts = self.cut(codes)
        self.order = [np.argsort(p, kind="stable") for p in parts]
        self.start = [np.searchsorted(p[o], np.arange((1 << WIDTH) + 1)) for p, o in zip(parts, self.order, strict=True)]

    @staticmethod
    def cut(codes: np.ndarray) -> list[np.ndarray]:
        return [((codes >> np.uint64(WIDTH * s)) & np.uint64((1 << WIDTH) - 1)).astype(np.int64) for s in range(SEGMENTS)]

    def nearest(self, code: int, weight: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Positions of all codes within the k-th smallest distance (codes count by weight), and distances."""
        segments = [int(p[0]) for p in self.cut(np.array([code], np.uint64))]
        seen = np.zeros(len(self.codes), bool)
        within = np.zeros(BITS + 1, np.int64)
        at, far = [], []
        for radius in range(WIDTH + 1):
            for s in range(SEGMENTS):
                probes = masks(radius) ^ segments[s]
                a, b = self.start[s][probes], self.start[s][probes + 1]
                got = self.order[s][ragged(a, b - a)]
                got = got[~seen[got]]
                if len(got):
                    seen[got] = True
                    d = np.bitwise_count(self.codes[got] ^ np.uint64(code)).astype(np.int64)
                    within += np.bincount(d, weights=weight[got], minlength=BITS + 1).astype(np.int64)
                    at.append(got)
                    far.append(d)
                covered = SEGMENTS * radius + s
                if within[: covered + 1].sum() >= k or len(self.codes) == seen.sum():
                    total = np.cumsum(within)
                    limit = int(np.searchsorted(total, min(k, total[-1])))
                    p, d = np.concatenate(at or [np.empty(0, np.int64)]), np.concatenate(far or [np.empty(0, np.int64)])
                    return p[d <= limit], d[d <= limit]
        raise AssertionError("every code is within the largest radius")


def top_k(codes: DataFrame, queries: DataFrame, k: int = K, block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """codes, queries: (id, code). Returns (query_id, rank, neighbour_id, distance)."""
    ranked = Window.partitionBy("code", "part").orderBy("id")
    # k smallest ids of each code, first within 64 parts so that no code's ids meet in one place before they are k
    parts = codes.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(64))).withColumn("n", F.row_number().over(ranked)).where(F.col("n") <= k)
    index = durable(parts.groupBy("code").agg(F.slice(F.sort_array(F.collect_list("id")), 1, k).alias("ids")))
    asked = durable(queries.groupBy("code").agg(F.count("*").alias("n")))
    n, m = index.count(), asked.count()
    b, q = max(1, -(-n // block_rows)), max(1, -(-m // block_queries))
    deal = lambda c, of: F.pmod(F.xxhash64(F.lit(7), c), F.lit(of)).cast("int")
    every = lambda of: F.explode(F.sequence(F.lit(0), F.lit(of - 1)))
    left = index.select(deal("code", b).alias("block"), "code", "ids").withColumn("of", every(q))
    right = asked.select(deal("code", q).alias("of"), "code").withColumn("block", every(b))

    def search(rows: pd.DataFrame, ask: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple[int, int, int]] = []
        if len(rows) and len(ask):
            ids = rows["ids"].to_list()
            tables = Tables(rows["code"].to_numpy(np.int64).view(np.uint64))
            weight = np.array([len(x) for x in ids], np.int64)
            for code in ask["code"].to_list():
                at, far = tables.nearest(code & ((1 << 64) - 1), weight, k)
                out += [(code, i, d) for d, i in sorted((d, int(i)) for p, d in zip(at.tolist(), far.tolist()) for i in ids[p])[:k]]
        return pd.DataFrame(out, columns=["code", "neighbour_id", "distance"])

    found = left.groupBy("block", "of").cogroup(right.groupBy("block", "of")).applyInPandas(search, "code long, neighbour_id long, distance int")
    best = Window.partitionBy("code").orderBy("distance", "neighbour_id")
    merged = found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    names = queries.select(F.col("id").alias("query_id"), F.col("code").alias("_code"))
    return names.join(merged, F.col("_code") == F.col("code")).select("query_id", "rank", "neighbour_id", "distance")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes = durable(binary_codes(table(spark, sf_dir, "embeddings")))
    return top_k(codes, codes.where(F.col("id") % QUERY_EVERY == 0))


ORACLE = """
WITH c AS (SELECT DISTINCT vec_id AS id, [coalesce(embedding[i] > 0 AND NOT isnan(embedding[i]), false) FOR i IN range(1, 65)] AS bits
           FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
d AS (SELECT q.id AS query_id, c.id AS neighbour_id, len([1 FOR i IN range(1, 65) IF q.bits[i] <> c.bits[i]])::INT AS distance
      FROM c q, c WHERE q.id % 20 = 0)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY distance, neighbour_id)::INT AS rank, neighbour_id, distance
FROM d QUALIFY rank <= 10
"""
