"""Repeated passages by a sparse suffix array over minimiser positions.

A passage is a run of at least ``MIN_WORDS`` = 50 words (white space between them doesn't matter).
Of every 26 neighbouring word positions, the one whose next ``GRAM`` words hash lowest is kept, the
leftmost of equals. Two equal passages of 50 words choose the same position among their first 26, and
there the suffixes agree in the 25 words that follow. Suffixes whose first 25 words no other has are
let go. Those that also agree in all their surroundings (25 words to the left, 50 to the right) are
one variant: all but the first occurrence repeat it whole.

The first occurrences of the other variants are sorted twice, word by word: by the words that follow,
and, among those of equal first 25 words, by the words before, read backwards. Of all suffixes, the
one that agrees longest to the right stands next to a suffix in the first order, and the one
that agrees longest to the left in the second; so comparing neighbours extends each suffix as far as
any other follows it, at most 25 words to the left and 50 to the right. An order is spread over the
cluster by ranges; the first and last row of each range, two for each partition, are compared on the
driver. Only where both extensions make up 50 words can a window of 50 around the suffix
stand elsewhere, and such windows are then verified, and named after their first occurrence, by
grouping equal ones. The repeated windows of a document, put together, are its repeated passages,
exactly: word position i is in one if and only if some 50 words around i stand earlier, at a
smaller (doc_id, position).

Words are hashed with XXH64, runs of words with polynomials of these modulo 2^64; neighbours are
compared by 32 bits a word, windows by two 64-bit polynomials of their words.

Results: texts with fewer than 50 words have no passages; a null text is empty; rows with a null id
have none; rows that share an id are one document. Text that repeats within a document counts,
overlaps too, so a text of one word over and over keeps its first words; a text of any length is
read whole, by one task. Ties can't arise: of equal passages the smallest (doc_id, position) is the
one that stays. Further columns are not read, and come back as they were from ``without``; an empty
table gives an empty table.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import released, table, texts, written

MIN_WORDS, PREFIX, GRAM = 50, 25, 8
STARTS = MIN_WORDS - PREFIX + 1
WORDS = re.compile(rb"[^\x20\x09-\x0D]+")
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)  # odd, so they have inverses modulo 2^64


class Hashes:
    """Hashes of runs of words of one text."""

    _powers: dict[int, np.ndarray] = {}

    def __init__(self, words: list[bytes], base: int = BASES[0]):
        n = len(words)
        h = np.array([xxhash.xxh64_intdigest(w) for w in words], np.uint64) if n else np.empty(0, np.uint64)
        if base != BASES[0]:
            h = _mix(h)
        self.back = self.powers(pow(base, -1, 1 << 64), n)
        self.sums = np.concatenate([[np.uint64(0)], np.cumsum(h * self.powers(base, n), dtype=np.uint64)])

    @classmethod
    def powers(cls, base: int, n: int) -> np.ndarray:
        known = cls._powers.get(base)
        if known is None or len(known) < n:
            known = np.full(max(n, 1 << 15), np.uint64(base))
            known[0] = 1
            known = cls._powers[base] = np.cumprod(known, dtype=np.uint64)
        return known[:n]

    def runs(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Of words start..end-1 (end > start)."""
        return _mix((self.sums[end] - self.sums[start]) * self.back[start])


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def kept_positions(hashes: Hashes, n: int) -> np.ndarray:
    """Positions of minimisers; n >= MIN_WORDS."""
    at = np.arange(n - PREFIX + 1)
    order = hashes.runs(at, at + GRAM)
    best, width = at, 1
    lower = lambda a, b: np.where(order[a] <= order[b], a, b)  # noqa: E731  the left one of equals
    while width * 2 <= STARTS:
        best = lower(best[:-width], best[width:])
        width *= 2
    if width < STARTS:
        rest = STARTS - width
        best = lower(best[: len(best) - rest], best[rest:])
    return np.unique(best)


def suffixes(docs: DataFrame) -> DataFrame:
    """(key, around, doc, pos, right): of each suffix the hash of its first words, that of its surroundings, and how
    many words to its right these hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            out: list[list[np.ndarray]] = [[], [], [], [], []]
            for doc, text in zip(part.column("doc").to_pylist(), found, strict=True):
                words = text.split()
                n = len(words)
                if n < MIN_WORDS:
                    continue
                h = Hashes(words)
                pos = kept_positions(h, n)
                left, right = np.minimum(pos, MIN_WORDS - PREFIX), np.minimum(n - pos, MIN_WORDS)
                around = _mix(h.runs(pos - left, pos + right) + (left * 64 + right).astype(np.uint64))
                for c, x in zip(out, (h.runs(pos, pos + PREFIX).view(np.int64), around.view(np.int64), np.full(len(pos), doc), pos.astype(np.int32), right.astype(np.int32)), strict=True):
                    c.append(x)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in out], names=["key", "around", "doc", "pos", "right"])
        released()

    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc"), "text").mapInArrow(run, "key long, around long, doc long, pos int, right int")


def contexts(docs: DataFrame, places: DataFrame) -> DataFrame:
    """(doc, pos, key, ahead, behind) of places (doc, pos, key): the words from a place on and those before it, read
    backwards, four bytes a word."""
    by_doc = places.groupBy("doc").agg(F.collect_list(F.struct("pos", "key")).alias("at"))
    both = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc"), "text").join(by_doc, "doc")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches, rows=256):
            out: list[list] = [[], [], [], [], []]
            for doc, text, at in zip(part.column("doc").to_pylist(), found, part.column("at").to_pylist(), strict=True):
                words = text.split()
                of = np.array([xxhash.xxh64_intdigest(w) for w in words], np.uint64).astype(">u4")
                for place in at:
                    i = place["pos"]
                    if i + PREFIX <= len(words):  # else another row of this document has the place
                        for c, x in zip(out, (doc, i, place["key"], of[i : i + MIN_WORDS].tobytes(), of[max(0, i - MIN_WORDS + PREFIX) : i][::-1].tobytes()), strict=True):
                            c.append(x)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.binary(), pa.binary()), strict=True)], names=["doc", "pos", "key", "ahead", "behind"])
        released()

    return both.mapInArrow(run, "doc long, pos int, key long, ahead binary, behind binary")


def agree(rows: list[bytes], width: int) -> np.ndarray:
    """In how many words, from the first on, each row agrees with the one before it; 0 for the first."""
    if len(rows) < 2:
        return np.zeros(len(rows), np.int32)
    words = np.frombuffer(b"".join([r.ljust(4 * width, b"\0") for r in rows]), np.uint32).reshape(-1, width)
    differ = np.concatenate([words[1:] != words[:-1], np.ones((len(rows) - 1, 1), bool)], axis=1)
    size = np.array([len(r) // 4 for r in rows])
    return np.concatenate([[0], np.minimum(differ.argmax(axis=1), np.minimum(size[1:], size[:-1]))]).astype(np.int32)


def extended(rows: DataFrame, width: int) -> DataFrame:
    """(doc, pos, reach): rows (doc, pos, words) sorted by their words, and in how many words, from the first on, the
    better of its two neighbours agrees with each."""
    order = ["words", "doc", "pos"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        names = ["doc", "pos", "reach", "part", "edge"]
        held: tuple | None = None  # the last row of the batch before, and its agreement with its left neighbour
        ends: list[tuple] = []

        def out(doc: list, pos: list, reach: list, edges: list | None = None) -> pa.RecordBatch:
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip((doc, pos, reach, [part] * len(doc), edges or [None] * len(doc)), kinds, strict=True)], names=names)

        for batch in batches:
            doc, pos, words = (batch.column(i).to_pylist() for i in range(3))
            if not doc:
                continue
            left = 0
            if held:
                doc, pos, words, left = [held[0], *doc], [held[1], *pos], [held[2], *words], held[3]
            else:
                ends.append((doc[0], pos[0], words[0]))
            with_left = agree(words, width)
            with_left[0] = left
            best = np.maximum(with_left, np.append(with_left[1:], 0))
            yield out(doc[:-1], pos[:-1], best[:-1].tolist())
            held = (doc[-1], pos[-1], words[-1], int(with_left[-1]))
        if held:
            yield out([held[0]], [held[1]], [held[3]])
            ends.append(held[:3])
            yield out([e[0] for e in ends], [e[1] for e in ends], [-1, -2], [e[2] for e in ends])

    spark = rows.sparkSession
    found = written(rows.select("doc", "pos", "words").repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(run, "doc long, pos int, reach int, part int, edge binary"))
    edges = sorted(((r["part"], -r["reach"]), r) for r in found.where("reach < 0").collect())  # two rows a partition
    seams = []
    for (_, a), (_, b) in zip(edges[1::2], edges[2::2]):
        reach = int(agree([bytes(a["edge"]), bytes(b["edge"])], width)[1])
        seams += [(r["doc"], r["pos"], reach) for r in (a, b)]
    more = spark.createDataFrame(seams, "doc long, pos int, reach int")
    return found.where("reach >= 0").select("doc", "pos", "reach").union(more).groupBy("doc", "pos").agg(F.max("reach").alias("reach"))


def windows(reached: DataFrame) -> DataFrame:
    """(a, b, doc, pos): two hashes of each 50-word window that neighbours on both sides agree with; reached has the
    columns of ``contexts`` with how far its rows reach to the left and to the right."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        most = MIN_WORDS - PREFIX
        for batch in batches:
            doc, pos, left, right = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("doc", "pos", "to_left", "to_right"))
            before = [x.ljust(4 * most, b"\0") for x in batch.column("behind").to_pylist()]
            after = [x.ljust(4 * MIN_WORDS, b"\0") for x in batch.column("ahead").to_pylist()]
            words = np.concatenate([np.frombuffer(b"".join(before), ">u4").reshape(-1, most)[:, ::-1], np.frombuffer(b"".join(after), ">u4").reshape(-1, MIN_WORDS)], axis=1).astype(np.uint64)
            mixed = (words, _mix(words))
            for back in range(most + 1):
                at = np.flatnonzero((left >= back) & (right >= MIN_WORDS - back))
                if len(at):
                    a, b = (_mix(m[at, most - back : most - back + MIN_WORDS] @ Hashes.powers(base, MIN_WORDS)).view(np.int64) for m, base in zip(mixed, BASES, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (a, b, doc[at], (pos[at] - back).astype(np.int32))], names=["a", "b", "doc", "pos"])
        released()

    return reached.mapInArrow(run, "a long, b long, doc long, pos int")


def repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, start, end, n_words, first_doc): passages, as word positions, all of whose words stand earlier; first_doc
    is the smallest id of a document that has some 50 words of it first."""
    every = suffixes(docs)
    # what is grouped is written before it is joined back, so that the join's partitions can be split where a key is hot
    shared = written(every.groupBy("key").agg(F.count("*").alias("_n")).where("_n > 1").select("key"))
    met = written(every.join(shared, "key", "left_semi"))
    variants = met.groupBy("key", "around").agg(F.min(F.struct("doc", "pos")).alias("first"), F.count("*").alias("n"))
    variants = written(variants)
    whole = met.join(variants.where("n > 1").select("key", "around", "first"), ["key", "around"]).where("struct(doc, pos) <> first")
    left = F.least(F.col("pos"), F.lit(MIN_WORDS - PREFIX))
    whole = whole.select("doc", (F.col("pos") - left).alias("start"), (F.col("pos") + F.col("right")).alias("end"), F.col("first.doc").alias("src"))

    many = written(variants.groupBy("key").agg(F.count("*").alias("_n")).where("_n > 1").select("key"))
    at = written(contexts(docs, variants.join(many, "key", "left_semi").select("first.doc", "first.pos", "key")))
    to_right = extended(at.withColumnRenamed("ahead", "words"), MIN_WORDS).withColumnRenamed("reach", "to_right")
    # the key goes before the words, as two words that equal first 25 words agree in
    keyed = at.withColumn("words", F.concat(F.unhex(F.lpad(F.hex("key"), 16, "0")), "behind"))
    to_left = extended(keyed, MIN_WORDS - PREFIX + 2).select("doc", "pos", F.greatest(F.col("reach") - 2, F.lit(0)).alias("to_left"))
    reached = at.join(to_right, ["doc", "pos"]).join(to_left, ["doc", "pos"]).where(F.col("to_left") + F.col("to_right") >= MIN_WORDS)
    fine = written(windows(reached.select("doc", "pos", "ahead", "behind", "to_left", "to_right")))
    firsts = written(fine.groupBy("a", "b").agg(F.min(F.struct("doc", "pos")).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"))
    again = fine.join(firsts, ["a", "b"]).where("struct(doc, pos) <> first").select("doc", F.col("pos").alias("start"), (F.col("pos") + MIN_WORDS).alias("end"), F.col("first.doc").alias("src"))

    ordered = Window.partitionBy("doc").orderBy("start", "end")
    ahead = F.max("end").over(ordered.rowsBetween(Window.unboundedPreceding, -1))
    marked = whole.union(again).withColumn("new", F.coalesce((F.col("start") > ahead).cast("int"), F.lit(1)))
    grouped = marked.withColumn("g", F.sum("new").over(ordered.rowsBetween(Window.unboundedPreceding, 0)))
    spans = grouped.groupBy("doc", "g").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.min("src").alias("first_doc"))
    return spans.select(F.col("doc").alias("doc_id"), "start", "end", (F.col("end") - F.col("start")).alias("n_words"), "first_doc")


def without(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """docs with the words of the spans (doc_id, start, end) taken out, and the white space behind each."""
    by_doc = spans.groupBy(F.col("doc_id").alias("_doc")).agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("_cut"))
    joined = docs.join(by_doc, F.col("doc_id") == F.col("_doc"), "left").drop("_doc")
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            done = []
            for text, cut in zip(found, part.column("_cut").to_pylist(), strict=True):
                if cut:
                    at = [m.start() for m in WORDS.finditer(text)] + [len(text)]
                    keep, last = [], 0
                    for c in cut:
                        keep.append(text[last : at[min(c["start"], len(at) - 1)]])
                        last = at[min(c["end"], len(at) - 1)]
                    text = b"".join([*keep, text[last:]])
                done.append(text)
            yield pa.RecordBatch.from_arrays([pa.array(done, pa.binary()).cast(pa.string()) if n == "text" else part.column(n) for n in names], names=names)
        released()

    return joined.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats(table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that stand earlier; those of which no word is left go."""
    docs = docs.select("doc_id", "text", "lang", "source", "n_chars")
    cut = without(docs, repeats(docs)).withColumn("n_chars", F.length("text").cast("long"))
    return cut.where(F.col("text").rlike(r"[^\x20\x09-\x0D]"))
