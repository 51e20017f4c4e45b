"""Quality rules: shape of a text, and lines that too many documents of one host share.

Every ``\\n``-split line with a word is normalised (A-Z lowered, white space runs made one space,
ends trimmed) and hashed together with its host, the column ``source``. A line that stands in more
than ``max(min_docs, max_share * documents of the host)`` documents, or ``most_docs`` if given, is
boilerplate, so that with ``most_docs`` the limit doesn't grow with the host (the stage of the pipeline
has ``min_docs`` for it; the query is held against SQL without it). Boilerplate is removed,
and a document that keeps less than ``min_left`` of its words is depleted and rejected. The base
rules look at the text as it came.

Results: a null text has no words, so it fails the base rules; a null source is a host of its own;
rows are documents, so a repeated row counts again; within one document a line counts once; a count
equal to the limit is within it; a text of any length is judged whole, by one task; an empty table
gives an empty table.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, released, table, texts, written

#: Fixed values of the base rules.
SYMBOLS, MIN_WORDS, MAX_REPEAT_SHARE = b"#*$%&|<>", 50, 0.5
WHITE = b" \t\n\x0b\x0c\r"
INSIDE = bytes(range(0x80, 0xC0))  # bytes of UTF-8 that don't begin a character
MAX_SHARE, MIN_DOCS, MIN_LEFT = 0.10, 10, 0.5
#: Up to so many boilerplate lines, they are sent with the code; beyond, lines are joined by shuffle.
BROADCAST_LINES = 50_000


def line_hash(host: bytes, line: bytes) -> int:
    return xxhash.xxh64_intdigest(host + b"\n" + b" ".join(line.lower().split())) - (1 << 63)


def repeated_words(words: list[bytes]) -> int:
    """Words inside a 3-word window that the text has twice or more."""
    windows = list(zip(words, words[1:], words[2:]))
    if len(set(windows)) == len(windows):
        return 0
    times = Counter(windows)
    twice = np.fromiter((times[w] > 1 for w in windows), bool, len(windows))
    inside = np.zeros(len(words), bool)
    for shift in range(3):
        inside[shift : shift + len(windows)] |= twice
    return int(inside.sum())


def shape(text: bytes) -> tuple[int, int, int, int, int, bool]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    words = text.split()
    lines = text.split(b"\n")
    dup = 0
    if len(set(lines)) < len(lines):
        lines = [x for x in lines if x.strip(WHITE)]
        dup = len(lines) - len(set(lines))
    repeat = repeated_words(words)
    failed = len(words) < MIN_WORDS or repeat > MAX_REPEAT_SHARE * len(words)
    return len(words), len(text.translate(None, WHITE + INSIDE)), len(text) - len(text.translate(None, SYMBOLS)), dup, repeat, failed


def line_counts(docs: DataFrame, flush: int = 200_000) -> DataFrame:
    """Of each host, the lines and in how many documents they stand (source, line, n); the row with
    line null has the number of documents. Counts are added up in each task before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def out() -> pa.RecordBatch:
            keys = list(held)
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int64()), pa.array(list(held.values()), pa.int64())], names=["source", "line", "n"])

        for part, found in texts(batches):
            for host, text in zip(part.column("source").to_pylist(), found, strict=True):
                name = b"\x00" if host is None else b"\x01" + host.encode()
                held[host, None] += 1
                held.update({(host, line_hash(name, x)) for x in text.split(b"\n") if x.strip(WHITE)})
            if len(held) > flush:
                yield out()
                held = Counter()
        yield out()
        held = Counter()
        released()

    return docs.select("source", "text").mapInArrow(run, "source string, line long, n long").groupBy("source", "line").agg(F.sum("n").alias("n"))


def line_rows(rows: DataFrame) -> DataFrame:
    """(_row, line): the hashes of the lines of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            row, line = [], []
            for r, host, text in zip(part.column("_row").to_pylist(), part.column("source").to_pylist(), found, strict=True):
                name = b"\x00" if host is None else b"\x01" + host.encode()
                own = {line_hash(name, x) for x in text.split(b"\n") if x.strip(WHITE)}
                line.extend(own)
                row.extend([r] * len(own))
            yield pa.RecordBatch.from_arrays([pa.array(row, pa.int64()), pa.array(line, pa.int64())], names=["_row", "line"])

    return rows.select("_row", "source", "text").mapInArrow(run, "_row long, line long")


def boilerplate(docs: DataFrame, max_share: float = MAX_SHARE, min_docs: int = MIN_DOCS, most_docs: int | None = None) -> DataFrame:
    """(line): the hashes, each of host and line, of the lines that are above their host's limit."""
    counts = durable(line_counts(docs).where((F.col("n") > min_docs) | F.col("line").isNull()))
    hosts = counts.where("line is null").select(F.col("source").alias("host"), F.col("n").alias("docs"))
    limit = F.greatest(F.lit(float(min_docs)), F.lit(max_share) * F.col("docs"))
    if most_docs is not None:
        limit = F.least(limit, F.lit(float(max(min_docs, most_docs))))
    return counts.where("line is not null").join(hosts, F.col("source").eqNullSafe(F.col("host"))).where(F.col("n") > limit).select("line").distinct()


def judged(docs: DataFrame, max_share: float = MAX_SHARE, min_docs: int = MIN_DOCS, min_left: float = MIN_LEFT, most_docs: int | None = None, broadcast: int = BROADCAST_LINES) -> DataFrame:
    """All columns of docs (doc_id, text, source, ...), text without its boilerplate lines, and the
    base columns, n_removed_lines, words_left, base_failed, kept, which take the place of columns of these names."""
    docs = docs.drop(*BASE, "_row", "_lines")
    over = durable(boilerplate(docs, max_share, min_docs, most_docs))
    names = docs.columns
    if over.limit(broadcast + 1).count() <= broadcast:
        joined, every = docs, frozenset(r["line"] for r in over.collect())
    else:  # a row meets its own lines only, not all of its host's
        every = None
        rows = written(docs.withColumn("_row", F.monotonically_increasing_id()))
        own = line_rows(rows).join(over, "line").groupBy("_row").agg(F.collect_set("line").alias("_lines"))
        joined = rows.join(own, "_row", "left").drop("_row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            rows, left = [], []
            of_rows = [every] * len(found) if every is not None else [set(x or ()) for x in part.column("_lines").to_pylist()]
            for host, text, bad in zip(part.column("source").to_pylist(), found, of_rows, strict=True):
                row = shape(text)
                removed, words = 0, row[0]
                if bad:
                    name = b"\x00" if host is None else b"\x01" + host.encode()
                    lines = text.split(b"\n")
                    stay = [x for x in lines if not x.strip(WHITE) or line_hash(name, x) not in bad]
                    removed = len(lines) - len(stay)
                    if removed:
                        text = b"\n".join(stay)
                        words = len(text.split())
                left.append(text)
                rows.append((*row, removed, words, not row[5] and words >= min_left * row[0]))
            columns = list(zip(*rows))
            kinds = [pa.int64()] * 5 + [pa.bool_()] + [pa.int64()] * 2 + [pa.bool_()]
            own = [pa.array(left, pa.binary()).cast(pa.string()) if n == "text" else part.column(n) for n in names]
            yield pa.RecordBatch.from_arrays([*own, *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=[*names, *BASE])
        released()

    schema = ", ".join(f"`{n}` {t}" for n, t in [*docs.dtypes, *zip(BASE, ["long"] * 5 + ["boolean"] + ["long"] * 2 + ["boolean"], strict=True)])
    return joined.mapInArrow(run, schema)


BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "n_removed_lines", "words_left", "kept"]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "documents").select("doc_id", "text", "source")).select("doc_id", *BASE)


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are kept, without their boilerplate lines."""
    docs = docs.select("doc_id", "text", "lang", "source", "n_chars")
    return judged(docs, most_docs=MIN_DOCS).where("kept").select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text, source FROM documents),
w AS (SELECT rid, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
g AS (SELECT rid, i, ws[i] || ' ' || ws[i+1] || ' ' || ws[i+2] AS g
      FROM (SELECT rid, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
t AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS n FROM g) WHERE n > 1),
r AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, i AS p FROM t UNION ALL SELECT rid, i + 1 FROM t UNION ALL SELECT rid, i + 2 FROM t) GROUP BY 1),
l AS (SELECT rid, line, regexp_replace(trim(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), chr(9) || chr(10) || chr(11) || chr(12) || chr(13) || ' '), '[\x20\x09-\x0D]+', ' ', 'g') AS norm
      FROM (SELECT rid, unnest(ls) AS line FROM w)),
h AS (SELECT source, count(*) AS docs FROM d GROUP BY 1),
c AS (SELECT d.source, norm, count(DISTINCT l.rid) AS n FROM l JOIN d USING (rid) GROUP BY 1, 2),
o AS (SELECT c.source, norm FROM c JOIN h ON c.source IS NOT DISTINCT FROM h.source WHERE n > greatest(10, 0.10 * docs)),
b AS (SELECT rid, count(*) AS removed, sum(len(list_filter(regexp_split_to_array(line, '[\x20\x09-\x0D]+'), lambda x: x <> ''))) AS gone
      FROM l JOIN d USING (rid) JOIN o ON o.source IS NOT DISTINCT FROM d.source AND o.norm = l.norm GROUP BY 1),
f AS (SELECT doc_id, len(ws) AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
             length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
             len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words,
             coalesce(removed, 0) AS n_removed_lines, len(ws) - coalesce(gone, 0) AS words_left
      FROM d JOIN w USING (rid) LEFT JOIN r USING (rid) LEFT JOIN b USING (rid)),
q AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM f)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
       n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed,
       n_removed_lines::BIGINT AS n_removed_lines, words_left::BIGINT AS words_left,
       NOT base_failed AND words_left >= 0.5 * n_words AS kept
FROM q
"""
