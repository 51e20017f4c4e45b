"""Quality classifier: quadratic discriminant with shrunken class covariances.

Statistics of a text (``FEATURES``) are brought close to normal by logarithms and square roots. Each
class of ``labels.quality`` has a mean and a covariance, drawn towards its own diagonal and the
covariance that the classes share; the score is the logistic of the difference of the two
log-densities and log-priors, by Mahalanobis distances through Cholesky factors that are computed
once on the driver and sent with the code. All labelled training rows count: sums, products and
numbers of rows are added up in each task and then by Spark, and a fixed number of sums comes to the driver.

Results: a null text is scored like the empty text; rows with a null label or a null id don't train,
and a null id is not held out; a document labelled twice counts twice; without rows of both classes
every score is the share of label 1 (0.5 without any); repeated rows get equal scores, whatever their
order; a text of any length is read whole, by one task; an empty table gives an empty table; further
columns are not read, whatever their names.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import remainder, table, texts, written
from .line_rules import INSIDE, SYMBOLS, WHITE

FOLDS, HELD_OUT, THRESHOLD = 5, 0, 0.3
SHRINK, POOL, FLOOR = 0.1, 0.2, 1e-4
FEATURES = ["words", "lines", "word_length", "symbols", "upper", "digits", "marks", "exclaims", "bars", "other", "distinct_words", "top_word", "distinct_lines", "symbol_words", "words_a_line"]
#: Added to what a share is of, so that the shares of a few words don't look extreme.
SMOOTH = 20
PUNCTUATION = b".,;:!?\"'()-"
UPPER, DIGITS = bytes(range(65, 91)), b"0123456789"
NEITHER = bytes(b for b in range(33, 127) if not chr(b).isalnum() and b not in SYMBOLS + PUNCTUATION)


def statistics(text: bytes) -> list[float]:
    words = text.split()
    n, times = len(words), Counter(words)
    del words
    count = lambda some: len(text) - len(text.translate(None, some))
    chars = max(1, len(text.translate(None, WHITE + INSIDE)))
    lines = [x for x in text.split(b"\n") if x.strip(WHITE)]
    share = lambda k, of, own=0: ((k + own) / (of + SMOOTH)) ** 0.5
    ends = sum(k for w, k in times.items() if w[-1:] in b"#*$%&|<>!")
    return [
        np.log1p(n), np.log1p(len(lines)), np.log1p(chars / max(1, n)), share(count(SYMBOLS), chars), share(count(UPPER), chars), share(count(DIGITS), chars),
        share(count(PUNCTUATION), chars), share(text.count(b"!"), chars), share(text.count(b"|"), chars), share(count(NEITHER), chars),
        share(len(times), n, SMOOTH), share(max(times.values(), default=0), n), share(len(set(lines)), len(lines), SMOOTH), share(ends, n), np.log1p(n / max(1, len(lines))),
    ]


def features(docs: DataFrame) -> DataFrame:
    """(doc_id, x) for each row, x array<double>."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, found in texts(batches):
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([statistics(t) for t in found], pa.list_(pa.float64()))], names=["doc_id", "x"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, x array<double>")


@dataclass
class Model:
    prior: float
    means: np.ndarray | None = None  # class, feature
    factors: np.ndarray | None = None  # inverses of the Cholesky factors
    logdet: np.ndarray | None = None

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.means is None:
            return np.full(len(x), self.prior)
        logs = []
        for k in range(2):
            z = (x - self.means[k]) @ self.factors[k].T
            logs.append(-0.5 * (z * z).sum(axis=1) - 0.5 * self.logdet[k])
        gap = np.clip(logs[1] - logs[0] + np.log(self.prior) - np.log1p(-self.prior), -500, 500)
        return 1 / (1 + np.exp(-gap))


def moments(labelled: DataFrame) -> tuple[list[int], list[np.ndarray], list[np.ndarray]]:
    """labelled: (x, label), label 0 or 1. Of each class the number of rows, and the sums of x and of its products;
    each task adds up its rows, and a row for each class and task goes on."""
    d = len(FEATURES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, 1 + d + d * d))
        for batch in batches:
            x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            label = batch.column("label").to_numpy(zero_copy_only=False)
            for k in range(2):
                own = x[label == k]
                total[k] += np.concatenate([[len(own)], own.sum(axis=0), (own.T @ own).ravel()])
        at = np.arange(total.size)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total.ravel())], names=["i", "s"])

    got = labelled.select("x", "label").mapInArrow(run, "i long, s double").groupBy("i").agg(F.sum("s").alias("s")).toArrow()
    sums = np.zeros((2, 1 + d + d * d))
    sums.ravel()[got.column("i").to_numpy()] = got.column("s").to_numpy()
    return [int(k) for k in sums[:, 0]], [r[1 : 1 + d] for r in sums], [r[1 + d :].reshape(d, d) for r in sums]


def fit(labelled: DataFrame, shrink: float = SHRINK, pool: float = POOL) -> Model:
    """labelled: (x, label), label 0 or 1."""
    d = len(FEATURES)
    n, sums, products = moments(labelled)
    if min(n) < 2:
        return Model(prior=n[1] / sum(n) if sum(n) else 0.5)
    means = [sums[k] / n[k] for k in range(2)]
    scatter = [products[k] / n[k] - np.outer(means[k], means[k]) for k in range(2)]
    shared = (n[0] * scatter[0] + n[1] * scatter[1]) / sum(n)
    factors, logdet = [], []
    for c in scatter:
        c = (1 - shrink - pool) * c + shrink * np.diag(np.diag(c)) + pool * shared + FLOOR * np.eye(d)
        low = np.linalg.cholesky(c)
        factors.append(np.linalg.inv(low))
        logdet.append(2 * np.log(np.diag(low)).sum())
    return Model(n[1] / sum(n), np.array(means), np.array(factors), np.array(logdet))


def scored(feats: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score) of (doc_id, x)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(model.score(x))], names=["doc_id", "score"])

    return feats.mapInArrow(run, "doc_id long, score double")


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row of docs."""
    feats = written(features(docs))
    own = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col("quality").cast("int").alias("label")).where(F.col("label").isin(0, 1))
    train = feats.where(~remainder(F.col("doc_id"), FOLDS).isin(HELD_OUT, -1)).join(own, F.col("doc_id") == F.col("_id"))
    done = scored(feats, fit(train))
    return done.select("doc_id", (remainder(F.col("doc_id"), FOLDS) == HELD_OUT).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
