"""Mixing documents to target weights with soft memberships, in DataFrame functions alone.

The domains are what the table ``labels`` tells apart: ``toxic``, ``low`` (quality 0) and ``clean``.
Naive Bayes over the distinct hashed words of a text gives each document a posterior. It is fitted on a
bounded number of labelled rows a domain (about ``ROWS_A_DOMAIN``, by hash of the id); a word is evidence
only where its frequencies in two domains differ by ``SURE`` standard errors, as the sum of many words
that happen to differ would outweigh all others in long texts. That a text lacks the words of a domain
is evidence against it, too, which the sum leaves out; for it, log-odds are multiplied by ``SHARP``, priors
included. Rates are then fitted to
all documents: with r the rate, t the tokens and p the posterior of a document, the expected tokens
of domain k are S_k = sum(r t p_k), and projected gradient steps bring S to the targets T in least
squares, r <- min(max_rate, max(0, r - p . g)), where g is the residual S - T in the metric of the
domains' token matrix sum(t p p') over those whose rate isn't 0. A step needs the few sums S from one pass over documents' tokens
and posteriors, and nothing else reaches the driver; a document's rate is a function of its
posterior and the steps so far.

A target weight is a share of the mix's tokens. Unless a total is given, it is the one at which the
domain of the largest weight is kept whole. A domain that has less than its target, at the largest
rate, is asked for what it has; ``reached`` tells by how much a domain falls short. A row is kept ``copies`` times: its rate rounded up or down by a
hash of its id.

Results: a null or empty text has no tokens and the prior as its posterior; a labelled row whose
label is null counts as not having it; a domain without labelled rows gets posterior 0, without any
labels all is clean; a target for a domain without tokens can't be met and is left out, and without any target all rates
are 1; null ids
hash like a value; repeated rows get equal rates; an empty table gives an empty table.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, table, words_of

DOMAINS = ("clean", "low", "toxic")
TARGETS = {"clean": 0.98, "low": 0.01, "toxic": 0.01}
ROWS_A_DOMAIN, BUCKETS, SURE, SHARP, STEPS, CLOSE = 20_000, 1 << 16, 8.0, 4.0, 12, 1e-3
MAX_RATE = 4.0  # of the query: a domain may be repeated so often to reach its target


def unit(doc_id: Column, salt: int) -> Column:
    """A number in [0, 1) that depends on the id."""
    return F.pmod(F.xxhash64(F.lit(salt), doc_id), F.lit(1 << 30)) / F.lit(float(1 << 30))


def domain(labels: DataFrame) -> DataFrame:
    name = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "low").otherwise("clean")
    return labels.where("doc_id is not null").select(F.col("doc_id").alias("_id"), name.alias("domain"))


def word_evidence(docs: DataFrame, labels: DataFrame, rows: int = ROWS_A_DOMAIN) -> tuple[list[float], np.ndarray]:
    """Log-priors of the domains, and what a word of each bucket is evidence for a domain against the first, domain by
    bucket; three numbers a bucket are collected."""
    named = domain(labels)
    sizes = {r["domain"]: r["n"] for r in named.groupBy("domain").agg(F.count("*").alias("n")).collect()}
    total = sum(sizes.values())
    counts = np.zeros((len(DOMAINS), BUCKETS))
    if total:
        share = F.coalesce(*[F.when(F.col("domain") == d, F.lit(min(1.0, rows / n))) for d, n in sizes.items()])
        sample = named.where(unit(F.col("_id"), 11) < share)
        # an id that is labelled again and again is sampled whole, so the sample is counted before it is broadcast
        small = sample.limit(2 * rows * len(DOMAINS) + 1).count() <= 2 * rows * len(DOMAINS)
        words = docs.select("doc_id", "text").join(F.broadcast(sample) if small else sample, F.col("doc_id") == F.col("_id"))
        words = words.groupBy("domain", F.xxhash64("text")).agg(F.first("text").alias("text"))  # copies are no further evidence
        found = words.select("domain", F.explode(words_of(F.col("text"))).alias("w")).groupBy("domain", bucket(F.col("w")).alias("b")).agg(F.count("*").alias("n"))
        for r in found.collect():
            counts[DOMAINS.index(r["domain"]), r["b"]] = r["n"]
    priors = [np.log(sizes.get(d, 0) / total) if sizes.get(d) else -1e9 for d in DOMAINS] if total else [0.0, -1e9, -1e9]
    smooth = counts + 0.5
    ratio = np.log(smooth / smooth.sum(axis=1, keepdims=True))
    ratio = ratio - ratio[0]
    n = counts.sum(axis=1, keepdims=True)
    apart = np.abs(counts * n[0] - counts[0] * n)  # of equal frequencies, this is 0 on average
    return priors, np.where(apart > SURE * np.sqrt(n[0] * n * (counts + counts[0])), ratio, 0.0)


def bucket(word: Column) -> Column:
    return F.pmod(F.xxhash64(word), F.lit(BUCKETS)).cast("int")


def memberships(docs: DataFrame, evidence: tuple[list[float], np.ndarray]) -> DataFrame:
    """docs with n_tokens and the posteriors p_clean, p_low, p_toxic."""
    priors, logs = evidence
    gains = [(logs[k] - logs[0]).round(5) for k in range(1, len(DOMAINS))]
    arrays = [F.split(F.lit(",".join(f"{x:.5g}" for x in g)), ",").cast("array<double>") for g in gains]  # folded into constants
    zero = F.struct(*[F.lit(0.0).alias(f"g{k}") for k in range(len(gains))])

    def add(state: Column, w: Column) -> Column:
        at = bucket(w) + 1
        return F.struct(*[(state[f"g{k}"] + F.element_at(a, at)).alias(f"g{k}") for k, a in enumerate(arrays)])

    words = words_of(F.col("text"))
    seen = docs.withColumn("_s", F.struct(F.size(words).cast("long").alias("n"), F.aggregate(F.array_distinct(words), zero, add).alias("g")))
    odds = [F.lit(SHARP * float(priors[0]))] + [SHARP * (F.lit(float(priors[k + 1])) + F.col("_s")["g"][f"g{k}"]) for k in range(len(gains))]
    top = F.greatest(*odds)
    each = [F.exp(F.greatest(o - top, F.lit(-700.0))) for o in odds]
    whole = each[0] + each[1] + each[2]
    found = F.struct(F.col("_s")["n"].alias("n_tokens"), *[(e / whole).alias(f"p_{d}") for d, e in zip(DOMAINS, each, strict=True)])
    # generated, one row each, so that a later condition on the posteriors is not written out down to the words
    return seen.select(*docs.columns, F.inline(F.array(found)))


def rate_of(steps: list[np.ndarray], max_rate: float) -> Column:
    r: Column = F.lit(1.0)
    for g in steps:
        move = sum((F.lit(float(x)) * F.col(f"p_{d}") for x, d in zip(g, DOMAINS, strict=True)), F.lit(0.0))
        r = F.least(F.lit(float(max_rate)), F.greatest(F.lit(0.0), r - move))
    return r


def fit_rates(members: DataFrame, targets: dict[str, float] = TARGETS, total: float | None = None, max_rate: float = 1.0, steps: int = STEPS) -> list[np.ndarray]:
    """members: (n_tokens, p_*). The gradient steps that bring expected domain tokens to their targets."""
    p = [F.col(f"p_{d}") for d in DOMAINS]
    k = len(DOMAINS)

    def pass_over(done: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Expected tokens by domain, and the token matrix of the documents whose rate can still move down."""
        r = F.col("_r")
        free = F.when(r > 0, F.col("n_tokens")).otherwise(0)
        row = members.withColumn("_r", rate_of(done, max_rate)).agg(*[F.sum(r * F.col("n_tokens") * x).alias(f"s{i}") for i, x in enumerate(p)], *[F.sum(free * p[i] * p[j]).alias(f"m{i}{j}") for i in range(k) for j in range(i, k)]).first()
        return np.array([row[f"s{i}"] or 0.0 for i in range(k)]), np.array([[row[f"m{min(i, j)}{max(i, j)}"] or 0.0 for j in range(k)] for i in range(k)])

    sums, gram = pass_over([])
    if sums.sum() == 0:
        return []
    there = sums > 1e-9 * sums.sum()
    weight = np.where(there, [targets.get(d, 0.0) for d in DOMAINS], 0)
    if weight.sum() == 0:
        return []
    weight = weight / weight.sum()
    main = int(np.argmax(weight))
    goal = np.minimum(weight * (total if total is not None else sums[main] / weight[main]), max_rate * sums)
    done: list[np.ndarray] = []
    while len(done) < steps:
        residual = np.where(there, sums - goal, 0)
        if np.abs(residual).max() <= CLOSE * goal.sum():
            break
        done.append(np.linalg.pinv(gram + 1e-9 * np.trace(gram) * np.eye(k)) @ residual)
        sums, gram = pass_over(done)
    return done


def reached(mix: DataFrame, targets: dict[str, float] = TARGETS) -> DataFrame:
    """(domain, target, share, expected_tokens) of a mix: the share of its expected tokens that a domain has, beside its
    target; lower where the domain has too few at the largest rate."""
    sums = mix.agg(*[F.sum(F.col("rate") * F.col("n_tokens") * F.col(f"p_{d}")).alias(d) for d in DOMAINS])
    whole = F.expr(" + ".join(DOMAINS))
    return sums.select(F.inline(F.array(*[F.struct(F.lit(d).alias("domain"), F.lit(float(targets.get(d, 0.0))).alias("target"), (F.col(d) / whole).alias("share"), F.col(d).alias("expected_tokens")) for d in DOMAINS])))


def mixed(docs: DataFrame, labels: DataFrame, targets: dict[str, float] = TARGETS, total: float | None = None, max_rate: float = 1.0) -> DataFrame:
    """(doc_id, n_tokens, p_*, rate, copies) for each row of docs."""
    docs = docs.select("doc_id", "text")
    members = durable(memberships(docs, word_evidence(docs, labels)).drop("text"))
    r = rate_of(fit_rates(members, targets, total, max_rate), max_rate)
    return members.withColumn("rate", r).withColumn("copies", (F.floor("rate") + (unit(F.col("doc_id"), 13) < F.col("rate") - F.floor("rate")).cast("int")).cast("int"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixed(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), max_rate=MAX_RATE)


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix keeps; with a largest rate of 1, none twice. Posteriors are worked out again
    beside the texts rather than joined to them."""
    docs = docs.select("doc_id", "text", "lang", "source", "n_chars")
    members = memberships(docs, word_evidence(docs, table(spark, sf_dir, "labels")))
    r = rate_of(fit_rates(durable(members.select("n_tokens", *(f"p_{d}" for d in DOMAINS)))), 1.0)
    return members.where(unit(F.col("doc_id"), 13) < r).select(docs.columns)
