"""Quality classifier with hierarchical empirical Bayes over sites.

Three levels of evidence meet in log odds:

* the document: a logistic regression over surface features of the whole text
  (character classes, shouting, table bars, symbol tails, repeated lines and
  words, word lengths), fitted on a bounded sample of labelled rows;
* the site (``source``) and the path below it (``source`` and ``lang``): beta
  posteriors of the share of good documents. A site's evidence is the sum of
  the classifier's probabilities over all its documents; the
  prior of a path is its site's posterior and the prior of a site is the
  global share, with strengths from the method of moments, so sparse sites
  shrink to what is known above them. A document's own part is left out of the
  posteriors that it meets, so nothing counts twice.

The documents' ``source`` stands for the host and ``lang`` for the path, as the
table has no urls.

Sites are aggregated before the shuffle, so a hot source is one row a task. The
only things that reach the driver are the sample's features (about
``SAMPLE`` rows) and a few global moments.

Defined results: a null or empty text has all features 0 and is judged by its
site; a null source or lang is a site of its own; repeated rows are judged
alike; without usable labels the classifier is silent and every document keeps
the prior share of 1/2 or the labels' share, so nothing is rejected below it.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import cut, map_slices, stored

#: Labelled rows that the regression is fitted on, about; a share of all by a hash of their id, at most 1.2 times as many.
SAMPLE = 10_000
#: A document is rejected if its probability of being good is below this.
KEEP_FROM = 0.5
#: How much a site may move the log odds of a document.
SITE_WEIGHT = 0.5

NAMES = ("log_words", "symbols", "upper", "digits", "bars", "word_length", "long_words", "symbol_tails", "repeated_words", "repeated_lines", "line_length", "stops", "first_upper", "half_repeat", "commas")
_CLASS = bytes(1 if 97 <= b <= 122 or b >= 128 else 2 if 65 <= b <= 90 else 3 if 48 <= b <= 57 else 4 if b in (32, 9, 10, 11, 12, 13) else 5 if b in b".,;:'\"-()" else 6 for b in range(256))
_TAIL = re.compile(rb"[^\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f][^\w\s.,;:'\"()\x80-\xff-]{2,}(?=\s|\Z)")


def features(text: bytes) -> list[float]:
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    kinds = np.bincount(np.frombuffer(text.translate(_CLASS), np.uint8), minlength=7)
    solid = max(1, len(text) - int(kinds[4]))
    lines = [x for x in text.split(b"\n") if x.strip()]
    repeated = sum(map(len, lines)) - sum(map(len, set(lines)))
    half = n // 2
    return [
        math.log1p(n),
        kinds[6] / solid,
        kinds[2] / max(1, int(kinds[1] + kinds[2])),
        kinds[3] / solid,
        text.count(b"|") / n,
        solid / n / 10,
        sum(1 for w in words if len(w) > 24) / n,
        len(_TAIL.findall(text)) / n,
        1 - len(set(words)) / n,
        repeated / len(text),
        math.log1p(len(text) / max(1, len(lines))) / 10,
        (text.count(b".") + text.count(b"!") + text.count(b"?")) / n,
        sum(1 for w in words if 65 <= w[0] <= 90) / n,
        float(n >= 8 and words[:half] == words[half : 2 * half]) + sum(1 for a, b in zip(words, words[20:], strict=False) if a == b) / n,
        text.count(b",") / n,
    ]


def with_features(documents: DataFrame) -> DataFrame:
    """doc_id, source, lang and x, the features of the whole text."""

    def make():
        def work(part):
            x = [features(b or b"") for b in part.column("body").to_pylist()]
            return {c: part.column(c) for c in ("doc_id", "source", "lang")} | {"x": x}

        return work

    kinds = dict(documents.dtypes)
    source = documents.select("doc_id", "source", "lang", F.col("text").cast("binary").alias("body"))
    return map_slices(source, "body", make, "".join(f"{c} {kinds[c]}, " for c in ("doc_id", "source", "lang")) + "x array<double>")


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    share: float

    def logit(self, x: np.ndarray) -> np.ndarray:
        """Log odds of being good."""
        return np.clip((x - self.mean) / self.scale, -6, 6) @ self.weights + self.bias


def fit(x: np.ndarray, y: np.ndarray, penalty: float = 1.0, rounds: int = 30) -> Model:
    """Logistic regression by reweighted least squares with a ridge."""
    n = len(y)
    share = (y.sum() + 1) / (n + 2)
    zero = Model(np.zeros(len(NAMES)), np.ones(len(NAMES)), np.zeros(len(NAMES)), math.log(share / (1 - share)), float(share))
    if not 0 < y.sum() < n:
        return zero
    mean, scale = x.mean(0), x.std(0) + 1e-6
    z = np.hstack([np.clip((x - mean) / scale, -6, 6), np.ones((n, 1))])
    w = np.zeros(z.shape[1])
    ridge = np.diag([penalty] * (z.shape[1] - 1) + [1e-6])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve(z.T @ (z * np.maximum(p * (1 - p), 1e-6)[:, None]) + ridge, z.T @ (y - p) - ridge @ w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return Model(mean, scale, w[:-1], float(w[-1]), float(share))


def train(featured: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Fits on a share of the labelled rows; the share is taken before the join, so no task sends more than its part of it."""
    marked = labels.filter("quality IS NOT NULL").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    share = min(1.0, sample / max(1, labels.count()))
    chosen = marked.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int(share * (1 << 20)))
    rows = featured.select("doc_id", "x").join(chosen, "doc_id").select("x", "quality", F.xxhash64("doc_id", "x").alias("draw")).orderBy("draw", "quality").limit(int(1.2 * sample)).collect()
    x = np.array([r.x for r in rows], float).reshape(-1, len(NAMES))
    return fit(x, np.array([r.quality for r in rows], float))


def scored(featured: DataFrame, model: Model) -> DataFrame:
    """Adds the classifier's log odds and probability."""

    def logits(batches):
        for batch in batches:
            flat = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, len(NAMES))
            z = model.logit(flat)
            columns = [batch.column(c) for c in ("doc_id", "source", "lang")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(z), pa.array(1 / (1 + np.exp(-z)))], names=["doc_id", "source", "lang", "evidence", "p"])

    kinds = dict(featured.dtypes)
    return featured.mapInArrow(logits, "".join(f"{c} {kinds[c]}, " for c in ("doc_id", "source", "lang")) + "evidence double, p double")


def strength(groups: DataFrame, n: str, share: str) -> float:
    """Prior strength by the method of moments over groups with ``n`` documents: between-group against binomial variance."""
    r = groups.filter(f"{n} > 1").agg(
        F.sum(n).alias("n"), F.sum(F.col(n) * F.col(share)).alias("s"), F.sum(F.col(n) * F.col(share) * F.col(share)).alias("q"), F.sum(F.col(n) * F.col(n)).alias("nn"), F.count(F.lit(1)).alias("k")
    ).first()
    if not r.k or r.k < 2:
        return 10.0
    mean = r.s / r.n
    spread = mean * (1 - mean)
    if spread <= 0:
        return 1000.0
    within = (r.k - 1) * spread
    size = r.n - r.nn / r.n
    between = max(0.0, (r.q - r.n * mean * mean - within) / max(1e-9, size))
    return float(min(1000.0, max(2.0, spread / between - 1))) if between > 0 else 1000.0


@dataclass
class Prior:
    """Global share of good documents and the prior strengths of sites and paths."""

    share: float
    site: float
    path: float


def learn(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> tuple[Model, DataFrame, DataFrame, Prior]:
    """(classifier, its evidence for each row, evidence sums by source and lang, prior)."""
    featured = cut(with_features(documents))
    model = train(featured, labels, sample)
    rows = cut(scored(featured, model))
    paths = cut(rows.groupBy("source", "lang").agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum("p").alias("good")))
    sites = paths.groupBy("source").agg(F.sum("n").alias("site_n"), F.sum("good").alias("site_good")).withColumn("site_share", F.col("site_good") / F.col("site_n"))
    total = sites.agg(F.sum("site_n").alias("n"), F.sum("site_good").alias("good")).first()
    share = (total.good / total.n) if total.n else model.share
    share = min(max(share, 1e-3), 1 - 1e-3)
    m_site = strength(sites, "site_n", "site_share")
    m_path = strength(paths.withColumn("share", F.col("good") / F.col("n")), "n", "share")
    levels = paths.withColumnRenamed("source", "_s").join(sites.select(F.col("source").alias("_t"), "site_n", "site_good"), F.col("_s").eqNullSafe(F.col("_t")))
    levels = levels.select("_s", F.col("lang").alias("_l"), F.col("n").alias("_n"), F.col("good").alias("_good"), F.col("site_n").alias("_site_n"), F.col("site_good").alias("_site_good"))
    # a written table has a size that the planner knows, so it is broadcast only while it is small
    return model, rows, stored(levels), Prior(share, m_site, m_path)


def combined(rows: DataFrame, levels: DataFrame, prior: Prior, own) -> DataFrame:
    """Adds the posteriors, quality and the decision to rows with source, lang and evidence. own: what the row itself adds to its site."""
    out = rows.join(levels, F.col("source").eqNullSafe(F.col("_s")) & F.col("lang").eqNullSafe(F.col("_l")))
    site = (F.greatest(F.col("_site_good") - own, F.lit(0.0)) + prior.site * prior.share) / (F.col("_site_n") - 1 + prior.site)
    path = (F.greatest(F.col("_good") - own, F.lit(0.0)) + prior.path * F.col("site_posterior")) / (F.col("_n") - 1 + prior.path)
    out = out.withColumn("site_posterior", site).withColumn("path_posterior", path)
    bounded = F.least(F.greatest("path_posterior", F.lit(1e-4)), F.lit(1 - 1e-4))
    logit = F.col("evidence") + F.lit(SITE_WEIGHT) * (F.log(bounded / (1 - bounded)) - F.lit(math.log(prior.share / (1 - prior.share))))
    out = out.drop("_s", "_l", "_n", "_good", "_site_n", "_site_good")
    return out.withColumn("quality", 1 / (1 + F.exp(-logit))).withColumn("keep", F.col("quality") >= KEEP_FROM)


def classify(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, source, lang, evidence, site_posterior, path_posterior, quality (probability of being good), keep."""
    _, rows, levels, prior = learn(documents, labels, sample)
    return combined(rows, levels, prior, F.col("p")).select("doc_id", "source", "lang", "evidence", "site_posterior", "path_posterior", "quality", "keep")


def keep_good(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """The documents that are kept, with all their columns; their texts are read again instead of being shuffled."""
    model, _, levels, prior = learn(documents, labels, sample)

    names = documents.columns
    own = ("evidence", "quality", "keep", "site_posterior", "path_posterior", "_s", "_l", "_n", "_good", "_site_n", "_site_good")
    taken = {c: f"_in_{i}" for i, c in enumerate(names) if c in own}
    inputs = documents.withColumnsRenamed(taken)
    kinds = dict(inputs.dtypes)

    def make():
        def work(part):
            x = np.array([features(b or b"") for b in part.column("text").cast(pa.binary()).to_pylist()])
            return {c: part.column(c) for c in kinds} | {"evidence": model.logit(x.reshape(-1, len(NAMES)))}

        return work

    rows = map_slices(inputs, "text", make, "".join(f"`{c}` {k}, " for c, k in kinds.items()) + "evidence double")
    kept = combined(rows, levels, prior, 1 / (1 + F.exp(-F.col("evidence")))).filter("keep").drop(*own)
    return kept.withColumnsRenamed({v: k for k, v in taken.items()}).select(*names)
