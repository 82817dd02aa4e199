"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each document becomes a short vector of counts and ratios, log- or logit-transformed towards normal
shape. Per class the mean and a covariance shrunk to its diagonal (and to a small ridge) are estimated from
all labelled rows by summed moments, so nothing but (d + 1)**2 numbers a class reaches the driver. The model
caches the inverse Cholesky factor of each class; the score is the logistic of the difference of
Mahalanobis log densities, plus the log prior ratio.

Defined cases: null text counts as empty; null labels are left out; a repeated label row counts
again; a class with fewer than two rows, or no labels at all, gives the prior alone as score; an empty
table gives an empty result; extra columns are kept.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import columns_of, fresh, small_batches, staged, table

FOLDS, HELD_OUT = 3, 1
SHRINKAGE, RIDGE = 0.3, 1e-2
#: Log-density differences are clipped here before the logistic, so no score is exactly 0 or 1.
CLIP = 30.0
FEATURES = ("words", "word_length", "capitals", "symbols", "stops", "digits", "distinct", "lines", "repeated_lines", "short_lines", "top_word", "symbol_words", "capital_words", "worst_symbols", "worst_capitals")
_SYMBOLS = np.zeros(256, bool)
_SYMBOLS[[ord(c) for c in "#$%&*!|<>{}[]=+^~@\\/_`"]] = True
_STOPS = np.zeros(256, bool)
_STOPS[[ord(c) for c in ".,;:?"]] = True
_LETTERS = np.zeros(256, bool)
_LETTERS[65:91] = _LETTERS[97:123] = _LETTERS[128:] = True


def _logit(part: float, whole: float) -> float:
    return float(np.log((part + 0.5) / (whole - part + 0.5)))


def statistics(text: str | None) -> list[float]:
    """The transformed statistics of one text, in the order of FEATURES."""
    text = text or ""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    seen = np.bincount(raw, minlength=256)
    size, letters = int(len(raw)), int(seen[_LETTERS].sum())
    words, lines = text.split(), [x for x in text.split("\n") if x]
    n, kinds = len(words), Counter(words)
    capital_words = sum(w.isupper() for w in words)
    ends = sum(w[-1] in "#$%&*!|" for w in words)
    chunk = max(1, -(-size // 8))
    parts = [raw[i : i + chunk] for i in range(0, size, chunk)] or [raw]
    worst_symbols = max(float(np.log((_SYMBOLS[p].sum() + 0.5) / (len(p) + 1.0))) for p in parts)
    worst_capitals = max(float(np.log((((p >= 65) & (p <= 90)).sum() + 0.5) / (len(p) + 1.0))) for p in parts)
    return [
        float(np.log1p(n)), float(np.log1p(size / max(n, 1))), _logit(int(seen[65:91].sum()), max(letters, int(seen[65:91].sum()))), _logit(int(seen[_SYMBOLS].sum()), size), _logit(int(seen[_STOPS].sum()), size),
        _logit(int(seen[48:58].sum()), size), float(np.log((len(kinds) + 0.5) / (n**0.9 + 0.5))), float(np.log1p(len(lines) / max(n, 1) * 10)), _logit(len(lines) - len(set(lines)), len(lines)),
        _logit(sum(len(x) < 20 for x in lines), len(lines)), _logit(max(kinds.values(), default=0), n), _logit(ends, n), _logit(capital_words, n), worst_symbols, worst_capitals,
    ]


def add_statistics(docs: DataFrame, text_col: str = "text", name: str = "stats") -> DataFrame:
    small_batches(docs.sparkSession)

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def stats(texts: pd.Series) -> pd.Series:
        return texts.map(statistics)

    return docs.withColumn(name, stats(F.col(text_col)))


@dataclass
class Discriminant:
    """Means, inverse Cholesky factors, log determinants and log priors of classes 0 and 1."""

    means: list
    factors: list
    logdets: list
    priors: list

    def score(self, x: np.ndarray) -> np.ndarray:
        if not len(x):
            return np.zeros(0)
        parts = []
        for mean, factor, logdet, prior in zip(self.means, self.factors, self.logdets, self.priors, strict=True):
            away = np.zeros(len(x)) if factor is None else (((x - mean) @ factor.T) ** 2).sum(axis=1)
            parts.append(prior - 0.5 * (away + logdet))
        return 1.0 / (1.0 + np.exp(-np.clip(parts[1] - parts[0], -CLIP, CLIP)))


def _moments(rows: DataFrame) -> dict[int, np.ndarray]:
    """Per class the matrix of summed products of (1, x); summed map-side by numpy, then by Spark."""
    d = len(FEATURES) + 1

    def summed(batches):
        for batch in batches:
            for label, part in batch.groupby("label"):
                x = np.column_stack([np.ones(len(part)), np.stack(part["stats"].to_list())])
                yield pd.DataFrame({"label": int(label), "at": np.arange(d * d), "value": (x.T @ x).ravel()})

    total = rows.mapInPandas(summed, "label int, at int, value double").groupBy("label", "at").agg(F.sum("value").alias("value"))
    out: dict[int, np.ndarray] = {}
    for row in total.collect():  # d * d numbers a class
        out.setdefault(row.label, np.zeros(d * d))[row.at] = row.value
    return {k: v.reshape(d, d) for k, v in out.items()}


def fit_discriminant(labelled: DataFrame, shrinkage: float = SHRINKAGE, ridge: float = RIDGE) -> Discriminant:
    """labelled has (stats, label); every row counts."""
    sums = _moments(labelled.where("label in (0, 1)").select("stats", F.col("label").cast("int").alias("label")))
    count = [float(sums[k][0, 0]) if k in sums else 0.0 for k in (0, 1)]
    priors = [float(np.log((c + 1.0) / (sum(count) + 2.0))) for c in count]
    if min(count) < 2:
        return Discriminant([None, None], [None, None], [0.0, 0.0], priors)
    means, factors, logdets = [], [], []
    for k in (0, 1):
        m = sums[k]
        mean = m[0, 1:] / count[k]
        cov = m[1:, 1:] / count[k] - np.outer(mean, mean)
        diagonal = np.maximum(np.diag(cov), 0.0)
        cov = (1 - shrinkage) * cov + shrinkage * np.diag(diagonal) + ridge * np.eye(len(mean))
        low = np.linalg.cholesky(cov)
        means.append(mean)
        factors.append(np.linalg.inv(low))
        logdets.append(float(2 * np.log(np.diag(low)).sum()))
    return Discriminant(means, factors, logdets, priors)


def held_out(id_col: str = "doc_id"):
    """True for the fold that is never learned from."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % FOLDS == HELD_OUT, F.lit(False))


def add_score(df: DataFrame, model: Discriminant, stats: str = "stats", name: str = "score") -> DataFrame:
    @F.pandas_udf("double")
    def score(batch: pd.Series) -> pd.Series:
        return pd.Series(model.score(np.stack(batch.to_list())) if len(batch) else np.zeros(0))

    return df.withColumn(name, score(F.col(stats)))


def training_rows(stats: DataFrame, labels: DataFrame) -> DataFrame:
    learned = labels.where(~held_out() & F.col("quality").isNotNull()).select(F.col("doc_id").alias("l_id"), F.col("quality").alias("label"))
    return stats.join(learned, F.col("doc_id") == F.col("l_id")).select("stats", "label")


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of every document; the statistics are taken once."""
    stats = staged(add_statistics(docs.select("doc_id", "text")).select("doc_id", "stats"), "statistics")
    scored = add_score(stats, fit_discriminant(training_rows(stats, labels)))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_quality(docs: DataFrame, labels: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows of docs that score `least` or more, columns as they were.

    The statistics are taken twice, once to learn and once to score, so that no text is shuffled or stored.
    """
    learn = staged(add_statistics(docs.select("doc_id", "text")).select("doc_id", "stats"), "statistics")
    model = fit_discriminant(training_rows(learn, labels))
    stats, score = fresh("stats", docs.columns), fresh("score", docs.columns)
    scored = add_score(add_statistics(docs, "text", stats), model, stats, score)
    return scored.where(F.col(score) >= least).select(*columns_of(docs))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
