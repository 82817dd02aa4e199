"""Supervised baselines: labels from open tickets, balanced samples, and MLlib classifiers tuned on a later period."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import ratio


def label_from_tickets(df: DataFrame, tickets: DataFrame, period_end: str) -> DataFrame:
    """df with label 1 where a ticket of the account is open (created <= ts <= closed), else 0.

    Tickets without closing time stay open to period_end. The range join goes by day buckets: a ticket is spread over
    the days it is open, a record has one day.
    """
    close = F.coalesce("closed", F.lit(period_end).cast("timestamp_ntz"))
    open_days = tickets.select("account", "created", close.alias("closed")).where("closed >= created")
    spread = open_days.withColumn("day", F.explode(F.sequence(F.to_date("created"), F.to_date("closed"))))
    rows = df.select("rec_id", "account", "ts", F.to_date("ts").alias("day"))
    hit = rows.join(spread, ["account", "day"]).where((F.col("ts") >= F.col("created")) & (F.col("ts") <= F.col("closed"))).select("rec_id").distinct()
    return df.join(hit.withColumn("label", F.lit(1)), "rec_id", "left").withColumn("label", F.coalesce("label", F.lit(0)))


def balance(labelled: DataFrame, seed: int = 1, key: str = "rec_id") -> DataFrame:
    """All rows of the rarer label and about as many of the other, by a hash threshold and no global sort."""
    counts = {r["label"]: r["n"] for r in labelled.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    least = min(counts.get(0, 0), counts.get(1, 0))
    draw = F.conv(F.substring(F.md5(F.concat_ws(":", F.col(key), F.lit(seed))), 1, 8), 16, 10).cast("double") / F.lit(float(2**32))
    keep = F.lit(False)
    for label, n in counts.items():
        keep = keep | ((F.col("label") == label) & (draw < F.lit(least / n if n else 0.0)))
    return labelled.where(keep)


def _fourier(size: int, inputs: int, gamma: float, seed: int):
    """Random Fourier features of an array column: a nonlinear kernel for a linear machine."""
    rng = np.random.default_rng(seed)
    weights, phase = rng.normal(0, math.sqrt(2 * gamma), (inputs, size)), rng.uniform(0, 2 * math.pi, size)

    @F.pandas_udf("array<double>")
    def mapped(batch: pd.Series) -> pd.Series:
        x = np.stack(batch.to_list()) if len(batch) else np.zeros((0, inputs))
        return pd.Series(list(math.sqrt(2.0 / size) * np.cos(x @ weights + phase)), dtype=object)

    return mapped


def standardise(df: DataFrame, features: Sequence[str], train: DataFrame) -> DataFrame:
    """Features centred and scaled by the training rows; nulls become the training mean."""
    row = train.agg(*[F.avg(f).alias(f"m{i}") for i, f in enumerate(features)], *[F.stddev_pop(f).alias(f"s{i}") for i, f in enumerate(features)]).first()
    put = {f: (F.coalesce(F.col(f), F.lit(row[f"m{i}"] or 0.0)) - F.lit(row[f"m{i}"] or 0.0)) / F.lit(row[f"s{i}"] or 1.0) for i, f in enumerate(features)}
    return df.withColumns(put)


#: Settings tried per method: the same number for each, so none is tuned longer than another.
GRIDS = {
    "tree": [{"maxDepth": d} for d in (3, 5, 8)],
    "forest": [{"maxDepth": d, "numTrees": 20} for d in (3, 5, 8)],
    "svm": [{"regParam": r, "maxIter": 30} for r in (0.001, 0.01, 0.1)],
    "svm_fourier": [{"regParam": r, "maxIter": 30} for r in (0.001, 0.01, 0.1)],
}


def train_and_predict(kind: str, train: DataFrame, valid: DataFrame, score: DataFrame, features: Sequence[str], seed: int = 1) -> tuple[DataFrame, list[dict]]:
    """score with abnormal from the best setting of the method by F1 on `valid`, and what every setting reached.

    train and valid carry label; valid is a later period, not a random split.
    """
    from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, RandomForestClassifier
    from pyspark.ml.functions import array_to_vector

    makers = {"tree": lambda o: DecisionTreeClassifier(seed=seed, **o), "forest": lambda o: RandomForestClassifier(seed=seed, **o), "svm": lambda o: LinearSVC(**o), "svm_fourier": lambda o: LinearSVC(**o)}
    packed = F.array(*[F.col(f) for f in features])
    value = array_to_vector(_fourier(64, len(features), 0.1, seed)(packed) if kind == "svm_fourier" else packed)
    train_v, valid_v, score_v = (standardise(x, features, train).withColumn("__vector", value) for x in (train, valid, score))
    train_v = train_v.select(F.col("label").cast("double").alias("label"), "__vector").persist()
    valid_v = valid_v.select("label", "__vector").persist()
    tried, best = [], None
    for options in GRIDS[kind]:
        model = makers[kind](options).setFeaturesCol("__vector").setLabelCol("label").fit(train_v)
        hit = model.transform(valid_v).agg(F.sum(F.when((F.col("prediction") == 1) & (F.col("label") == 1), 1).otherwise(0)).alias("tp"), F.sum((F.col("prediction") == 1).cast("int")).alias("p"), F.sum((F.col("label") == 1).cast("int")).alias("t")).first()
        f1 = 2 * (hit["tp"] or 0) / max(1, (hit["p"] or 0) + (hit["t"] or 0))
        tried.append({**options, "f1": f1})
        if best is None or f1 > best[0]:
            best = (f1, model)
    train_v.unpersist()
    valid_v.unpersist()
    original = score.columns
    out = best[1].transform(score_v)
    verdict = out.select("rec_id", (F.col("prediction") == 1).alias("abnormal"))
    return score.join(verdict, "rec_id").select(*original, "abnormal"), tried


def self_train(labelled: DataFrame, unlabelled: DataFrame, score: DataFrame, features: Sequence[str], sure: float = 0.9, rounds: int = 2, seed: int = 1) -> DataFrame:
    """score with abnormal, by a tree that after each round also learns from the unlabelled rows it is sure about, balanced
    anew; labels of `unlabelled` are not read."""
    from pyspark.ml.classification import DecisionTreeClassifier
    from pyspark.ml.functions import array_to_vector, vector_to_array

    start = balance(labelled)
    packed = array_to_vector(F.array(*[F.col(f) for f in features]))
    ready = lambda x: standardise(x, features, start).withColumn("__vector", packed)
    known = ready(start).select("rec_id", F.col("label").cast("double").alias("label"), "__vector")
    others = ready(unlabelled).select("rec_id", "__vector")
    fit = lambda rows: DecisionTreeClassifier(maxDepth=5, seed=seed, featuresCol="__vector").fit(rows)
    model = fit(known)
    for _ in range(rounds):
        chance = F.element_at(vector_to_array("probability"), 2)
        guessed = model.transform(others).withColumn("p", chance).where((F.col("p") >= sure) | (F.col("p") <= 1 - sure))
        more = guessed.select("rec_id", (F.col("p") >= sure).cast("double").alias("label"), "__vector")
        model = fit(known.unionByName(balance(more, seed)))
    out = model.transform(ready(score)).select("rec_id", (F.col("prediction") == 1).alias("abnormal"))
    return score.join(out, "rec_id")


def label_quality(verdicts: DataFrame) -> DataFrame:
    """(tp, predicted, positive, precision, recall) of verdicts that carry label."""
    row = verdicts.agg(F.sum((F.col("abnormal") & (F.col("label") == 1)).cast("int")).alias("tp"), F.sum(F.col("abnormal").cast("int")).alias("predicted"), F.sum((F.col("label") == 1).cast("int")).alias("positive"))
    return row.select("*", ratio(F.col("tp"), F.col("predicted")).alias("precision"), ratio(F.col("tp"), F.col("positive")).alias("recall"))
