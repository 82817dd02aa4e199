"""Learned baselines and the comparison of all methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.naming import feature_grid
from ..operators import features as FE
from ..operators import learned as L
from ..sources import adapters as A
from ..sources.staging import staged
from . import experiments as E
from . import oracle as O
from .base import END, TRAIN_DAYS, net, tel
from .book import query

VALID_DAYS = 13
#: Smoothed inputs of the learned baselines: every metric, windows of one and two days.
EXTRA = feature_grid(A.METRICS, (1, 2), ())

LABELS = f"SELECT rec_id, EXISTS (SELECT 1 FROM tkt k WHERE k.is_network AND k.account = t.account AND k.created <= t.ts AND t.ts <= coalesce(k.closed, {O.END}))::INT AS label FROM tel t"


@query("b_label", f"WITH {O.BASE} {LABELS}")
def b_label(s, d):
    return L.label_from_tickets(tel(s, d), net(s, d), END).select("rec_id", "label")


@query("b_balance", f"""WITH {O.BASE}, l AS ({LABELS}), c AS (SELECT label, count(*) AS n FROM l GROUP BY label),
drawn AS (SELECT rec_id, l.label, ('0x' || substr(md5(l.rec_id || ':1'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS draw, (SELECT CASE WHEN count(*) = 2 THEN min(n) ELSE 0 END FROM c) / c.n AS share FROM l JOIN c ON c.label = l.label)
SELECT label, count(*) AS n FROM drawn WHERE draw < share GROUP BY label""")
def b_balance(s, d):
    """Rows of each label in the balanced sample."""
    return L.balance(L.label_from_tickets(tel(s, d), net(s, d), END)).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def labelled(s, d):
    """Labelled records with the inputs, computed once for all the passes of a learner."""
    return staged(FE.build_features(L.label_from_tickets(tel(s, d), net(s, d), END), EXTRA, A.POINTS_PER_DAY), "labelled")


def learned(s, d, kind: str):
    """Quality against the ticket labels of the test days; trained on the first days, tuned on the next."""
    rows = labelled(s, d)
    day = F.col("day")
    train, valid, test = rows.where(day < VALID_DAYS), rows.where((day >= VALID_DAYS) & (day < TRAIN_DAYS)), rows.where(day >= TRAIN_DAYS)
    scored, _ = L.train_and_predict(kind, L.balance(train), valid, test, [*A.METRICS, *[f.column for f in EXTRA]])
    return L.label_quality(scored)


@query("b_tree")
def b_tree(s, d):
    return learned(s, d, "tree")


@query("b_forest")
def b_forest(s, d):
    return learned(s, d, "forest")


@query("b_svm")
def b_svm(s, d):
    return learned(s, d, "svm")


@query("b_svm_fourier")
def b_svm_fourier(s, d):
    return learned(s, d, "svm_fourier")


@query("b_self_training")
def b_self_training(s, d):
    """Extension: a tree that learns from a few labelled days and then from its own confident verdicts on the others."""
    rows = labelled(s, d)
    day = F.col("day")
    scored = L.self_train(rows.where(day < 7), rows.where((day >= 7) & (day < TRAIN_DAYS)), rows.where(day >= TRAIN_DAYS), [*A.METRICS, *[f.column for f in EXTRA]])
    return L.label_quality(scored)


@query("q_methods")
def q_methods(s, d):
    """All methods side by side: thresholds and windows from the first 19 days, measures on the rest."""
    return E.compare_methods(tel(s, d), net(s, d), END, TRAIN_DAYS, VALID_DAYS)


@query("q_seconds")
def q_seconds(s, d):
    """Seconds that each method takes to learn and to score all records."""
    return E.timed_methods(tel(s, d), net(s, d), END, TRAIN_DAYS, VALID_DAYS)
