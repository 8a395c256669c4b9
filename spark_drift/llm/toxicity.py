"""Toxicity from positive and unlabelled text.

A linear classifier on hashed indicators of word beginnings learns from confirmed toxic
documents and from documents taken without their labels. The risk of calling
unlabelled text toxic is corrected by the class prior: the positives hidden in it are
subtracted with the weight of their share. Where that difference turns negative, the
model has begun to fit the positives' absence from the unlabelled sample, and the
step goes the other way (the non-negative estimator). Logistic loss, proximal steps
with an L1 threshold, so that most n-grams get no weight at all.

The prior is the share of toxic rows among the labels outside the held-out fold. At
most ``positives`` and ``unlabelled`` documents, and ``samples.SAMPLE_BYTES`` of text of each, chosen by
id digest, are sampled, none of them held out; an id that several rows share is drawn once. Scoring reads whole texts of all rows.

Edge cases: null and empty texts get the score of no indicator at all; without
confirmed positives every score is the prior's; repeated rows repeat; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.llm.batches import slices, texts
from spark_drift.llm.ngrams import SIZE, Rows, feature_rows, stem_indicators
from spark_drift.llm.samples import bounded, drawn, held_out, labelled

PARTS, PART = 5, 0


@dataclass
class Linear:
    weights: np.ndarray
    bias: float

    def score(self, margin: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(margin + self.bias, -40, 40)))


def corrected_risk(z_pos: np.ndarray, z_unl: np.ndarray, prior: float) -> tuple[float, float]:
    """Positive part and prior-corrected negative part of the logistic risk."""
    loss = lambda z: np.logaddexp(0.0, -z)
    return float(prior * loss(z_pos).mean()), float(loss(-z_unl).mean() - prior * loss(-z_pos).mean())


def fit_pu(rows: Rows, prior: float, rounds: int = 120, rate: float = 2.0, l1: float = 2e-4, screen: float = 3.0) -> Linear:
    """Accelerated proximal descent on the non-negative risk. ``rows.y``: 1 confirmed, 0 unlabelled."""
    pos = rows.y == 1
    prior = min(max(prior, 1e-3), 0.5)
    bias = float(np.log(prior / (1 - prior)))
    if not pos.any() or pos.all():
        return Linear(np.zeros(SIZE, np.float32), bias)
    # screening: n-grams whose share differs between the samples beyond chance
    p1, p0 = rows.spread(pos / pos.sum()), rows.spread(~pos / (~pos).sum())
    error = np.sqrt(p1 * (1 - p1) / pos.sum() + p0 * (1 - p0) / (~pos).sum())
    seen = np.bincount(rows.values, minlength=SIZE) >= 5
    rows.only(seen & (np.abs(p1 - p0) > screen * error))
    a = np.where(pos, 1.0 / pos.sum(), 0.0)
    b = np.where(pos, 0.0, 1.0 / (~pos).sum())
    w, v, c = np.zeros(SIZE), np.zeros(SIZE), bias
    for t in range(rounds):
        z = rows.dot(v) + c
        p = 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))
        _, negative = corrected_risk(z[pos], z[~pos], prior)
        up = prior * a * (p - 1)
        down = (b - prior * a) * p
        slope = up + down if negative >= 0 else -down
        grad = rows.spread(slope)
        new = v - rate * grad
        new = np.sign(new) * np.maximum(np.abs(new) - rate * l1, 0.0)
        c -= 0.25 * rate * slope.sum()
        v = new + t / (t + 3) * (new - w)
        w = new
    return Linear(w.astype(np.float32), c)


def fit_toxicity(docs: DataFrame, labels: DataFrame, positives: int = 2000, unlabelled: int = 6000) -> Linear:
    good = labels.where(F.col("toxic").isNotNull() & ~held_out(F.col("doc_id"), PARTS, PART))
    prior = good.agg(F.avg((F.col("toxic") == 1).cast("double"))).first()[0] or 0.0
    confirmed = labelled(docs, labels.where("toxic = 1"), "toxic", positives, PARTS, PART)
    ids = docs.where(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), PARTS, PART))
    ids = drawn(ids.select(F.col("doc_id").cast("long").alias("doc_id")).distinct(), unlabelled, "unlabelled")
    plain = bounded(docs, ids, "unlabelled").select(F.lit(0).alias("y"), "text")
    sample = confirmed.select(F.lit(1).alias("y"), "text").union(plain)
    return fit_pu(Rows(sample.mapInArrow(feature_rows("stems"), "y int, x array<int>").toArrow()), prior)


def score_documents(docs: DataFrame, model: Linear) -> DataFrame:
    """``doc_id, held_out, score, predicted`` for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model = sent.value
        for part in slices(batches, "text"):
            margins = np.array([model.weights[stem_indicators(x)].sum(dtype=np.float64) for x in texts(part)])
            yield pa.RecordBatch.from_arrays(
                [part.column(0), part.column(1), pa.array(model.score(margins))], names=["doc_id", "held_out", "score"]
            )

    lean = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        held_out(F.col("doc_id"), PARTS, PART).alias("held_out"),
        F.col("text").cast("string").alias("text"),
    )
    scored = lean.mapInArrow(run, "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
