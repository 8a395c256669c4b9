"""Quality classifier: naive Bayes features under a linear support vector machine.

Indicators of byte trigrams, word beginnings and repetition are scaled by the log ratio of
their smoothed frequencies in the two classes; rows are brought to unit length. The
machine, with hinge loss and an L2 term, is fitted by dual coordinate descent: each
visit of a row solves its dual variable exactly and updates the weights of its
indicators. A logistic curve through the margins turns them into scores.

At most ``limit`` labelled documents and ``samples.SAMPLE_BYTES`` of their text, chosen by id
digest and none held out, are sampled; an id that several rows share is drawn once. Scoring reads whole texts of all rows.

Edge cases: null and empty texts have the bias alone as their margin; without both
classes every score is the share of class 1; repeated rows repeat; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.llm.batches import slices, texts
from spark_drift.llm.ngrams import SIZE, Rows, feature_rows, phrase_indicators
from spark_drift.llm.samples import held_out, labelled

PARTS, PART = 5, 0


def log_count_ratio(rows: Rows, smooth: float = 1.0) -> np.ndarray:
    """log of each indicator's share in class 1 over its share in class 0."""
    one = rows.y == 1
    p = smooth + rows.spread(one.astype(np.float64))
    q = smooth + rows.spread((~one).astype(np.float64))
    seen = np.bincount(rows.values, minlength=SIZE) > 0
    return np.where(seen, np.log((p / (one.sum() + 2 * smooth)) / (q / ((~one).sum() + 2 * smooth))), 0.0)


def dual_descent(rows: Rows, scale: np.ndarray, cost: float = 1.0, rounds: int = 12, seed: int = 3) -> tuple[np.ndarray, float, np.ndarray]:
    """Weights (on scaled unit rows) and bias of the hinge-loss machine, and its dual variables."""
    n = len(rows)
    sign = np.where(rows.y == 1, 1.0, -1.0)
    # both classes weigh the same
    bound = cost * np.where(sign > 0, n / (2.0 * max((sign > 0).sum(), 1)), n / (2.0 * max((sign < 0).sum(), 1)))
    data = [scale[rows.row(k)] for k in range(n)]
    sizes = [float(np.sqrt((d * d).sum())) or 1.0 for d in data]
    data = [d / s for d, s in zip(data, sizes, strict=True)]
    own = np.array([float((d * d).sum()) + 1.0 for d in data])
    alpha, w, bias = np.zeros(n), np.zeros(SIZE), 0.0
    random = np.random.Generator(np.random.PCG64(seed))
    for _ in range(rounds):
        moved = 0.0
        for k in random.permutation(n):
            at, d, s = rows.row(k), data[k], sign[k]
            slope = s * (float(w[at] @ d) + bias) - 1.0
            new = min(max(alpha[k] - slope / own[k], 0.0), bound[k])
            step = (new - alpha[k]) * s
            if step:
                w[at] += step * d
                bias += step
                moved = max(moved, abs(step))
                alpha[k] = new
        if moved < 1e-3:
            break
    return w, bias, alpha


def calibrate(margin: np.ndarray, y: np.ndarray, rounds: int = 60) -> tuple[float, float]:
    """Slope and intercept of a logistic curve through margins, classes weighing the same."""
    n1, n0 = max((y == 1).sum(), 1), max((y == 0).sum(), 1)
    weight = np.where(y == 1, 0.5 / n1, 0.5 / n0)
    # targets a little inside 0 and 1, as for separable margins the slope has no end
    want = np.where(y == 1, (n1 + 1.0) / (n1 + 2.0), 1.0 / (n0 + 2.0))
    theta = np.array([1.0, 0.0])
    x = np.stack([margin, np.ones_like(margin)], axis=1)
    for _ in range(rounds):
        p = 1.0 / (1.0 + np.exp(-np.clip(x @ theta, -40, 40)))
        grad = x.T @ (weight * (p - want))
        hess = (x * (weight * p * (1 - p))[:, None]).T @ x + 1e-9 * np.eye(2)
        move = np.linalg.solve(hess, grad)
        theta -= move * min(1.0, 2.0 / max(float(np.abs(move).max()), 1e-9))
    return float(theta[0]), float(theta[1])


@dataclass
class Machine:
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    slope: float
    intercept: float

    def margin(self, places: np.ndarray) -> float:
        scaled = self.scale[places]
        size = float(np.sqrt((scaled * scaled).sum())) or 1.0
        return float(scaled @ self.weights[places]) / size + self.bias

    def score(self, margin: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.slope * margin + self.intercept, -40, 40)))


def fit_machine(rows: Rows) -> Machine:
    one = float((rows.y == 1).mean()) if len(rows) else 0.5
    zero = np.zeros(SIZE, np.float32)
    if not 0.0 < one < 1.0:
        share = min(max(one, 1e-3), 1 - 1e-3)
        return Machine(zero, zero, 0.0, 0.0, float(np.log(share / (1 - share))))
    rows.only(np.bincount(rows.values, minlength=SIZE) >= 3)
    scale = log_count_ratio(rows)
    weights, bias, _ = dual_descent(rows, scale)
    machine = Machine(scale.astype(np.float32), weights.astype(np.float32), bias, 1.0, 0.0)
    margins = np.array([machine.margin(rows.row(k)) for k in range(len(rows))])
    machine.slope, machine.intercept = calibrate(margins, rows.y)
    return machine


def fit_quality(docs: DataFrame, labels: DataFrame, limit: int = 6000) -> Machine:
    sample = labelled(docs, labels, "quality", limit, PARTS, PART).select("y", "text")
    return fit_machine(Rows(sample.mapInArrow(feature_rows("pieces"), "y int, x array<int>").toArrow()))


def score_documents(docs: DataFrame, machine: Machine, threshold: float = 0.3) -> DataFrame:
    """``doc_id, held_out, score, predicted`` for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(machine)

    def run(batches):
        machine = sent.value
        for part in slices(batches, "text"):
            margins = np.array([machine.margin(phrase_indicators(x)) for x in texts(part)])
            yield pa.RecordBatch.from_arrays(
                [part.column(0), part.column(1), pa.array(machine.score(margins))], names=["doc_id", "held_out", "score"]
            )

    lean = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        held_out(F.col("doc_id"), PARTS, PART).alias("held_out"),
        F.col("text").cast("string").alias("text"),
    )
    scored = lean.mapInArrow(run, "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
