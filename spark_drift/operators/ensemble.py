"""Weighted ensembles of base learners: training, votes, weights, scripted adaptation."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.plans.lineage import cut


@dataclass(frozen=True)
class LinearMachines:
    """Linear support vector machines, one against the rest for each class that was met; predicts in
    generated expressions: the class with the largest value, ties to the smallest."""

    features: list[str]
    classes: list[int]
    weights: np.ndarray  # (classes, 1 + features), the intercept first

    def transform(self, rows: DataFrame) -> DataFrame:
        each = []
        for c, w in zip(self.classes, self.weights, strict=True):
            value = F.lit(float(w[0]))
            for name, v in zip(self.features, w[1:], strict=True):
                value = value + F.col(name).cast("double") * F.lit(float(v))
            each.append(F.struct(value.alias("value"), F.lit(-c).alias("class")))
        return rows.withColumn("pred_", (-F.array_max(F.array(*each))["class"]).cast("double"))


def fit_machines(rows: DataFrame, features: list[str], label: str, ridge: float = 1e-3, rounds: int = 25, tol: float = 1e-6) -> LinearMachines:
    """Newton steps on the squared hinge loss of all classes at once: one job a round, whose sums (a
    gradient and a Hessian per class) are added on the executors. A single class is always predicted."""
    lean = cut(rows.where(F.col(label).isNotNull()).select(F.array(*[F.col(c).cast("double") for c in features]).alias("x"), F.col(label).cast("int").alias("y")))
    counts = {r["y"]: r["n"] for r in lean.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    classes, d = sorted(counts), len(features) + 1
    w = np.zeros((len(classes), d))
    if len(classes) < 2:
        return LinearMachines(features, classes or [0], w if classes else np.zeros((1, d)))
    known, n = np.array(classes), sum(counts.values())

    def sums(w: np.ndarray) -> np.ndarray:
        def run(batches):
            total = np.zeros((len(classes), d + d * d))
            for batch in batches:
                flat = batch.column(0).flatten().to_numpy(zero_copy_only=False)
                x = np.column_stack([np.ones(batch.num_rows), flat.reshape(batch.num_rows, d - 1)])
                sign = np.where(batch.column(1).to_numpy()[:, None] == known[None], 1.0, -1.0)
                short = np.maximum(1 - sign * (x @ w.T), 0.0)
                total[:, :d] += -(sign * short).T @ x
                for k in range(len(classes)):
                    active = x[short[:, k] > 0]
                    total[k, d:] += (active.T @ active).ravel()
            flat = total.ravel()
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["k", "v"])

        found = lean.mapInArrow(run, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).toPandas()
        out = np.zeros(len(classes) * (d + d * d))
        out[found["k"].to_numpy()] = found["v"].to_numpy()
        return out.reshape(len(classes), -1)

    for _ in range(rounds):
        total, moved = sums(w), 0.0
        for k in range(len(classes)):
            gradient = total[k, :d] / n + ridge * w[k]
            step = np.linalg.solve(total[k, d:].reshape(d, d) / n + ridge * np.eye(d), gradient)
            w[k] -= step
            moved = max(moved, float(np.abs(step).max()))
        if moved < tol:
            break
    return LinearMachines(list(features), classes, w)


def train_learner(rows: DataFrame, features: list[str], label: str = "label", kind: str = "logistic") -> PipelineModel | LinearMachines:
    """Classifier on a subset: logistic regression, or linear machines one against the rest."""
    if kind == "svm":
        return fit_machines(rows, features, label)
    vector = VectorAssembler(inputCols=features, outputCol="vector_", handleInvalid="skip")
    model = LogisticRegression(featuresCol="vector_", labelCol=label, predictionCol="pred_", maxIter=50, regParam=1e-3)
    return Pipeline(stages=[vector, model]).fit(rows.select(*features, F.col(label).cast("double").alias(label)))


def predict(models: dict[str, PipelineModel | LinearMachines], rows: DataFrame, key: list[str]) -> DataFrame:
    """``key.., learner, pred``: one pass per learner, predictions side by side, no join."""
    out = rows
    for name, model in models.items():
        out = model.transform(out).withColumn(f"p_{name}", F.col("pred_").cast("int"))
        out = out.select(*rows.columns, *[c for c in out.columns if c.startswith("p_")])
    each = F.array(*[F.struct(F.lit(n).alias("learner"), F.col(f"p_{n}").alias("pred")) for n in models])
    return out.select(*key, F.inline(each))


def vote(predictions: DataFrame, weights: DataFrame, key: list[str], on: list[str] = ("learner",)) -> DataFrame:
    """``key.., pred, confidence``: the class with the largest weight, ties to the smallest."""
    sums = predictions.join(weights, list(on)).groupBy(*key, "pred").agg(F.sum("weight").alias("w"))
    by = Window.partitionBy(*key)
    best = F.row_number().over(by.orderBy(F.desc("w"), "pred"))
    out = sums.select("*", best.alias("r"), (F.col("w") / F.sum("w").over(by)).alias("confidence"))
    return out.where("r = 1").select(*key, "pred", "confidence")


def majority_weights(predictions: DataFrame, t: str, beta: float = 0.5) -> DataFrame:
    """``t, learner, weight`` before the rows of ``t``: beta to the power of earlier mistakes
    on labelled rows, normalised over learners. Mistakes count from the fewest of any learner at ``t``: the
    shares are the same, and no number of mistakes makes all powers zero."""
    wrong = F.sum(F.when(F.col("label").isNotNull() & (F.col("pred") != F.col("label")), 1).otherwise(0))
    by = predictions.groupBy(t, "learner").agg(wrong.alias("mistakes"))
    before = Window.partitionBy("learner").orderBy(t).rowsBetween(Window.unboundedPreceding, -1)
    counts = by.select(t, "learner", F.coalesce(F.sum("mistakes").over(before), F.lit(0)).alias("n"))
    powers = counts.select(t, "learner", F.pow(F.lit(beta), F.col("n") - F.min("n").over(Window.partitionBy(t))).alias("w"))
    return powers.select(t, "learner", (F.col("w") / F.sum("w").over(Window.partitionBy(t))).alias("weight"))


@dataclass(frozen=True)
class WeightPolicy:
    """``majority``: weights below ``theta`` of the largest are dropped, a learner is added
    when the ensemble errs. ``additive``: a new learner enters with ``gamma`` of the total."""

    kind: str = "majority"
    beta: float = 0.5
    theta: float = 0.01
    gamma: float = 0.1
    period: int = 1
    most: int = 20


def run_policy(truth: np.ndarray, votes: np.ndarray, policy: WeightPolicy, births: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Row-sequential weights and votes of the ensemble.

    ``votes``: (rows, learners), the class each learner would give; ``births``: when each
    learner may enter at the earliest. Returns (predictions, weights before each row).
    """
    n, k = votes.shape
    births = np.zeros(k, int) if births is None else births
    w = np.where(births <= 0, 1.0, 0.0)
    if not w.any():
        w[0] = 1.0
    # a weight is w * 2**power: long streams halve weights further than a float reaches
    power = np.zeros(k, int)
    seen, out = np.zeros((n, k)), np.zeros(n, votes.dtype)
    for i in range(n):
        share = np.ldexp(w, power - power[w > 0].max())
        seen[i] = share / share.sum()
        classes = np.unique(votes[i, w > 0])
        sums = np.array([share[votes[i] == c].sum() for c in classes])
        out[i] = classes[sums.argmax()]
        if (i + 1) % policy.period:
            continue
        wrong = votes[i] != truth[i]
        w, more = np.frexp(np.where(wrong, w * policy.beta, w))
        power = power + more
        top = power[w > 0].max()
        if policy.kind == "majority":
            w = np.ldexp(w, power - top)
            w = w / w.max()
            w[w < policy.theta] = 0.0
            power, top = np.zeros(k, int), 0
        if out[i] != truth[i]:
            idle = np.nonzero((w == 0) & (births <= i))[0]
            if len(idle) and (w > 0).sum() < policy.most:
                total = np.ldexp(w, power - top).sum()
                w[idle[0]] = total * policy.gamma if policy.kind == "additive" else 1.0
                power[idle[0]] = top
    return out, seen


def policy_series(predictions: DataFrame, order: str, learners: list[str], policy: WeightPolicy, key: list[str] = ()) -> DataFrame:
    """``key.., order, pred, label`` of the ensemble, rows of a key in order in one task."""
    wide = predictions.groupBy(*key, order, "label").pivot("learner", learners).agg(F.first("pred"))
    name = list(key) or ["all_"]
    wide = wide if key else wide.withColumn("all_", F.lit(0))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order)
        pred, _ = run_policy(pdf["label"].to_numpy(), pdf[learners].to_numpy(), policy)
        return pd.DataFrame({**{c: pdf[c] for c in name}, order: pdf[order], "label": pdf["label"], "pred": pred})

    types = dict(wide.dtypes)
    schema = ", ".join(f"{c} {types[c]}" for c in [*name, order, "label"]) + f", pred {types['label']}"
    return wide.groupBy(*name).applyInPandas(run, schema)


def reference(membership: DataFrame, active: DataFrame) -> DataFrame:
    """``sample_id`` of the union of the active learners' training rows: after an
    adaptation, the rows that drift is measured against."""
    return membership.join(active.where("active").select("learner_id"), "learner_id", "left_semi").select("sample_id").distinct()


def accuracy(predictions: DataFrame, by: list[str]) -> DataFrame:
    rows = predictions.where("label is not null")
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("pred") == F.col("label")).cast("double")).alias("accuracy"))


def labelling_cost(rows: DataFrame, requested: DataFrame, t: str) -> DataFrame:
    """``t, arrived, asked, share``: labels asked for against all rows that arrived."""
    asked = rows.join(requested.select("sample_id").withColumn("asked", F.lit(1)), "sample_id", "left")
    return asked.groupBy(t).agg(F.count(F.lit(1)).alias("arrived"), F.count("asked").alias("asked")).withColumn(
        "share", F.col("asked") / F.col("arrived")
    )


def confidence_gap(column: Column) -> Column:
    """Difference of the two largest entries of a probability vector."""
    top = F.sort_array(vector_to_array(column), asc=False)
    return F.get(top, F.lit(0)) - F.coalesce(F.get(top, F.lit(1)), F.lit(0.0))


# ------------------------------------------------------------ scripted analyst


@dataclass(frozen=True)
class Adaptation:
    """State of an adapting monitor: learners with the components they were trained for."""

    learners: tuple[tuple[str, tuple[int, ...]], ...] = ()
    actions: tuple[tuple[float, str, str], ...] = ()


def adapt(state: Adaptation, t: float, contributions: pd.DataFrame, new: set[int], rule: str = "largest", k: int = 1) -> tuple[Adaptation, list[int]]:
    """On an alarm: which components to label and what to do with them.

    New components come first, else the ``k`` largest contributions. A learner already
    trained for a chosen component is replaced, otherwise one is added.
    """
    parts = contributions.sort_values(["part", "comp_id"], ascending=[False, True])
    fresh = [int(c) for c in parts["comp_id"] if int(c) in new]
    chosen = fresh[:k] if fresh and rule != "largest_only" else [int(c) for c in parts["comp_id"].head(k)]
    kept = tuple((n, c) for n, c in state.learners if not set(c) <= set(chosen))
    verb = "replace" if len(kept) < len(state.learners) else "add"
    name = f"learner_{len(state.actions) + 1}"
    return replace(state, learners=(*kept, (name, tuple(chosen))), actions=(*state.actions, (t, verb, name))), chosen
