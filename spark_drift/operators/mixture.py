"""Gaussian mixtures as DataFrame operations.

Components are a small table that travels as literals: the density of every component
is one generated expression per row, so assignment is a map over the scan. An
expectation-maximisation round is that map and one partial aggregate. The expressions grow with the components and the
square of the features; beyond ``WIDE`` such terms they would no longer compile to one method, and their plans, which the
driver keeps, would fill it. There the same map runs in Arrow batches, and each task hands on its sums, which are added by
place on the executors.
"""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions import numeric
from spark_drift.functions.numeric import LOG2PI, Mixture, OnlineConfig
from spark_drift.plans.lineage import cut


#: components times squared features up to which densities and moments are generated expressions
WIDE = 15


def _wide(mix: Mixture) -> bool:
    return len(mix.ids) * mix.dims**2 > WIDE


def _added(rows: DataFrame, features: list[str], size: int, partial) -> np.ndarray:
    """Sums over all rows of the arrays that ``partial(x, batch)`` gives, one partial array per task."""
    lean = rows.select(F.array(*[F.col(c).cast("double") for c in features]).alias("x_"), *[c for c in rows.columns if c not in features])

    def run(batches):
        total = np.zeros(size)
        for batch in batches:
            if batch.num_rows:
                total += partial(batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1), batch)
        some = np.nonzero(total)[0]
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["k", "v"])

    out = np.zeros(size)
    for r in lean.mapInArrow(run, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).collect():
        out[r["k"]] = r["v"]
    return out


def _statistics(x: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Per column of weights: their sum, the weighted sum of rows, and that of outer products, flat."""
    second = np.einsum("nk,ni,nj->kij", weight, x, x).reshape(weight.shape[1], -1)
    return np.concatenate([weight.sum(0)[:, None], weight.T @ x, second], axis=1).ravel()


def _from_statistics(flat: np.ndarray, ids, d: int, ridge: float) -> Mixture:
    rows = flat.reshape(len(ids), 1 + d + d * d)
    n = np.maximum(rows[:, 0], 1e-9)
    mean = rows[:, 1 : 1 + d] / n[:, None]
    cov = rows[:, 1 + d :].reshape(-1, d, d) / n[:, None, None] - np.einsum("ki,kj->kij", mean, mean) + ridge * np.eye(d)[None]
    return Mixture(np.array(ids), n, mean, cov)


def table(spark: SparkSession, mix: Mixture) -> DataFrame:
    """``comp_id, n, mean, cov`` (row-major), one row per component."""
    rows = [
        (int(i), float(n), m.tolist(), c.ravel().tolist(), float(b))
        for i, n, m, c, b in zip(mix.ids, mix.n, mix.mean, mix.cov, mix.born, strict=True)
    ]
    return spark.createDataFrame(rows, "comp_id int, n double, mean array<double>, cov array<double>, born double")


def from_table(df: DataFrame) -> Mixture:
    rows = sorted(df.collect(), key=lambda r: r["comp_id"])
    d = len(rows[0]["mean"])
    return Mixture(
        np.array([r["comp_id"] for r in rows]), np.array([r["n"] for r in rows]), np.array([r["mean"] for r in rows]),
        np.array([r["cov"] for r in rows]).reshape(-1, d, d), np.array([r["born"] for r in rows]),
    )


def mahalanobis(features: list[str], mix: Mixture) -> list[Column]:
    """Squared Mahalanobis distance of a row to each component."""
    inverse, _ = numeric.factors(mix.cov)
    out = []
    for k in range(len(mix.ids)):
        total = F.lit(0.0)
        for i in range(mix.dims):
            z = F.lit(0.0)
            for j in range(i + 1):
                z = z + F.lit(float(inverse[k, i, j])) * (F.col(features[j]).cast("double") - F.lit(float(mix.mean[k, j])))
            total = total + z * z
        out.append(total)
    return out


def log_densities(features: list[str], mix: Mixture) -> list[Column]:
    _, logdet = numeric.factors(mix.cov)
    return [
        F.lit(-0.5 * (float(logdet[k]) + mix.dims * LOG2PI)) - 0.5 * d2 for k, d2 in enumerate(mahalanobis(features, mix))
    ]


def log_density(df: DataFrame, features: list[str], mix: Mixture) -> DataFrame:
    """One row per row of ``df`` and component: ``comp_id, log_density``."""
    df = df.drop("comp_id", "log_density")
    each = [F.struct(F.lit(int(i)).alias("comp_id"), c.alias("log_density")) for i, c in zip(mix.ids, log_densities(features, mix), strict=True)]
    return df.select("*", F.inline(F.array(*each)))


def assign(df: DataFrame, features: list[str], mix: Mixture, gate: str = "chi2", level: float = 0.95) -> DataFrame:
    """``df`` with ``comp_id, provisional, log_density`` (replacing columns of these names);
    ties go to the smallest id."""
    df = df.drop("comp_id", "provisional", "log_density")
    if _wide(mix):
        return _assign_wide(df, features, mix, gate, level)
    # the quadratic forms become columns once; all else is arithmetic on them
    _, logdet = numeric.factors(mix.cov)
    names = df.columns
    df = df.select("*", *[d.alias(f"d2_{k}_") for k, d in enumerate(mahalanobis(features, mix))])
    d2 = [F.col(f"d2_{k}_") for k in range(len(mix.ids))]
    logs = [F.lit(-0.5 * (float(logdet[k]) + mix.dims * LOG2PI)) - 0.5 * d for k, d in enumerate(d2)]
    score = logs
    if gate == "posterior":
        score = [c + F.lit(math.log(mix.n[k] / mix.n.sum())) for k, c in enumerate(logs)]
    each = F.array(*[
        F.struct((-s).alias("order"), F.lit(int(i)).alias("comp_id"), c.alias("logpdf"), d.alias("d2"), s.alias("score"))
        for i, c, d, s in zip(mix.ids, logs, d2, score, strict=True)
    ])
    best = F.array_min(each)
    out = df.withColumn("best_", best)
    if gate == "chi2":
        ok = F.col("best_.d2") <= numeric.chi2_quantile(level, mix.dims)
    elif gate == "density":
        ok = F.exp(F.col("best_.logpdf")) > level
    else:
        total = None
        for s in score:
            term = F.exp(s - F.col("best_.score"))
            total = term if total is None else total + term
        ok = 1.0 / total > level
    return out.select(
        *names, F.col("best_.comp_id").alias("comp_id"), (~ok).alias("provisional"), F.col("best_.logpdf").alias("log_density")
    )


def _assign_wide(df: DataFrame, features: list[str], mix: Mixture, gate: str, level: float) -> DataFrame:
    cfg = OnlineConfig(gate=gate, level=level)

    @F.pandas_udf("comp_id int, provisional boolean, log_density double")
    def place(rows: pd.Series) -> pd.DataFrame:
        x = np.stack(rows.to_numpy()) if len(rows) else np.zeros((0, mix.dims))
        own, ok = numeric.gated(x, mix, cfg)
        logpdf = numeric.mahalanobis_and_logpdf(x, mix)[1]
        return pd.DataFrame({"comp_id": mix.ids[own].astype(np.int32), "provisional": ~ok, "log_density": logpdf[np.arange(len(x)), own]})

    out = df.withColumn("best_", place(F.array(*[F.col(c).cast("double") for c in features])))
    return out.select(*df.columns, "best_.comp_id", "best_.provisional", "best_.log_density")


def _moments(features: list[str], weight: Column, tag: str) -> list[Column]:
    d = len(features)
    x = [F.col(c).cast("double") for c in features]
    out = [F.sum(weight).alias(f"{tag}n")]
    out += [F.sum(weight * x[i]).alias(f"{tag}s{i}") for i in range(d)]
    out += [F.sum(weight * x[i] * x[j]).alias(f"{tag}q{i}_{j}") for i in range(d) for j in range(i + 1)]
    return out


def _mixture_of(row, tags: list[str], ids, d: int, ridge: float) -> Mixture:
    n = np.array([max(row[f"{t}n"] or 0.0, 1e-9) for t in tags])
    mean = np.array([[(row[f"{t}s{i}"] or 0.0) / n[k] for i in range(d)] for k, t in enumerate(tags)])
    cov = np.empty((len(tags), d, d))
    for k, t in enumerate(tags):
        for i in range(d):
            for j in range(i + 1):
                cov[k, i, j] = cov[k, j, i] = (row[f"{t}q{i}_{j}"] or 0.0) / n[k] - mean[k, i] * mean[k, j]
        cov[k] += ridge * np.eye(d)
    return Mixture(np.array(ids), n, mean, cov)


def _em_sums(x: np.ndarray, mix: Mixture) -> np.ndarray:
    """What a round takes from the rows ``x``: flat statistics per component, and the log likelihood."""
    joint = numeric.mahalanobis_and_logpdf(x, mix)[1] + np.log(np.maximum(mix.n, 1e-12) / mix.n.sum())[None]
    top = joint.max(1, keepdims=True)
    lse = top + np.log(np.exp(joint - top).sum(1, keepdims=True))
    return np.concatenate([_statistics(x, np.exp(joint - lse)), [lse.sum()]])


def em_step(df: DataFrame, features: list[str], mix: Mixture, ridge: float = 1e-6) -> tuple[Mixture, float]:
    """One round over all rows: the new mixture and the log likelihood of the old one."""
    if _wide(mix):
        size = len(mix.ids) * (1 + mix.dims + mix.dims**2) + 1
        flat = _added(df.select(*features), features, size, lambda x, _: _em_sums(x, mix))
        return _from_statistics(flat[:-1], mix.ids, mix.dims, ridge), float(flat[-1])
    joint = [c + F.lit(math.log(max(mix.n[k], 1e-12) / mix.n.sum())) for k, c in enumerate(log_densities(features, mix))]
    rows = df.select(*features, *[c.alias(f"j{k}") for k, c in enumerate(joint)])
    top = F.greatest(*[F.col(f"j{k}") for k in range(len(joint))]) if len(joint) > 1 else F.col("j0")
    total = sum((F.exp(F.col(f"j{k}") - top) for k in range(len(joint))), F.lit(0.0))
    rows = rows.withColumn("lse", top + F.log(total))
    sums = [F.sum("lse").alias("value")]
    for k in range(len(joint)):
        sums += _moments(features, F.exp(F.col(f"j{k}") - F.col("lse")), f"k{k}")
    row = rows.agg(*sums).first()
    return _mixture_of(row, [f"k{k}" for k in range(len(joint))], mix.ids, len(features), ridge), row["value"] or 0.0


def fit(
    df: DataFrame, features: list[str], k: int, seed: int = 0, rounds: int = 25, tol: float = 1e-5, ridge: float = 1e-6, start_rows: int = 2000
) -> tuple[Mixture, float]:
    """Mixture of ``k`` components over all rows, and its log likelihood.

    Starts from a fit on ``start_rows`` rows chosen by hash, then runs distributed rounds; where these are all rows,
    the rounds stay with them.
    """
    return _fit(*_start(cut(df.select(*features)), features, seed, start_rows), features, k, seed, rounds, tol, ridge)


def _start(rows: DataFrame, features: list[str], seed: int, start_rows: int) -> tuple[DataFrame, int, np.ndarray]:
    """All rows, their number, and those that a fit starts from: the smallest digests, bounded by ``start_rows``."""
    order = [F.xxhash64(F.lit(seed), *features), *features]
    x = np.array([[float(v) for v in r] for r in rows.orderBy(*order).limit(start_rows).collect()]).reshape(-1, len(features))
    return rows, rows.count(), x[np.lexsort(x.T)]


def _fit(rows: DataFrame, n: int, x: np.ndarray, features: list[str], k: int, seed: int, rounds: int, tol: float, ridge: float) -> tuple[Mixture, float]:
    mix, _ = numeric.em_fit(x, k, seed)
    mix.n = mix.n * n / len(x)
    last = -math.inf
    for _ in range(rounds):
        if len(x) == n:
            flat = _em_sums(x, mix)
            mix, value = _from_statistics(flat[:-1], mix.ids, mix.dims, ridge), float(flat[-1])
        else:
            mix, value = em_step(rows, features, mix, ridge)
        if abs(value - last) <= tol * abs(value):
            break
        last = value
    order = np.lexsort(mix.mean.T[::-1])
    return Mixture(np.arange(k), mix.n[order], mix.mean[order], mix.cov[order]), value


def select(
    df: DataFrame, features: list[str], orders: range = range(1, 11), kind: str = "bic", seed: int = 0, rounds: int = 25, tol: float = 1e-5,
    ridge: float = 1e-6, start_rows: int = 2000, at_once: int = 4,
):
    """Scores per number of components and the mixture of the best: ``(rows, mixture)``.

    Orders with fewer than five rows per parameter are left out, but for one component. ``at_end``: the best order is the
    largest that was tried, so a larger one might be better still. The fits' jobs run ``at_once`` at a time.
    """
    start = _start(cut(df.select(*features)), features, seed, start_rows)
    tried = [k for k in orders if k == 1 or start[1] >= 5 * numeric.parameters(k, len(features))]
    with ThreadPoolExecutor(at_once) as pool:
        fits = list(pool.map(lambda k: _fit(*start, features, k, seed, rounds, tol, ridge), tried))
    found = [(numeric.criterion(value, k, len(features), start[1], kind), k, value, mix) for k, (mix, value) in zip(tried, fits, strict=True)]
    best = min(found, key=lambda f: f[0])
    rows = [
        (k, float(v), numeric.parameters(k, len(features)), float(s), k == best[1], best[1] == tried[-1]) for s, k, v, _ in found
    ]
    schema = "k int, log_likelihood double, params int, score double, chosen boolean, at_end boolean"
    return df.sparkSession.createDataFrame(rows, schema), best[3]


def absorb(df: DataFrame, features: list[str], mix: Mixture, cfg: OnlineConfig | None = None) -> Mixture:
    """Statistics of the accepted rows of ``df`` (``comp_id, provisional``) merged into
    their components; one partial aggregate, one row per component to the driver."""
    cfg = cfg or OnlineConfig()
    accepted, found = df.where(~F.col("provisional")), {}
    if _wide(mix):
        size = len(mix.ids) * (1 + mix.dims + mix.dims**2)

        def partial(x: np.ndarray, batch) -> np.ndarray:
            own = batch.column(1).to_numpy(zero_copy_only=False)
            return _statistics(x, (own[:, None] == mix.ids[None]).astype(float))

        flat = _added(accepted.select(*features, "comp_id"), features, size, partial)
        new = _from_statistics(flat, mix.ids, mix.dims, 0.0)
        found = {int(c): Mixture(new.ids[k : k + 1], new.n[k : k + 1], new.mean[k : k + 1], new.cov[k : k + 1]) for k, c in enumerate(mix.ids) if new.n[k] >= 1}
    else:
        for row in accepted.groupBy("comp_id").agg(*_moments(features, F.lit(1.0), "k")).collect():
            found[row["comp_id"]] = _mixture_of(row, ["k"], [row["comp_id"]], len(features), 0.0)
    shrink = numeric.truncation_factor(cfg.level, mix.dims) if cfg.gate == "chi2" and cfg.truncation == "correct" else 1.0
    out = mix.copy()
    where = {int(c): k for k, c in enumerate(mix.ids)}
    for comp, new in found.items():
        k = where[comp]
        n1, n2, gap = out.n[k], new.n[0], new.mean[0] - out.mean[k]
        out.cov[k] = (n1 * out.cov[k] + n2 * new.cov[0] / shrink) / (n1 + n2) + n1 * n2 / (n1 + n2) ** 2 * np.outer(gap, gap)
        out.mean[k] += gap * n2 / (n1 + n2)
        out.n[k] = n1 + n2
    return out


def pool_threshold(assigned: DataFrame) -> DataFrame:
    """``threshold``: half the mean number of rows in a component."""
    sizes = assigned.groupBy("comp_id").agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg((F.avg("n") / 2).alias("threshold"))


def merge_components(mix: Mixture, source: int, target: int) -> Mixture:
    """Component ``source`` folded into ``target`` by exact statistics."""
    return numeric.merged(mix, source, target)


def fold_twins(mix: Mixture, most: float) -> Mixture:
    """Components nearer than ``most`` in Bhattacharyya distance folded together."""
    return numeric.fold_twins(mix, most)


def merge_and_judge(assigned: DataFrame, features: list[str], mix: Mixture, source: int, target: int, gate: str = "chi2", level: float = 0.95) -> tuple[Mixture, DataFrame]:
    """An analyst's merge: the joined mixture, and ``assigned`` (``comp_id, provisional``) in which the rows of
    both components and the provisional ones are judged anew; all others keep their place."""
    joined = numeric.merged(mix, source, target)
    touched = F.col("provisional") | F.col("comp_id").isin(int(source), int(target))
    again = assign(assigned.where(touched), features, joined, gate, level)
    return joined, assigned.where(~touched).unionByName(again)


def activity(assigned: DataFrame, t: str, window: int, least: int) -> DataFrame:
    """``comp_id, rows_recent, active``: components without enough rows of late are stale."""
    last = assigned.agg(F.max(t).alias("last"))
    recent = F.sum(F.when(F.col(t) > F.col("last") - window, 1).otherwise(0))
    by = assigned.withColumn("one", F.lit(1)).join(F.broadcast(last.withColumn("one", F.lit(1))), "one").groupBy("comp_id")
    return by.agg(recent.alias("rows_recent")).withColumn("active", F.col("rows_recent") >= least)
