"""Drift series over a stream, in two batch runtimes with one step function.

* ``kernel``: all time points of a key in order inside one task; for many short
  streams (one per key) and thin batches.
* ``stepwise``: the driver walks the time points and each step is a distributed job;
  for batches too large for one task.

Order at a time point: rows are judged by the mixture before it, accepted rows update
it, rejected rows are pooled, a pool with enough support gives birth to components,
then the degree is taken from the final assignment.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.functions import numeric
from spark_drift.functions.numeric import Monitor, OnlineConfig
from spark_drift.operators import degree, mixture
from spark_drift.plans.lineage import cut

SERIES = "t double, n long, degree double, components int, pool long, births int"


def series_of(ref: np.ndarray, batches, cfg: OnlineConfig, window: int = 1, reassign: bool = True, mix: numeric.Mixture | None = None):
    """Pure form: yields ``(t, n, degree, components, pool, births)`` per batch ``(t, rows)``.

    ``window``: the current rows are those of the last ``window`` batches; ``mix``: the mixture of ``ref``, if known.
    """
    monitor = Monitor(ref, cfg, reassign=reassign, mix=mix)
    sizes: list[int] = []
    for t, x in batches:
        sizes = [*sizes, len(x)][-window:]
        births = monitor.arrive(x, t, sum(sizes))
        if len(monitor.rows):
            value, _ = monitor.degree()
            yield t, len(monitor.rows), value, len(monitor.mix.ids), len(monitor.state.pool), births


FITS = "key string, score double, n array<double>, mean array<array<double>>, cov array<array<double>>"


def kernel_series(
    train: DataFrame, stream: DataFrame, t: str, features: list[str], key: str | None = None, cfg: OnlineConfig | None = None, window: int = 1
) -> DataFrame:
    """Series per key; keys are independent monitors, spread over the cluster.

    The first mixture of a key is chosen from fits that are a task each, one per number of components.
    """
    cfg = cfg or OnlineConfig()
    name = F.col(key) if key else F.lit("all")
    side = lambda df, time, ref: df.select(name.cast("string").alias("key"), time.alias("t"), F.lit(ref).alias("ref"), *[F.col(c).cast("double").alias(c) for c in features])
    first = side(train, F.lit(0.0), True)
    both = first.unionByName(side(stream, F.col(t).cast("double"), False))

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        ref = pdf.sort_values(features, kind="stable")[features].to_numpy(float)
        found = numeric.scored(ref, int(pdf["k"].iloc[0]), cfg.kind, cfg.seed) if len(ref) > len(features) else None
        rows = [(pdf["key"].iloc[0], found[0], found[1].n, list(found[1].mean), [c.ravel() for c in found[1].cov])] if found else []
        return pd.DataFrame(rows, columns=["key", "score", "n", "mean", "cov"])

    # most components first, as these fits take longest
    orders = F.explode(F.array(*[F.lit(k) for k in range(cfg.most, 0, -1)])).alias("k")
    fits = first.select("key", *features, orders).groupBy("key", "k").applyInPandas(fit, FITS)

    def run(pdf: pd.DataFrame, tried: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame(columns=["key", "t", "n", "degree", "components", "pool", "births"])
        if not len(tried):  # too few training rows
            return out
        pdf = pdf.sort_values(["t", *features], kind="stable")
        ref = pdf[pdf["ref"]][features].to_numpy(float)
        rest = pdf[~pdf["ref"]]
        if len(rest):
            best = min(tried.itertuples(), key=lambda f: (f.score, len(f.n)))
            d = len(features)
            mix = numeric.Mixture(np.arange(len(best.n)), np.array(best.n), np.vstack(best.mean), np.vstack(best.cov).reshape(-1, d, d))
            batches = ((float(at), g[features].to_numpy(float)) for at, g in rest.groupby("t", sort=True))
            rows = list(series_of(ref, batches, cfg, window, mix=mix))
            out = pd.DataFrame(rows, columns=["t", "n", "degree", "components", "pool", "births"])
            out.insert(0, "key", pdf["key"].iloc[0])
        return out

    return both.groupBy("key").cogroup(fits.groupBy("key")).applyInPandas(run, f"key string, {SERIES}")


class Stepper:
    """Drift steps as distributed jobs over batches of any size.

    Component fits start from a bounded sample (``mixture.fit``); assignment, absorption
    and the degree use all rows. Only the components, one row each, come to the driver.
    ``pool`` and ``ref`` are written tables, so a step's plan does not grow with time.
    """

    def __init__(self, train: DataFrame, features: list[str], cfg: OnlineConfig | None = None, mix: numeric.Mixture | None = None) -> None:
        self.features, self.cfg = list(features), cfg or OnlineConfig()
        self.mix = mix if mix is not None else self._fitted(train)
        self.ref = self._assigned(train)
        self.pool: DataFrame | None = None
        self.last: DataFrame | None = None  # the newest batch with its components

    def _fitted(self, rows: DataFrame) -> numeric.Mixture:
        return mixture.select(rows, self.features, range(1, self.cfg.most + 1), self.cfg.kind, self.cfg.seed)[1]

    def _assigned(self, rows: DataFrame) -> DataFrame:
        return cut(mixture.assign(rows.select(*self.features), self.features, self.mix).select(*self.features, "comp_id"))

    def step(self, batch: DataFrame, at: float) -> tuple | None:
        """``(t, n, degree, components, pool, births)`` of one batch; none if it has no rows."""
        features, cfg = self.features, self.cfg
        rows = batch.select(*features, F.lit(at).cast("double").alias("t_"))
        marked = cut(mixture.assign(rows, features, self.mix, cfg.gate, cfg.level))
        n = marked.count()
        if not n:
            return None
        self.mix = mixture.absorb(marked, features, self.mix, cfg)
        rejected = marked.where("provisional").select(*features)
        self.pool = rejected if self.pool is None else cut(self.pool.union(rejected))
        size, births = self.pool.count(), 0
        need = cfg.min_pool if cfg.min_pool is not None else self.mix.n.mean() / 2
        if size >= max(need, len(features) + 2):
            new = self._fitted(self.pool)
            births = len(new.ids)
            self.mix = numeric.Mixture(
                np.concatenate([self.mix.ids, int(self.mix.ids.max()) + 1 + np.arange(births)]),
                np.concatenate([self.mix.n, new.n]), np.concatenate([self.mix.mean, new.mean]),
                np.concatenate([self.mix.cov, new.cov]), np.concatenate([self.mix.born, np.full(births, float(at))]),
            )
            self.ref = self._assigned(self.ref)
            late = mixture.assign(marked.where("provisional").select(*features, "t_"), features, self.mix)
            known = F.col("comp_id").isin(*[int(i) for i in self.mix.ids])
            lost = mixture.assign(marked.where(~known & ~F.col("provisional")).select(*features, "t_"), features, self.mix)
            marked = marked.where(known & ~F.col("provisional")).unionByName(late).unionByName(lost)
            self.pool, size = None, 0
        self.last = marked
        value = degree.drift_degree(self.ref, marked, "t_", features).first()["degree"]
        return float(at), n, float(value), len(self.mix.ids), size, births


def stepwise_series(train: DataFrame, stream: DataFrame, t: str, features: list[str], times: list, cfg: OnlineConfig | None = None) -> DataFrame:
    """Series by distributed steps over the given time points."""
    stream = cut(stream.select(t, *features))
    stepper = Stepper(cut(train.select(*features)), features, cfg)
    rows = [stepper.step(stream.where(F.col(t) == at), at) for at in times]
    return train.sparkSession.createDataFrame([r for r in rows if r], SERIES)
