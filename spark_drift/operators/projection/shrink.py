"""Dispersion-weighted shrinking of distances inside components."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.functions.numeric import LOG2PI, Mixture


def entropies(mix: Mixture, eps: float = 1e-3) -> np.ndarray:
    """Differential entropy of each component, at least ``eps``."""
    return np.array([max(0.5 * np.linalg.slogdet(c)[1] + mix.dims / 2 * (1 + LOG2PI), eps) for c in mix.cov])


def factors_of(mix: Mixture, alpha: float = 0.9, beta: float = 0.5, eps: float = 1e-3) -> np.ndarray:
    h = entropies(mix, eps)
    return alpha * (1 - beta * h / h.max())


def entropy(components: DataFrame, eps: float = 1e-3) -> DataFrame:
    """``comp_id, entropy`` of two-dimensional components ``(cov: 4 numbers)``."""
    det = F.col("cov")[0] * F.col("cov")[3] - F.col("cov")[1] * F.col("cov")[2]
    return components.select("comp_id", F.greatest(F.lit(eps), 0.5 * F.log(det) + 1 + LOG2PI).alias("entropy"))


def factors(entropy_table: DataFrame, alpha: float = 0.9, beta: float = 0.5) -> DataFrame:
    """``comp_id, factor``: the widest component gets ``alpha * (1 - beta)``."""
    top = F.max("entropy").over(Window.partitionBy(F.lit(0)))
    return entropy_table.select("comp_id", (alpha * (1 - beta * F.col("entropy") / top)).alias("factor"))


def shrunk(distance: np.ndarray, comp_a: np.ndarray, comp_b: np.ndarray, ids: np.ndarray, factor: np.ndarray) -> np.ndarray:
    """Distances, multiplied by the component's factor where both rows share one."""
    per_row = factor[np.searchsorted(ids, comp_a)]
    return np.where(comp_a[:, None] == comp_b[None], per_row[:, None] * distance, distance)
