"""Functions for SQL text: densities, the energy distance, halo cells, window members."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from spark_drift.functions.numeric import energy


def register(spark: SparkSession) -> None:
    @F.pandas_udf("double")
    def gauss_logpdf(x: pd.Series, mean: pd.Series, cov: pd.Series) -> pd.Series:
        out = np.empty(len(x))
        for i, (a, m, c) in enumerate(zip(x, mean, cov, strict=True)):
            d = len(a)
            c = np.asarray(c, float).reshape(d, d)
            gap = np.asarray(a, float) - np.asarray(m, float)
            out[i] = -0.5 * (gap @ np.linalg.solve(c, gap) + np.linalg.slogdet(c)[1] + d * math.log(2 * math.pi))
        return pd.Series(out)

    @F.pandas_udf("double")
    def energy_distance(x: pd.Series, side: pd.Series) -> float:
        x, side = x.to_numpy(float), side.to_numpy()
        return energy(x[side == 0][:, None], x[side != 0][:, None])

    @F.udtf(returnType="row int, col int, value double")
    class Halo:
        def eval(self, row: int, col: int, value: float):
            for i in range(-2, 3):
                for j in range(-2, 3):
                    yield row + i, col + j, value * (0.7 if i == j == 0 else 0.3 / 24)

    @F.udtf(returnType="window_end bigint")
    class WindowMembers:
        def eval(self, i: int, length: int, slide: int):
            end = -(-i // slide) * slide
            while end < i + length:
                yield (end,)
                end += slide

    spark.udf.register("gauss_logpdf", gauss_logpdf)
    spark.udf.register("energy_distance", energy_distance)
    spark.udtf.register("halo", Halo)
    spark.udtf.register("window_members", WindowMembers)
