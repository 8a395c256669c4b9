"""Linked selections: from rows to times and back, regions, summaries, details."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def times_of(rows: DataFrame, selected: DataFrame, t: str) -> DataFrame:
    """``t, n``: when the selected rows arrived."""
    return rows.join(selected.select("sample_id"), "sample_id", "left_semi").groupBy(t).agg(F.count(F.lit(1)).alias("n"))


def brush(rows: DataFrame, t: str, low, high) -> DataFrame:
    return rows.where(F.col(t).between(low, high))


def inside(x: Column, y: Column, polygon: list[tuple[float, float]]) -> Column:
    """Even-odd rule; edges are half open in y, so a shared corner counts once."""
    crossings = F.lit(0)
    for (ax, ay), (bx, by) in zip(polygon, polygon[1:] + polygon[:1], strict=True):
        if ay == by:
            continue
        spans = (F.lit(ay) > y) != (F.lit(by) > y)
        at = (bx - ax) * (y - ay) / (by - ay) + ax
        crossings = crossings + F.when(spans & (x < at), 1).otherwise(0)
    return crossings % 2 == 1


def lasso(rows: DataFrame, polygon: list[tuple[float, float]], x: str = "x", y: str = "y") -> DataFrame:
    return rows.where(inside(F.col(x), F.col(y), polygon))


def summary(selected: DataFrame, features: list[str]) -> DataFrame:
    """``feature, n, mean, sd, low, median, high`` of a selection."""
    pairs = F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("v")) for c in features])
    return selected.select(F.inline(pairs)).groupBy("feature").agg(
        F.count("v").alias("n"), F.avg("v").alias("mean"), F.stddev_pop("v").alias("sd"), F.min("v").alias("low"),
        F.percentile("v", 0.5).alias("median"), F.max("v").alias("high"),
    )


def training_rows(rows: DataFrame, membership: DataFrame, learner: str) -> DataFrame:
    ids = membership.where(F.col("learner_id") == learner).select("sample_id")
    return rows.join(ids, "sample_id", "left_semi")


def detail(rows: DataFrame, raw: DataFrame, ids: DataFrame, key: str = "sample_id") -> DataFrame:
    """The selected rows with their raw record."""
    return rows.join(ids.select(key), key, "left_semi").join(raw, key, "left")


def shown(assigned: DataFrame, hidden: DataFrame) -> DataFrame:
    """Rows of components that are not hidden."""
    return assigned.join(F.broadcast(hidden.select("comp_id")), "comp_id", "left_anti")
