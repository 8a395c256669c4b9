"""Drift degree: how far arriving rows lie from the training rows.

The main form compares only rows of one mixture component with each other and takes
the mean over components, weighted by their share of the batch. A component that the
training rows lack counts as distance 1.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.functions.expressions import distance
from spark_drift.operators import exact
from spark_drift.operators.energy import _terms, cells_of, energy_distance, pair_sums, sampled, sliced_distance
from spark_drift.plans.choose import Choice, choose


def method_for(ref: DataFrame, cur: DataFrame, features: list[str], max_error: float | None = None, pair_budget: float = 1e10) -> Choice:
    """The physical method that the sizes of both sides allow."""
    return choose(ref.count(), cur.count(), len(features), pair_budget, max_error=max_error)


def direct(ref: DataFrame, cur: DataFrame, t: str, features: list[str], **options) -> DataFrame:
    """``t, degree`` of each batch against all reference rows (no components)."""
    one = F.lit(0).alias("comp_id")
    # further columns stay, as they spread rows over tasks
    every = lambda df: df.select(*[c for c in df.columns if c != "comp_id"], one)
    parts = contributions(every(ref), every(cur), t, features, **options)
    return parts.select(t, F.col("distance").alias("degree"))


def contributions(
    ref: DataFrame, cur: DataFrame, t: str, features: list[str], estimator: str = "v", method: str | Choice | None = None, key: str = "row_id",
    max_error: float | None = None, pair_budget: float = 1e10,
) -> DataFrame:
    """``t, comp_id, share, distance, part`` for each batch and component it has rows in.

    The reference's self term is computed once per component and serves all batches. Without a ``method`` the
    distance is exact, by a path that goes by the number of features and not by sizes: in value order for one, by
    cells of rows for two (to some 1e-12), by pairs of blocks for more. With ``max_error``, cells with that
    certified error are taken where ``choose`` has them within ``pair_budget``. A caller may name one of ``exact,
    pairwise, sorted, cells, sliced, sampled`` or pass a choice; samples are drawn by the row id ``key``.
    """
    if method is None:
        method = "sorted" if len(features) == 1 else "exact"
        if max_error is not None:
            offered = method_for(ref, cur, features, max_error, pair_budget)
            method = offered if offered.method == "cells" else method
    choice = method if isinstance(method, Choice) else Choice(method, "asked for", {})
    m = cur.groupBy(t, "comp_id").agg(F.count(F.lit(1)).alias("m"))
    if choice.method == "sorted":
        out = energy_distance(ref, cur, features, ["comp_id"], "sorted", estimator, also=[t])
    elif choice.method == "sliced":
        out = sliced_distance(ref, cur, features, ["comp_id"], also=[t], **choice.options)
    elif choice.method == "exact":
        out = _terms(exact.terms(ref, cur, features, ["comp_id"], [t]), [t, "comp_id"], estimator, True)
    else:
        n = ref.groupBy("comp_id").agg(F.count(F.lit(1)).alias("n"))
        weight, a, b = None, ref, cur
        if choice.method == "cells":
            size = choice.options["cell"]
            weight, a, b = "weight", cells_of(ref, features, size, ["comp_id"]), cells_of(cur, features, size, [t, "comp_id"])
        elif choice.method == "sampled":
            a, b = sampled(ref, key, ["comp_id"], choice.options["cap"]), sampled(cur, key, [t, "comp_id"], choice.options["cap"])
            n, m_drawn = a.groupBy("comp_id").agg(F.count(F.lit(1)).alias("n")), b.groupBy(t, "comp_id").agg(F.count(F.lit(1)).alias("m"))
        sb = pair_sums(a, b, features, ["comp_id"], weight, also=[t]).withColumnRenamed("total", "sb")
        sr = pair_sums(a, a, features, ["comp_id"], weight).withColumnRenamed("total", "sr")
        sc = pair_sums(b, b, features, [t, "comp_id"], weight).withColumnRenamed("total", "sc")
        left = m_drawn if choice.method == "sampled" else m
        terms = left.join(n, "comp_id", "left").join(sb, [t, "comp_id"], "left").join(sr, "comp_id", "left").join(sc, [t, "comp_id"], "left")
        out = _terms(terms, [t, "comp_id"], estimator, True)
    # shares come from all rows, whatever the method
    out = out.select(t, "comp_id", "m", "distance") if choice.method == "exact" else out.select(t, "comp_id", "distance").join(m, [t, "comp_id"])
    share = F.col("m") / F.sum("m").over(Window.partitionBy(t))
    return out.select(t, "comp_id", share.alias("share"), "distance", (share * F.col("distance")).alias("part"))


def of_batch(ref: DataFrame, cur: DataFrame, t: str, features: list[str]) -> pd.DataFrame:
    """``comp_id, share, distance, part`` of one batch."""
    return contributions(ref, cur, t, features).drop(t).toPandas()


def combine(parts: DataFrame, t: str) -> DataFrame:
    return parts.groupBy(t).agg(F.sum("part").alias("degree"))


def drift_degree(
    ref: DataFrame, cur: DataFrame, t: str, features: list[str], compare: str = "component", k: int = 10, key: str = "row_id", **options
) -> DataFrame:
    """``t, degree`` per batch. ``component``: both sides carry ``comp_id``. ``direct``:
    all rows with all. ``knn``: each batch with the union of its rows' k nearest.
    ``options``: as for ``contributions``; the method is chosen from sizes unless named."""
    if compare == "direct":
        return direct(ref, cur, t, features, key=key, **options)
    if compare == "component":
        return combine(contributions(ref, cur, t, features, key=key, **options), t)
    chosen = nearest(ref, cur, t, features, k, key).select(t, F.col("ref_id").alias(key)).distinct()
    picked = chosen.join(ref.select(key, *features), key)
    return energy_distance(picked, cur, features, [t]).select(t, F.col("distance").alias("degree"))


def grid_width(ref: DataFrame, features: list[str], k: int, dims: int = 3) -> tuple[list[str], float]:
    """The features that cells are made of (the widest ones, ``dims`` at most) and a cell width at
    which a cell and its neighbours hold some ``k`` rows each, were the rows spread evenly."""
    row = ref.agg(F.count(F.lit(1)).alias("n"), *[F.stddev_pop(c).alias(c) for c in features]).first()
    wide = sorted(features, key=lambda c: -(row[c] or 0.0))[:dims]
    volume = 1.0
    for c in wide:
        volume *= max(4 * (row[c] or 0.0), 1e-12)
    return wide, max((volume * max(k, 1) / max(row["n"], 1)) ** (1 / len(wide)), 1e-9)


def nearest(ref: DataFrame, cur: DataFrame, t: str, features: list[str], k: int, key: str, salts: int = 16, cells: bool | None = None) -> DataFrame:
    """``t, key, ref_id, rank, d``: the k nearest reference rows of each row, ties by id.

    With ``cells`` (by default beyond 10^8 pairs) rows meet the reference rows of their own grid cell and of
    its neighbours; where the k-th of these lies farther than a cell's width, rows outside may be nearer,
    and the row meets the whole reference. So the result is exact either way.
    """
    named = [F.col(c).cast("double").alias(f"r_{c}") for c in features]
    left = ref.select(F.col(key).alias("ref_id"), *named)
    right = cur.select(t, key, *[F.col(c).cast("double").alias(c) for c in features])
    gap = distance([F.col(f"r_{c}") for c in features], [F.col(c) for c in features])
    order = Window.partitionBy(t, key).orderBy("d", "ref_id")

    def all_pairs(rows: DataFrame) -> DataFrame:
        """Reference rows dealt over shares; each share keeps its k best per row."""
        one = left.withColumn("salt", F.pmod(F.xxhash64("ref_id"), F.lit(salts)))
        two = rows.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
        pairs = one.join(two, "salt").select(t, key, "salt", "ref_id", gap.alias("d"))
        first = F.row_number().over(Window.partitionBy(t, key, "salt").orderBy("d", "ref_id"))
        return pairs.withColumn("rank", first).where(F.col("rank") <= k).drop("salt", "rank")

    if cells is None:
        cells = ref.count() * cur.count() > 10**8
    if not cells:
        best = all_pairs(right)
    else:
        wide, width = grid_width(ref, features, k)
        corner = lambda tag: [F.floor(F.col(f"{tag}{c}") / width).alias(f"cell_{i}") for i, c in enumerate(wide)]
        homes = [f"cell_{i}" for i in range(len(wide))]
        around = right.select("*", *corner(""))
        for c in homes:  # the cell and its neighbours
            around = around.withColumn(c, F.explode(F.array(*[F.col(c) + step for step in (-1, 0, 1)])))
        near = left.select("*", *corner("r_")).join(around, homes).select(t, key, "ref_id", gap.alias("d"))
        near = near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
        # a k-th neighbour within one width is nearer than all rows of farther cells
        sure = near.groupBy(t, key).agg(F.count(F.lit(1)).alias("found"), F.max("d").alias("far"))
        sure = sure.where((F.col("found") == k) & (F.col("far") <= width)).select(t, key)
        best = near.drop("rank").join(sure, [t, key], "left_semi").unionByName(all_pairs(right.join(sure, [t, key], "left_anti")))
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(t, key, "ref_id", "rank", "d")


def per_feature(ref: DataFrame, cur: DataFrame, t: str, features: list[str]) -> DataFrame:
    """``t, feature, degree``: the component-wise degree of each feature alone."""

    def long(df: DataFrame, keys: list[str]) -> DataFrame:
        pairs = F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("v")) for c in features]))
        return df.select(*keys, pairs.alias("p")).select(*keys, "p.feature", "p.v")

    # the reference's running sums are made once per component and feature and serve all times
    each = energy_distance(long(ref, ["comp_id"]), long(cur, [t, "comp_id"]), ["v"], ["comp_id", "feature"], "sorted", also=[t])
    share = F.col("m") / F.sum("m").over(Window.partitionBy(t, "feature"))
    return each.withColumn("part", share * F.col("distance")).groupBy(t, "feature").agg(F.sum("part").alias("degree"))


def time_windows(stream: DataFrame, ts: str, length: str, slide: str) -> DataFrame:
    """Rows with ``window_end``, of every time window that covers them (ends excluded)."""
    return stream.withColumn("window_end", F.window(F.col(ts), length, slide)["end"])


def time_windowed(ref: DataFrame, stream: DataFrame, ts: str, features: list[str], length: str, slide: str, least: int = 1, **options) -> DataFrame:
    """``window_end, n_rows, degree`` of sliding windows over time with ``least`` rows or more."""
    members = time_windows(stream, ts, length, slide)
    sizes = members.groupBy("window_end").agg(F.count(F.lit(1)).alias("n_rows")).where(F.col("n_rows") >= least)
    out = drift_degree(ref, members.join(sizes.select("window_end"), "window_end"), "window_end", features, **options)
    return out.join(sizes, "window_end").select("window_end", "n_rows", "degree")


def windows(stream: DataFrame, index: str, length: int, slide: int) -> DataFrame:
    """Rows with ``window_end``: each row joins every count window that covers it.

    Windows end at multiples of ``slide`` and hold the last ``length`` rows up to and
    including their end; memberships are generated, not joined.
    """
    i = F.col(index)
    first = F.ceil(i / slide) * slide
    last = F.floor((i + length - 1) / slide) * slide
    ends = F.when(last >= first, F.sequence(first.cast("long"), last.cast("long"), F.lit(slide).cast("long")))
    return stream.withColumn("window_end", F.explode(ends))


def windowed(ref: DataFrame, stream: DataFrame, index: str, features: list[str], length: int, slide: int, **options) -> DataFrame:
    """``window_end, n_rows, degree`` of count windows over the row index."""
    members = windows(stream, index, length, slide)
    ends = members.groupBy("window_end").agg(F.count(F.lit(1)).alias("n_rows"))
    full = ends.where(F.col("n_rows") == length).select("window_end", "n_rows")
    out = drift_degree(ref, members.join(full.select("window_end"), "window_end"), "window_end", features, **options)
    return out.join(full, "window_end").select("window_end", "n_rows", "degree")


def before_after(before: DataFrame, after: DataFrame, t: str) -> DataFrame:
    """``t, before, after, change``: two degree series of the same batches."""
    b = before.select(t, F.col("degree").alias("before"))
    return b.join(after.select(t, F.col("degree").alias("after")), t, "full").withColumn("change", F.col("after") - F.col("before"))


def feature_values(df: DataFrame, t: str, features: list[str]) -> DataFrame:
    """``t, feature, n, mean, low, high``: the features themselves over time."""
    pairs = F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("v")) for c in features]))
    long = df.select(t, pairs.alias("p")).select(t, "p.feature", "p.v")
    return long.groupBy(t, "feature").agg(
        F.count("v").alias("n"), F.avg("v").alias("mean"), F.min("v").alias("low"), F.max("v").alias("high")
    )


def ranked(parts: DataFrame, t: str, k: int = 3) -> DataFrame:
    """The k largest contributions of each batch."""
    order = Window.partitionBy(t).orderBy(F.desc("part"), "comp_id")
    return parts.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)

