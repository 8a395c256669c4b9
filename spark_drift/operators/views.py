"""The data behind every view, as tables: densities, learners, interest, performance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


# ------------------------------------------------------------------- density


def cell(value: Column, low: float, high: float, cells: int) -> Column:
    """Half-open cells over [low, high], the last closed; no extent gives cell 0."""
    if high <= low:
        return F.lit(0)
    at = F.floor((value - low) / (high - low) * cells).cast("int")
    return F.greatest(F.lit(0), F.least(F.lit(cells - 1), at))


def grid(df: DataFrame, x: str, y: str, bounds: tuple[float, float, float, float], cells: int = 32, by: list[str] = ()) -> DataFrame:
    """``by.., row, col, n, density``: each cell's share of its group's rows."""
    by = list(by)
    placed = df.select(*by, cell(F.col(y), bounds[2], bounds[3], cells).alias("row"), cell(F.col(x), bounds[0], bounds[1], cells).alias("col"))
    counts = placed.groupBy(*by, "row", "col").agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0)))
    return counts.withColumn("density", F.col("n") / total)


def halo(density: DataFrame, radius: int = 2, share: float = 0.3, split: str = "mass", by: list[str] = ()) -> DataFrame:
    """Each cell spread over its block. ``mass``: the ring cells divide ``share`` evenly;
    ``each``: every ring cell gets ``share`` of the cell and the centre keeps all."""
    by = list(by)
    ring = (2 * radius + 1) ** 2 - 1
    steps = F.array(*[
        F.struct(F.lit(i).alias("dr"), F.lit(j).alias("dc"), F.lit(float(_weight(i, j, ring, share, split))).alias("w"))
        for i in range(-radius, radius + 1) for j in range(-radius, radius + 1)
    ])
    spread = density.select(*by, "row", "col", "density", F.inline(steps))
    return spread.groupBy(*by, (F.col("row") + F.col("dr")).alias("row"), (F.col("col") + F.col("dc")).alias("col")).agg(
        F.sum(F.col("density") * F.col("w")).alias("density")
    )


def _weight(i: int, j: int, ring: int, share: float, split: str) -> float:
    if i == 0 and j == 0:
        return 1 - share if split == "mass" else 1.0
    return share / ring if split == "mass" else share


def density_diff(before: DataFrame, after: DataFrame, by: list[str] = ()) -> DataFrame:
    """``row, col, before, after, diff, sign``: denser where the later side has more."""
    keys = [*by, "row", "col"]
    a = before.select(*keys, F.col("density").alias("before"))
    b = after.select(*keys, F.col("density").alias("after"))
    both = a.join(b, keys, "full").select(
        *keys, F.coalesce("before", F.lit(0.0)).alias("before"), F.coalesce("after", F.lit(0.0)).alias("after")
    )
    diff = F.col("after") - F.col("before")
    sign = F.when(diff > 0, "denser").when(diff < 0, "sparser").otherwise("same")
    return both.select("*", diff.alias("diff"), sign.alias("sign"))


# ------------------------------------------------------------------ scatter


def frame(projection: DataFrame, bounds: tuple[float, float, float, float], cells: int = 32) -> DataFrame:
    """Density rows of the history and point rows of the current batch in one table."""
    old = grid(projection.where("not is_new"), "x", "y", bounds, cells)
    dens = old.select(
        F.lit("cell").alias("kind"), F.lit(None).cast("long").alias("sample_id"), F.lit(None).cast("int").alias("comp_id"),
        F.col("col").cast("double").alias("x"), F.col("row").cast("double").alias("y"), "density",
    )
    points = projection.where("is_new").select(
        F.lit("point").alias("kind"), "sample_id", "comp_id", "x", "y", F.lit(None).cast("double").alias("density")
    )
    return dens.unionByName(points)


def transition(previous: DataFrame, current: DataFrame) -> DataFrame:
    """Two stages: old rows move first, then new rows enter component by component."""
    p = previous.select("sample_id", F.col("x").alias("x0"), F.col("y").alias("y0"))
    both = current.join(p, "sample_id", "left")
    stage = F.when(F.col("x0").isNull(), 2).otherwise(1)
    group = F.dense_rank().over(Window.partitionBy("stage").orderBy("comp_id"))
    staged = both.withColumn("stage", stage)
    return staged.select(
        "sample_id", "stage", F.when(F.col("stage") == 2, group).otherwise(0).alias("turn"), "comp_id", "x0", "y0",
        F.col("x").alias("x1"), F.col("y").alias("y1"),
    )


def component_profile(assigned: DataFrame, features: list[str], t: str) -> DataFrame:
    """``comp_id, n, first_t, last_t`` and the mean and range of each feature."""
    stats = []
    for c in features:
        stats += [F.avg(c).alias(f"{c}_mean"), F.min(c).alias(f"{c}_low"), F.max(c).alias(f"{c}_high")]
    return assigned.groupBy("comp_id").agg(F.count(F.lit(1)).alias("n"), F.min(t).alias("first_t"), F.max(t).alias("last_t"), *stats)


# --------------------------------------------------------------- other views


def shares(members: DataFrame, assigned: DataFrame, group: str) -> DataFrame:
    """``group, comp_id, n, share``: how a learner's rows or a named set divide by component."""
    counts = members.join(assigned.select("sample_id", "comp_id"), "sample_id").groupBy(group, "comp_id").agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(group)))


def model_distribution(weights: DataFrame, members: DataFrame) -> DataFrame:
    """``set_id, learner, importance``: the weight a set's rows take from each learner."""
    sums = members.join(weights, "sample_id").groupBy("set_id", "learner").agg(F.sum("weight").alias("total"))
    return sums.select("set_id", "learner", (F.col("total") / F.sum("total").over(Window.partitionBy("set_id"))).alias("importance"))


def performance_bars(predictions: DataFrame, bins: int = 10) -> DataFrame:
    """``class, bin, role, n, share``: a wrong row is a false positive of the class it was
    given and a false negative of its own; unlabelled rows are left out."""
    rows = predictions.where("label is not null")
    bin_ = F.least(F.lit(bins - 1), F.floor(F.col("confidence") * bins)).cast("int")
    right = F.col("pred") == F.col("label")
    roles = F.when(right, F.array(_role("pred", "TP"))).otherwise(F.array(_role("pred", "FP"), _role("label", "FN")))
    long = rows.select(bin_.alias("bin"), F.inline(roles))
    counts = long.groupBy("class", "bin", "role").agg(F.count(F.lit(1)).alias("n"))
    total = rows.agg(F.count(F.lit(1)).alias("total"))
    return counts.withColumn("j", F.lit(1)).join(F.broadcast(total.withColumn("j", F.lit(1))), "j").select(
        "class", "bin", "role", "n", (F.col("n") / F.col("total")).alias("share")
    )


def _role(column: str, role: str) -> Column:
    return F.struct(F.col(column).alias("class"), F.lit(role).alias("role"))


def performance_compare(before: DataFrame, after: DataFrame, bins: int = 10) -> DataFrame:
    keys = ["class", "bin", "role"]
    a = performance_bars(before, bins).select(*keys, F.col("n").alias("n_before"))
    b = performance_bars(after, bins).select(*keys, F.col("n").alias("n_after"))
    zero = F.lit(0).cast("long")
    both = a.join(b, keys, "full").select(*keys, F.coalesce("n_before", zero).alias("n_before"), F.coalesce("n_after", zero).alias("n_after"))
    return both.withColumn("delta", F.col("n_after") - F.col("n_before"))
