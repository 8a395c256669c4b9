"""Normalised energy distance between two row sets, by several physical methods.

``1 - (within_ref + within_cur) / (2 * between)`` from three mean pair distances, self
pairs included. Pairs are never materialised: each method ends in partial sums.

* ``pairwise``: a salted join of blocks of rows, all pairs of two blocks in tiles of an Arrow task.
* ``blocks``: rows packed into blocks, pairs of blocks multiplied in Arrow tasks; for
  many dimensions, as columns or as one array column.
* ``sorted``: exact in one dimension, from counts in value order, bucket by bucket.
* ``cells``: rows replaced by weighted cell centres, with a certified error.
* ``sliced``: mean over random directions of the one-dimensional exact method.
* ``sampled``: pairwise on a deterministic share of each group, drawn by row id.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.functions.expressions import distance, hash_unit, placed
from spark_drift.operators import meet
from spark_drift.plans.lineage import cut

TERMS = ("n", "m", "between", "within_ref", "within_cur", "distance")


def pair_sums(
    x: DataFrame, y: DataFrame, features: list[str], by: list[str] = (), weight: str | None = None, salts: int = 32,
    also: list[str] = (),
) -> DataFrame:
    """``by.., also.., total``: weighted sum of distances over all pairs that agree in ``by``.

    ``also``: further keys of ``y`` kept in the result. Equal rows meet once, with their number as weight. Rows
    of ``x`` are dealt over ``salts`` blocks and each group of ``y`` visits them all, so one hot key spreads over
    that many tasks; pairs live in tiles inside an Arrow task.
    """
    by, also, d = list(by), list(also), len(features)

    def packed(df: DataFrame, keys: dict[str, list[str]], *more: Column) -> DataFrame:
        named = [F.struct(*[F.col(c).alias(f"k{i}") for i, c in enumerate(cs)]) if cs else F.struct(F.lit(0).alias("none")) for cs in keys.values()]
        values = [F.col(c).cast("double").alias(f"f{i}") for i, c in enumerate(features)]
        flat = df.select(*[c.alias(n) for n, c in zip(keys, named, strict=True)], *values, (F.col(weight) if weight else F.lit(1.0)).alias("w"))
        flat = flat.dropna(subset=[f"f{i}" for i in range(d)]).groupBy(*keys, *[f"f{i}" for i in range(d)]).agg(F.sum("w").alias("w"))
        rows = F.collect_list(F.array(*[F.col(f"f{i}") for i in range(d)], "w"))
        return flat.groupBy(*keys, *more).agg(rows.alias("rows"))

    salt = F.pmod(F.xxhash64(*[f"f{i}" for i in range(d)]), F.lit(salts)).alias("salt")
    left = packed(x, {"key": by}, salt).withColumnRenamed("rows", "xrows")
    right = packed(y, {"key": by, "own": also}).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    source = left.join(right.withColumnRenamed("rows", "yrows").hint("shuffle_hash"), ["key", "salt"]).select("key", "own", "xrows", "yrows")

    def matrix(lists) -> np.ndarray:
        flat = lists.values
        return flat.flatten().to_numpy().reshape(len(flat), -1)

    def run(batches):
        for batch in batches:
            totals = []
            for xs, ys in zip(batch.column(2), batch.column(3), strict=True):
                p, q = matrix(xs).T.copy(), matrix(ys).T.copy()
                total = 0.0
                for i in range(0, p.shape[1], 64):
                    one = p[:, i : i + 64]
                    for j in range(0, q.shape[1], 1024):
                        two = q[:, j : j + 1024]
                        gap = np.abs(one[0][:, None] - two[0]) if d == 1 else np.sqrt(meet.squares(list(one[:-1]), list(two[:-1])))
                        total += float(one[-1] @ (gap @ two[-1]))
                totals.append(total)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(totals, pa.float64())], names=["key", "own", "total"])

    sums = source.mapInArrow(run, source.select("key", "own", F.lit(0.0).alias("total")).schema)
    keys = [F.col(f"key.k{i}").alias(c) for i, c in enumerate(by)] + [F.col(f"own.k{i}").alias(c) for i, c in enumerate(also)]
    return sums.groupBy(*keys).agg(F.sum("total").alias("total"))


def block_sums(x: DataFrame, y: DataFrame, features: list[str], by: list[str] = (), rows: int = 1024) -> DataFrame:
    """As ``pair_sums`` for equal ``by`` keys, by matrix products over blocks of rows.

    ``features``: columns of numbers, or one array column. Each pair of blocks is a key of its
    own, so pairs spread over all tasks, with or without ``by``.
    """
    by = list(by)
    name = [F.col(c).alias(f"k{i}") for i, c in enumerate(by)]
    keys = [f"k{i}" for i in range(len(by))]
    array = len(features) == 1 and dict(x.dtypes)[features[0]].startswith("array")

    def packed(df: DataFrame, tag: str) -> DataFrame:
        vector = F.col(features[0]).cast("array<double>") if array else F.array(*[F.col(c).cast("double") for c in features])
        flat = df.select(*name, vector.alias("v"), F.xxhash64(*[F.col(f"`{c}`") for c in df.columns]).alias("spread"))
        size = flat.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
        # a group's size is one row per key, without keys one row altogether
        sized = flat.join(size, keys) if by else flat.crossJoin(F.broadcast(size))
        shares = F.greatest(F.lit(1).cast("long"), F.ceil(F.col("n") / rows))
        blocks = sized.withColumn("no", F.pmod("spread", shares)).groupBy(*keys, "no").agg(F.collect_list("v").alias("rows"))
        return blocks.select(*keys, F.col("no").alias(f"{tag}no"), F.col("rows").alias(f"{tag}rows"))

    a, b = packed(x, "x"), packed(y, "y")
    others = lambda blocks, no: blocks.groupBy(*keys).agg(F.collect_list(no).alias("others"))
    meet = lambda one, two: one.join(two, keys) if by else one.crossJoin(F.broadcast(two))
    left = meet(a, others(b.select(*keys, "yno"), "yno")).select(*keys, "xno", "xrows", F.explode("others").alias("yno"))
    right = meet(b, others(a.select(*keys, "xno"), "xno")).select(*keys, "yno", "yrows", F.explode("others").alias("xno"))
    pairs = left.join(right.hint("shuffle_hash"), [*keys, "xno", "yno"])
    source = pairs.select(F.struct(*keys).alias("key") if by else F.struct(F.lit(0).alias("none")).alias("key"), "xrows", "yrows")

    def matrix(lists) -> np.ndarray:
        flat = lists.values
        return flat.flatten().to_numpy().reshape(len(flat), -1)

    def run(batches):
        for batch in batches:
            totals = []
            for xs, ys in zip(batch.column(1), batch.column(2), strict=True):
                p, q = matrix(xs), matrix(ys)
                shift = p[0]
                p, q = p - shift, q - shift
                sq = (p * p).sum(1)[:, None] + (q * q).sum(1)[None] - 2 * p @ q.T
                # rows that coincide: the products cancel to rounding noise
                sq[sq < 1e-12 * ((p * p).sum(1)[:, None] + (q * q).sum(1)[None])] = 0.0
                totals.append(float(np.sqrt(np.maximum(sq, 0)).sum()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(totals, pa.float64())], names=["key", "total"])

    schema = source.select("key", F.lit(0.0).alias("total")).schema
    sums = source.mapInArrow(run, schema)
    return sums.groupBy(*[F.col(f"key.k{i}").alias(c) for i, c in enumerate(by)]).agg(F.sum("total").alias("total"))


def _counted(df: DataFrame, by: list[str], name: str, weight: str | None = None) -> DataFrame:
    return df.groupBy(*by).agg(F.sum(F.col(weight) if weight else F.lit(1)).alias(name))


def finish(n: Column, m: Column, between: Column, within_ref: Column, within_cur: Column, normalise: bool = True) -> Column:
    """The distance from its terms; all rows on one point give 0, no reference gives 1."""
    if not normalise:
        return 2 * between - within_ref - within_cur
    value = 1 - (within_ref + within_cur) / F.when(between > 0, 2 * between)
    bounded = F.greatest(F.lit(0.0), F.least(F.lit(1.0), value))
    return F.when(F.coalesce(n, F.lit(0)) == 0, 1.0).when(between == 0, 0.0).otherwise(bounded)


def energy_distance(
    ref: DataFrame,
    cur: DataFrame,
    features: list[str],
    by: list[str] = (),
    method: str = "pairwise",
    estimator: str = "v",
    normalise: bool = True,
    **options,
) -> DataFrame:
    """``by.., n, m, between, within_ref, within_cur, distance`` per group of ``cur``.

    ``estimator``: ``v`` counts self pairs, ``u`` divides by n(n-1), ``floor`` subtracts
    what equal distributions give by chance, 1/(2n) + 1/(2m).
    """
    by = list(by)
    if method == "sorted":
        (feature,) = features
        return sorted_distance(ref, cur, feature, by, estimator=estimator, normalise=normalise, **options)
    if method == "sliced":
        return sliced_distance(ref, cur, features, by, **options)
    if method == "sampled":
        draw = lambda df: sampled(df, options["key"], by, options.get("cap", 2000), options.get("seed", 0))
        return energy_distance(draw(ref), draw(cur), features, by, "pairwise", estimator, normalise)
    weight = None
    if method == "cells":
        cell = options["cell"]
        ref, cur, weight = cells_of(ref, features, cell, by), cells_of(cur, features, cell, by), "weight"
    sums = block_sums if method == "blocks" else lambda a, b, f, k: pair_sums(a, b, f, k, weight)
    parts = [
        _counted(cur, by, "m", weight), _counted(ref, by, "n", weight), sums(ref, cur, features, by).withColumnRenamed("total", "sb"),
        sums(ref, ref, features, by).withColumnRenamed("total", "sr"), sums(cur, cur, features, by).withColumnRenamed("total", "sc"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.join(p, by, "left") if by else out.withColumn("j", F.lit(1)).join(p.withColumn("j", F.lit(1)), "j", "left").drop("j")
    out = out.where("m > 0")
    out = _terms(out, by, estimator, normalise)
    if method == "cells":
        out = out.withColumn("max_error", F.lit(2 * options["cell"] * math.sqrt(len(features))))
    return out


def _terms(out: DataFrame, by: list[str], estimator: str, normalise: bool) -> DataFrame:
    n, m = F.coalesce(F.col("n"), F.lit(0)).cast("double"), F.col("m").cast("double")
    divide = F.try_divide
    less = 1.0 if estimator == "u" else 0.0
    between = divide(F.col("sb"), n * m)
    wr = F.coalesce(divide(F.col("sr"), n * (n - less)), F.lit(0.0))
    wc = F.coalesce(divide(F.col("sc"), m * (m - less)), F.lit(0.0))
    out = out.select(*by, n.cast("long").alias("n"), m.cast("long").alias("m"), between.alias("between"), wr.alias("within_ref"), wc.alias("within_cur"))
    args = [F.col(c) for c in TERMS[:-1]]
    if estimator == "u":
        value = F.when(args[0] == 0, 1.0).when(args[2] == 0, 0.0).otherwise(1 - (args[3] + args[4]) / F.when(args[2] > 0, 2 * args[2]))
    else:
        value = finish(*args, normalise)
    if estimator == "floor":
        value = F.when(args[0] == 0, 1.0).otherwise(F.greatest(F.lit(0.0), value - 0.5 / F.when(args[0] > 0, args[0]) - 0.5 / args[1]))
    return out.withColumn("distance", value)


def sorted_distance(
    ref: DataFrame, cur: DataFrame, feature: str, by: list[str] = (), buckets: int | None = None, estimator: str = "v", normalise: bool = True,
    also: list[str] = (),
) -> DataFrame:
    """Exact one-dimensional terms from counts in value order.

    ``also``: further keys of ``cur`` (times): each of its groups meets the whole reference of its
    ``by`` keys, whose own term and running sums are computed once. Values are counted, dealt
    to buckets between the quantiles of their own ``by`` group, and a bucket's running sums start from a
    table of one row per group and bucket, so no task ever orders all values of a group.
    """
    by, every = list(by), [*by, *also]
    v = F.col(feature).cast("double")
    a = ref.groupBy(*by, v.alias("v")).agg(F.count(F.lit(1)).alias("w"))
    b = cur.groupBy(*every, v.alias("v")).agg(F.count(F.lit(1)).alias("w"))
    if buckets is None:
        buckets = max(64, -(-ref.count() // 1_000_000))
    shares = F.lit([k / buckets for k in range(1, buckets)]) if buckets > 1 else None
    bounds = F.array().cast("array<double>") if shares is None else F.array_distinct(F.percentile_approx("v", shares, 10 * buckets))
    # one row of bounds per group
    spans = ref.select(*by, v.alias("v")).unionByName(cur.select(*by, v.alias("v"))).groupBy(*by).agg(bounds.alias("bounds"))

    def dealt(rows: DataFrame) -> DataFrame:
        met = rows.join(spans, by) if by else rows.crossJoin(F.broadcast(spans))
        return met.withColumn("bucket", placed(F.col("bounds"), F.col("v"))).drop("bounds")

    a, b = cut(dealt(a)), cut(dealt(b))
    out = _gaps(a, a, by, []).withColumnRenamed("total", "sr").withColumnRenamed("m", "n")
    out = b.groupBy(*every).agg(F.sum("w").alias("m")).join(out, by, "left") if by else b.groupBy(*every).agg(F.sum("w").alias("m")).crossJoin(F.broadcast(out))
    for name, one in (("sb", _gaps(a, b, by, list(also))), ("sc", _gaps(b, b, every, []))):
        one = one.drop("m").withColumnRenamed("total", name)
        out = out.join(one, every, "left") if every else out.crossJoin(F.broadcast(one))
    return _terms(out.where("m > 0"), every, estimator, normalise)


def _gaps(x: DataFrame, y: DataFrame, by: list[str], also: list[str]) -> DataFrame:
    """``by.., also.., total, m``: summed distances of all pairs of a row of ``x`` and one of ``y``
    that agree in ``by``, from running counts and sums of ``x`` in value order."""
    sides = x.groupBy(*by, "bucket").agg(F.sum("w").alias("c0"), F.sum(F.col("w") * F.col("v")).alias("s0"))
    marks = y.select(*by, "bucket").distinct().withColumns({"c0": F.lit(0).cast("long"), "s0": F.lit(0.0)})
    table = sides.unionByName(marks).groupBy(*by, "bucket").agg(F.sum("c0").alias("c0"), F.sum("s0").alias("s0"))
    group = Window.partitionBy(*by)
    before = group.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    start = {n: F.coalesce(F.sum(n).over(before), F.lit(0)) for n in ("c0", "s0")}
    table = table.select(
        *by, "bucket", start["c0"].alias("c_before"), start["s0"].alias("s_before"), F.sum("c0").over(group).alias("c_all"), F.sum("s0").over(group).alias("s_all")
    )
    none = [F.lit(None).cast(y.schema[c].dataType).alias(c) for c in also]
    mine = x.select(*by, *none, "bucket", "v", F.col("w").alias("a"), F.lit(0).cast("long").alias("b"))
    both = mine.unionByName(y.select(*by, *also, "bucket", "v", F.lit(0).cast("long").alias("a"), F.col("w").alias("b")))
    upto = Window.partitionBy(*by, "bucket").orderBy("v").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    rows = both.select("*", F.sum("a").over(upto).alias("c"), F.sum(F.col("a") * F.col("v")).over(upto).alias("s")).where("b > 0")
    rows = rows.join(table, [*by, "bucket"])
    c, s = F.col("c") + F.col("c_before"), F.col("s") + F.col("s_before")
    gap = F.col("v") * (2 * c - F.col("c_all")) + F.col("s_all") - 2 * s
    return rows.groupBy(*by, *also).agg(F.sum(F.col("b") * gap).alias("total"), F.sum("b").alias("m"))


def cells_of(df: DataFrame, features: list[str], cell: float, by: list[str] = ()) -> DataFrame:
    """Weighted cell centres: ``by.., features.., weight``."""
    corner = [F.floor(F.col(c) / cell).alias(f"c{i}") for i, c in enumerate(features)]
    return (
        df.groupBy(*by, *corner)
        .agg(*[F.avg(F.col(c).cast("double")).alias(c) for c in features], F.count(F.lit(1)).cast("double").alias("weight"))
        .drop(*[f"c{i}" for i in range(len(features))])
    )


def sampled(df: DataFrame, key: str, by: list[str], cap: int, seed: int = 0) -> DataFrame:
    """About ``cap`` rows per group (all rows of smaller ones), drawn by a digest of the row id
    ``key``: rows with equal features enter or leave each on its own."""
    draw = hash_unit(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")))
    if not by:
        n = df.count()
        return df.where(draw <= cap / max(n, 1))
    sizes = df.groupBy(*by).agg(F.count(F.lit(1)).alias("size"))
    return df.join(sizes, list(by)).where(draw <= F.lit(float(cap)) / F.col("size")).drop("size")


def norm_constant(d: int) -> float:
    """Ratio of a vector's norm to the mean absolute projection on unit directions."""
    return math.sqrt(math.pi) * math.gamma((d + 1) / 2) / math.gamma(d / 2)


def sliced_distance(
    ref: DataFrame, cur: DataFrame, features: list[str], by: list[str] = (), directions: int = 100, seed: int = 0, also: list[str] = ()
) -> DataFrame:
    """Distance from the exact one-dimensional terms of random projections; ``also`` as for ``sorted_distance``."""
    by, also, d = list(by), list(also), len(features)
    units = np.random.Generator(np.random.PCG64(seed)).normal(size=(directions, d))
    units /= np.linalg.norm(units, axis=1, keepdims=True)

    def cast_on(df: DataFrame, keys: list[str]) -> DataFrame:
        rays = F.lit(0.0)
        table = F.array(*[F.array(*[F.lit(float(v)) for v in u]) for u in units])
        return df.select(*keys, F.posexplode(table).alias("ray", "unit"), *features).select(
            *keys, "ray", sum((F.col(c).cast("double") * F.col("unit")[i] for i, c in enumerate(features)), rays).alias("v")
        )

    each = sorted_distance(cast_on(ref, by), cast_on(cur, [*by, *also]), "v", [*by, "ray"], also=also)
    c = norm_constant(d)
    mean = each.groupBy(*by, *also).agg(
        F.max("n").alias("n"), F.max("m").alias("m"), *[(F.avg(t) * c).alias(t) for t in ("between", "within_ref", "within_cur")]
    )
    return mean.withColumn("distance", finish(*[F.col(t) for t in TERMS[:-1]]))


def moment_lower_bound(ref: DataFrame, cur: DataFrame, features: list[str], by: list[str] = ()) -> DataFrame:
    """``by.., bound``: a distance no smaller than this is certain, from one pass of moments."""
    by = list(by)

    def moments(df: DataFrame, tag: str) -> DataFrame:
        return df.groupBy(*by).agg(
            *[F.avg(c).alias(f"{tag}m{i}") for i, c in enumerate(features)],
            sum((F.var_pop(c) for c in features[1:]), F.var_pop(features[0])).alias(f"{tag}s"),
        )

    a, b = moments(ref, "r"), moments(cur, "c")
    both = a.join(b, by) if by else a.withColumn("j", F.lit(1)).join(b.withColumn("j", F.lit(1)), "j")
    gap = distance([F.col(f"rm{i}") for i in range(len(features))], [F.col(f"cm{i}") for i in range(len(features))])
    bound = 1 - (F.sqrt(2 * F.col("rs")) + F.sqrt(2 * F.col("cs"))) / F.when(gap > 0, 2 * gap)
    return both.select(*by, F.greatest(F.lit(0.0), F.coalesce(bound, F.lit(0.0))).alias("bound"))


def mean_pair_distance(x: DataFrame, y: DataFrame, features: list[str]) -> DataFrame:
    """One row ``value``: the mean over all pairs of one row from each side."""
    one = F.lit(1).alias("j")
    total = pair_sums(x, y, features).select(one, "total")
    n = x.agg(F.count(F.lit(1)).alias("n")).select(one, "n")
    m = y.agg(F.count(F.lit(1)).alias("m")).select(one, "m")
    return total.join(n, "j").join(m, "j").select((F.col("total") / (F.col("n") * F.col("m"))).alias("value"))


def poisson_divergence(ref: DataFrame, cur: DataFrame, feature: str, by: list[str] = ()) -> DataFrame:
    """Symmetric divergence of two Poisson laws with the two sides' mean counts."""
    by = list(by)
    a = ref.groupBy(*by).agg(F.avg(feature).alias("a"))
    b = cur.groupBy(*by).agg(F.avg(feature).alias("b"))
    both = a.join(b, by) if by else a.withColumn("j", F.lit(1)).join(b.withColumn("j", F.lit(1)), "j")
    value = F.when((F.col("a") > 0) & (F.col("b") > 0), (F.col("a") - F.col("b")) * F.log(F.col("a") / F.col("b")))
    return both.select(*by, F.coalesce(value, F.when(F.col("a") == F.col("b"), 0.0)).alias("divergence"))
