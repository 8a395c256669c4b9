"""Summed distances of all pairs of a reference and its batches, by a path that goes by the number of features, never by sizes.

* two features: rows lie in cells (``functions/pairs.py``). A tile of cells is a task: pairs of cells that touch are summed
  one by one, farther ones from the cells' weights, which only the neighbouring tiles see; tiles meet by one weight each.
* otherwise: rows, a few numbers each, are sent to every task through the driver; pairs of blocks of rows are dealt over tasks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_drift.functions import pairs
from spark_drift.operators import meet
from spark_drift.plans.lineage import cut

#: rows of a block, for more than two features
ROWS = 4096


def terms(ref: DataFrame, cur: DataFrame, features: list[str], by: list[str], also: list[str]) -> DataFrame:
    """``by.., also.., n, m, sb, sr, sc`` per batch (``by``, ``also``) of ``cur``: the rows of the reference of its ``by`` keys and its own, and the
    summed distances between the two, within that reference and within the batch, over all rows without missing features."""
    return (_by_cells if len(features) == 2 else _by_blocks)(ref, cur, features, list(by), list(also))


# -------------------------------------------------------------------- more features


def _by_blocks(ref: DataFrame, cur: DataFrame, features: list[str], by: list[str], also: list[str]) -> DataFrame:
    spark, names, keys = cur.sparkSession, [f"f{i}" for i in range(len(features))], [*by, *also]
    values = [F.col(c).cast("double").alias(n) for c, n in zip(features, names, strict=True)]
    none = [F.lit(None).cast(cur.schema[c].dataType).alias(c) for c in also]
    both = ref.select(F.lit(False).alias("new_"), *by, *none, *values).unionByName(cur.select(F.lit(True).alias("new_"), *keys, *values))
    table = both.toArrow().combine_chunks()
    if not len(table):
        return spark.createDataFrame([], cur.select(*keys, *[F.lit(0).cast("long").alias(c) for c in "nm"], *[F.lit(0.0).alias(c) for c in ("sb", "sr", "sc")]).schema)
    plain = table.select(["new_", *keys]).to_pandas()
    number = lambda cs: plain.groupby(cs, dropna=False, sort=False).ngroup().to_numpy() if cs else np.zeros(len(plain), int)
    x, new = np.stack(meet.arrays(table.select(names)), 1), plain["new_"].to_numpy(bool)
    whole, key, group = ~np.isnan(x).any(1), number(by), number(["new_", *keys])
    # a group's rows, without those that lack a feature, side by side
    order = np.nonzero(whole)[0][np.argsort(group[whole], kind="stable")]
    groups = group.max() + 1
    size, first = np.bincount(group, minlength=groups), np.unique(group, return_index=True)[1]
    ends = np.concatenate([[0], np.cumsum(np.bincount(group[whole], minlength=groups))])
    refs = {int(key[first[g]]): g for g in range(groups) if not new[first[g]]}
    spans = lambda g: [(a, min(a + ROWS, ends[g + 1])) for a in range(ends[g], ends[g + 1], ROWS)]
    current = [g for g in range(groups) if new[first[g]]]
    met = [(g, refs[k], 1.0, p, q) for g in current if (k := int(key[first[g]])) in refs for p in spans(g) for q in spans(refs[k])]
    # within a group, a pair of blocks counts both ways
    for g in sorted({*current, *[refs[k] for g in current if (k := int(key[first[g]])) in refs]}):
        met += [(g, g, 1.0 if p == q else 2.0, p, q) for p in spans(g) for q in spans(g) if p <= q]
    sums = {}
    if met:
        sent = spark.sparkContext.broadcast(np.ascontiguousarray(x[order]))

        def run(some):
            rows = sent.value
            for g, other, times, (a, b), (c, d) in some:
                yield g, other, times * pairs.summed(rows[a:b], rows[c:d])

        met = [(int(g), int(o), t, tuple(map(int, p)), tuple(map(int, q))) for g, o, t, p, q in met]
        cores = spark.sparkContext.defaultParallelism
        dealt = [met[k] for k in np.random.Generator(np.random.PCG64(0)).permutation(len(met))]
        for g, other, total in spark.sparkContext.parallelize(dealt, min(len(met), 4 * cores)).mapPartitions(run).collect():
            sums.setdefault((g, other), []).append(total)
        sent.unpersist()
    out = []
    for g in current:
        other = refs.get(int(key[first[g]]))
        total = lambda a, b: float(np.sum(sums[a, b])) if (a, b) in sums else None
        out.append((int(size[other]) if other is not None else 0, int(size[g]), total(g, other), total(other, other), total(g, g)))
    n, m, *found = zip(*out, strict=True) if out else ([], [], [], [], [])
    kept = table.select(keys).take(pa.array([int(first[g]) for g in current], pa.int64()))
    for name, values in zip(("n", "m"), (n, m), strict=True):
        kept = kept.append_column(name, pa.array(values, pa.int64()))
    for name, values in zip(("sb", "sr", "sc"), found, strict=True):
        kept = kept.append_column(name, pa.array(values, pa.float64()))
    return spark.createDataFrame(kept)


# --------------------------------------------------------------------- two features

SUMS = "kid long, gid long, between double, within double"
CELLS = "kid long, tx long, ty long, kind int, gid long, level int, a double, b double, w double, weights array<double>"


def _tasks(df: DataFrame, wanted: float) -> int:
    return int(max(2 * df.sparkSession.sparkContext.defaultParallelism, min(wanted, 20_000)))


def _by_cells(ref: DataFrame, cur: DataFrame, features: list[str], by: list[str], also: list[str]) -> DataFrame:
    names = ["f0", "f1"]
    values = [F.col(c).cast("double").alias(n) for c, n in zip(features, names, strict=True)]
    key = F.struct(F.lit(0).alias("k"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(by)]).alias("key")
    # the reference is a group like the batches, without their further keys
    own = lambda side, cols: F.struct(F.lit(side).alias("side"), *[c.alias(f"a{i}") for i, c in enumerate(cols)]).alias("own")
    one = ref.select(key, own(0, [F.lit(None).cast(cur.schema[c].dataType) for c in also]), *values)
    rows = one.unionByName(cur.select(key, own(1, [F.col(c) for c in also]), *values))
    found = _cell_sums(rows.dropna(subset=names), names)
    found = found.groupBy("key", "own").agg(F.sum("between").alias("sb"), F.sum("within").alias("sc"))
    found = rows.groupBy("key", "own").agg(F.count(F.lit(1)).alias("m")).join(found, ["key", "own"], "left")
    inner = found.where("own.side = 0").select("key", F.col("m").alias("n"), F.col("sc").alias("sr"))
    out = found.where("own.side = 1").join(inner, "key", "left")
    named = [F.col(f"key.k{i}").alias(c) for i, c in enumerate(by)] + [F.col(f"own.a{i}").alias(c) for i, c in enumerate(also)]
    return out.select(*named, "n", "m", "sb", "sr", "sc")


def _cell_sums(rows: DataFrame, names: list[str]) -> DataFrame:
    """Partial sums ``key, own, between, within``; equal rows meet once, with their number as weight."""
    # numbers for keys and for batches; the reference is 0
    number = F.when(F.col("own.side") == 0, 0).otherwise(F.monotonically_increasing_id() + 1)
    owners = cut(rows.select("key", "own").distinct().withColumn("gid", number))
    owners = cut(owners.join(F.broadcast(owners.select("key").distinct().withColumn("kid", F.monotonically_increasing_id())), "key"))
    rows = rows.join(F.broadcast(owners), ["key", "own"])
    rows = cut(rows.groupBy("kid", "gid", *names).agg(F.count(F.lit(1)).cast("double").alias("w")))
    n, *ends = rows.agg(F.count(F.lit(1)), *[f(c) for c in names for f in (F.min, F.max)]).first()
    if not n:
        return owners.select("key", "own", F.lit(0.0).alias("between"), F.lit(0.0).alias("within"))
    low, span = [float(ends[0]), float(ends[2])], max(float(ends[1]) - float(ends[0]), float(ends[3]) - float(ends[2]))
    if not np.isfinite(span):
        raise ValueError("features must be finite")
    depth = 0
    at = lambda width: [F.floor((F.col(c) - F.lit(v)) / F.lit(width)).alias(s) for c, v, s in zip(names, low, "xy", strict=True)]
    if span > 0:
        # cells as small as a row needs to meet some hundred others in its own
        depth = max(0, int(np.log2(max(n / pairs.CROWD, 1)) / 2))
        while depth < pairs.DEEPEST:
            crowd = rows.groupBy("kid", *at(span / 2**depth)).count().agg(F.sum(F.col("count").cast("double") * F.col("count"))).first()[0]
            if crowd <= pairs.CROWD * n:
                break
            # one halving leaves a quarter where rows lie evenly
            depth += max(1, int(np.log2(crowd / (pairs.CROWD * n)) / 2))
    width, side = (span / 2**depth if span > 0 else 1.0), 2**pairs.STEPS
    tasks = _tasks(rows, n / 10_000)
    tile = lambda c: F.floor(F.col(c) / side)
    placed = rows.select("*", *at(width)).select("kid", "gid", *names, "w", "x", "y", tile("x").alias("tx"), tile("y").alias("ty"))

    def weigh(key, table):
        """Weights of a tile's cells at all levels, for the tiles that see them; the tile's own stands for it among tiles."""
        kid, tx, ty = (k.as_py() for k in key)
        gid, x, w = _numbers(table, "gid"), np.stack([_numbers(table, n) for n in names], 1), _numbers(table, "w")
        out = []
        for g in np.unique(gid):
            cells, weights = pairs.leaves(x[gid == g], w[gid == g], np.array(low), width)
            for level in range(pairs.STEPS + 1):
                if level == pairs.STEPS:
                    seen = [(tx, ty, np.ones(len(cells), bool))]
                else:
                    reach = 2 ** (pairs.STEPS - level)
                    near = lambda t, c: (c >= t * reach - 2) & (c < (t + 1) * reach + 2)  # noqa: B023, E731
                    seen = [(a, b, near(a, cells[:, 0]) & near(b, cells[:, 1])) for a in (tx - 1, tx, tx + 1) for b in (ty - 1, ty, ty + 1)]
                for a, b, mine in seen:
                    k = int(mine.sum())
                    if k:
                        fixed = [np.full(k, v, np.int64) for v in (kid, a, b)]
                        out.append((*fixed, np.full(k, 3 if level == pairs.STEPS else 2, np.int32), np.full(k, g, np.int64), np.full(k, level, np.int32),
                                    *cells[mine].T.astype(float), np.ones(k), weights[mine].reshape(k, -1)))
                cells, weights = pairs.above(cells, weights)
        columns = [np.concatenate(c) for c in zip(*out, strict=True)]
        return _table(columns)

    weighed = cut(placed.repartition(tasks, "kid", "tx", "ty").groupBy("kid", "tx", "ty").applyInArrow(weigh, CELLS))
    none = [F.lit(-1).alias("level"), F.col(names[0]).alias("a"), F.col(names[1]).alias("b"), "w", F.lit(None).cast("array<double>").alias("weights")]
    own = placed.select("kid", "tx", "ty", F.lit(0).alias("kind"), "gid", *none)
    # rows of the cells around a tile
    steps = lambda c, t: F.array_distinct(F.array(*[F.floor((F.col(c) + s) / side) for s in (-1, 0, 1)]))
    around = placed.withColumns({"ox": F.col("tx"), "oy": F.col("ty")}).withColumn("tx", F.explode(steps("x", "tx"))).withColumn("ty", F.explode(steps("y", "ty")))
    around = around.where((F.col("tx") != F.col("ox")) | (F.col("ty") != F.col("oy"))).select("kid", "tx", "ty", F.lit(1).alias("kind"), "gid", *none)
    near = own.unionByName(around).unionByName(weighed.where("kind = 2"))

    def meet(key, table):
        kid, tx, ty = (k.as_py() for k in key)
        kind, gid = _numbers(table, "kind"), _numbers(table, "gid")
        own, rows = kind == 0, kind < 2
        if not own.any():  # a tile without rows, next to some
            return _sums([])
        at, w = np.stack([_numbers(table, "a"), _numbers(table, "b")], 1), _numbers(table, "w")
        level = _numbers(table, "level")[~rows]
        cells, owner = at[~rows].astype(np.int64), gid[~rows]
        weights = _weights(table.filter(pa.array(~rows)))
        sides = {int(g): pairs.Crowd(at[rows & (gid == g)], w[rows & (gid == g)], np.array(low), width) for g in np.unique(gid[rows])}
        far = {}
        for g in np.unique(owner):
            for k in range(pairs.STEPS):
                mine = (owner == g) & (level == k)
                far[int(g), k] = (cells[mine], weights[mine])
        inside = lambda c, k: ((c >> (pairs.STEPS - k)) == [tx, ty]).all(1)
        out = []
        for g in np.unique(gid[own]).tolist():
            mine = pairs.Crowd(at[own & (gid == g)], w[own & (gid == g)], np.array(low), width)
            sums = []
            for other in (0, g):
                total = mine.touching(sides[other]) if other in sides else 0.0
                for k in range(pairs.STEPS):
                    if (g, k) in far and (other, k) in far:
                        c, v = far[g, k]
                        here = inside(c, k)
                        total += pairs.apart((c[here], v[here]), far[other, k], width * 2.0**k / 2)
                sums.append(total)
            out.append((kid, g, sums[0] if g else 0.0, sums[1]))
        return _sums(out)

    def meet_tiles(key, table):
        gid, cells = _numbers(table, "gid"), np.stack([_numbers(table, "a"), _numbers(table, "b")], 1).astype(np.int64)
        weights = _weights(table)
        towers = {int(g): (cells[gid == g], weights[gid == g]) for g in np.unique(gid)}
        out = []
        for g in towers:
            sums = [pairs.tower(towers[g], towers[other], width * side / 2) if other in towers else 0.0 for other in (0, g)]
            out.append((key[0].as_py(), g, sums[0] if g else 0.0, sums[1]))
        return _sums(out)

    first = near.repartition(tasks, "kid", "tx", "ty").groupBy("kid", "tx", "ty").applyInArrow(meet, SUMS)
    found = first.unionByName(weighed.where("kind = 3").groupBy("kid").applyInArrow(meet_tiles, SUMS))
    found = found.groupBy("kid", "gid").agg(F.sum("between").alias("between"), F.sum("within").alias("within"))
    return found.join(F.broadcast(owners), ["kid", "gid"]).select("key", "own", "between", "within")


def _numbers(table: pa.Table, name: str) -> np.ndarray:
    return table.column(name).to_numpy()


def _weights(table: pa.Table) -> np.ndarray:
    lists = table.column("weights").combine_chunks()
    flat = lists.flatten() if len(lists) else pa.array([], pa.float64())
    return flat.to_numpy(zero_copy_only=False).reshape(-1, pairs.NODES, pairs.NODES)


def _table(columns: list[np.ndarray]) -> pa.Table:
    *plain, weights = columns
    ends = np.arange(len(weights) + 1, dtype=np.int32) * weights.shape[1]
    lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(weights.ravel()))
    names = ["kid", "tx", "ty", "kind", "gid", "level", "a", "b", "w", "weights"]
    return pa.Table.from_arrays([*[pa.array(c) for c in plain], lists], names=names)


def _sums(out: list[tuple]) -> pa.Table:
    kid, gid, between, within = zip(*out, strict=True) if out else ([], [], [], [])
    return pa.table({"kid": pa.array(kid, pa.int64()), "gid": pa.array(gid, pa.int64()), "between": pa.array(between, pa.float64()), "within": pa.array(within, pa.float64())})
