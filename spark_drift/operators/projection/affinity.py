"""Distances, affinities and divergences of a map as tables: what the embedding kernel optimises.

Pairs of rows, and of rows and anchors, meet tile by tile in Arrow tasks (``operators/meet.py``) and end
there in sums, in nearest rows, or in one row per row and anchor; no pair is shuffled.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.functions.expressions import distance
from spark_drift.operators import meet

SALTS = 16


def _sided(rows: DataFrame, columns: list[str], tag: str) -> DataFrame:
    return rows.select(*[F.col(c).alias(f"{tag}{c}") for c in columns])


def pairs(rows: DataFrame, partners: DataFrame, columns: list[str], others: list[str], key: str = "sample_id") -> DataFrame:
    """All pairs, the columns of the first side named ``a_``, of the second ``b_``; the second is dealt over shares."""
    left = _sided(rows, columns, "a_").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    right = _sided(partners, others, "b_").withColumn("salt", F.pmod(F.hash(f"b_{key}"), F.lit(SALTS)))
    return left.join(right, "salt").drop("salt")


def gap(columns: list[str]) -> Column:
    return distance([F.col(f"a_{c}") for c in columns], [F.col(f"b_{c}") for c in columns])


def shrunk(features: list[str]) -> Column:
    """The pair's distance, times the component's factor where both sides share one."""
    return gap(features) * F.when(F.col("a_comp_id") == F.col("b_comp_id"), F.col("a_factor")).otherwise(1.0)


def with_factors(rows: DataFrame, factors: DataFrame) -> DataFrame:
    """Rows with the ``factor`` of their component (one row per component, broadcast)."""
    return rows.join(F.broadcast(factors.select("comp_id", "factor")), "comp_id")


def shrunk_distances(rows: DataFrame, factors: DataFrame, features: list[str]) -> DataFrame:
    """``comp_a, comp_b, n, mean``: mean shrunk distance of the pairs of different rows, by components."""
    named = with_factors(rows, factors)
    columns = ["sample_id", "comp_id", "factor", *features]
    met = pairs(named, named, columns, columns).where("a_sample_id <> b_sample_id")
    by = met.groupBy(F.col("a_comp_id").alias("comp_a"), F.col("b_comp_id").alias("comp_b"))
    return by.agg(F.count(F.lit(1)).alias("n"), F.avg(shrunk(features)).alias("mean"))


def centres(rows: DataFrame, features: list[str]) -> DataFrame:
    """One row per component: its size, its mean, and its place on the map."""
    means = [F.avg(c).alias(c) for c in (*features, "x", "y")]
    return rows.groupBy("comp_id").agg(F.count(F.lit(1)).alias("size"), *means).withColumn("sample_id", F.col("comp_id").cast("long"))


def _normal(df: DataFrame, *columns: str) -> DataFrame:
    whole = df.agg(*[F.sum(c).alias(f"whole_{c}") for c in columns])  # one row
    return df.crossJoin(F.broadcast(whole)).select(*[(F.col(c) / F.col(f"whole_{c}")).alias(c) if c in columns else c for c in df.columns])


def _scaled(met: DataFrame, rank: int) -> DataFrame:
    """``met`` with ``scale``: the median over rows of the distance to the ``rank``-th nearest partner."""
    order = F.row_number().over(Window.partitionBy("a_sample_id").orderBy("d"))
    scale = met.withColumn("r", order).where(F.col("r") == rank).agg(F.greatest(F.median("d"), F.lit(1e-12)).alias("scale"))
    return met.crossJoin(F.broadcast(scale))  # one row


def centre_affinity(rows: DataFrame, factors: DataFrame, features: list[str]) -> DataFrame:
    """``sample_id, centre, p, q``: joint affinity of rows to component centres, weighted by the root of the
    size, and the heavy-tailed one on the map."""
    named, middle = with_factors(rows, factors), centres(rows, features)
    met = pairs(named, middle, ["sample_id", "comp_id", "factor", "x", "y", *features], ["sample_id", "comp_id", "size", "x", "y", *features])
    met = _scaled(met.withColumn("d", shrunk(features)), 1)
    out = met.select(
        F.col("a_sample_id").alias("sample_id"), F.col("b_comp_id").alias("centre"), (F.sqrt("b_size") * F.exp(-F.col("d") / F.col("scale"))).alias("p"),
        (1 / (1 + gap(["x", "y"]) ** 2)).alias("q"),
    )
    return _normal(out, "p", "q")


#: joint affinities from here on count in a divergence
LEAST = 1e-11


def _met(rows: DataFrame, partners: DataFrame, features: list[str]) -> tuple[DataFrame, meet.Broadcast, int]:
    """Both sides as ``sample_id, comp_id, factor, x, y, features..``, the second on every executor."""
    columns = ["sample_id", "comp_id", "factor", "x", "y", *features]
    side, n = meet.sent(partners.select(*columns), ["sample_id"])
    return meet.spread(rows.select(*columns), n), side, n


def _tiles(part: list[np.ndarray], side: list[np.ndarray]):
    """Per tile of the sent side: its columns, whose pairs are a row's own, shrunk distances and squared ones on the map."""
    for start in range(0, len(side[0]), meet.TILE):
        other = [c[start : start + meet.TILE] for c in side]
        d = np.sqrt(meet.squares(part[5:], other[5:]))
        d *= np.where(part[1][:, None] == other[1][None], part[2][:, None], 1.0)
        yield other, part[0][:, None] == other[0][None], d, meet.squares(part[3:5], other[3:5])


class _Anchors:
    """Rows met with anchors: the scale and both sums first, then shares of them."""

    def __init__(self, rows: DataFrame, anchors: DataFrame, factors: DataFrame, features: list[str]) -> None:
        self.rows, self.side, n = _met(with_factors(rows, factors), with_factors(anchors, factors), features)
        side = self.side

        def second(batches):
            for part in meet.chunks(batches):
                low = np.full((len(part[0]), 2), np.inf)
                for _, _, d, _ in _tiles(part, side.value):
                    low = np.sort(np.concatenate([low, np.partition(d, min(1, d.shape[1] - 1), axis=1)[:, :2]], axis=1), axis=1)[:, :2]
                yield pa.RecordBatch.from_arrays([pa.array(low[:, 1])], names=["d"])

        found = self.rows.mapInArrow(second, "d double").where("d < double('inf')").agg(F.median("d").alias("d")).first() if n > 1 else {"d": None}
        self.scale = max(found["d"] or 0.0, 1e-12)
        self.whole = meet.sums(self.rows, self._summed(lambda p, q: (np.nansum(p), np.nansum(q))), 2)

    def _each(self):
        scale, side = self.scale, self.side

        def each(part):
            for other, own, d, m in _tiles(part, side.value):
                p = np.exp(-d / scale)
                p[own] = 1.0
                yield other, p, 1 / (1 + m)

        return each

    def _summed(self, add):
        each = self._each()
        return lambda part: sum((np.array(add(p, q)) for _, p, q in each(part)), np.zeros(1))

    def divergence(self) -> float:
        return float(meet.sums(self.rows, self._summed(_term(*self.whole)), 1)[0])

    def table(self) -> DataFrame:
        each, (sp, sq) = self._each(), self.whole

        def run(batches):
            for part in meet.chunks(batches, 32):
                for other, p, q in each(part):
                    n, m = p.shape
                    columns = [np.repeat(part[0], m), np.tile(other[0], n), p.ravel() / sp, q.ravel() / sq]
                    yield pa.RecordBatch.from_arrays([pa.array(c, from_pandas=True) for c in columns], names=["sample_id", "anchor", "p", "q"])

        return self.rows.mapInArrow(run, "sample_id long, anchor long, p double, q double")


def _term(sp: float, sq: float):
    """What pairs of raw affinities add to the divergence of their shares."""

    def add(p, q):
        p, q = p / sp, q / sq
        counts = p > LEAST
        p, q = p[counts], q[counts]
        return [np.sum(p * np.log(p / q))]

    return add


def anchor_affinity(rows: DataFrame, anchors: DataFrame, factors: DataFrame, features: list[str]) -> DataFrame:
    """``sample_id, anchor, p, q``: joint affinity of rows to anchors, 1 before normalising with a row's own."""
    return _Anchors(rows, anchors, factors, features).table()


def row_divergence(rows: DataFrame, factors: DataFrame, features: list[str], width: float) -> float:
    """The divergence over the pairs of different rows of Gaussian affinities of one width from those of the map."""
    named = with_factors(rows, factors)
    passing, side, _ = _met(named, named, features)

    def summed(add):
        def run(part):
            total = np.zeros(1)
            for _, own, d, m in _tiles(part, side.value):
                d *= d
                d *= -1 / (2 * width**2)
                p, q = np.exp(d, out=d), 1 / (1 + m)
                p[own] = q[own] = 0.0
                total = total + np.array(add(p, q))
            return total

        return run

    sp, sq = meet.sums(passing, summed(lambda p, q: (np.nansum(p), np.nansum(q))), 2)
    return float(meet.sums(passing, summed(_term(sp, sq)), 1)[0]) if sp > 0 else 0.0


def divergence(joint: DataFrame) -> DataFrame:
    """One row ``value``: the divergence of ``p`` from ``q``."""
    return joint.where(F.col("p") > LEAST).agg(F.sum(F.col("p") * F.log(F.col("p") / F.col("q"))).alias("value"))


def objective(rows: DataFrame, anchors: DataFrame, factors: DataFrame, features: list[str], width: float, lam: float = 0.6, phi: float = 0.2) -> DataFrame:
    """One row ``map, shape, position, total``: the three divergences of a fixed map and their weighted sum."""
    out = divergence(centre_affinity(rows, factors, features)).select(
        F.lit(row_divergence(rows, factors, features, width)).alias("map"), F.col("value").alias("shape"),
        F.lit(_Anchors(rows, anchors, factors, features).divergence()).alias("position"),
    )
    return out.withColumn("total", lam * F.col("map") + phi * F.col("shape") + (1 - lam - phi) * F.col("position"))


def preservation(rows: DataFrame, features: list[str], k: int = 10) -> DataFrame:
    """``n, preserved``: the mean share of each row's ``k`` nearest rows that are among its ``k`` nearest on the map."""
    columns = ["sample_id", "x", "y", *features]
    side, n = meet.sent(rows.select(*columns), ["sample_id"])

    def run(batches):
        all_ = side.value
        on_map, own = meet.Nearest(all_[0], all_[1:3], k), meet.Nearest(all_[0], all_[3:], k)
        for part in meet.chunks(batches, meet.MANY):
            low, high = on_map.of(part[0], part[1:3]), own.of(part[0], part[3:])
            both = ((high[:, :, None] == low[:, None]) & (high[:, :, None] >= 0)).sum((1, 2))
            yield pa.RecordBatch.from_arrays([pa.array(both[high[:, 0] >= 0] / k)], names=["share"])

    each = meet.spread(rows.select(*columns), n).mapInArrow(run, "share double")
    return each.agg(F.count(F.lit(1)).alias("n"), F.avg("share").alias("preserved"))


def overlap(rows: DataFrame, k: int = 10) -> DataFrame:
    """``comp_id, n, mixed``: how many of the ``k`` nearest rows on the map belong to other components, on average."""
    columns = ["sample_id", "comp_id", "x", "y"]
    side, n = meet.sent(rows.select(*columns), ["sample_id"])

    def run(batches):
        all_ = side.value
        nearest = meet.Nearest(all_[0], all_[2:], k)
        for part in meet.chunks(batches, meet.MANY):
            near = nearest.of(part[0], part[2:])
            own, other = part[1][:, None], all_[1][near]
            # a row or neighbour without a component counts in no share
            counts = (near >= 0) & (own == own) & (other == other)
            some = near[:, 0] >= 0
            out = [part[0], part[1].astype(float), counts.sum(1), (counts & (own != other)).sum(1)]
            yield pa.RecordBatch.from_arrays([pa.array(c[some], from_pandas=True) for c in out], names=["a", "c", "near", "other"])

    near = meet.spread(rows.select(*columns), n).mapInArrow(run, "a long, c double, near long, other long")
    share = F.try_divide(F.sum("other"), F.sum("near"))
    return near.groupBy(F.col("c").cast(rows.schema["comp_id"].dataType).alias("comp_id")).agg(F.count_distinct("a").alias("n"), share.alias("mixed"))
