"""Neighbour embedding with shape and position constraints, as numpy kernels.

The optimisation runs inside one Arrow task on a bounded sample; the rest of the rows
is placed afterwards near its sampled neighbours. With a previous map, old rows start at
their old places, keep their affinity to component centres (shape) and to a few anchors
(position); both partners stand still.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.functions.numeric import Mixture
from spark_drift.operators.projection.shrink import factors_of, shrunk


@dataclass(frozen=True)
class EmbedConfig:
    mode: str = "constrained"  # plain | supervised | constrained
    alpha: float = 0.9
    beta: float = 0.5
    lam: float = 0.6
    phi: float = 0.2
    perplexity: float = 30.0
    rounds: int = 300
    rate: float = 50.0
    anchors: int = 500
    squared: bool = False
    seed: int = 0


def pair_distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    sq = (a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * a @ b.T
    return np.sqrt(np.maximum(sq, 0))


def affinities(d: np.ndarray, perplexity: float) -> np.ndarray:
    """Symmetric joint affinities; each row's bandwidth fits the perplexity."""
    n = len(d)
    perplexity = max(1.5, min(perplexity, (n - 1) / 3))
    sq = d * d
    np.fill_diagonal(sq, np.inf)
    sq -= sq.min(1, keepdims=True)
    np.fill_diagonal(sq, 0.0)
    goal = np.log(perplexity)
    low, high = np.full(n, -np.inf), np.full(n, np.inf)
    beta = 1.0 / np.maximum(np.median(sq, axis=1), 1e-12)
    e = np.empty_like(sq)
    for _ in range(60):
        np.multiply(sq, -beta[:, None], out=e)
        np.exp(e, out=e)
        np.fill_diagonal(e, 0.0)
        total = np.maximum(e.sum(1), 1e-300)
        h = np.log(total) + beta * np.einsum("ij,ij->i", sq, e) / total
        if np.abs(h - goal).max() < 1e-6:
            break
        wide = h > goal
        low, high = np.where(wide, beta, low), np.where(wide, high, beta)
        beta = np.where(np.isinf(high), beta * 2, np.where(np.isinf(low), beta / 2, (low + high) / 2))
    e /= total[:, None]
    return np.maximum((e + e.T) / (2 * n), 1e-12)


def _scale(d: np.ndarray, rank: int) -> float:
    """Typical distance to the ``rank``-th nearest partner; sets the width of the kernel,
    whose exponent is a plain distance."""
    k = min(rank, d.shape[1] - 1)
    near = np.partition(d, k, axis=1)[:, k]
    return max(float(np.median(near)), 1e-12)


def centre_affinity(d: np.ndarray, sizes: np.ndarray, squared: bool = False) -> np.ndarray:
    """Joint affinity of old rows to component centres, weighted by the root of the size."""
    u = d / _scale(d, 0)
    p = np.sqrt(sizes)[None] * np.exp(-(u * u if squared else u))
    return p / p.sum()


def anchor_affinity(d: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Joint affinity of old rows to anchors; 1 before normalising with a row's own anchor."""
    p = np.exp(-d / _scale(d, 1))
    rows = np.nonzero(own >= 0)[0]
    p[rows, own[rows]] = 1.0
    return p / p.sum()


def heavy(a: np.ndarray, b: np.ndarray, self_pairs: bool) -> tuple[np.ndarray, np.ndarray]:
    """Heavy-tailed kernel and its normalised form on 2-D places."""
    k = (a * a).sum(1)[:, None] + (b * b).sum(1)[None] + 1.0
    k -= 2 * a @ b.T
    np.maximum(k, 1.0, out=k)
    np.reciprocal(k, out=k)
    if self_pairs:
        np.fill_diagonal(k, 0)
    return k, np.maximum(k / k.sum(), 1e-15)


def divergence(p: np.ndarray, q: np.ndarray) -> float:
    some = p > 1e-11
    return float((p[some] * np.log(p[some] / q[some])).sum())


def objective(y, p, old=None, centres=None, pc=None, anchors=None, ps=None, lam=1.0, phi=0.0, values=True):
    """The three divergences and their weighted sum, with the gradient of the sum; without
    ``values`` the gradient alone, as the descent needs no more."""
    k, q = heavy(y, y, True)
    terms = [divergence(p, q) if values else 0.0, 0.0, 0.0]
    pull = np.subtract(p, q, out=q)
    pull *= k
    grad = 4 * lam * (pull.sum(1)[:, None] * y - pull @ y)
    for slot, (places, joint, weight) in enumerate(((centres, pc, phi), (anchors, ps, 1 - lam - phi)), 1):
        if joint is None or weight <= 0:
            continue
        k, q = heavy(y[old], places, False)
        terms[slot] = divergence(joint, q) if values else 0.0
        pull = (joint - q) * k
        grad[old] += 2 * weight * (pull.sum(1)[:, None] * y[old] - pull @ places)
    return terms, lam * terms[0] + phi * terms[1] + max(0.0, 1 - lam - phi) * terms[2], grad


def blue_noise(y: np.ndarray, size: int, seed: int = 0) -> np.ndarray:
    """Well-spread rows: the largest spacing at which greedy picking in random order
    still yields ``size`` rows; all rows where there are no more."""
    if len(y) <= size:
        return np.arange(len(y))
    order = np.random.Generator(np.random.PCG64(seed)).permutation(len(y))
    span = float(np.ptp(y, axis=0).max()) or 1.0

    def picked(gap: float) -> list[int]:
        taken: dict[tuple[int, int], list[int]] = {}
        out = []
        for i in order:
            cx, cy = int(y[i, 0] // gap), int(y[i, 1] // gap)
            near = [j for a in (-1, 0, 1) for b in (-1, 0, 1) for j in taken.get((cx + a, cy + b), ())]
            if all((y[i, 0] - y[j, 0]) ** 2 + (y[i, 1] - y[j, 1]) ** 2 >= gap * gap for j in near):
                taken.setdefault((cx, cy), []).append(i)
                out.append(i)
        return out

    low, high = span * 1e-6, span
    best = order[:size].tolist()
    for _ in range(18):
        gap = (low + high) / 2
        found = picked(gap)
        if len(found) >= size:
            low, best = gap, found[:size]
        else:
            high = gap
    return np.sort(np.array(best))


def embed(x: np.ndarray, comp: np.ndarray, mix: Mixture, cfg: EmbedConfig, previous: np.ndarray | None = None) -> np.ndarray:
    """Places of all rows. ``previous``: (rows, 2), NaN for rows that are new."""
    n = len(x)
    d = pair_distances(x, x)
    base = d
    ids = mix.ids
    factor = np.ones(len(ids))
    if cfg.mode == "supervised":
        factor = np.full(len(ids), cfg.alpha)
    elif cfg.mode == "constrained":
        factor = factors_of(mix, cfg.alpha, cfg.beta)
    d = shrunk(base, comp, comp, ids, factor)
    p = affinities(d, cfg.perplexity)
    random = np.random.Generator(np.random.PCG64(cfg.seed))
    y = random.normal(scale=1e-2, size=(n, 2))
    extra: dict = {"lam": 1.0, "phi": 0.0}
    old = None if previous is None else ~np.isnan(previous[:, 0])
    if old is not None and old.any():
        y[old] = previous[old]
        near = d[~old][:, old]
        k = min(3, int(old.sum()))
        at = np.argpartition(near, k - 1, axis=1)[:, :k] if len(near) else np.zeros((0, k), int)
        w = 1.0 / (np.take_along_axis(near, at, 1) + 1e-9)
        y[~old] = (previous[old][at] * w[..., None]).sum(1) / w.sum(1)[:, None] + y[~old] * 0.1
        if cfg.mode == "constrained" and (cfg.phi > 0 or cfg.lam + cfg.phi < 1):
            own = comp[old]
            present = np.unique(own)
            centres = np.array([previous[old][own == c].mean(0) for c in present])
            at_k = np.searchsorted(ids, present)
            to_centre = shrunk(pair_distances(x[old], mix.mean[at_k]), own, present, ids, factor)
            pick = blue_noise(previous[old], cfg.anchors, cfg.seed)
            place = np.full(int(old.sum()), -1)
            place[pick] = np.arange(len(pick))
            xo = x[old]
            to_anchor = shrunk(pair_distances(xo, xo[pick]), own, own[pick], ids, factor)
            extra = {
                "lam": cfg.lam, "phi": cfg.phi, "old": np.nonzero(old)[0], "centres": centres,
                "pc": centre_affinity(to_centre, np.array([(own == c).sum() for c in present], float), cfg.squared),
                "anchors": previous[old][pick], "ps": anchor_affinity(to_anchor, place),
            }
    move, gains = np.zeros_like(y), np.ones_like(y)
    warm = old is not None and old.any()
    for step in range(cfg.rounds):
        lift = 4.0 if step < 50 and not warm else 1.0
        _, _, grad = objective(y, p * lift if lift != 1.0 else p, **extra, values=False)
        gains = np.maximum(np.where(np.sign(grad) != np.sign(move), gains + 0.2, gains * 0.8), 0.01)
        move = (0.5 if step < 100 else 0.8) * move - cfg.rate * gains * grad
        length = np.linalg.norm(move, axis=1, keepdims=True)
        move *= np.minimum(1.0, 5.0 / np.maximum(length, 1e-12))
        y = y + move
        if not warm:
            y -= y.mean(0)
    return y


def project(rows: DataFrame, features: list[str], mix: Mixture, cfg: EmbedConfig, key: str | None = None) -> DataFrame:
    """``sample_id, x, y, comp_id, is_new`` per row of ``rows`` (``sample_id, comp_id``,
    ``x0, y0`` null for new rows, features); one task per ``key``, inputs bounded by sampling."""
    name = key or "all_"
    rows = rows if key else rows.withColumn("all_", F.lit(0))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("sample_id")
        y = embed(pdf[features].to_numpy(float), pdf["comp_id"].to_numpy(int), mix, cfg, pdf[["x0", "y0"]].to_numpy(float))
        return pd.DataFrame({
            name: pdf[name], "sample_id": pdf["sample_id"], "x": y[:, 0], "y": y[:, 1], "comp_id": pdf["comp_id"], "is_new": pdf["x0"].isna()
        })

    schema = f"{name} {dict(rows.dtypes)[name]}, sample_id long, x double, y double, comp_id int, is_new boolean"
    out = rows.groupBy(name).applyInPandas(run, schema)
    return out if key else out.drop("all_")


# ------------------------------------------------------------ around the kernel


def sample_by_component(df: DataFrame, size: int, key: str = "sample_id") -> DataFrame:
    """About ``size`` rows in all, each component with its share, chosen by hash."""
    n = F.count(F.lit(1)).over(Window.partitionBy("comp_id"))
    total = df.count()
    rank = F.row_number().over(Window.partitionBy("comp_id").orderBy(F.md5(F.col(key).cast("string").cast("binary")), key))
    quota = F.ceil(F.col("n_") * F.lit(size / max(total, 1)))
    return df.withColumn("n_", n).withColumn("r_", rank).where(F.col("r_") <= quota).drop("n_", "r_")


def place(sampled: DataFrame, rest: DataFrame, features: list[str], k: int = 3, key: str = "sample_id") -> DataFrame:
    """``key, x, y`` of rows outside the sample: inverse-distance mean of the k nearest sampled rows.

    The sample, bounded by its quota, goes to each task, which places its rows in Arrow batches;
    no row is moved."""
    known = sampled.select(key, "x", "y", *features).orderBy(key).toPandas()
    sent = rest.sparkSession.sparkContext.broadcast((known[features].to_numpy(float), known[["x", "y"]].to_numpy(float)))
    lean = rest.select(key, F.array(*[F.col(c).cast("double") for c in features]).alias("v"))

    def run(batches):
        x, y = sent.value
        near = min(k, len(x))
        for batch in batches:
            rows = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            for at in range(0, len(rows), 2048):
                some = rows[at : at + 2048]
                d = np.sqrt(sum((some[:, f, None] - x[None, :, f]) ** 2 for f in range(x.shape[1])))
                pick = np.argsort(d, axis=1, kind="stable")[:, :near]
                w = 1.0 / (np.take_along_axis(d, pick, 1) + 1e-9)
                out = (y[pick] * w[..., None]).sum(1) / w.sum(1)[:, None]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(some)), pa.array(out[:, 0]), pa.array(out[:, 1])], names=[key, "x", "y"])

    return lean.mapInArrow(run, f"{key} {dict(rest.dtypes)[key]}, x double, y double")


def quality(previous: DataFrame, current: DataFrame) -> DataFrame:
    """One row: rows on both maps and how far they moved on average and at most."""
    both = previous.select("sample_id", F.col("x").alias("x0"), F.col("y").alias("y0")).join(current.select("sample_id", "x", "y"), "sample_id")
    gap = F.sqrt((F.col("x") - F.col("x0")) ** 2 + (F.col("y") - F.col("y0")) ** 2)
    return both.select(gap.alias("g")).agg(F.count("g").alias("n"), F.avg("g").alias("mean_move"), F.max("g").alias("most_move"))


def neighbour_preservation(high: np.ndarray, low: np.ndarray, k: int = 10) -> float:
    """Mean share of each row's k nearest rows that are near on the map too."""
    a, b = pair_distances(high, high), pair_distances(low, low)
    np.fill_diagonal(a, np.inf)
    np.fill_diagonal(b, np.inf)
    p, q = np.argpartition(a, k, axis=1)[:, :k], np.argpartition(b, k, axis=1)[:, :k]
    return float(np.mean([len(np.intersect1d(i, j)) / k for i, j in zip(p, q, strict=True)]))
