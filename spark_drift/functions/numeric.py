"""Numpy kernels: chi-square, Gaussian mixtures, energy distance. No Spark in here."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from spark_drift.functions.pairs import Field

LOG2PI = math.log(2 * math.pi)


# ------------------------------------------------------------------ chi-square


def gamma_p(a: float, x: float) -> float:
    """Regularised lower incomplete gamma function."""
    if x <= 0:
        return 0.0
    front = math.exp(a * math.log(x) - x - math.lgamma(a))
    if x < a + 1:
        term = total = 1.0 / a
        k = a
        while abs(term) > 1e-16 * abs(total):
            k += 1
            term *= x / k
            total += term
        return front * total
    # continued fraction for the upper tail
    tiny = 1e-300
    b = x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or tiny)
        c = b + an / c or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return 1 - front * h


def chi2_cdf(x: float, dims: float) -> float:
    return gamma_p(dims / 2, x / 2)


def chi2_quantile(level: float, dims: int) -> float:
    """Bisection on the distribution function; closed form for two dimensions."""
    if not 0 < level < 1:
        raise ValueError("level must lie inside (0, 1)")
    if dims == 2:
        return -2 * math.log(1 - level)
    low, high = 0.0, max(10.0, 4.0 * dims)
    while chi2_cdf(high, dims) < level:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_cdf(mid, dims) < level else (low, mid)
    return (low + high) / 2


def truncation_factor(level: float, dims: int) -> float:
    """Variance left when a Gaussian is cut to its central ``level`` ellipsoid."""
    return chi2_cdf(chi2_quantile(level, dims), dims + 2) / level


# ------------------------------------------------------------- energy distance


#: pairs of rows of two features up to which they are summed one by one
PAIRS = 2e7


def mean_distance(x: np.ndarray, y: np.ndarray, block: int = 2048, fields: dict | None = None) -> float:
    """Mean Euclidean distance over all pairs of rows, block by block; beyond ``PAIRS`` pairs of two features by
    cells (``pairs.Field``), to some 1e-12 of the same sum. ``fields`` keeps the cells of ``x`` for further calls."""
    if not len(x) or not len(y):
        return math.nan
    total = 0.0
    if x.shape[1] == 2 and len(x) * len(y) > PAIRS:
        field = (fields or {}).get("field") or Field(x)
        if fields is not None:
            fields["field"] = field
        if field.reaches(y):
            return field.total(y) / (len(x) * len(y))
    if x.shape[1] == 1:
        # sorted: every pair's distance from one cumulative sum
        a, b = np.sort(x[:, 0]), np.sort(y[:, 0])
        at = np.searchsorted(b, a)
        below = np.concatenate([[0.0], np.cumsum(b)])
        total = float((a * at - below[at] + (below[-1] - below[at]) - a * (len(b) - at)).sum())
        return total / (len(x) * len(y))
    shift = x.mean(axis=0)
    x, y = x - shift, y - shift
    for i in range(0, len(x), block):
        for j in range(0, len(y), block):
            p, q = x[i : i + block], y[j : j + block]
            if x.shape[1] <= 4:
                sq = sum((p[:, k, None] - q[None, :, k]) ** 2 for k in range(x.shape[1]))
            else:
                sq = (p * p).sum(1)[:, None] + (q * q).sum(1)[None, :] - 2 * p @ q.T
            total += float(np.sqrt(np.maximum(sq, 0)).sum())
    return total / (len(x) * len(y))


def energy(x: np.ndarray, y: np.ndarray, within_x: float | None = None, unbiased: bool = False, fields: dict | None = None) -> float:
    """Normalised energy distance, 0 to 1; 1 if the reference is empty."""
    if not len(x):
        return 1.0
    between = mean_distance(x, y, fields=fields)
    wx = mean_distance(x, x, fields=fields) if within_x is None else within_x
    wy = mean_distance(y, y)
    if unbiased:
        wx = wx * len(x) / (len(x) - 1) if len(x) > 1 else 0.0
        wy = wy * len(y) / (len(y) - 1) if len(y) > 1 else 0.0
    if between <= 0:
        return 0.0
    value = 1 - (wx + wy) / (2 * between)
    return value if unbiased else min(max(value, 0.0), 1.0)


# --------------------------------------------------------------- Gaussian parts


@dataclass
class Mixture:
    """Components with stable ids. ``n``: rows; ``mean``: (K, D); ``cov``: (K, D, D)."""

    ids: np.ndarray
    n: np.ndarray
    mean: np.ndarray
    cov: np.ndarray
    born: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def __post_init__(self) -> None:
        if not len(self.born):
            self.born = np.zeros(len(self.ids))

    @property
    def dims(self) -> int:
        return self.mean.shape[1]

    def copy(self) -> Mixture:
        return Mixture(self.ids.copy(), self.n.copy(), self.mean.copy(), self.cov.copy(), self.born.copy())


def factors(cov: np.ndarray, ridge: float = 1e-6) -> tuple[np.ndarray, np.ndarray]:
    """Inverse Cholesky factors and log determinants, with a ridge where needed."""
    d = cov.shape[-1]
    try:
        low = np.linalg.cholesky(cov)
        return np.linalg.inv(low), 2 * np.log(np.diagonal(low, axis1=1, axis2=2)).sum(1)
    except np.linalg.LinAlgError:  # one by one, as some need a ridge
        pass
    inverse, logdet = np.empty_like(cov), np.empty(len(cov))
    for k, c in enumerate(cov):
        add = 0.0
        while True:
            try:
                low = np.linalg.cholesky(c + add * np.eye(d))
                break
            except np.linalg.LinAlgError:
                add = ridge if not add else add * 10
        inverse[k] = np.linalg.inv(low)
        logdet[k] = 2 * np.log(np.diag(low)).sum()
    return inverse, logdet


def mahalanobis_and_logpdf(x: np.ndarray, mix: Mixture) -> tuple[np.ndarray, np.ndarray]:
    """Squared Mahalanobis distances and log densities, (rows, components)."""
    inverse, logdet = factors(mix.cov)
    d2 = np.empty((len(x), len(mix.ids)))
    for k, low in enumerate(inverse):
        z = (x - mix.mean[k]) @ low.T
        d2[:, k] = np.einsum("ni,ni->n", z, z)
    return d2, -0.5 * (d2 + logdet[None] + mix.dims * LOG2PI)


def kmeans_seeds(x: np.ndarray, k: int, random: np.random.Generator) -> np.ndarray:
    """Spread-out start centres, each drawn with the squared distance to those before."""
    centres = [x[random.integers(len(x))]]
    d2 = ((x - centres[0]) ** 2).sum(1)
    for _ in range(1, k):
        p = d2 / d2.sum() if d2.sum() > 0 else None
        centres.append(x[random.choice(len(x), p=p)])
        d2 = np.minimum(d2, ((x - centres[-1]) ** 2).sum(1))
    return np.array(centres)


def em_fit(
    x: np.ndarray, k: int, seed: int = 0, rounds: int = 60, tol: float = 1e-4, ridge: float = 1e-6, starts: int = 2
) -> tuple[Mixture, float]:
    """Best of a few expectation-maximisation runs: the mixture and its log likelihood."""
    n, d = x.shape
    best: tuple[Mixture, float] | None = None
    spread = np.cov(x.T, bias=True).reshape(d, d) + ridge * np.eye(d)
    for start in range(starts if k > 1 else 1):
        random = np.random.Generator(np.random.PCG64(seed * 1000 + start))
        centres = kmeans_seeds(x, k, random)
        for _ in range(5):
            own = ((x[:, None] - centres[None]) ** 2).sum(-1).argmin(1)
            centres = np.array([x[own == j].mean(0) if (own == j).any() else centres[j] for j in range(k)])
        share = np.maximum(np.bincount(own, minlength=k), 1) / n
        mix = Mixture(np.arange(k), share * n, centres, np.repeat(spread[None], k, axis=0))
        for j in range(k):
            if (own == j).sum() > d:
                mix.cov[j] = np.cov(x[own == j].T, bias=True).reshape(d, d) + ridge * np.eye(d)
        last = -np.inf
        for _ in range(rounds):
            _, logpdf = mahalanobis_and_logpdf(x, mix)
            joint = logpdf + np.log(np.maximum(mix.n, 1e-12) / mix.n.sum())[None]
            top = joint.max(1, keepdims=True)
            r = np.exp(joint - top)
            total = r.sum(1, keepdims=True)
            value = float((top + np.log(total)).sum())
            r /= total
            mass = np.maximum(r.sum(0), 1e-9)
            mix.n = mass
            mix.mean = (r.T @ x) / mass[:, None]
            for j in range(k):
                diff = x - mix.mean[j]
                mix.cov[j] = (diff * r[:, j : j + 1]).T @ diff / mass[j] + ridge * np.eye(d)
            if abs(value - last) < tol * max(1.0, abs(value)) * 1e-2:
                break
            last = value
        if best is None or value > best[1]:
            best = (mix, value)
    mix, value = best
    order = np.lexsort(mix.mean.T[::-1])
    mix = Mixture(np.arange(k), mix.n[order], mix.mean[order], mix.cov[order])
    return mix, value


def parameters(k: int, d: int) -> int:
    return k - 1 + k * d + k * d * (d + 1) // 2


def criterion(loglik: float, k: int, d: int, n: int, kind: str = "bic") -> float:
    p = parameters(k, d)
    return -2 * loglik + (p * math.log(n) if kind == "bic" else 2 * p)


def scored(x: np.ndarray, k: int, kind: str = "bic", seed: int = 0) -> tuple[float, Mixture] | None:
    """The criterion and the mixture of ``k`` components; none with fewer than five rows per parameter."""
    if k > 1 and len(x) < 5 * parameters(k, x.shape[1]):
        return None
    mix, value = em_fit(x, k, seed)
    return criterion(value, k, x.shape[1], len(x), kind), mix


def select_order(x: np.ndarray, most: int = 10, kind: str = "bic", seed: int = 0) -> Mixture:
    """Number of components by an information criterion, at least five rows per parameter."""
    fits = (scored(x, k, kind, seed) for k in range(1, most + 1))
    return min((f for f in fits if f), key=lambda f: f[0])[1]


# -------------------------------------------------------------- online mixture


@dataclass
class OnlineState:
    mix: Mixture
    pool: np.ndarray  # rows assigned provisionally, awaiting support
    pool_ids: np.ndarray


@dataclass
class OnlineConfig:
    level: float = 0.95
    gate: str = "chi2"  # chi2 | density | posterior
    truncation: str = "correct"  # correct | none
    order: str = "batch"  # batch | row
    min_pool: int | None = None
    most: int = 10
    fold: float | None = None  # new components nearer than this to another are folded into it
    kind: str = "bic"
    seed: int = 0


def gated(x: np.ndarray, mix: Mixture, cfg: OnlineConfig) -> tuple[np.ndarray, np.ndarray]:
    """Index of each row's component and whether the row is close enough to join it."""
    d2, logpdf = mahalanobis_and_logpdf(x, mix)
    if cfg.gate == "posterior":
        joint = logpdf + np.log(mix.n / mix.n.sum())[None]
        post = np.exp(joint - joint.max(1, keepdims=True))
        post /= post.sum(1, keepdims=True)
        own = post.argmax(1)
        return own, post[np.arange(len(x)), own] > cfg.level
    own = logpdf.argmax(1)
    rows = np.arange(len(x))
    if cfg.gate == "density":
        return own, np.exp(logpdf[rows, own]) > cfg.level
    return own, d2[rows, own] <= chi2_quantile(cfg.level, mix.dims)


def absorb(mix: Mixture, x: np.ndarray, own: np.ndarray, cfg: OnlineConfig) -> Mixture:
    """Merge the statistics of accepted rows into their components."""
    out = mix.copy()
    shrink = truncation_factor(cfg.level, mix.dims) if cfg.gate == "chi2" and cfg.truncation == "correct" else 1.0
    for k in np.unique(own):
        rows = x[own == k]
        n1, n2 = out.n[k], float(len(rows))
        mean2 = rows.mean(0)
        diff = rows - mean2
        cov2 = diff.T @ diff / n2 / shrink
        gap = mean2 - out.mean[k]
        n = n1 + n2
        out.cov[k] = (n1 * out.cov[k] + n2 * cov2) / n + n1 * n2 / n**2 * np.outer(gap, gap)
        out.mean[k] += gap * n2 / n
        out.n[k] = n
    return out


def online_step(
    state: OnlineState, x: np.ndarray, ids: np.ndarray, t: float, cfg: OnlineConfig
) -> tuple[OnlineState, np.ndarray, np.ndarray]:
    """One time point: gate, absorb, pool, perhaps new components.

    Returns the state after it, and per row the component id and the provisional flag.
    """
    mix = state.mix
    own, ok = np.zeros(len(x), int), np.zeros(len(x), bool)
    if cfg.order == "row":
        for i in range(len(x)):
            own[i : i + 1], ok[i : i + 1] = gated(x[i : i + 1], mix, cfg)
            if ok[i]:
                mix = absorb(mix, x[i : i + 1], own[i : i + 1], OnlineConfig(**{**vars(cfg), "truncation": "none"}))
    elif len(x):
        own, ok = gated(x, mix, cfg)
        if ok.any():
            mix = absorb(mix, x[ok], own[ok], cfg)
    comp, provisional = mix.ids[own] if len(x) else np.zeros(0, int), ~ok
    pool = np.concatenate([state.pool, x[~ok]]) if len(x) else state.pool
    pool_ids = np.concatenate([state.pool_ids, ids[~ok]]) if len(x) else state.pool_ids
    need = cfg.min_pool if cfg.min_pool is not None else mix.n.mean() / 2
    if len(pool) >= max(need, mix.dims + 2):
        new = select_order(pool, cfg.most, cfg.kind, cfg.seed)
        first = int(mix.ids.max()) + 1
        mix = Mixture(
            np.concatenate([mix.ids, first + np.arange(len(new.ids))]),
            np.concatenate([mix.n, new.n]),
            np.concatenate([mix.mean, new.mean]),
            np.concatenate([mix.cov, new.cov]),
            np.concatenate([mix.born, np.full(len(new.ids), t)]),
        )
        if cfg.fold is not None:
            mix = fold_twins(mix, cfg.fold)
        if len(x):
            late = ~ok
            late |= ~np.isin(comp, mix.ids)  # a fold may have taken a component away
            if late.any():
                _, logpdf = mahalanobis_and_logpdf(x[late], mix)
                comp = comp.copy()
                comp[late] = mix.ids[logpdf.argmax(1)]
                provisional = np.zeros(len(x), bool)
        pool, pool_ids = pool[:0], pool_ids[:0]
    return OnlineState(mix, pool, pool_ids), comp, provisional


def merged(mix: Mixture, source: int, target: int) -> Mixture:
    """Component ``source`` folded into ``target`` by exact statistics."""
    a, b = int(np.nonzero(mix.ids == target)[0][0]), int(np.nonzero(mix.ids == source)[0][0])
    n1, n2, gap = mix.n[a], mix.n[b], mix.mean[b] - mix.mean[a]
    out = mix.copy()
    out.cov[a] = (n1 * mix.cov[a] + n2 * mix.cov[b]) / (n1 + n2) + n1 * n2 / (n1 + n2) ** 2 * np.outer(gap, gap)
    out.mean[a] = mix.mean[a] + gap * n2 / (n1 + n2)
    out.n[a] = n1 + n2
    keep = np.arange(len(mix.ids)) != b
    return Mixture(out.ids[keep], out.n[keep], out.mean[keep], out.cov[keep], out.born[keep])


def bhattacharyya(mix: Mixture, i: int, j: int) -> float:
    """Distance between two components, by position."""
    middle = (mix.cov[i] + mix.cov[j]) / 2
    gap = mix.mean[i] - mix.mean[j]
    half_log = lambda c: np.linalg.slogdet(c)[1] / 2
    return float(gap @ np.linalg.solve(middle, gap) / 8 + half_log(middle) - (half_log(mix.cov[i]) + half_log(mix.cov[j])) / 2)


def fold_twins(mix: Mixture, most: float) -> Mixture:
    """Components nearer than ``most`` in Bhattacharyya distance folded together, into the smaller id."""
    changed = True
    while changed and len(mix.ids) > 1:
        changed = False
        for i in range(len(mix.ids)):
            for j in range(i + 1, len(mix.ids)):
                if bhattacharyya(mix, i, j) < most:
                    mix, changed = merged(mix, int(mix.ids[j]), int(mix.ids[i])), True
                    break
            if changed:
                break
    return mix


class Monitor:
    """The whole method over a stream that fits one task: clustering, window, degree.

    ``window``: rows that the current window holds at most. Where components are born, merged or
    folded, the reference and the rows of the window whose place is open are judged anew.
    """

    def __init__(
        self, ref: np.ndarray, cfg: OnlineConfig, window: int | None = None, floor: bool = False, reassign: bool = True, mix: Mixture | None = None
    ) -> None:
        self.cfg, self.window, self.floor, self.reassign = cfg, window, floor, reassign
        self.state = OnlineState(mix or select_order(ref, cfg.most, cfg.kind, cfg.seed), ref[:0], np.zeros(0, np.int64))
        self.rows, self.own, self.open = ref[:0], np.zeros(0, np.int64), np.zeros(0, bool)
        self.refer(ref)

    @property
    def mix(self) -> Mixture:
        return self.state.mix

    def closest(self, x: np.ndarray) -> np.ndarray:
        """Component of the largest density, without a gate."""
        return self.mix.ids[mahalanobis_and_logpdf(x, self.mix)[1].argmax(1)] if len(x) else np.zeros(0, np.int64)

    def refer(self, ref: np.ndarray) -> None:
        """A new reference."""
        self.ref, self.ref_own, self.within = ref, self.closest(ref), {}

    def _judge_anew(self, also: np.ndarray | None = None) -> None:
        if self.reassign:
            self.ref_own, self.within = self.closest(self.ref), {}
        again = self.open | ~np.isin(self.own, self.mix.ids) | (np.isin(self.own, also) if also is not None else False)
        if again.any():
            self.own[again] = self.closest(self.rows[again])
        self.open[:] = False

    def arrive(self, x: np.ndarray, t: float, window: int | None = None) -> int:
        """Rows of one time point; returns how many components they gave birth to."""
        known = set(self.mix.ids.tolist())
        self.state, comp, open_ = online_step(self.state, x, np.zeros(len(x), np.int64), t, self.cfg)
        keep = window or self.window or len(self.rows) + len(x)
        self.rows = np.concatenate([self.rows, x])[-keep:]
        self.own, self.open = np.concatenate([self.own, comp])[-keep:], np.concatenate([self.open, open_])[-keep:]
        births = len(set(self.mix.ids.tolist()) - known)
        if births or set(self.mix.ids.tolist()) != known:
            self._judge_anew()
        return births

    def merge(self, source: int, target: int) -> None:
        """An analyst's merge: statistics are joined, rows of both and those still open are judged anew."""
        self.state = OnlineState(merged(self.mix, source, target), self.state.pool, self.state.pool_ids)
        self._judge_anew(np.array([source, target]))

    def degree(self) -> tuple[float, list[tuple[int, float, float]]]:
        return component_degree(self.ref, self.ref_own, self.rows, self.own, floor=self.floor, within=self.within)


def component_degree(
    ref: np.ndarray, ref_comp: np.ndarray, cur: np.ndarray, cur_comp: np.ndarray, floor: bool = False,
    within: dict | None = None, unbiased: bool = False,
) -> tuple[float, list[tuple[int, float, float]]]:
    """Degree and its parts ``(component, share, distance)``; ``within`` caches
    the reference's self distances, and its cells, between time points."""
    parts = []
    for k in np.unique(cur_comp):
        r, c = ref[ref_comp == k], cur[cur_comp == k]
        key = (int(k), len(r))
        inner, fields = None, None
        if within is not None and len(r):
            fields = within.setdefault((*key, "cells"), {})
            inner = within.setdefault(key, None) or mean_distance(r, r, fields=fields)
            within[key] = inner
        value = energy(r, c, inner, unbiased, fields)
        if floor and len(r):
            value = max(0.0, value - 0.5 / len(c) - 0.5 / len(r))
        parts.append((int(k), len(c) / len(cur), value))
    return sum(s * d for _, s, d in parts), parts
