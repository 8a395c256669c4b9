"""Kernels against published values, hand examples and invariants."""

from __future__ import annotations

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spark_drift.functions import numeric as nu
from spark_drift.operators.baselines import information, local_degree, total_variation
from spark_drift.operators.detect import Detector
from spark_drift.operators.ensemble import WeightPolicy, run_policy
from spark_drift.operators.projection import embed, shrink
from spark_drift.plans.choose import choose


def col(*values):
    return np.array(values, float)[:, None]


@pytest.mark.parametrize(("level", "dims", "value"), [(0.95, 1, 3.841), (0.95, 2, 5.991), (0.95, 5, 11.070), (0.99, 10, 23.209)])
def test_chi_square_quantiles(level, dims, value):
    assert nu.chi2_quantile(level, dims) == pytest.approx(value, abs=1e-3)


def test_truncation_factor_two_dimensions():
    assert nu.truncation_factor(0.95, 2) == pytest.approx(0.842, abs=1e-3)


def test_energy_hand_examples():
    assert nu.energy(col(0, 2), col(1)) == pytest.approx(0.5)
    assert nu.energy(col(3), col(7)) == 1
    assert nu.energy(col(1, 2, 3), col(1, 2, 3)) == pytest.approx(0)
    assert nu.energy(col(), col(1)) == 1
    assert nu.energy(col(5, 5), col(5)) == 0


def test_degree_weights_components_by_share():
    ref, comp = col(0, 0, 10), np.array([0, 0, 1])
    cur, own = col(0, 0, 0, 20), np.array([0, 0, 0, 1])
    value, parts = nu.component_degree(ref, comp, cur, own)
    assert value == pytest.approx(0.25)
    assert [p[0] for p in parts] == [0, 1]
    assert nu.component_degree(ref, comp, col(1), np.array([9]))[0] == 1


@settings(max_examples=40, deadline=None)
@given(st.lists(st.floats(-50, 50), min_size=1, max_size=30), st.lists(st.floats(-50, 50), min_size=1, max_size=30))
def test_energy_invariants(a, b):
    x, y = col(*a), col(*b)
    d = nu.energy(x, y)
    assert 0 <= d <= 1
    assert nu.energy(y, x) == pytest.approx(d, abs=1e-7)
    assert nu.energy(np.repeat(x, 2, axis=0), y) == pytest.approx(d, abs=1e-7)
    naive = np.abs(x - y.T).mean()
    assert nu.mean_distance(x, y) == pytest.approx(naive, abs=1e-7)


def test_mixture_recovers_components_and_order():
    random = np.random.default_rng(0)
    x = np.concatenate([random.normal(0, 1, (300, 2)), random.normal(8, 1, (300, 2))])
    mix = nu.select_order(x, 4)
    assert len(mix.ids) == 2
    assert mix.mean[:, 0] == pytest.approx([0, 8], abs=0.3)
    assert nu.criterion(-100.0, 2, 2, 50) == pytest.approx(200 + 11 * math.log(50))
    assert nu.criterion(-100.0, 2, 2, 50, "aic") == 222


def test_absorb_equals_refit_on_union():
    random = np.random.default_rng(1)
    a, b = random.normal(size=(50, 2)), random.normal(1, 2, size=(30, 2))
    mix = nu.Mixture(np.array([0]), np.array([50.0]), a.mean(0)[None], np.cov(a.T, bias=True)[None])
    out = nu.absorb(mix, b, np.zeros(30, int), nu.OnlineConfig(truncation="none"))
    both = np.concatenate([a, b])
    assert out.n[0] == 80
    assert out.mean[0] == pytest.approx(both.mean(0))
    assert out.cov[0] == pytest.approx(np.cov(both.T, bias=True))


def test_truncation_correction_keeps_a_stationary_component():
    for kind, low, high in (("correct", 0.8, 1.25), ("none", 0.3, 0.8)):
        random = np.random.default_rng(2)
        ref = random.normal(size=(1000, 2))
        state = nu.OnlineState(nu.em_fit(ref, 1)[0], ref[:0], np.zeros(0, int))
        for t in range(150):
            x = random.normal(size=(100, 2))
            state, _, _ = nu.online_step(state, x, np.arange(100), t, nu.OnlineConfig(truncation=kind, min_pool=10**9))
        assert low < np.linalg.det(state.mix.cov[0]) < high


def test_birth_of_a_component():
    random = np.random.default_rng(3)
    ref = random.normal(size=(200, 2))
    state = nu.OnlineState(nu.em_fit(ref, 1)[0], ref[:0], np.zeros(0, int))
    cfg = nu.OnlineConfig(min_pool=60)
    for t in range(5):
        state, comp, late = nu.online_step(state, random.normal(12, 1, (20, 2)), np.arange(20), t, cfg)
    assert set(state.mix.ids) >= {0, 1}
    assert (comp >= 1).all()
    assert state.mix.ids.max() < 5


def test_detectors_find_a_large_change():
    random = np.random.default_rng(4)
    x = np.concatenate([random.normal(0, 1, (400, 2)), random.normal(3, 1, (400, 2))])
    settings_ = {"component": 0.1, "direct": 0.1, "knn": 0.15, "information": 2.0, "local_degree": 6.0, "total_variation": 0.35}
    for method, threshold in settings_.items():
        found = list(Detector(method, threshold=threshold).run(x))
        assert any(400 <= t < 520 for t in found), method
        assert not [t for t in found if t < 400], method


def test_baseline_statistics_on_equal_windows():
    random = np.random.default_rng(5)
    a, b = random.normal(size=(100, 2)), random.normal(size=(100, 2))
    assert information.statistic(a, b, {}) < 2
    assert abs(local_degree.statistic(a, b, {})) < 5
    assert total_variation.statistic(a, a, {}) == 0


def test_weight_policies():
    truth = np.zeros(40, int)
    votes = np.stack([np.zeros(40, int), np.ones(40, int)], axis=1)
    for kind in ("majority", "additive"):
        pred, weights = run_policy(truth, votes, WeightPolicy(kind))
        assert (pred[1:] == 0).all()
        assert weights.sum(1) == pytest.approx(np.ones(40))
        assert weights[-1, 0] > 0.8


def test_shrink_factor_limits():
    mix = nu.Mixture(np.arange(2), np.ones(2), np.zeros((2, 2)), np.stack([np.eye(2), np.eye(2) * 9]))
    f = shrink.factors_of(mix, 0.9, 0.5)
    assert f.min() == pytest.approx(0.45)
    assert f[0] > f[1]
    wide = nu.Mixture(np.arange(2), np.ones(2), np.zeros((2, 2)), np.stack([np.eye(2), np.eye(2)]))
    assert shrink.factors_of(wide, 0.9, 0.0) == pytest.approx([0.9, 0.9])


def test_objective_gradient_by_finite_differences():
    random = np.random.default_rng(6)
    y = random.normal(size=(12, 2))
    p = embed.affinities(embed.pair_distances(random.normal(size=(12, 4)), random.normal(size=(12, 4))) + np.ones((12, 12)), 3)
    p = p / p.sum()
    np.fill_diagonal(p, 1e-12)
    old = np.arange(8)
    extra = {
        "old": old, "centres": random.normal(size=(2, 2)), "pc": embed.centre_affinity(random.random((8, 2)), np.array([3.0, 5.0])),
        "anchors": y[:4].copy(), "ps": embed.anchor_affinity(random.random((8, 4)), np.array([0, 1, 2, 3, -1, -1, -1, -1])), "lam": 0.6, "phi": 0.2,
    }
    _, _, grad = embed.objective(y, p, **extra)
    for i, k in ((0, 0), (5, 1), (10, 0)):
        up, down = y.copy(), y.copy()
        up[i, k] += 1e-5
        down[i, k] -= 1e-5
        slope = (embed.objective(up, p, **extra)[1] - embed.objective(down, p, **extra)[1]) / 2e-5
        assert grad[i, k] == pytest.approx(slope, rel=2e-3, abs=1e-6)


def test_constrained_map_moves_old_rows_less():
    random = np.random.default_rng(7)
    centres = np.array([[0, 0], [6, 0], [0, 6]], float)
    comp = np.repeat(np.arange(3), 30)
    x = centres[comp] + random.normal(size=(90, 2))
    mix = nu.Mixture(np.arange(3), np.full(3, 30.0), centres, np.repeat(np.eye(2)[None], 3, axis=0))
    cfg = embed.EmbedConfig(rounds=120, perplexity=10)
    first = embed.embed(x, comp, mix, cfg)
    new = centres[np.zeros(10, int)] + random.normal(size=(10, 2))
    xs, cs = np.concatenate([x, new]), np.concatenate([comp, np.zeros(10, int)])
    previous = np.concatenate([first, np.full((10, 2), np.nan)])
    moves = {}
    for mode in ("constrained", "plain"):
        # the plain map has no memory: it is made anew
        y = embed.embed(xs, cs, mix, embed.EmbedConfig(mode, rounds=120, perplexity=10), previous if mode == "constrained" else None)
        moves[mode] = np.linalg.norm(y[:90] - first, axis=1).mean()
    assert moves["constrained"] < moves["plain"]


def test_blue_noise_is_spread():
    y = np.random.default_rng(8).random((400, 2))
    pick = embed.blue_noise(y, 50)
    d = embed.pair_distances(y[pick], y[pick]) + np.eye(50) * 9
    assert len(pick) == 50
    assert d.min() > 0.03
    assert len(embed.blue_noise(y[:20], 50)) == 20


def test_choice_of_method():
    assert choose(10**9, 10**9, 1).method == "sorted"
    assert choose(1000, 1000, 3).method == "pairwise"
    assert choose(1000, 1000, 30).method == "blocks"
    assert choose(10**7, 10**7, 2, max_error=0.5).method == "cells"
    assert choose(10**7, 10**6, 8).method == "sliced"
    assert choose(10**11, 10**10, 8).method == "sampled"
