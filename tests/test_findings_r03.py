from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from spark_drift.functions import pairs
from spark_drift.operators import degree, detect
from spark_drift.operators.detect import Detector
from spark_drift.plans.choose import Choice
from spark_drift.sources import generator
from spark_drift.workloads import detectors


def _sides(spark, d: int, n: int = 500, m: int = 300):
    random = np.random.Generator(np.random.PCG64(d))
    rows = lambda n, times: spark.createDataFrame(pd.DataFrame({"comp_id": random.integers(0, 3, n), "t": random.integers(0, times, n)} | {f"x{k}": random.normal(size=n) for k in range(d)}))  # noqa: E731, E501
    ref, cur = rows(n, 1).drop("t"), rows(m, 2)
    return ref.union(ref.limit(20)), cur.union(cur.limit(20)), [f"x{k}" for k in range(d)]


def _gap(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(((a[:, None] - b[None]) ** 2).sum(-1))


def _distance(r: np.ndarray, c: np.ndarray) -> float:
    return 1 - (_gap(r, r).mean() + _gap(c, c).mean()) / (2 * _gap(r, c).mean())


@pytest.mark.parametrize("compare", ["direct", "component"])
def test_degree_of_two_features_does_not_go_by_sizes(spark, compare):
    """beyond the pair budget the degree was that of slices."""
    ref, cur, features = _sides(spark, 2)
    got = {r["t"]: r["degree"] for r in degree.drift_degree(ref, cur, "t", features, compare, pair_budget=1e5).collect()}
    r, c = ref.toPandas(), cur.toPandas()
    for t, one in c.groupby("t"):
        groups = [(r, one)] if compare == "direct" else [(r[r["comp_id"] == k], g) for k, g in one.groupby("comp_id")]
        want = sum(len(b) / len(one) * _distance(a[features].to_numpy(), b[features].to_numpy()) for a, b in groups)
        assert got[t] == pytest.approx(want, abs=1e-12)


def test_tiles_of_cells_add_up_to_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(pairs, "CROWD", 3)  # several tiles, several levels above them
    ref, cur, features = _sides(spark, 2, 3000, 2000)
    far = ref.limit(3).selectExpr("comp_id", "x0 + 300 as x0", "x1 - 200 as x1")
    got, want = (degree.contributions(ref.union(far), cur, "t", features, method=how).toPandas().sort_values(["t", "comp_id"]) for how in (None, "pairwise"))
    assert len(got) == 6 and np.allclose(got.to_numpy(float), want.to_numpy(float), atol=1e-12)


def test_degree_of_a_batch_does_not_go_by_sizes(spark, monkeypatch):
    """batches beyond 10,000 rows, and those beyond the pair budget, took other paths."""
    monkeypatch.setattr(degree, "SMALL", 0, raising=False)
    monkeypatch.setattr(degree, "choose", lambda *a, **k: Choice("sliced", "", {"directions": 20}))
    ref, cur, features = _sides(spark, 10)
    cur = cur.where("t = 0")
    got = degree.of_batch(ref, cur, "t", features).set_index("comp_id")
    r, c = ref.toPandas(), cur.toPandas()
    assert len(got) == 3
    for k, one in c.groupby("comp_id"):
        assert got.loc[k, "distance"] == pytest.approx(_distance(r[r["comp_id"] == k][features].to_numpy(), one[features].to_numpy()), abs=1e-12)
        assert got.loc[k, "share"] == pytest.approx(len(one) / len(c))


def test_thresholds_of_one_kind_share_their_scores(monkeypatch):
    """each threshold walked the whole stream by itself."""
    x = generator.stream(4000, 10, "mean", 1.0, 3)
    settings = detectors.grid(["direct", "total_variation"], [50]) + [Detector("direct", 50, 10, 0.03, 2), Detector("direct", 50, 10, 9.0)]
    asked, plain = [], detect.METHODS["direct"]
    monkeypatch.setitem(detect.METHODS, "direct", lambda ref, cur, cache: asked.append(0) or plain(ref, cur, cache))
    apart, kins = {}, {}
    for k, d in enumerate(settings):
        kins.setdefault(d.kin, {})[k] = d
        # the rule by itself: a report takes the reference anew
        test, cache, streak, ref, end, apart[k] = detect.METHODS[d.method], d.options | {"step": d.step}, 0, x[: d.window], 2 * d.window, []
        while end <= len(x):
            streak = streak + 1 if test(ref, x[end - d.window : end], cache) >= d.threshold else 0
            if streak >= d.persist:
                apart[k].append(end - 1)
                ref, cache, streak, end = x[end : end + d.window], d.options | {"step": d.step}, 0, end + 2 * d.window
            else:
                end += d.step
    each, asked[:] = len(asked), []
    found = {k: [] for k in apart}
    for kin in kins.values():
        for k, t in detect.run_kin(kin, x):
            found[k].append(t)
    assert found == apart and sum(map(len, found.values())) > 50
    assert len(asked) < 0.7 * each
