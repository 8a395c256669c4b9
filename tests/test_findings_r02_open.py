"""One small test for each finding of round 2 that was open after its first session and was right."""

from __future__ import annotations

import time

import numpy as np
import pytest
from pyspark.errors import AnalysisException

from spark_drift.functions import numeric, pairs
from spark_drift.operators import degree, mixture, online
from spark_drift.operators.detect import Detector
from spark_drift.sources import generator
from spark_drift.workloads import detectors


def _gaps(x: np.ndarray, y: np.ndarray) -> float:
    return float(np.sqrt(((x[:, None] - y[None]) ** 2).sum(-1)).mean())


@pytest.mark.parametrize("kind", ["near", "apart", "heavy", "line", "copies"])
def test_cells_sum_all_pairs(monkeypatch, kind):
    monkeypatch.setattr(numeric, "PAIRS", 0)
    monkeypatch.setattr(pairs, "CROWD", 8)
    random = np.random.Generator(np.random.PCG64(5))
    x, y = random.normal(size=(1500, 2)), random.normal(size=(900, 2))
    if kind == "apart":
        y = y + [1000.0, -300.0]
    elif kind == "heavy":
        x, y = random.standard_cauchy(size=(1500, 2)), random.standard_cauchy(size=(900, 2))
    elif kind == "line":
        x[:, 1], y[:, 1] = 0.0, 1e-3
    elif kind == "copies":
        x, y = np.round(x), np.round(y)
    kept: dict = {}
    for part in (y[:100], y):  # the second call finds the cells of the first
        assert numeric.mean_distance(x, part, fields=kept) == pytest.approx(_gaps(x, part), rel=1e-11)
    assert numeric.mean_distance(x, x) == pytest.approx(_gaps(x, x), rel=1e-11)


def test_rows_without_cells_are_summed_one_by_one(monkeypatch):
    monkeypatch.setattr(numeric, "PAIRS", 0)
    x = np.zeros((5, 2))
    assert numeric.mean_distance(x, x + [3.0, 4.0]) == 5.0
    assert np.isnan(numeric.mean_distance(x + np.nan, x))
    far = np.array([[0.0, 0.0], [1.0, 0.0], [1e15, 0.0]])
    assert numeric.mean_distance(far[:2], far) == pytest.approx(_gaps(far[:2], far))


def test_a_large_batch_is_compared_in_seconds():
    random = np.random.Generator(np.random.PCG64(6))
    x, y = random.normal(size=(150_000, 2)), random.normal(size=(150_000, 2))
    began = time.process_time()
    value = numeric.mean_distance(x, y)
    assert value == pytest.approx(np.sqrt(np.pi), abs=0.01)  # of two standard normals
    assert time.process_time() - began < 40  # 2.25e10 pairs one by one take minutes


def test_first_mixture_of_a_series_is_chosen_from_all_orders(spark):
    random = np.random.Generator(np.random.PCG64(7))
    x = np.concatenate([random.normal(size=(300, 2)), random.normal(size=(300, 2)) + 8])
    rows = [(k, t, float(a), float(b)) for k in ("p", "q") for t in range(3) for a, b in x[t::3]]
    df = spark.createDataFrame([*rows, ("few", 0, 0.0, 0.0), ("few", 1, 0.0, 0.0)], "k string, t int, x double, y double")
    got = online.kernel_series(df.where("t = 0"), df.where("t > 0"), "t", ["x", "y"], "k").toPandas().sort_values(["key", "t"])
    order = lambda a: a[np.lexsort(a.T[::-1])]
    want = list(online.series_of(order(x[0::3]), [(1.0, order(x[1::3])), (2.0, order(x[2::3]))], numeric.OnlineConfig()))
    assert got["key"].tolist() == ["p", "p", "q", "q"]
    assert np.allclose(got[["t", "n", "degree", "components", "pool", "births"]].to_numpy(float), np.array(want + want, float))


def test_rounds_over_few_rows_need_no_jobs(spark, monkeypatch):
    random = np.random.Generator(np.random.PCG64(8))
    x = np.concatenate([random.normal(size=(200, 4)), random.normal(size=(200, 4)) + 6])
    df = spark.createDataFrame([tuple(map(float, r)) for r in x], "a double, b double, c double, d double")
    whole = mixture.fit(df, df.columns, 2, start_rows=399)  # one row short: rounds are jobs
    monkeypatch.setattr(mixture, "em_step", None)
    near = mixture.fit(df, df.columns, 2, start_rows=400)
    assert near[1] == pytest.approx(whole[1], rel=1e-5) and np.allclose(near[0].mean, whole[0].mean, atol=1e-3)


def test_rounds_of_many_terms_leave_no_large_plans(spark, monkeypatch):
    monkeypatch.setattr(mixture, "log_densities", None)  # the expressions that plans would hold
    random = np.random.Generator(np.random.PCG64(9))
    x = random.normal(size=(300, 4))
    df = spark.createDataFrame([tuple(map(float, r)) for r in x], "a double, b double, c double, d double")
    mix = numeric.Mixture(np.arange(3), np.full(3, 100.0), x[:3], np.repeat(np.eye(4)[None], 3, axis=0))
    new, value = mixture.em_step(df, df.columns, mix)
    logs = numeric.mahalanobis_and_logpdf(x, mix)[1] - np.log(3)
    top = logs.max(1, keepdims=True)
    assert value == pytest.approx((top[:, 0] + np.log(np.exp(logs - top).sum(1))).sum()) and new.n.sum() == pytest.approx(300)


def test_small_batches_have_the_degree_of_large_ones(spark):
    random = np.random.Generator(np.random.PCG64(10))
    rows = lambda n, comps: spark.createDataFrame([(int(c), 0, *map(float, random.normal(size=2) + c)) for c in random.choice(comps, n)] + [(0, 0, None, 1.0)], "comp_id int, t int, x double, y double")  # noqa: E731, E501
    ref, cur = rows(120, [0, 1, 3]), rows(90, [0, 1, 2])
    tables = [degree.contributions(ref, cur, "t", ["x", "y"]).toPandas(), degree.of_batch(ref, cur, "t", ["x", "y"])]
    want, got = (t.sort_values("comp_id")[["comp_id", "share", "distance", "part"]].to_numpy(float) for t in tables)
    assert len(want) == 3 and np.allclose(got, want, atol=1e-12)


@pytest.mark.parametrize("kind", ["mean", "spread"])
def test_comparison_takes_its_streams_from_a_given_table(spark, small, tmp_path, kind):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        detectors.compare(spark, kind, sf_dir=str(tmp_path))
    chosen = [Detector("direct", 30, 6, 0.1), Detector("total_variation", 30, 6, 0.3, 1, {"bins": 5}), Detector("direct", 20, 4, 0.1)]
    found = detectors.scores(spark, kind, chosen, 1000, 5, [7, 8], sf_dir=small).toPandas().set_index(["run", "detector"])
    assert len(found) == 6 and (found[["detected", "late", "missed"]].sum(axis=1) == 4).all()
    # every row of the table is in the stream, in order
    rows = detectors.noise(spark, small, [7]).toPandas().sort_values("i")
    assert len(rows) == 1000 and rows["i"].is_monotonic_increasing
    x = generator.planted(rows[["x", "y"]].to_numpy(), 5, kind, 1.0, 7)
    at = np.array(list(chosen[0].run(x)))
    ends = [200, 400, 600, 800, 1000]
    first = [at[(at >= a) & (at < b)] for a, b in zip(ends, ends[1:], strict=False)]
    assert found.loc[(7, 0), "missed"] == sum(not len(f) for f in first)
    assert found.loc[(7, 0), "detected"] == sum(bool(len(f)) and f[0] - a < 30 for f, a in zip(first, ends, strict=False))
