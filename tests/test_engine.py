"""Behaviour of the Spark operators: runtimes agree, methods agree, edge rows, streams."""

from __future__ import annotations

import importlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from spark_drift.functions import numeric as nu
from spark_drift.operators import degree, detect, energy, ensemble, mixture, online
from spark_drift.queries.base import COMPONENTS, POINT, points
from spark_drift.sources import generator, tables
from spark_drift.streaming import monitors


def frames(spark, small):
    p = points(spark, small).select("i", "x", "y")
    return p.where("i % 2 = 0"), p.where("i % 2 = 1").withColumn("x", F.col("x") + 0.7)


def test_methods_agree(spark, small):
    ref, cur = frames(spark, small)
    exact = energy.energy_distance(ref, cur, POINT).first()["distance"]
    assert energy.energy_distance(ref, cur, POINT, method="blocks").first()["distance"] == pytest.approx(exact, abs=1e-9)
    cells = energy.energy_distance(ref, cur, POINT, method="cells", cell=0.05).first()
    assert cells["distance"] == pytest.approx(exact, abs=0.02)
    assert energy.energy_distance(ref, cur, POINT, method="sliced", directions=200).first()["distance"] == pytest.approx(exact, abs=0.02)
    assert energy.moment_lower_bound(ref, cur, POINT).first()["bound"] <= exact + 1e-12
    one = energy.energy_distance(ref, cur, ["x"]).first()["distance"]
    assert energy.energy_distance(ref, cur, ["x"], method="sorted").first()["distance"] == pytest.approx(one, abs=1e-9)
    assert energy.energy_distance(ref, cur, ["x"], method="sorted", buckets=3).first()["distance"] == pytest.approx(one, abs=1e-9)


def test_degenerate_distances(spark):
    one = spark.createDataFrame([(5.0, 0)], "x double, comp_id int")
    two = spark.createDataFrame([(5.0, 0, 1), (7.0, 3, 1)], "x double, comp_id int, t int")
    parts = {r["comp_id"]: r["distance"] for r in degree.contributions(one, two, "t", ["x"]).collect()}
    assert parts == {0: 0.0, 3: 1.0}
    none = two.where("t > 5")
    assert degree.drift_degree(one, none, "t", ["x"]).count() == 0
    assert energy.energy_distance(one.where("x > 9"), one, ["x"]).first()["distance"] == 1


def test_far_cluster_in_reference_moves_only_the_direct_degree(spark):
    random = np.random.default_rng(0)
    rows = [(float(a), 0) for a in random.normal(size=200)]
    far = [(float(a), 1) for a in random.normal(30, 1, size=200)]
    cur = spark.createDataFrame([(float(a), 0, 1) for a in random.normal(size=100)], "x double, comp_id int, t int")
    near_ref = spark.createDataFrame(rows, "x double, comp_id int")
    wide_ref = spark.createDataFrame(rows + far, "x double, comp_id int")
    value = lambda ref, how: degree.drift_degree(ref, cur, "t", ["x"], how).first()["degree"]
    assert value(near_ref, "component") == pytest.approx(value(wide_ref, "component"))
    assert value(wide_ref, "direct") > value(near_ref, "direct") + 0.1


def test_feature_checks(spark):
    df = spark.createDataFrame([(1.0,), (None,), (float("nan"),)], "x double")
    assert tables.features(df, ["x"], "drop").count() == 1
    assert [r["x"] for r in tables.features(df, ["x"], "mean").collect()] == [1.0, 1.0, 1.0]
    with pytest.raises(Exception, match="null or NaN"):
        tables.features(df, ["x"]).collect()
    flat = spark.createDataFrame([(2.0,), (2.0,)], "x double")
    assert {r["x"] for r in tables.standardise(flat, ["x"]).collect()} == {0.0}


def test_assignment_equals_kernel(spark, small):
    rows = points(spark, small)
    got = mixture.assign(rows, POINT, COMPONENTS).orderBy("i").toPandas()
    x = rows.orderBy("i").toPandas()[POINT].to_numpy(float)
    own, ok = nu.gated(x, COMPONENTS, nu.OnlineConfig())
    assert (got["comp_id"].to_numpy() == COMPONENTS.ids[own]).all()
    assert (got["provisional"].to_numpy() == ~ok).all()


def test_distributed_fit_equals_kernel(spark):
    random = np.random.default_rng(1)
    x = np.concatenate([random.normal(0, 1, (400, 2)), random.normal(7, 1, (400, 2))])
    df = spark.createDataFrame(x.tolist(), "a double, b double")
    mix, value = mixture.fit(df, ["a", "b"], 2)
    local, expected = nu.em_fit(x, 2)
    assert mix.mean == pytest.approx(local.mean, abs=0.05)
    assert value == pytest.approx(expected, rel=1e-3)
    assert mixture.select(df, ["a", "b"], range(1, 4))[1].ids.tolist() == [0, 1]
    back = mixture.from_table(mixture.table(spark, mix))
    assert back.cov == pytest.approx(mix.cov)
    assert len(mixture.fold_twins(nu.Mixture(np.arange(2), np.ones(2), np.zeros((2, 2)), np.repeat(np.eye(2)[None], 2, axis=0)), 0.1).ids) == 1


def test_kernel_and_batch_monitor_agree(spark):
    random = np.random.default_rng(2)
    ref = random.normal(size=(150, 2))
    batches = [random.normal(0.2 * k, 1, size=(40, 2)) for k in range(4)]
    train = spark.createDataFrame(ref.tolist(), "a double, b double")
    rows = [(float(k), *map(float, r)) for k, b in enumerate(batches) for r in b]
    stream = spark.createDataFrame(rows, "t double, a double, b double")
    cfg = nu.OnlineConfig()
    series = online.kernel_series(train, stream, "t", ["a", "b"], cfg=cfg).orderBy("t").toPandas()
    sorted_ref = ref[np.lexsort(ref.T[::-1])]
    monitor = monitors.BatchMonitor(sorted_ref, ["a", "b"], cfg)
    for k in range(4):
        monitor(stream.where(F.col("t") == k), k)
    monitor(stream.where("t = 3"), 3)  # a replayed batch is skipped
    assert [r["degree"] for r in monitor.rows] == pytest.approx(series["degree"].tolist(), abs=1e-9)
    assert series["degree"].iloc[-1] > series["degree"].iloc[0]


def test_stepwise_monitor_equals_series_and_goes_on_after_a_restart(spark, tmp_path):
    random = np.random.default_rng(4)
    train = spark.createDataFrame(random.normal(size=(200, 2)).tolist(), "a double, b double")
    rows = [(float(k), *map(float, r)) for k in range(4) for r in random.normal(3.0 * k, 1, size=(60, 2))]
    stream = spark.createDataFrame(rows, "t double, a double, b double")
    cfg = nu.OnlineConfig(most=2)
    series = online.stepwise_series(train, stream, "t", ["a", "b"], [0.0, 1.0, 2.0, 3.0], cfg).orderBy("t").collect()
    assert sum(r["births"] for r in series) > 0
    home = str(tmp_path / "state")
    monitor = monitors.StepwiseMonitor(train, ["a", "b"], cfg, home)
    for k in (0, 1):
        monitor(stream.where(F.col("t") == k), k)
    monitor = monitors.StepwiseMonitor(train, ["a", "b"], cfg, home)
    assert monitor.last == 1
    for k in (1, 2, 3):  # the first is a replay
        monitor(stream.where(F.col("t") == k), k)
    assert [r["components"] for r in monitor.rows] == [r["components"] for r in series]
    assert [r["degree"] for r in monitor.rows] == pytest.approx([r["degree"] for r in series], abs=1e-6)
    thin = monitors.BatchMonitor(np.zeros((9, 2)) + np.arange(9)[:, None], ["a", "b"], cfg, max_rows=10)
    with pytest.raises(ValueError, match="StepwiseMonitor"):
        thin(stream, 0)


def test_scores_add_up(spark):
    reports = spark.createDataFrame([(0, 105), (0, 150), (0, 230)], "run int, t long")
    truth = spark.createDataFrame([(1, 100), (2, 200)], "drift_no int, t long")
    got = {r["drift_no"]: (r["status"], r["delay"], r["false_reports"]) for r in detect.score(reports, truth, 20, 300, ["run"]).collect()}
    assert got == {1: ("detected", 5, 1), 2: ("late", 30, 0)}
    total = detect.totals(reports, truth, 20, 300, ["run"]).first()
    assert total["detected"] + total["late"] + total["missed"] == 2


def test_planted_source(spark):
    generator.register(spark)
    read = lambda parts: spark.read.format("planted_drift").options(rows=5000, segments=10, partitions=parts, seed=3).load()
    a, b = read(2).orderBy("i").toPandas(), read(7).orderBy("i").toPandas()
    assert (a == b).all().all()
    assert a["i"].tolist() == list(range(5000))
    assert sorted(a["seg"].unique()) == list(range(10))


def brute_counts(reports, truth, w, end):
    """Detected, late, missed and false reports, one report after the other."""
    edges = [*truth, end]
    out = [0, 0, 0, sum(t < truth[0] for t in reports)]
    for a, b in zip(edges, edges[1:]):
        inside = sorted(t for t in reports if a <= t < b)
        out[2 if not inside else 0 if inside[0] - a < w else 1] += 1
        out[3] += max(0, len(inside) - 1)
    return out


def test_comparison_equals_a_plain_count(spark):
    from spark_drift.workloads import detectors

    settings = [detect.Detector("direct", 100, 20, 0.03), detect.Detector("total_variation", 200, 100, 0.2, 1, {"bins": 8}), detect.Detector("component", 100, 50, 0.03)]
    got = {(r["run"], r["detector"]): r for r in detectors.scores(spark, "mean", settings, 9_000, 10, [3, 4], 0.5).collect()}
    truth = [900 * k for k in range(1, 10)]
    for seed in (3, 4):
        x = generator.stream(9_000, 10, "mean", 1.0, seed, 0.5)
        for k, d in enumerate(settings):
            r = got[seed, k]
            assert [r["detected"], r["late"], r["missed"], r["false_reports"]] == brute_counts(list(d.run(x)), truth, d.window, 9_000)


def test_planted_stream_equals_its_source(spark):
    generator.register(spark)
    read = spark.read.format("planted_drift").options(rows=20_000, segments=7, kind="spread", size=0.8, least=0.3, seed=5).load()
    x = read.orderBy("i").toPandas()[["x", "y"]].to_numpy()
    assert (x == generator.stream(20_000, 7, "spread", 0.8, 5, 0.3)).all()


def test_detector_uses_gate_pool_and_births():
    random = np.random.default_rng(8)
    x = np.concatenate([random.normal(0, 1, (400, 2)), random.normal(6, 1, (400, 2))])
    cache = {"step": 50}
    ref, seen = x[:200], []
    for end in range(400, 801, 50):
        seen.append(detect.METHODS["component"](ref, x[end - 200 : end], cache))
    monitor = cache["monitor"]
    assert len(monitor.mix.ids) > 1 and monitor.mix.born.max() == 0.0 and len(monitor.state.pool) < 200
    assert seen[0] < 0.05 and seen[-1] > 0.9  # rows of the new component have no reference
    assert set(monitor.own[-100:].tolist()).isdisjoint(set(monitor.ref_own.tolist()))


def test_birth_judges_pooled_rows_anew():
    random = np.random.default_rng(3)
    monitor = nu.Monitor(random.normal(size=(200, 2)), nu.OnlineConfig(min_pool=40), window=100)
    monitor.arrive(random.normal(9, 1, (30, 2)), 1.0)
    assert monitor.open.all() and set(monitor.own.tolist()) <= set(range(len(monitor.mix.ids)))
    old = set(monitor.mix.ids.tolist())
    assert monitor.arrive(random.normal(9, 1, (30, 2)), 2.0) >= 1
    assert not monitor.open.any() and set(monitor.own.tolist()).isdisjoint(old)  # those of the first batch too
    assert monitor.degree()[0] == pytest.approx(1.0)


def test_merge_joins_statistics_and_judges_rows_anew(spark, small):
    random = np.random.default_rng(4)
    ref = np.concatenate([random.normal(0, 1, (150, 2)), random.normal(5, 1, (150, 2))])
    monitor = nu.Monitor(ref, nu.OnlineConfig(), window=60)
    assert len(monitor.mix.ids) == 2
    monitor.arrive(np.concatenate([random.normal(0, 1, (30, 2)), random.normal(5, 1, (30, 2))]), 1.0)
    whole = nu.Mixture(np.array([0]), np.array([monitor.mix.n.sum()]), np.zeros((1, 2)), np.zeros((1, 2, 2)))
    mean = (monitor.mix.n[:, None] * monitor.mix.mean).sum(0) / whole.n[0]
    monitor.merge(1, 0)
    assert monitor.mix.ids.tolist() == [0] and monitor.mix.mean[0] == pytest.approx(mean)
    assert set(monitor.own.tolist()) == {0} and set(monitor.ref_own.tolist()) == {0}


def test_folding_of_new_twins():
    random = np.random.default_rng(6)
    for fold, least in ((None, 2), (3.0, 1)):
        monitor = nu.Monitor(random.normal(size=(300, 2)), nu.OnlineConfig(min_pool=30, fold=fold))
        for t in range(30):
            monitor.arrive(random.normal(0.8, 1.2, (20, 2)), float(t))
        assert len(monitor.mix.ids) >= least
        if fold:
            assert len(monitor.mix.ids) == 1 and set(monitor.own.tolist()) == {0}


def test_wide_mixtures_equal_the_kernels(spark):
    random = np.random.default_rng(7)
    names = [f"f{k}" for k in range(8)]
    x = np.concatenate([random.normal(0, 1, (300, 8)), random.normal(3, 1, (200, 8))])
    df = spark.createDataFrame(x.tolist(), ", ".join(f"{c} double" for c in names)).repartition(3)
    mix, _ = nu.em_fit(x, 2)
    for gate in ("chi2", "posterior"):
        got = mixture.assign(df, names, mix, gate).toPandas()
        own, ok = nu.gated(got[names].to_numpy(), mix, nu.OnlineConfig(gate=gate))
        assert (got["comp_id"].to_numpy() == mix.ids[own]).all() and (got["provisional"].to_numpy() == ~ok).all()
    marked = mixture.assign(df, names, mix)
    own, ok = nu.gated(x, mix, nu.OnlineConfig())
    want = nu.absorb(mix, x[ok], own[ok], nu.OnlineConfig())
    out = mixture.absorb(marked, names, mix)
    assert out.mean == pytest.approx(want.mean) and out.cov == pytest.approx(want.cov) and out.n == pytest.approx(want.n)
    stepped, value = mixture.em_step(df, names, mix)
    joint = nu.mahalanobis_and_logpdf(x, mix)[1] + np.log(mix.n / mix.n.sum())
    top = joint.max(1, keepdims=True)
    r = np.exp(joint - top)
    assert value == pytest.approx(float((top[:, 0] + np.log(r.sum(1))).sum()))
    r /= r.sum(1, keepdims=True)
    assert stepped.mean == pytest.approx((r.T @ x) / r.sum(0)[:, None])


@pytest.mark.parametrize("salted", [False, True])
def test_nearest_rows_are_exact_with_cells(spark, salted):
    random = np.random.default_rng(9)
    ref = np.concatenate([random.normal(size=(400, 3)), random.normal(40, 1, (3, 3)), np.repeat(random.normal(size=(1, 3)), 20, axis=0)])
    cur = np.concatenate([random.normal(size=(60, 3)), random.normal(20, 8, (10, 3))])
    frame = lambda x: spark.createDataFrame([(k, 0, *map(float, r)) for k, r in enumerate(x)], "row_id long, t int, a double, b double, c double")
    got = degree.nearest(frame(ref), frame(cur), "t", ["a", "b", "c"], 5, "row_id", cells=salted).collect()
    d = np.sqrt(((cur[:, None] - ref[None]) ** 2).sum(-1))
    want = {(k, int(j), r + 1) for k in range(len(cur)) for r, j in enumerate(sorted(range(len(ref)), key=lambda j: (d[k, j], j))[:5])}
    assert {(r["row_id"], r["ref_id"], r["rank"]) for r in got} == want


def test_degree_chooses_its_method(spark, small, monkeypatch):
    p = points(spark, small).select("i", "x", "y").withColumn("comp_id", (F.col("i") % 3).cast("int"))
    ref, cur = p.where("i < 500"), p.where("i >= 500").withColumn("t", (F.col("i") % 2).cast("int"))
    values = lambda **o: {r["t"]: r["degree"] for r in degree.drift_degree(ref, cur, "t", POINT, key="i", **o).collect()}
    exact = values(method="pairwise")
    assert degree.method_for(ref, cur, POINT).method == "pairwise" and values() == pytest.approx(exact)
    assert degree.method_for(ref, cur, ["x"]).method == "sorted"
    assert degree.method_for(ref, cur, POINT, 0.5, 1e4).method == "cells"
    one = lambda how: {r["t"]: r["degree"] for r in degree.drift_degree(ref, cur, "t", ["x"], method=how).collect()}
    assert one("sorted") == pytest.approx(one("pairwise"), abs=1e-9)
    from spark_drift.plans.choose import Choice

    for choice, error in ((Choice("cells", "", {"cell": 0.05}), 0.03), (Choice("sliced", "", {"directions": 150}), 0.03), (Choice("sampled", "", {"cap": 120}), 0.08)):
        assert values(method=choice) == pytest.approx(exact, abs=error)


def test_reference_is_not_repeated_for_each_time(spark, small):
    p = points(spark, small).select("i", "x", F.lit(0).alias("comp_id"))
    ref, cur = p.where("i < 300"), p.where("i >= 300").withColumn("t", (F.col("i") % 40).cast("int"))
    far = degree.contributions(ref, cur, "t", ["x"], method="sorted")
    near = degree.contributions(ref, cur, "t", ["x"], method="pairwise")
    both = far.join(near.select("t", F.col("distance").alias("d2")), "t").collect()
    assert len(both) == 40 and all(r["distance"] == pytest.approx(r["d2"], abs=1e-9) for r in both)


def test_equal_rows_are_drawn_each_on_its_own(spark):
    df = spark.range(2000).select(F.col("id").alias("i"), F.lit(1.0).alias("x"), F.lit("a").alias("k"))
    assert 350 < energy.sampled(df, "i", ["k"], 500).count() < 650
    spread = df.groupBy(energy._share(df, F.lit(16))).count().agg(F.max("count")).first()[0]
    assert spread < 250


def test_linear_machines(spark):
    random = np.random.default_rng(5)
    centres = {3: (0, 0), 5: (5, 0), 9: (0, 5)}
    rows = [(*map(float, random.normal(c, 1)), k) for k, c in centres.items() for _ in range(80)] + [(0.0, 0.0, None)]
    df = spark.createDataFrame(rows, "a double, b double, label int")
    model = ensemble.train_learner(df, ["a", "b"], kind="svm")
    got = model.transform(df.where("label is not null")).select("label", "pred_").collect()
    assert model.classes == [3, 5, 9] and np.mean([r["label"] == r["pred_"] for r in got]) > 0.95
    # the gradient vanishes at the solution
    x = np.array([[1, a, b] for a, b, k in rows if k is not None])
    for c, w in zip(model.classes, model.weights):
        sign = np.where([k == c for *_, k in rows if k is not None], 1.0, -1.0)
        short = np.maximum(1 - sign * (x @ w), 0)
        assert np.abs(-(sign * short) @ x / len(x) + 1e-3 * w).max() < 1e-5
    alone = ensemble.train_learner(df.where("label = 5"), ["a", "b"], kind="svm")
    assert {r["pred_"] for r in alone.transform(df).collect()} == {5.0}
    assert ensemble.train_learner(df.where("false"), ["a", "b"], kind="svm").transform(df).count() == len(rows)


def test_seasonal_replay_meets_its_incidents(spark):
    from spark_drift.workloads import seasonal

    rows = seasonal.replay(spark, "/root/testdata/sf0.001").toPandas()
    assert set(rows["incident"]) == {"", *seasonal.INCIDENTS}
    by = lambda name: rows[rows["incident"] == name]
    assert by("autumn")["alarm"].any() and rows["components"].max() > 1  # a new component
    assert by("astray")["degree"].max() > 0.2
    still = seasonal.replay(spark, "/root/testdata/sf0.001", seasonal.Script(adapting=False)).toPandas()
    assert (still["learners"] == 1).all() and set(still["action"]) == {""}
    share = lambda f: f["right"].sum() / f["scored"].sum()
    assert share(rows) > share(still)  # on held-out days, whose labels nothing has seen
    assert rows["degree"].mean() < still["degree"].mean()


def test_later_generations_are_no_worse(spark):
    from spark_drift.workloads import seasonal

    table = seasonal.generations(spark, "/root/testdata/sf0.001").toPandas()
    mean = table.groupby("generation")["accuracy"].mean().tolist()
    assert len(mean) == 3 and table.groupby("generation")["n"].sum().nunique() == 1  # the same rows for all
    assert mean[0] <= mean[1] + 0.01 and mean[1] <= mean[2] + 0.01 and mean[2] > mean[0]


def test_held_out_labels_change_nothing():
    from spark_drift.workloads import seasonal

    random = np.random.default_rng(2)
    t = np.arange(100, 420)
    x, held = random.normal(size=(len(t), 8)), random.random(len(t)) < 0.3
    y = (x[:, 0] > 0).astype(int)
    other = np.where(held, 1 - y, y)
    walk = lambda labels: [(i, d, a, p) for i, d, _, a, _, _, p in seasonal.run_script(t, x, labels, held, seasonal.Script(), seasonal.CONFIG)]
    assert walk(y) == walk(other)


def test_recurring_patterns_give_no_births(spark):
    from spark_drift.queries import workloads

    rows = workloads.w10_recurrence(spark, "/root/testdata/sf0.01").collect()
    assert rows and sum(r["births"] for r in rows) == 0


def test_component_method_detects_mean_changes(spark):
    from spark_drift.workloads import detectors

    out = detectors.compare(spark, "mean", ["component", "total_variation"], rows=12_000, segments=20, tune_seeds=(50,), seeds=(0, 1), windows=[100])
    rows = {r["method"]: r for r in out.collect()}
    for r in rows.values():
        assert r["detected"] + r["late"] + r["missed"] == pytest.approx(19)
    assert rows["component"]["detected"] >= 14


def test_stream_windows_equal_batch(spark, small, tmp_path):
    source = tmp_path / "in"
    rows = tables.read(spark, small, "events")
    rows.repartition(3).write.parquet(str(source))
    live = monitors.read_events(spark, str(source))
    q = monitors.tumbling(live, "1 day").writeStream.outputMode("complete").format("memory").queryName("sd_t").start()
    q.processAllAvailable()
    q.stop()
    batch = monitors.tumbling(rows.withColumn("ts", F.col("ts").cast("timestamp")), "1 day")
    key = lambda df: sorted((r["start"], r["event_type"], r["n"]) for r in df.collect())
    assert key(spark.sql("select * from sd_t")) == key(batch)


@pytest.mark.parametrize("kind", ["parquet", "csv", "json"])
def test_files_read_alike_in_batch_and_stream(spark, small, tmp_path, kind):
    schema = "event_id long, event_type string, value double, props string"
    given = tables.read(spark, small, "events").select("event_id", "event_type", "value", "props")
    writer = given.repartition(2).write.format(kind)
    (writer.option("header", True).option("escape", '"') if kind == "csv" else writer).save(str(tmp_path / "in"))
    want = sorted(map(tuple, given.collect()))
    assert sorted(map(tuple, tables.rows(spark, str(tmp_path / "in"), schema, kind).collect())) == want
    live = tables.rows(spark, str(tmp_path / "in"), schema, kind, stream=True, files_per_trigger=1)
    for _ in range(2):  # the second call finds nothing new
        tables.append_parts(live, str(tmp_path / "out"), str(tmp_path / "mark"), ["event_type"]).awaitTermination(60)
    back = spark.read.parquet(str(tmp_path / "out")).select("event_id", "event_type", "value", "props")
    assert sorted(map(tuple, back.collect())) == want
    with pytest.raises(ValueError, match="unknown kind"):
        tables.rows(spark, "x", schema, "orc")


def test_ticks_are_a_stream(spark):
    assert tables.ticks(spark).isStreaming


def test_stream_drops_replays_and_keeps_state(spark, small, tmp_path):
    source = tmp_path / "in"
    rows = tables.read(spark, small, "events").limit(400)
    rows.union(rows).coalesce(1).write.parquet(str(source))
    live = monitors.fresh(monitors.read_events(spark, str(source)), "60 days")
    q = monitors.keyed_monitor(live.select("event_type", "value"), "event_type", ["value"], 20)
    q = q.writeStream.outputMode("update").format("memory").queryName("sd_k").start()
    q.processAllAvailable()
    q.stop()
    got = spark.sql("select key, max(seen) as seen from sd_k group by key").collect()
    assert sum(r["seen"] for r in got) == 400


def test_entry_and_names(spark, small, monkeypatch):
    entry = importlib.import_module("__spark_entry__")
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize(("name", "kind"), [("w1_compare_means", "mean"), ("w2_compare_spreads", "spread")])
def test_registered_comparisons_run_the_full_form(monkeypatch, name, kind):
    from spark_drift.queries import workloads

    asked = []
    monkeypatch.setattr(workloads.detectors, "compare", lambda *a, **k: asked.append((a, k)))
    getattr(workloads, name)(None, "")
    assert asked == [((None, kind), {"sf_dir": ""})]
