"""One small test for each finding of round 2 that was right."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from spark_drift import registry
from spark_drift.operators import energy, ensemble, meet
from spark_drift.operators.projection import affinity
from spark_drift.queries import projections
from spark_drift.workloads import topics


def test_pseudo_years_start_where_a_language_enters(spark):
    docs = spark.createDataFrame([(i, lang, "a") for i, lang in enumerate(["en", "fr", "de", "es"] * 200)], "doc_id long, lang string, text string")
    first = {r["lang"]: r["y"] for r in topics.pseudo_years(docs).groupBy("lang").agg(F.min("year").alias("y")).collect()}
    assert first == {"en": 2000, "fr": 2005, "de": 2010, "es": 2014}


def test_weights_survive_more_mistakes_than_a_float_has_halvings(spark):
    rows = [(i, name, i // 1000, 0 if name == "good" and i % 2 else 1, 0) for i in range(4000) for name in ("good", "bad")]
    p = spark.createDataFrame(rows, "sample_id long, learner string, t long, pred int, label int")
    found = {(r["t"], r["learner"]): r["weight"] for r in ensemble.majority_weights(p, "t").collect()}
    assert found[0, "bad"] == 0.5
    assert [found[3, "good"], found[3, "bad"]] == [pytest.approx(1.0), pytest.approx(0.0)]
    votes = ensemble.vote(p, ensemble.majority_weights(p, "t"), ["sample_id", "t"], ["t", "learner"])
    assert {r["pred"] for r in votes.where("t = 3 and sample_id % 2 = 1").collect()} == {0}


def test_additive_weights_survive_long_streams():
    truth = np.zeros(4000, int)
    votes = np.column_stack([np.ones(4000, int), np.arange(4000) % 2])
    out, seen = ensemble.run_policy(truth, votes, ensemble.WeightPolicy("additive"))
    assert np.isfinite(seen).all() and np.allclose(seen.sum(1), 1)
    # the better learner keeps all the weight, and no decayed learner enters anew
    assert (out[10:] == votes[10:, 1]).all() and (seen[100:, 1] > 0.999).all()


@pytest.mark.parametrize("kind", ["spread", "ties", "copies"])
def test_nearest_tiles_equal_brute_force(monkeypatch, kind):
    monkeypatch.setattr(meet, "TILE", 37)
    random = np.random.Generator(np.random.PCG64(3))
    x = [random.normal(size=400) for _ in range(2)]
    x = {"spread": x, "ties": [np.round(c) for c in x], "copies": [c * 0 for c in x]}[kind]
    keys = np.arange(400)
    d = np.sqrt(sum((c[:, None] - c[None]) ** 2 for c in x))
    d[keys[:, None] == keys[None]] = np.inf
    want = np.lexsort([np.broadcast_to(keys, d.shape), d], axis=1)[:, :5]
    assert (meet.Nearest(keys, x, 5).of(keys, x) == want).all()


def _plan(df) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("simple"))


@pytest.mark.parametrize("name", ["component_overlap", "map_preservation", "local_drift_degree", "anchor_affinity"])
def test_pairs_of_rows_are_not_shuffled(spark, small, name):
    plan = _plan(registry.QUERIES[name](spark, small))
    assert "SortMergeJoin" not in plan and "Window [row_number" not in plan and "sample_id" not in "".join(x for x in plan.splitlines() if "Exchange hashpartitioning" in x)


def test_row_divergence_adds_pairs_in_tasks(spark, small):
    rows = projections.mapped(spark, small).where("sample_id < 90")
    factors = projections.factors_of(rows)
    t = rows.join(factors, "comp_id").select("a", "b", "x", "y", "comp_id", "factor").toPandas()
    gaps = lambda *c: np.sqrt(sum((t[k].to_numpy()[:, None] - t[k].to_numpy()[None]) ** 2 for k in c))
    same, f = t["comp_id"].to_numpy()[:, None] == t["comp_id"].to_numpy()[None], t["factor"].to_numpy()[:, None]
    p, q = np.exp(-((gaps("a", "b") * np.where(same, f, 1.0)) ** 2) / 0.02), 1 / (1 + gaps("x", "y") ** 2)
    off = ~np.eye(len(t), dtype=bool)
    p, q = p[off] / p[off].sum(), q[off] / q[off].sum()
    counts = p > 1e-11
    want = (p[counts] * np.log(p[counts] / q[counts])).sum()
    assert affinity.row_divergence(rows, factors, ["a", "b"], 0.1) == pytest.approx(want, abs=1e-9)


def test_equal_rows_meet_once_and_their_number_weighs(spark):
    rows = spark.range(200_000).select(F.col("id"), (F.col("id") % 37).cast("double").alias("x"), F.lit(0.0).alias("y"))
    ref, cur = rows.where("id % 2 = 0"), rows.where("id % 2 = 1").withColumn("x", F.col("x") * 1.5)
    exact = energy.energy_distance(ref, cur, ["x"], method="sorted").first()
    for features in (["x"], ["x", "y"]):
        found = energy.energy_distance(ref, cur, features).first()
        assert [found[c] for c in energy.TERMS] == [pytest.approx(exact[c], abs=1e-9) for c in energy.TERMS]


def test_pair_sums_agree_in_missing_keys(spark):
    x = spark.createDataFrame([(None, 1.0), (1, 2.0), (1, None)], "k int, v double")
    found = {(r["k"], r["t"]): r["total"] for r in energy.pair_sums(x, x.withColumn("t", F.col("v")), ["v"], ["k"], also=["t"]).collect()}
    assert found == {(None, 1.0): 0.0, (1, 2.0): 0.0}


@pytest.mark.parametrize("name", ["entropy_2d", "shrink_factors", "merge_component", "score_drifts", "score_runs", "score_means", "sql_halo"])
def test_query_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        registry.QUERIES[name](spark, str(tmp_path)).collect()
