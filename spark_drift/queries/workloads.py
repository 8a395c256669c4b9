"""The experiments as queries."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions import numeric
from spark_drift.functions.expressions import hash_normal
from spark_drift.functions.numeric import Mixture, OnlineConfig
from spark_drift.operators import degree, energy, mixture, online
from spark_drift.operators.projection import embed
from spark_drift.plans.lineage import cut
from spark_drift.queries.base import DAY_FEATURES, SPLIT_SQL, finish_sql, normal_sql, query, rounded, split_days
from spark_drift.queries.distances import embedded, features_sql
from spark_drift.queries.displays import places
from spark_drift.sources.tables import read
from spark_drift.workloads import detectors, seasonal, topics

# ------------------------------------------------------------ planted drifts, all methods


@query()
def w1_compare_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All detectors on planted changes of the mean over the rows of ``events``: 99 changes, ten seeds."""
    return detectors.compare(spark, "mean", sf_dir=sf_dir)


@query()
def w2_compare_spreads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As ``w1_compare_means`` for changes of the deviation."""
    return detectors.compare(spark, "spread", sf_dir=sf_dir)


# ------------------------------------------------------------------- over-estimation

CENTRES = [(0.0, 0.0), (4.0, 0.0), (0.0, 4.0), (4.0, 4.0)]


def clusters(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """A reference over four clusters and a batch from the first alone."""
    e = read(spark, sf_dir, "events").select("event_id")
    key = F.concat(F.lit("c:"), F.col("event_id").cast("string"))
    comp = F.when(F.col("event_id") % 5 == 4, 0).otherwise(F.col("event_id") % 5).cast("int")
    cx, cy = F.lit(0.0), F.lit(0.0)
    for k, (a, b) in enumerate(CENTRES):
        cx, cy = F.when(comp == k, a).otherwise(cx), F.when(comp == k, b).otherwise(cy)
    rows = e.select("event_id", F.lit(0).alias("t"), comp.alias("comp_id"), (hash_normal(key) * 0.7 + cx).alias("x"), (hash_normal(key, True) * 0.7 + cy).alias("y"))
    return rows.where("event_id % 5 <> 4").drop("t"), rows.where("event_id % 5 = 4")


_K = "'c:' || event_id::varchar"
CLUSTER_SQL = f"""cl as (select event_id, comp_id, {normal_sql(_K)} * 0.7 + case when comp_id in (1, 3) then 4.0 else 0.0 end as x,
  {normal_sql(_K, True)} * 0.7 + case when comp_id in (2, 3) then 4.0 else 0.0 end as y
  from (select event_id, case when event_id % 5 = 4 then 0 else event_id % 5 end as comp_id from events)),
rf as (select * from cl where event_id % 5 <> 4), cu as (select * from cl where event_id % 5 = 4)"""
_D = "sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))"


@query(
    f"""with {CLUSTER_SQL}, v as (select avg({_D}) as v from cu a, cu b),
d as (select avg({_D}) as b from rf a, cu b), e as (select avg({_D}) as w from rf a, rf b),
c as (select avg({_D}) as b from rf a, cu b where a.comp_id = 0), f as (select avg({_D}) as w from rf a, rf b where a.comp_id = 0 and b.comp_id = 0)
select 'direct' as compare, round({finish_sql("d.b", "e.w", "v.v")}, 6) as degree from d, e, v union all select 'component', round({finish_sql("c.b", "f.w", "v.v")}, 6) from c, f, v"""
)
def w6_overestimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    ref, cur = clusters(spark, sf_dir)
    out = None
    for how in ("direct", "component"):
        one = degree.drift_degree(ref, cur, "t", ["x", "y"], how).select(F.lit(how).alias("compare"), "degree")
        out = one if out is None else out.unionByName(one)
    return rounded(out, "degree")


# --------------------------------------------------------------- seasons and topics


@query()
def w4_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return seasonal.replay(spark, sf_dir)


@query()
def w4_single_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The initial model alone, for comparison."""
    return seasonal.replay(spark, sf_dir, seasonal.Script(adapting=False))


@query()
def w4_generations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return seasonal.generations(spark, sf_dir)


def _day_sql(feature: str, value: str) -> str:
    """A feature with the incident of its day, as ``seasonal.planted`` has it."""
    cases = [f"when t between {low} and {high} then ({value}) * {factor} + {moves.get(feature, 0.0)}" for low, high, moves, factor in seasonal.INCIDENTS.values()]
    return f"round(case {' '.join(cases)} else {value} end, 5) as {feature}"


_W = "2 * pi() * dayofyear(day) / 365.0"
_WHEN = " ".join(f"when t between {low} and {high} then '{name}'" for name, (low, high, _, _) in seasonal.INCIDENTS.items())


@query(
    f"""with d as (select l_shipdate::date as day, avg(l_quantity) as f1, avg(l_extendedprice) as f2, avg(l_discount) as f3, count(*)::double as f5 from lineitem group by 1),
z as (select day, datediff('day', date '1995-01-01', day) as t, (f1 - avg(f1) over ()) / stddev_pop(f1) over () as f1, (f2 - avg(f2) over ()) / stddev_pop(f2) over () as f2,
  (f3 - avg(f3) over ()) / stddev_pop(f3) over () as f3, (f5 - avg(f5) over ()) / stddev_pop(f5) over () as f5 from d),
w as (select day, t, f1 + 2.4 * cos({_W} + 1) + t * 0.0001 * -3 as f1, f2 - 2.0 * cos({_W} + 2) + t * 0.0001 * -2 as f2,
  f3 + 2.4 * cos({_W} + 3) + t * 0.0001 * -1 as f3, f5 + 2.4 * sin({_W}) + t * 0.0001 as f5 from z)
select day, t::int as t, case {_WHEN} else '' end as incident, (f1 * cos({_W}) + f2 * sin({_W}) - 0.5 * f3 + 0.3 * f5 > 0)::int as label,
  ('0x' || substr(md5('split:' || t::varchar), 1, 8))::bigint % 10 < 3 as held_out, {_day_sql("f1", "f1")}, {_day_sql("f2", "f2")}, {_day_sql("f5", "f5")} from w"""
)
def seasonal_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The daily stream with its five planted incidents, classes and held-out days."""
    days = seasonal.daily(spark, sf_dir).select("day", "t", "incident", "label", "held_out", "f1", "f2", "f5")
    return rounded(days, "f1", "f2", "f5", digits=5)


@query()
def w5_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topics.replay(spark, sf_dir)


# ------------------------------------------------------------------ latency and scale


@query()
def w7_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds per new day after 1,500 historical ones: detection over the days that follow, and the
    map's update with one new day, over the first three."""

    def run(pdf):
        import pandas as pd

        x = pdf.sort_values("t")[seasonal.FEATURES].to_numpy(float)
        history = 1500
        monitor = numeric.Monitor(x[:history], OnlineConfig(), 15)
        began = time.perf_counter()
        for i in range(history, len(x)):
            monitor.arrive(x[i : i + 1], float(i))
            monitor.degree()
        detect = (time.perf_counter() - began) / max(len(x) - history, 1)
        cfg = embed.EmbedConfig(rounds=40)
        comp = monitor.closest(x)
        places = embed.embed(x[:history], comp[:history], monitor.mix, cfg)
        began, updates = time.perf_counter(), 3
        for i in range(history, history + updates):
            old = np.concatenate([places, np.full((1, 2), np.nan)])
            places = embed.embed(x[: i + 1], comp[: i + 1], monitor.mix, cfg, old)
        project = (time.perf_counter() - began) / updates
        return pd.DataFrame({"history": [history], "points": [len(x) - history], "detect_seconds": [detect], "project_seconds": [project], "seconds": [detect + project]})

    days = seasonal.daily(spark, sf_dir)
    schema = "history long, points long, detect_seconds double, project_seconds double, seconds double"
    return days.groupBy(F.lit(0).alias("all_")).applyInPandas(run, schema)


def _dims_sql(d: int) -> str:
    return f"""select {d}::int as dims, round({finish_sql("b", "w", "v")}, 6) as distance from (select avg(list_distance(r.v[1:{d}], c.v[1:{d}])) as b from r, c),
  (select avg(list_distance(r.v[1:{d}], s.v[1:{d}])) as w from r, r s), (select avg(list_distance(c.v[1:{d}], s.v[1:{d}])) as v from c, c s)"""


@query(
    f"""with e as (select vec_id, list_transform(embedding, lambda x: x::double) as v from embeddings), r as (select v from e where vec_id % 2 = 0), c as (select v from e where vec_id % 2 = 1)
{" union all ".join(_dims_sql(d) for d in (2, 8, 16, 32, 64))}"""
)
def w8_dims(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for d in (2, 8, 16, 32, 64):
        ref, cur, names = embedded(spark, sf_dir, d)
        one = energy.energy_distance(ref, cur, names, method="blocks").select(F.lit(d).alias("dims"), "distance")
        out = one if out is None else out.unionByName(one)
    return rounded(out, "distance")


SHIFT_SQL = SPLIT_SQL.replace("cur as (select * from", "cur as (select day, month, comp_id, x1, x2, x3 + case when month >= 36 then 5.0 else 0.0 end as x3, x4 from")


@query(features_sql(SHIFT_SQL))
def w9_feature_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sensor offset in one feature after 1998: only that feature's line rises."""
    ref, cur = split_days(spark, sf_dir)
    moved = cur.withColumn("x3", F.col("x3") + F.when(F.col("month") >= 36, 5.0).otherwise(0.0))
    return rounded(degree.per_feature(ref, moved, "month", DAY_FEATURES), "degree")


@query()
def w10_recurrence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly batches with a daily cycle: the cycle's components are met again, not born anew."""
    e = read(spark, sf_dir, "events")
    hour = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 21600)
    night = F.when((F.hour("ts") < 6) | (F.hour("ts") >= 18), 1.0).otherwise(0.0)
    key = F.col("event_id").cast("string")
    rows = e.select(hour.alias("h"), (hash_normal(key) + 6 * night).alias("x"), (hash_normal(key, True) - 6 * night).alias("y"))
    first = rows.agg(F.min("h")).first()[0]
    return online.kernel_series(rows.where(F.col("h") < first + 12), rows.where(F.col("h") >= first + 12), "h", ["x", "y"], cfg=OnlineConfig(level=0.999))


@query(
    f"""with q as (select c_mktsegment as segment, year(l_shipdate)::int as year, l_quantity as x from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey),
r as (select segment, x, count(*) as w from q where year = 1995 group by 1, 2), c as (select segment, year, x, count(*) as w from q where year > 1995 group by 1, 2, 3),
b as (select c.segment, c.year, sum(abs(r.x - c.x) * r.w * c.w) / sum(r.w * c.w) as b from r join c using (segment) group by 1, 2),
w as (select r.segment, sum(abs(r.x - s.x) * r.w * s.w) / sum(r.w * s.w) as w from r join r s using (segment) group by 1),
v as (select c.segment, c.year, sum(abs(c.x - s.x) * c.w * s.w) / sum(c.w * s.w) as v from c join c s using (segment, year) group by 1, 2)
select segment, year, round({finish_sql("b", "w", "v")}, 6) as degree from b join v using (segment, year) join w using (segment)"""
)
def w11_keyed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Independent monitors per market segment on joined tables, exact at any size."""
    li, o, c = (read(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    rows = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).select(
        F.col("c_mktsegment").alias("segment"), F.year("l_shipdate").alias("year"), F.col("l_quantity").alias("x")
    )
    ref = rows.where("year = 1995").select("segment", "x")
    out = energy.energy_distance(ref, rows.where("year > 1995"), ["x"], ["segment"], "sorted", also=["year"])
    return rounded(out.select("segment", "year", F.col("distance").alias("degree")), "degree")


# ------------------------------------------------------------------------ projection


def _map(spark: SparkSession, sf_dir: str, cfg: embed.EmbedConfig, size: int = 600) -> DataFrame:
    """A map of sampled clusters, its update with a sample of the rows that come later, and all
    other rows placed by their neighbours on it."""
    ref, cur = clusters(spark, sf_dir)
    named = lambda df: df.select(F.col("event_id").alias("sample_id"), "comp_id", F.col("x").alias("a"), F.col("y").alias("b"))
    rows, arrived = named(ref), named(cur)
    sample = cut(embed.sample_by_component(rows, size))
    mix = Mixture(np.arange(4), np.full(4, size / 4), np.array(CENTRES), np.repeat(np.eye(2)[None] * 0.49, 4, axis=0))
    none = F.lit(None).cast("double")
    first = cut(embed.project(sample.withColumns({"x0": none, "y0": none}), ["a", "b"], mix, cfg))
    later = cut(embed.sample_by_component(arrived, size // 6))
    known = sample.join(first.select("sample_id", F.col("x").alias("x0"), F.col("y").alias("y0")), "sample_id")
    drawn = known.unionByName(later.withColumns({"x0": none, "y0": none}))
    done = cut(embed.project(drawn, ["a", "b"], mix, cfg)).withColumn("sampled", F.lit(True))
    everything = rows.withColumn("is_new", F.lit(False)).unionByName(arrived.withColumn("is_new", F.lit(True)))
    rest = everything.join(drawn.select("sample_id"), "sample_id", "left_anti")
    placed = embed.place(done.join(drawn.select("sample_id", "a", "b"), "sample_id"), rest, ["a", "b"])
    placed = placed.join(rest.select("sample_id", "comp_id", "is_new"), "sample_id").withColumn("sampled", F.lit(False))
    return done.unionByName(placed.select(*done.columns))


@query()
def tsne_plain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _map(spark, sf_dir, embed.EmbedConfig("plain", rounds=150))


@query()
def tsne_supervised(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _map(spark, sf_dir, embed.EmbedConfig("supervised", rounds=150))


@query()
def tsne_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The constrained map."""
    return _map(spark, sf_dir, embed.EmbedConfig(rounds=150))


@query()
def tsne_without_shape(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _map(spark, sf_dir, embed.EmbedConfig(phi=0.0, rounds=150))


@query()
def tsne_without_position(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _map(spark, sf_dir, embed.EmbedConfig(lam=0.8, phi=0.2, rounds=150))


@query()
def tsne_without_dispersion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _map(spark, sf_dir, embed.EmbedConfig(beta=0.0, rounds=150))


@query()
def blue_noise(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At most 100 well-spread rows of each component of the fixed map."""

    def run(pdf):
        pdf = pdf.sort_values("sample_id")
        return pdf.iloc[embed.blue_noise(pdf[["x", "y"]].to_numpy(float), 100)][["sample_id", "comp_id", "x", "y"]]

    return places(spark, sf_dir).groupBy("comp_id").applyInPandas(run, "sample_id long, comp_id int, x double, y double")


_C = "sqrt((r.x - s.x) * (r.x - s.x) + (r.y - s.y) * (r.y - s.y))"


@query(
    f"""with {CLUSTER_SQL}, o as (select *, count(*) over (partition by comp_id) as n, count(*) over () as total,
  row_number() over (partition by comp_id order by md5(event_id::varchar), event_id) as k from rf), s as (select event_id, x, y from o where k <= ceil(n * (200 / total::double))),
e as (select event_id, x, y from rf where event_id not in (select event_id from s) union all select event_id, x, y from cu),
m as (select r.event_id, s.x, s.y, {_C} as d, row_number() over (partition by r.event_id order by {_C}, s.event_id) as k from e r, s)
select event_id as sample_id, round(sum(x / (d + 1e-9)) / sum(1 / (d + 1e-9)), 5) as x, round(sum(y / (d + 1e-9)) / sum(1 / (d + 1e-9)), 5) as y from m where k <= 3 group by 1"""
)
def place_rest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All rows outside the sampled map, placed by their nearest sampled rows."""
    ref, cur = clusters(spark, sf_dir)
    named = lambda df: df.select(F.col("event_id").alias("sample_id"), "comp_id", "x", "y", F.col("x").alias("a"), F.col("y").alias("b"))
    sample = cut(embed.sample_by_component(named(ref), 200))
    rest = named(ref).join(sample.select("sample_id"), "sample_id", "left_anti").unionByName(named(cur))
    return rounded(embed.place(sample, rest.drop("x", "y"), ["a", "b"]), "x", "y", digits=5)


@query()
def assign_provisional(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of provisional rows per cluster of the batch under the reference's components."""
    ref, cur = clusters(spark, sf_dir)
    mix, _ = mixture.fit(ref, ["x", "y"], 4)
    marked = mixture.assign(cur, ["x", "y"], mix)
    return marked.groupBy("comp_id").agg(F.avg(F.col("provisional").cast("double")).alias("share"), F.count(F.lit(1)).alias("n"))
