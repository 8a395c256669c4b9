"""Gaussian components: densities, gates, statistics, order selection, online series."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions import numeric
from spark_drift.functions.numeric import LOG2PI, OnlineConfig
from spark_drift.operators import mixture, online
from spark_drift.operators.projection import shrink
from spark_drift.queries.base import (
    COMPONENTS,
    DAY_FEATURES,
    DENSITY_SQL,
    POINT,
    components_sql,
    points,
    query,
    rounded,
    split_days,
)
from spark_drift.queries.projections import MAP_SQL, mapped


@query(f"with {DENSITY_SQL} select i, comp_id, round(logpdf, 6) as log_density from dens")
def gauss_logpdf_2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(mixture.log_density(points(spark, sf_dir), POINT, COMPONENTS).select("i", "comp_id", "log_density"), "log_density")


def _gated(spark: SparkSession, sf_dir: str, gate: str, level: float) -> DataFrame:
    return mixture.assign(points(spark, sf_dir), POINT, COMPONENTS, gate, level).select("i", "comp_id", "provisional")


@query(f"with {DENSITY_SQL} select i, comp_id, d2 > {-2 * np.log(0.05)} as provisional from best where r = 1")
def gate_chi2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _gated(spark, sf_dir, "chi2", 0.95)


@query(f"with {DENSITY_SQL} select i, comp_id, exp(logpdf) <= 0.2 as provisional from best where r = 1")
def gate_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _gated(spark, sf_dir, "density", 0.2)


@query(
    f"""with {DENSITY_SQL}, j as (select *, logpdf + ln(n / 1000) as s from dens),
k as (select *, row_number() over (partition by i order by s desc, comp_id) as q, max(s) over (partition by i) as top from j),
p as (select i, sum(exp(s - top)) as total from k group by 1)
select k.i, comp_id, 1 / total <= 0.95 as provisional from k join p using (i) where q = 1"""
)
def gate_posterior(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _gated(spark, sf_dir, "posterior", 0.95)


@query(
    f"""with {DENSITY_SQL}, ok as (select comp_id, x, y from best where r = 1 and d2 <= {-2 * np.log(0.05)}),
s as (select comp_id, count(*) as m, avg(x) as ax, avg(y) as ay, var_pop(x) as vx, covar_pop(x, y) as cxy, var_pop(y) as vy from ok group by 1)
select comp_id, round(n + m, 6) as n, round((n * mx + m * ax) / (n + m), 6) as mean_x, round((n * my + m * ay) / (n + m), 6) as mean_y,
  round((n * a + m * vx) / (n + m) + n * m / ((n + m) * (n + m)) * (mx - ax) * (mx - ax), 6) as var_x,
  round((n * b + m * cxy) / (n + m) + n * m / ((n + m) * (n + m)) * (mx - ax) * (my - ay), 6) as cov_xy,
  round((n * d + m * vy) / (n + m) + n * m / ((n + m) * (n + m)) * (my - ay) * (my - ay), 6) as var_y
from comps join s using (comp_id)"""
)
def absorb_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    marked = mixture.assign(points(spark, sf_dir), POINT, COMPONENTS)
    mix = mixture.absorb(marked, POINT, COMPONENTS, OnlineConfig(truncation="none"))
    return statistics(spark, mix)


def statistics(spark: SparkSession, mix: numeric.Mixture) -> DataFrame:
    rows = [
        (int(i), float(mix.n[k]), *map(float, mix.mean[k]), float(mix.cov[k, 0, 0]), float(mix.cov[k, 0, 1]), float(mix.cov[k, 1, 1]))
        for k, i in enumerate(mix.ids)
    ]
    out = spark.createDataFrame(rows, "comp_id int, n double, mean_x double, mean_y double, var_x double, cov_xy double, var_y double")
    return rounded(out, "n", "mean_x", "mean_y", "var_x", "cov_xy", "var_y")


@query(
    f"""with {DENSITY_SQL}, j as (select *, logpdf + ln(n / 1000) as s from dens),
t as (select *, max(s) over (partition by i) as top from j), l as (select *, top + ln(sum(exp(s - top)) over (partition by i)) as lse from t),
g as (select comp_id, exp(s - lse) as w, x, y, lse from l)
select comp_id, round(sum(w), 6) as n, round(sum(w * x) / sum(w), 6) as mean_x, round(sum(w * y) / sum(w), 6) as mean_y,
  round(sum(w * x * x) / sum(w) - (sum(w * x) / sum(w)) ** 2, 6) as var_x,
  round(sum(w * x * y) / sum(w) - sum(w * x) / sum(w) * sum(w * y) / sum(w), 6) as cov_xy,
  round(sum(w * y * y) / sum(w) - (sum(w * y) / sum(w)) ** 2, 6) as var_y from g group by 1"""
)
def em_step_2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix, _ = mixture.em_step(points(spark, sf_dir), POINT, COMPONENTS, ridge=0.0)
    return statistics(spark, mix)


@query(
    f"""with {DENSITY_SQL}, j as (select i, ln(sum(exp(logpdf) * n / 1000)) as l from dens group by 1),
s as (select count(*) as n, sum(l) as loglik from j)
select 17::int as params, round(loglik, 4) as log_likelihood, round(-2 * loglik + 17 * ln(n), 4) as bic, round(-2 * loglik + 34, 4) as aic from s"""
)
def information_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both criteria of the fixed components on all rows."""
    rows = points(spark, sf_dir)
    _, value = mixture.em_step(rows, POINT, COMPONENTS)
    n = rows.count()
    k, d = len(COMPONENTS.ids), 2
    scores = [(numeric.parameters(k, d), value, numeric.criterion(value, k, d, n, "bic"), numeric.criterion(value, k, d, n, "aic"))]
    return rounded(spark.createDataFrame(scores, "params int, log_likelihood double, bic double, aic double"), "log_likelihood", "bic", "aic", digits=4)


@query()
def mixture_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix, _ = mixture.fit(points(spark, sf_dir), POINT, 3)
    return statistics(spark, mix)


@query()
def mixture_fit_library(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The library's own fit, for comparison."""
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=POINT, outputCol="features").transform(points(spark, sf_dir))
    model = GaussianMixture(k=3, seed=1, maxIter=30).fit(rows)
    return spark.createDataFrame([(k, float(w)) for k, w in enumerate(model.weights)], "comp_id int, weight double")


@query()
def mixture_select_bic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.select(points(spark, sf_dir), POINT)[0]


@query()
def mixture_select_aic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.select(points(spark, sf_dir), POINT, kind="aic")[0]


@query(f"with {DENSITY_SQL}, s as (select comp_id, count(*) as n from best where r = 1 group by 1) select round(avg(n) / 2, 6) as threshold from s")
def pool_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(mixture.pool_threshold(mixture.assign(points(spark, sf_dir), POINT, COMPONENTS)), "threshold")


def labelled(spark: SparkSession, sf_dir: str) -> numeric.Mixture:
    """The labels of ``embeddings`` as components over two of its dimensions."""
    x, y = F.col("a"), F.col("b")
    found = mapped(spark, sf_dir).groupBy("comp_id").agg(
        F.count(F.lit(1)).cast("double").alias("n"), F.array(F.avg(x), F.avg(y)).alias("mean"),
        F.array(F.var_pop(x), F.covar_pop(x, y), F.covar_pop(x, y), F.var_pop(y)).alias("cov"), F.lit(0.0).alias("born"),
    )
    return mixture.from_table(found)


@query(
    f"""with {MAP_SQL} select (case when comp_id = 1 then 0 else comp_id end)::int as comp_id, round(count(*)::double, 6) as n, round(avg(a), 6) as mean_x, round(avg(b), 6) as mean_y,
  round(var_pop(a), 6) as var_x, round(covar_pop(a, b), 6) as cov_xy, round(var_pop(b), 6) as var_y from mp group by 1"""
)
def merge_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    return statistics(spark, mixture.merge_components(labelled(spark, sf_dir), 1, 0))


_JOINED = """jo as (select 0 as comp_id, s.n, s.mx, s.my, sum(u.n * (a + (u.mx - s.mx) * (u.mx - s.mx))) / s.n as a, sum(u.n * (b + (u.mx - s.mx) * (u.my - s.my))) / s.n as b,
  sum(u.n * (d + (u.my - s.my) * (u.my - s.my))) / s.n as d from (select * from comps where comp_id in (0, 1)) u,
  (select sum(n) as n, sum(n * mx) / sum(n) as mx, sum(n * my) / sum(n) as my from comps where comp_id in (0, 1)) s group by s.n, s.mx, s.my
union all select comp_id, n, mx, my, a, b, d from comps where comp_id = 2),
jm as (select i, comp_id, (d * (x - mx) * (x - mx) - 2 * b * (x - mx) * (y - my) + a * (y - my) * (y - my)) / (a * d - b * b) as d2, a * d - b * b as det from pts, jo),
jd as (select *, row_number() over (partition by i order by -0.5 * (d2 + ln(det)) desc, comp_id) as r from jm)"""


@query(
    f"""with {DENSITY_SQL}, {_JOINED}, o as (select i, comp_id, d2 > {-2 * np.log(0.05)} as provisional from best where r = 1)
select o.i, case when o.provisional or o.comp_id in (0, 1) then jd.comp_id else o.comp_id end::int as comp_id,
  case when o.provisional or o.comp_id in (0, 1) then jd.d2 > {-2 * np.log(0.05)} else o.provisional end as provisional from o join jd on jd.i = o.i and jd.r = 1"""
)
def merge_judges_anew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An analyst's merge: rows of both components and provisional ones find their place again."""
    marked = mixture.assign(points(spark, sf_dir), POINT, COMPONENTS)
    return mixture.merge_and_judge(marked, POINT, COMPONENTS, 1, 0)[1].select("i", "comp_id", "provisional")


@query(
    f"""with {DENSITY_SQL}, b as (select comp_id, day from best where r = 1)
select comp_id, sum((day > (select max(day) from b) - 3)::int)::bigint as rows_recent, sum((day > (select max(day) from b) - 3)::int) >= 100 as active from b group by 1"""
)
def stale_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    marked = mixture.assign(points(spark, sf_dir), POINT, COMPONENTS).withColumn("d", F.unix_date("day"))
    return mixture.activity(marked, "d", 3, 100)


@query(f"with {MAP_SQL} select comp_id, round(h, 6) as entropy from en")
def entropy_2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(shrink.entropy(mixture.table(spark, labelled(spark, sf_dir))), "entropy")


@query(f"with {MAP_SQL} select comp_id, round(factor, 6) as factor from fa")
def shrink_factors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(shrink.factors(shrink.entropy(mixture.table(spark, labelled(spark, sf_dir)))), "factor")


@query()
def online_series_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole method in order within one task per key: monthly series of the days."""
    ref, cur = split_days(spark, sf_dir)
    return online.kernel_series(ref, cur, "month", DAY_FEATURES)


@query()
def online_series_row_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    ref, cur = split_days(spark, sf_dir)
    return online.kernel_series(ref, cur, "month", DAY_FEATURES, cfg=OnlineConfig(order="row"))


@query()
def online_series_analyst_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    ref, cur = split_days(spark, sf_dir)
    return online.kernel_series(ref, cur, "month", DAY_FEATURES, cfg=OnlineConfig(min_pool=40))


@query()
def online_series_stepwise(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first yearly batches of the days as distributed steps."""
    ref, cur = split_days(spark, sf_dir)
    yearly = cur.withColumn("year", F.floor(F.col("month") / 12).cast("int"))
    times = [r[0] for r in yearly.select("year").distinct().orderBy("year").collect()]
    return online.stepwise_series(ref, yearly, "year", DAY_FEATURES, times)


@query()
def online_series_keyed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Independent monitors, one per event type."""
    p = points(spark, sf_dir).withColumn("d", F.unix_date("day"))
    first = p.agg(F.min("d")).first()[0]
    return online.kernel_series(p.where(F.col("d") < first + 7), p.where(F.col("d") >= first + 7), "d", POINT, "event_type")


@query(
    f"""with {DENSITY_SQL} select comp_id, count(*)::bigint as n, min(day) as first_t, max(day) as last_t, round(avg(x), 6) as x_mean, round(min(x), 6) as x_low,
  round(max(x), 6) as x_high, round(avg(y), 6) as y_mean, round(min(y), 6) as y_low, round(max(y), 6) as y_high from best where r = 1 group by 1"""
)
def component_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spark_drift.operators import views

    out = views.component_profile(mixture.assign(points(spark, sf_dir), POINT, COMPONENTS), POINT, "day")
    return rounded(out, *[c for c in out.columns if c.startswith(("x_", "y_"))])


