"""Energy distances and drift degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.operators import degree, energy
from spark_drift.queries.base import (
    DAY_FEATURES,
    POINT,
    POINTS_SQL,
    SPLIT_SQL,
    finish_sql,
    gap_sql,
    points,
    query,
    rounded,
    split_days,
    unit_sql,
)
from spark_drift.sources.tables import read

TERMS = ("between", "within_ref", "within_cur", "distance")


def halves(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Values of even and odd events, the odd ones stretched."""
    e = read(spark, sf_dir, "events").select("event_id", "event_type", F.col("value").alias("x"))
    ref = e.where("event_id % 2 = 0")
    return ref, e.where("event_id % 2 = 1").withColumn("x", F.col("x") * 1.5 + 10)


HALVES_SQL = """
r as (select event_type, value as x from events where event_id % 2 = 0),
c as (select event_type, value * 1.5 + 10 as x from events where event_id % 2 = 1)"""

ALL_SQL = f"""with {HALVES_SQL},
t as (select (select count(*) from r) as n, (select count(*) from c) as m,
  (select avg(abs(r.x - c.x)) from r, c) as b, (select avg(abs(r.x - s.x)) from r, r s) as w, (select avg(abs(c.x - s.x)) from c, c s) as v)
select n::bigint as n, m::bigint as m, round(b, 6) as between, round(w, 6) as within_ref, round(v, 6) as within_cur,
  round({finish_sql("b", "w", "v")}, 6) as distance from t"""


@query(ALL_SQL)
def energy_pairwise_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(energy.energy_distance(*halves(spark, sf_dir), ["x"]), *TERMS)


@query(ALL_SQL)
def energy_sorted_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(energy.energy_distance(*halves(spark, sf_dir), ["x"], method="sorted"), *TERMS)


@query(
    f"""with {HALVES_SQL},
b as (select event_type, avg(abs(r.x - c.x)) as b from r join c using (event_type) group by 1),
w as (select r.event_type, avg(abs(r.x - s.x)) as w, sqrt(count(*))::bigint as n from r join r s using (event_type) group by 1),
v as (select c.event_type, avg(abs(c.x - s.x)) as v, sqrt(count(*))::bigint as m from c join c s using (event_type) group by 1)
select event_type, n, m, round(b, 6) as between, round(w, 6) as within_ref, round(v, 6) as within_cur, round({finish_sql("b", "w", "v")}, 6) as distance
from b join w using (event_type) join v using (event_type)"""
)
def energy_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(energy.energy_distance(*halves(spark, sf_dir), ["x"], ["event_type"], "sorted"), *TERMS)


UNBIASED_SQL = f"""with {HALVES_SQL},
t as (select (select count(*) from r) as n, (select count(*) from c) as m,
  (select avg(abs(r.x - c.x)) from r, c) as b, (select sum(abs(r.x - s.x)) from r, r s) as w, (select sum(abs(c.x - s.x)) from c, c s) as v)
select n::bigint as n, m::bigint as m, round(b, 6) as between, round(w / (n * (n - 1)), 6) as within_ref, round(v / (m * (m - 1)), 6) as within_cur,
  round(1 - (w / (n * (n - 1)) + v / (m * (m - 1))) / (2 * b), 6) as distance from t"""


@query(UNBIASED_SQL)
def energy_unbiased(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(energy.energy_distance(*halves(spark, sf_dir), ["x"], method="sorted", estimator="u"), *TERMS)


@query(
    f"""with {HALVES_SQL},
t as (select (select count(*) from r) as n, (select count(*) from c) as m,
  (select avg(abs(r.x - c.x)) from r, c) as b, (select avg(abs(r.x - s.x)) from r, r s) as w, (select avg(abs(c.x - s.x)) from c, c s) as v)
select round(2 * b - w - v, 6) as squared, round(sqrt(greatest(0, 2 * b - w - v)), 6) as root from t"""
)
def energy_unnormalised(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = energy.energy_distance(*halves(spark, sf_dir), ["x"], method="sorted", normalise=False)
    root = F.sqrt(F.greatest(F.lit(0.0), F.col("distance")))
    return rounded(out.select(F.col("distance").alias("squared"), root.alias("root")), "squared", "root")


@query(
    f"""with {HALVES_SQL},
rc as (select avg(x) as x, count(*) as w from r group by floor(x / 5)), cc as (select avg(x) as x, count(*) as w from c group by floor(x / 5)),
t as (select (select sum(abs(p.x - q.x) * p.w * q.w) / (sum(p.w * q.w)) from rc p, cc q) as b,
  (select sum(abs(p.x - q.x) * p.w * q.w) / (sum(p.w * q.w)) from rc p, rc q) as w,
  (select sum(abs(p.x - q.x) * p.w * q.w) / (sum(p.w * q.w)) from cc p, cc q) as v)
select (select count(*) from r)::bigint as n, (select count(*) from c)::bigint as m, round(b, 6) as between, round(w, 6) as within_ref,
  round(v, 6) as within_cur, round({finish_sql("b", "w", "v")}, 6) as distance, 10.0::double as max_error from t"""
)
def energy_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(energy.energy_distance(*halves(spark, sf_dir), ["x"], method="cells", cell=5.0), *TERMS)


def embedded(spark: SparkSession, sf_dir: str, dims: int = 64) -> tuple[DataFrame, DataFrame, list[str]]:
    """Even and odd rows with the first ``dims`` entries of their vectors as one array."""
    v = read(spark, sf_dir, "embeddings").select("vec_id", F.slice("embedding", 1, dims).cast("array<double>").alias("v"))
    return v.where("vec_id % 2 = 0"), v.where("vec_id % 2 = 1"), ["v"]


@query(
    f"""with e as (select vec_id, list_transform(embedding, lambda x: x::double) as v from embeddings),
r as (select v from e where vec_id % 2 = 0), c as (select v from e where vec_id % 2 = 1),
t as (select (select count(*) from r) as n, (select count(*) from c) as m, (select avg(list_distance(r.v, c.v)) from r, c) as b,
  (select avg(list_distance(r.v, s.v)) from r, r s) as w, (select avg(list_distance(c.v, s.v)) from c, c s) as v)
select n::bigint as n, m::bigint as m, round(b, 6) as between, round(w, 6) as within_ref, round(v, 6) as within_cur,
  round({finish_sql("b", "w", "v")}, 6) as distance from t"""
)
def energy_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    ref, cur, names = embedded(spark, sf_dir)
    return rounded(energy.energy_distance(ref, cur, names, method="blocks"), *TERMS)


@query(name="energy_sliced")
def energy_sliced(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir)
    return energy.energy_distance(p.where("i % 2 = 0"), p.where("i % 2 = 1").withColumn("x", F.col("x") + 0.5), POINT, method="sliced", directions=50)


_U = unit_sql("'0:' || i::varchar")
_P = [("r", "0", "x"), ("c", "1", "x + 0.5")]
SAMPLED_SQL = f"""with {POINTS_SQL}, """ + ", ".join(
    f"""{n} as (select event_type, {x} as x, y from (select *, {_U} as u, count(*) over (partition by event_type) as size from pts where i % 2 = {odd}) where u <= 200.0::double / size)"""
    for n, odd, x in _P
)
_G = "sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))"


@query(
    f"""{SAMPLED_SQL}, n as (select event_type, count(*) as n from r group by 1), m as (select event_type, count(*) as m from c group by 1),
b as (select a.event_type, avg({_G}) as b from r a join c b using (event_type) group by 1), w as (select a.event_type, avg({_G}) as w from r a join r b using (event_type) group by 1),
v as (select a.event_type, avg({_G}) as v from c a join c b using (event_type) group by 1)
select event_type, n::bigint as n, m::bigint as m, round(b, 6) as between, round(w, 6) as within_ref, round(v, 6) as within_cur, round({finish_sql("b", "w", "v")}, 6) as distance
from n join m using (event_type) join b using (event_type) join w using (event_type) join v using (event_type)"""
)
def energy_sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir)
    cur = p.where("i % 2 = 1").withColumn("x", F.col("x") + 0.5)
    return rounded(energy.energy_distance(p.where("i % 2 = 0"), cur, POINT, ["event_type"], method="sampled", cap=200, key="i"), *TERMS)


@query(
    f"""with {POINTS_SQL}, r as (select * from pts where i % 2 = 0), c as (select x * 0.1 + 9 as x, y, event_type from pts where i % 2 = 1),
a as (select event_type, avg(x) as mx, avg(y) as my, var_pop(x) + var_pop(y) as s from r group by 1),
b as (select event_type, avg(x) as mx, avg(y) as my, var_pop(x) + var_pop(y) as s from c group by 1)
select event_type, round(greatest(0, 1 - (sqrt(2 * a.s) + sqrt(2 * b.s)) / (2 * sqrt((a.mx - b.mx) * (a.mx - b.mx) + (a.my - b.my) * (a.my - b.my)))), 6) as bound
from a join b using (event_type)"""
)
def energy_moment_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir)
    cur = p.where("i % 2 = 1").withColumn("x", F.col("x") * 0.1 + 9)
    return rounded(energy.moment_lower_bound(p.where("i % 2 = 0"), cur, POINT, ["event_type"]), "bound")


@query(
    """with a as (select event_type, avg(value) as a from events where event_id % 2 = 0 group by 1),
b as (select event_type, avg(value) as b from events where event_id % 2 = 1 group by 1)
select event_type, round((a - b) * ln(a / b), 6) as divergence from a join b using (event_type)"""
)
def poisson_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events")
    return rounded(energy.poisson_divergence(e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1"), "value", ["event_type"]), "divergence")


# -------------------------------------------------------------------- degrees


@query(
    f"""with {SPLIT_SQL},
b as (select c.month, avg({gap_sql("r", "c", DAY_FEATURES)}) as b from ref r, cur c group by 1),
v as (select c.month, avg({gap_sql("c", "s", DAY_FEATURES)}) as v from cur c join cur s on c.month = s.month group by 1),
w as (select avg({gap_sql("r", "s", DAY_FEATURES)}) as w from ref r, ref s)
select month, round({finish_sql("b", "w", "v")}, 6) as degree from b join v using (month), w"""
)
def drift_direct_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(degree.drift_degree(*split_days(spark, sf_dir), "month", DAY_FEATURES, "direct"), "degree")


PARTS_SQL = f"""{SPLIT_SQL},
g as (select month, comp_id, count(*) as m from cur group by 1, 2),
b as (select c.month, c.comp_id, avg({gap_sql("r", "c", DAY_FEATURES)}) as b from cur c join ref r on r.comp_id = c.comp_id group by 1, 2),
v as (select c.month, c.comp_id, avg({gap_sql("c", "s", DAY_FEATURES)}) as v from cur c join cur s on c.month = s.month and c.comp_id = s.comp_id group by 1, 2),
w as (select r.comp_id, avg({gap_sql("r", "s", DAY_FEATURES)}) as w from ref r join ref s on r.comp_id = s.comp_id group by 1),
parts as (select g.month, g.comp_id, m / sum(m) over (partition by g.month) as share, {finish_sql("b", "w", "v")} as distance
  from g left join b on b.month = g.month and b.comp_id = g.comp_id left join v on v.month = g.month and v.comp_id = g.comp_id left join w on w.comp_id = g.comp_id)"""


@query(f"with {PARTS_SQL} select month, round(sum(share * distance), 6) as degree from parts group by 1")
def drift_component_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(degree.drift_degree(*split_days(spark, sf_dir), "month", DAY_FEATURES), "degree")


@query(f"with {PARTS_SQL} select month, comp_id, round(share, 6) as share, round(distance, 6) as distance, round(share * distance, 6) as part from parts")
def drift_contributions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(degree.contributions(*split_days(spark, sf_dir), "month", DAY_FEATURES), "share", "distance", "part")


@query(
    f"""with {PARTS_SQL}, k as (select *, row_number() over (partition by month order by round(share * distance, 6) desc, comp_id) as rank from parts)
select month, comp_id, round(share * distance, 6) as part, rank::int as rank from k where rank <= 1"""
)
def op_topk_contrib(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = rounded(degree.contributions(*split_days(spark, sf_dir), "month", DAY_FEATURES), "part")
    return degree.ranked(parts, "month", 1).select("month", "comp_id", "part", "rank")


def _feature_sql(f: str) -> str:
    one = [f]
    return f"""select '{f}' as feature, g.month, m / sum(m) over (partition by g.month) as share, {finish_sql("b", "w", "v")} as distance
from (select month, comp_id, count(*) as m from cur group by 1, 2) g
left join (select c.month, c.comp_id, avg({gap_sql("r", "c", one)}) as b from cur c join ref r on r.comp_id = c.comp_id group by 1, 2) b using (month, comp_id)
left join (select c.month, c.comp_id, avg({gap_sql("c", "s", one)}) as v from cur c join cur s on c.month = s.month and c.comp_id = s.comp_id group by 1, 2) v using (month, comp_id)
left join (select r.comp_id, avg({gap_sql("r", "s", one)}) as w from ref r join ref s on r.comp_id = s.comp_id group by 1) w using (comp_id)"""


def features_sql(split: str) -> str:
    return f"""with {split}, f as ({" union all ".join(_feature_sql(f) for f in DAY_FEATURES)})
select month, feature, round(sum(share * distance), 6) as degree from f group by 1, 2"""


@query(features_sql(SPLIT_SQL))
def drift_per_feature(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(degree.per_feature(*split_days(spark, sf_dir), "month", DAY_FEATURES), "degree")


@query(
    f"""with {SPLIT_SQL},
k as (select c.month, c.day, r.day as near, row_number() over (partition by c.day order by {gap_sql("r", "c", DAY_FEATURES)}, r.day) as rk from cur c, ref r),
u as (select distinct month, near from k where rk <= 5),
s as (select u.month, r.* exclude (month) from u join ref r on r.day = u.near),
b as (select c.month, avg({gap_sql("s", "c", DAY_FEATURES)}) as b from cur c join s on s.month = c.month group by 1),
v as (select c.month, avg({gap_sql("c", "s", DAY_FEATURES)}) as v from cur c join cur s on c.month = s.month group by 1),
w as (select s.month, avg({gap_sql("s", "z", DAY_FEATURES)}) as w from s join s z on s.month = z.month group by 1)
select month, round({finish_sql("b", "w", "v")}, 6) as degree from b join v using (month) join w using (month)"""
)
def drift_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    ref, cur = split_days(spark, sf_dir)
    return rounded(degree.drift_degree(ref, cur, "month", DAY_FEATURES, "knn", 5, "day"), "degree")


@query(
    f"""with {SPLIT_SQL} select month, feature, count(v)::bigint as n, round(avg(v), 6) as mean, round(min(v), 6) as low, round(max(v), 6) as high
from (select month, unnest(['x1', 'x2', 'x3', 'x4']) as feature, unnest([x1, x2, x3, x4]) as v from cur) group by 1, 2"""
)
def feature_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(degree.feature_values(split_days(spark, sf_dir)[1], "month", DAY_FEATURES), "mean", "low", "high")


@query(
    """with p as (select event_id as i, value as x from events), ref as (select x from p where i < 300),
win as (select e.window_end, p.x from p join (select distinct (i // 100) * 100 as window_end from p) e on p.i > e.window_end - 200 and p.i <= e.window_end),
full_ as (select window_end, count(*) as n_rows from win group by 1 having count(*) = 200),
b as (select w.window_end, avg(abs(w.x - r.x)) as b from win w, ref r group by 1),
v as (select w.window_end, avg(abs(w.x - z.x)) as v from win w join win z using (window_end) group by 1),
w as (select avg(abs(a.x - b.x)) as w from ref a, ref b)
select window_end, n_rows::bigint as n_rows, round(greatest(0, 1 - (w + v) / (2 * b)), 6) as degree from full_ join b using (window_end) join v using (window_end), w"""
)
def sliding_window_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events").select(F.col("event_id").alias("i"), F.col("value").alias("x"), F.lit(0).alias("comp_id"))
    return rounded(degree.windowed(rows.where("i < 300"), rows, "i", ["x"], 200, 100), "degree")


@query(
    """with p as (select ts, event_id as i, value as x from events), ref as (select x from p where i < 300),
win as (select date_trunc('day', ts) + to_days(k::int) as window_end, x from p, (select unnest([1, 2]) as k)),
n as (select window_end, count(*) as n_rows from win group by 1 having count(*) >= 20),
b as (select w.window_end, avg(abs(w.x - r.x)) as b from win w, ref r group by 1),
v as (select w.window_end, avg(abs(w.x - z.x)) as v from win w join win z using (window_end) group by 1),
w as (select avg(abs(a.x - b.x)) as w from ref a, ref b)
select strftime(window_end, '%Y-%m-%d') as window_end, n_rows::bigint as n_rows, round(greatest(0, 1 - (w + v) / (2 * b)), 6) as degree
from n join b using (window_end) join v using (window_end), w"""
)
def sliding_time_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of two days that begin every day."""
    rows = read(spark, sf_dir, "events").select("ts", F.col("event_id").alias("i"), F.col("value").alias("x"), F.lit(0).alias("comp_id"))
    out = degree.time_windowed(rows.where("i < 300"), rows, "ts", ["x"], "2 days", "1 day", 20)
    return rounded(out.withColumn("window_end", F.date_format("window_end", "yyyy-MM-dd")), "degree")


@query(
    f"""with {PARTS_SQL}, s as (select month, round(sum(share * distance), 6) as degree from parts group by 1)
select month, degree, coalesce(sum((degree >= 0.2)::int) over (order by month rows between 1 preceding and current row), 0) >= 2 as alarm from s"""
)
def alarms_persist(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spark_drift.operators import detect

    series = rounded(degree.drift_degree(*split_days(spark, sf_dir), "month", DAY_FEATURES), "degree")
    return detect.alarms(series, "month", 0.2, persist=2)


@query(
    f"""with {PARTS_SQL}, s as (select month, round(sum(share * distance), 6) as degree from parts group by 1)
select month, degree, degree >= 0.1 and coalesce(degree - lag(degree) over (order by month) >= 0.02, false) as alarm from s"""
)
def alarms_rise(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spark_drift.operators import detect

    series = rounded(degree.drift_degree(*split_days(spark, sf_dir), "month", DAY_FEATURES), "degree")
    return detect.alarms(series, "month", 0.1, min_rise=0.02)


@query(
    f"""with {PARTS_SQL}, s as (select month, sum(share * distance) as before, max(distance) as after from parts group by 1)
select month, round(before, 6) as before, round(after, 6) as after, round(after - before, 6) as change from s"""
)
def degree_before_after(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = degree.contributions(*split_days(spark, sf_dir), "month", DAY_FEATURES)
    after = parts.groupBy("month").agg(F.max("distance").alias("degree"))
    return rounded(degree.before_after(degree.combine(parts, "month"), after, "month"), "before", "after", "change")
