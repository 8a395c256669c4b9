"""Distances, affinities and divergences on a fixed map."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions.numeric import LOG2PI
from spark_drift.operators.projection import affinity, shrink
from spark_drift.queries.base import query, rounded
from spark_drift.sources.tables import read

FEATURES = ["a", "b"]
WIDTH = 0.1


def mapped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``sample_id, comp_id, a, b, x, y``: two dimensions as features, two others as the map."""
    e = F.col("embedding")
    v = read(spark, sf_dir, "embeddings")
    return v.select(
        F.col("vec_id").cast("long").alias("sample_id"), F.col("label").cast("int").alias("comp_id"),
        *[e[k].cast("double").alias(c) for k, c in enumerate(("a", "b", "x", "y"))],
    )


def factors_of(rows: DataFrame) -> DataFrame:
    """Shrink factors from the components' own covariances."""
    cov = F.array(F.var_pop("a"), F.covar_pop("a", "b"), F.covar_pop("a", "b"), F.var_pop("b"))
    table = rows.groupBy("comp_id").agg(cov.alias("cov"))
    return shrink.factors(shrink.entropy(table, 1e-3))


def anchored(rows: DataFrame) -> DataFrame:
    return rows.where("sample_id % 7 = 0")


_D = "sqrt((p.a - q.a) * (p.a - q.a) + (p.b - q.b) * (p.b - q.b))"
_M = "((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y))"
_S = f"{_D} * case when p.comp_id = q.comp_id then p.factor else 1.0 end"
MAP_SQL = f"""mp as (select vec_id::bigint as sample_id, label::int as comp_id, embedding[1]::double as a, embedding[2]::double as b, embedding[3]::double as x, embedding[4]::double as y from embeddings),
en as (select comp_id, greatest(0.001, 0.5 * ln(var_pop(a) * var_pop(b) - covar_pop(a, b) * covar_pop(a, b)) + 1 + {LOG2PI}) as h from mp group by 1),
fa as (select comp_id, 0.9 * (1 - 0.5 * h / max(h) over ()) as factor from en), rw as (select mp.*, factor from mp join fa using (comp_id)),
ce as (select comp_id, count(*) as size, avg(a) as a, avg(b) as b, avg(x) as x, avg(y) as y from mp group by 1),
c1 as (select p.sample_id, q.comp_id as centre, size, {_S} as d, 1 / (1 + {_M}) as k from rw p, ce q),
c2 as (select median(d) as s from (select min(d) as d from c1 group by sample_id)),
c3 as (select sample_id, centre, sqrt(size) * exp(-d / s) as p, k from c1, c2),
ca as (select sample_id, centre, p / sum(p) over () as p, k / sum(k) over () as q from c3),
a1 as (select p.sample_id, q.sample_id as anchor, {_S} as d, 1 / (1 + {_M}) as k from rw p, rw q where q.sample_id % 7 = 0),
a2 as (select median(d) as s from (select d, row_number() over (partition by sample_id order by d) as r from a1) where r = 2),
a3 as (select sample_id, anchor, case when sample_id = anchor then 1.0 else exp(-d / s) end as p, k from a1, a2),
aa as (select sample_id, anchor, p / sum(p) over () as p, k / sum(k) over () as q from a3),
r1 as (select p.sample_id as a, q.sample_id as b, exp(-({_S}) * ({_S}) / (2 * {WIDTH} * {WIDTH})) as p, 1 / (1 + {_M}) as k from rw p, rw q where p.sample_id <> q.sample_id),
ra as (select a, b, p / sum(p) over () as p, k / sum(k) over () as q from r1)"""


@query(
    f"""with {MAP_SQL} select p.comp_id as comp_a, q.comp_id as comp_b, count(*)::bigint as n, round(avg({_S}), 6) as mean
from rw p, rw q where p.sample_id <> q.sample_id group by 1, 2"""
)
def shrunk_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mapped(spark, sf_dir)
    return rounded(affinity.shrunk_distances(rows, factors_of(rows), FEATURES), "mean")


@query(f"with {MAP_SQL} select sample_id, centre, round(p, 9) as p, round(q, 9) as q from ca")
def centre_affinity(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mapped(spark, sf_dir)
    return rounded(affinity.centre_affinity(rows, factors_of(rows), FEATURES), "p", "q", digits=9)


@query(f"with {MAP_SQL} select sample_id, anchor, round(p, 9) as p, round(q, 9) as q from aa")
def anchor_affinity(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mapped(spark, sf_dir)
    return rounded(affinity.anchor_affinity(rows, anchored(rows), factors_of(rows), FEATURES), "p", "q", digits=9)


@query(
    f"""with {MAP_SQL}, m as (select sum(p * ln(p / q)) as v from ra where p > 1e-11), s as (select sum(p * ln(p / q)) as v from ca where p > 1e-11),
o as (select sum(p * ln(p / q)) as v from aa where p > 1e-11)
select round(m.v, 6) as map, round(s.v, 6) as shape, round(o.v, 6) as position, round(0.6 * m.v + 0.2 * s.v + 0.2 * o.v, 6) as total from m, s, o"""
)
def kl_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mapped(spark, sf_dir)
    return rounded(affinity.objective(rows, anchored(rows), factors_of(rows), FEATURES, WIDTH), "map", "shape", "position", "total")


@query(
    f"""with {MAP_SQL}, r as (select p.sample_id as a, row_number() over (partition by p.sample_id order by {_D}, q.sample_id) <= 10 as h,
  row_number() over (partition by p.sample_id order by sqrt({_M}), q.sample_id) <= 10 as l from mp p, mp q where p.sample_id <> q.sample_id),
e as (select a, count(*) filter (where h and l) / 10.0::double as share from r group by 1) select count(*)::bigint as n, round(avg(share), 6) as preserved from e"""
)
def map_preservation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(affinity.preservation(mapped(spark, sf_dir), FEATURES), "preserved")


@query(
    f"""with {MAP_SQL}, r as (select p.sample_id as a, p.comp_id, p.comp_id <> q.comp_id as other,
  row_number() over (partition by p.sample_id order by sqrt({_M}), q.sample_id) as r from mp p, mp q where p.sample_id <> q.sample_id)
select comp_id, count(distinct a)::bigint as n, round(avg(other::int::double), 6) as mixed from r where r <= 10 group by 1"""
)
def component_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(affinity.overlap(mapped(spark, sf_dir)), "mixed")
