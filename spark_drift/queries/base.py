"""Registration and the fixtures that queries share, in Spark and in SQL."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions.expressions import fixed, hash_normal, hash_unit
from spark_drift.functions.numeric import Mixture
from spark_drift.sources.tables import read

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Register a query under its function's name, with its SQL twin."""

    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: fixed(F.col(c), digits) for c in columns})


# ------------------------------------------------------- portable deviates in SQL


def unit_sql(text: str, part: int = 0) -> str:
    return f"((('0x' || substr(md5({text}), {1 + 8 * part}, 8))::bigint + 1) / 4294967296::double)"


def normal_sql(text: str, second: bool = False) -> str:
    wave = "sin" if second else "cos"
    return f"(sqrt(-2 * ln({unit_sql(text)})) * {wave}(2 * pi() * {unit_sql(text, 1)}))"


# ------------------------------------------------------------------- planted streams

SEGMENTS = 100


def gaussian(spark: SparkSession, sf_dir: str, kind: str = "mean", seed: int = 0) -> DataFrame:
    """``i, seg, x, y``: rows of ``events`` as a stream whose law changes 99 times."""
    events = read(spark, sf_dir, "events").select(F.col("event_id").alias("i"))
    n = events.agg(F.count(F.lit(1)).alias("n_"))
    rows = events.withColumn("j", F.lit(1)).join(F.broadcast(n.withColumn("j", F.lit(1))), "j")
    rows = rows.select("i", F.floor(F.col("i") * SEGMENTS / F.col("n_")).cast("int").alias("seg"))
    key = F.concat(F.lit(f"{seed}:"), F.col("i").cast("string"))
    level = lambda axis: 4 * hash_unit(F.concat(F.lit(f"{kind}{axis}:"), F.col("seg").cast("string"))) - 2
    z1, z2 = hash_normal(key), hash_normal(key, True)
    if kind == "mean":
        return rows.select("i", "seg", (z1 + level("x")).alias("x"), (z2 + level("y")).alias("y"))
    sd = F.when(F.col("seg") % 2 == 0, 1.0).otherwise(2.5)
    return rows.select("i", "seg", (z1 * sd).alias("x"), (z2 * sd).alias("y"))


def gaussian_sql(kind: str = "mean", seed: int = 0) -> str:
    key = f"'{seed}:' || i::varchar"
    level = lambda axis: f"(4 * {unit_sql(f"'{kind}{axis}:' || seg::varchar")} - 2)"
    if kind == "mean":
        x, y = f"{normal_sql(key)} + {level('x')}", f"{normal_sql(key, True)} + {level('y')}"
    else:
        sd = "(case when seg % 2 = 0 then 1.0 else 2.5 end)"
        x, y = f"{normal_sql(key)} * {sd}", f"{normal_sql(key, True)} * {sd}"
    return (
        f"(select i, seg, {x} as x, {y} as y from (select event_id as i, "
        f"(event_id * {SEGMENTS} // (select count(*) from events))::int as seg from events))"
    )


# ----------------------------------------------------------------------- daily stream

DAY_FEATURES = ["x1", "x2", "x3", "x4"]
FIRST, LAST = "1995-06-01", "1995-08-31"


def days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``day, month, x1..x4, comp_id``: daily line items with a yearly wave on x1 and a
    slow trend on x2. ``month`` counts from January 1995."""
    li = read(spark, sf_dir, "lineitem").select(F.to_date("l_shipdate").alias("day"), "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    by = li.groupBy("day").agg(
        F.avg("l_quantity").alias("q"), F.avg("l_extendedprice").alias("p"), F.avg("l_discount").alias("d"), F.avg("l_tax").alias("t")
    )
    month = (F.year("day") - 1995) * 12 + F.month("day") - 1
    wave = F.sin(2 * math.pi * F.dayofyear("day") / 365.0)
    rows = by.select(
        "day", month.cast("int").alias("month"), (F.col("q") + 6 * wave).alias("x1"),
        (F.col("p") / 10000 + month / 24.0).alias("x2"), (F.col("d") * 100).alias("x3"), (F.col("t") * 100).alias("x4"),
    )
    return rows.withColumn("comp_id", F.when(F.round("x1", 6) > 25.5, 1).otherwise(0))


DAYS_SQL = """
days as (select day, month, x1, x2, x3, x4, case when round(x1, 6) > 25.5 then 1 else 0 end as comp_id from (
  select day, ((year(day) - 1995) * 12 + month(day) - 1)::int as month,
    q + 6 * sin(2 * pi() * dayofyear(day) / 365.0) as x1,
    p / 10000 + ((year(day) - 1995) * 12 + month(day) - 1) / 24.0 as x2, d * 100 as x3, t * 100 as x4
  from (select l_shipdate::date as day, avg(l_quantity) as q, avg(l_extendedprice) as p, avg(l_discount) as d, avg(l_tax) as t
    from lineitem group by 1)))
"""


def split_days(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    rows = days(spark, sf_dir)
    ref = rows.where(F.col("day").between(F.lit(FIRST).cast("date"), F.lit(LAST).cast("date")))
    return ref, rows.where(F.col("day") > F.lit(LAST).cast("date"))


SPLIT_SQL = DAYS_SQL + f""",
ref as (select * from days where day between date '{FIRST}' and date '{LAST}'),
cur as (select * from days where day > date '{LAST}')
"""


def gap_sql(a: str, b: str, features: list[str]) -> str:
    return "sqrt(" + " + ".join(f"({a}.{f} - {b}.{f}) * ({a}.{f} - {b}.{f})" for f in features) + ")"


def finish_sql(b: str, r: str, c: str) -> str:
    return f"case when {b} is null then 1.0 when {b} = 0 then 0.0 else greatest(0.0, least(1.0, 1 - ({r} + {c}) / (2 * {b}))) end"


# ------------------------------------------------------------------ fixed components

#: mean and covariance of three components over (value / 50, hour / 12 - 1) (fixed values)
COMPONENTS = Mixture(
    ids=np.array([0, 1, 2]),
    n=np.array([500.0, 300.0, 200.0]),
    mean=np.array([[0.5, -0.5], [0.6, 0.5], [2.5, 0.0]]),
    cov=np.array([[[0.25, 0.02], [0.02, 0.1]], [[0.3, -0.03], [-0.03, 0.09]], [[1.2, 0.1], [0.1, 0.4]]]),
)
POINT = ["x", "y"]


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``i, x, y, day, event_type`` of ``events``."""
    e = read(spark, sf_dir, "events")
    return e.select(
        F.col("event_id").alias("i"), (F.col("value") / 50).alias("x"), (F.hour("ts") / 12.0 - 1).alias("y"),
        F.to_date("ts").alias("day"), "event_type",
    )


POINTS_SQL = "pts as (select event_id as i, value / 50 as x, hour(ts) / 12.0::double - 1 as y, ts::date as day, event_type from events)"


def components_sql() -> str:
    rows = []
    for k, i in enumerate(COMPONENTS.ids):
        (a, b), (_, d) = COMPONENTS.cov[k]
        mx, my = COMPONENTS.mean[k]
        rows.append(f"({i}, {COMPONENTS.n[k]}::double, {mx}::double, {my}::double, {a}::double, {b}::double, {d}::double)")
    return f"comps as (select * from (values {', '.join(rows)}) v(comp_id, n, mx, my, a, b, d))"


DENSITY_SQL = f"""{POINTS_SQL}, {components_sql()},
m as (select i, x, y, day, event_type, comp_id, n,
  (d * (x - mx) * (x - mx) - 2 * b * (x - mx) * (y - my) + a * (y - my) * (y - my)) / (a * d - b * b) as d2, a * d - b * b as det from pts, comps),
dens as (select *, -0.5 * (d2 + ln(det) + 2 * ln(2 * pi())) as logpdf from m),
best as (select *, row_number() over (partition by i order by logpdf desc, comp_id) as r from dens)"""
