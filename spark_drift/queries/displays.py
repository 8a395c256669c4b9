"""View tables, selections, ensembles and scores on fixed predictions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions.expressions import hash_unit
from spark_drift.operators import detect, ensemble, interact, mixture, views
from spark_drift.operators.baselines import information, local_degree, total_variation
from spark_drift.operators.projection import embed
from spark_drift.queries.base import (
    COMPONENTS,
    DENSITY_SQL,
    POINT,
    POINTS_SQL,
    gaussian,
    gaussian_sql,
    points,
    query,
    rounded,
    unit_sql,
)
from spark_drift.sources.tables import read

BOX = (-0.3, 0.3, -0.3, 0.3)
CELLS = 12


def places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``sample_id, x, y, comp_id, is_new``: the first two dimensions as a fixed map."""
    v = read(spark, sf_dir, "embeddings")
    return v.select(
        F.col("vec_id").alias("sample_id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"),
        F.col("label").cast("int").alias("comp_id"), (F.col("vec_id") % 3 == 0).alias("is_new"),
    )


PLACES_SQL = "pl as (select vec_id as sample_id, embedding[1]::double as x, embedding[2]::double as y, label::int as comp_id, vec_id % 3 = 0 as is_new from embeddings)"


def _cell_sql(v: str) -> str:
    return f"greatest(0, least({CELLS - 1}, floor(({v} - (-0.3)) / 0.6 * {CELLS})))::int"


def _grid_sql(where: str) -> str:
    return f"""select row, col, n, n / sum(n) over () as density from (select {_cell_sql("y")} as row, {_cell_sql("x")} as col, count(*) as n from pl where {where} group by 1, 2)"""


@query(f"with {PLACES_SQL} select row, col, n::bigint as n, round(density, 6) as density from ({_grid_sql('true')})")
def grid_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(views.grid(places(spark, sf_dir), "x", "y", BOX, CELLS), "density")


def _halo_sql(centre: str, ring: str) -> str:
    return f"""with {PLACES_SQL}, g as ({_grid_sql("true")}), o as (select * from range(-2, 3) a(dr), range(-2, 3) b(dc))
select (row + dr)::int as row, (col + dc)::int as col, round(sum(density * case when dr = 0 and dc = 0 then {centre} else {ring} end), 6) as density from g, o group by 1, 2"""


@query(_halo_sql("0.7", "0.3 / 24"))
def halo_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(views.halo(views.grid(places(spark, sf_dir), "x", "y", BOX, CELLS)), "density")


@query(_halo_sql("1.0", "0.3"))
def halo_each(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(views.halo(views.grid(places(spark, sf_dir), "x", "y", BOX, CELLS), split="each"), "density")


def _diff_sql(a: str, b: str) -> str:
    return f"""with {PLACES_SQL}, a as ({_grid_sql(a)}), b as ({_grid_sql(b)})
select row, col, round(coalesce(a.density, 0), 6) as before, round(coalesce(b.density, 0), 6) as after, round(coalesce(b.density, 0) - coalesce(a.density, 0), 6) as diff,
  case when coalesce(b.density, 0) > coalesce(a.density, 0) then 'denser' when coalesce(b.density, 0) < coalesce(a.density, 0) then 'sparser' else 'same' end as sign
from a full join b using (row, col)"""


def _diff(a: DataFrame, b: DataFrame) -> DataFrame:
    grid = lambda df: views.grid(df, "x", "y", BOX, CELLS)
    return rounded(views.density_diff(grid(a), grid(b)), "before", "after", "diff")


@query(_diff_sql("not is_new", "is_new"))
def density_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    return _diff(p.where("not is_new"), p.where("is_new"))


@query(_diff_sql("not is_new and comp_id = 3", "is_new and comp_id = 3"))
def density_diff_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir).where("comp_id = 3")
    return _diff(p.where("not is_new"), p.where("is_new"))


@query(
    f"""with {PLACES_SQL}, g as (select comp_id as label, {_cell_sql("y")} as row, {_cell_sql("x")} as col, count(*) as n from pl group by 1, 2, 3)
select label, row, col, n::bigint as n, round(n / sum(n) over (partition by label), 6) as density from g"""
)
def joint_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir).withColumnRenamed("comp_id", "label")
    return rounded(views.grid(p, "x", "y", BOX, CELLS, ["label"]), "density")


@query(
    f"""with {PLACES_SQL}, g as ({_grid_sql("not is_new")})
select 'cell' as kind, (-1)::bigint as sample_id, (-1)::int as comp_id, col::double as x, row::double as y, round(density, 6) as density from g
union all select 'point', sample_id, comp_id, round(x, 6), round(y, 6), -1.0 from pl where is_new"""
)
def scatter_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = rounded(views.frame(places(spark, sf_dir), BOX, CELLS), "x", "y", "density")
    return out.fillna(-1, ["sample_id", "comp_id", "density"])


@query(
    f"""with {PLACES_SQL}, c as (select p.*, q.x as x0, q.y as y0 from (select * from pl) p left join (select * from pl where not is_new) q using (sample_id)),
s as (select *, case when x0 is null then 2 else 1 end as stage from c)
select sample_id, stage, (case when stage = 2 then dense_rank() over (partition by stage order by comp_id) else 0 end)::int as turn, comp_id,
  round(x0, 6) as x0, round(y0, 6) as y0, round(x * 2, 6) as x1, round(y * 2, 6) as y1 from s"""
)
def transition_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    moved = p.withColumns({"x": F.col("x") * 2, "y": F.col("y") * 2})
    return rounded(views.transition(p.where("not is_new"), moved), "x0", "y0", "x1", "y1")


@query(
    f"""with {PLACES_SQL}, g as (select sqrt((x * 2 - x) ** 2 + (y * 2 - y) ** 2) as g from pl)
select count(*)::bigint as n, round(avg(g), 6) as mean_move, round(max(g), 6) as most_move from g"""
)
def projection_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    return rounded(embed.quality(p, p.withColumns({"x": F.col("x") * 2, "y": F.col("y") * 2})), "mean_move", "most_move")


@query(
    f"""with {PLACES_SQL}, q as (select *, count(*) over (partition by comp_id) as n, count(*) over () as total,
  row_number() over (partition by comp_id order by md5(sample_id::varchar), sample_id) as r from pl)
select sample_id, comp_id from q where r <= ceil(n * (100 / total::double))"""
)
def sample_by_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.sample_by_component(places(spark, sf_dir), 100).select("sample_id", "comp_id")


# ------------------------------------------------------------- fixed predictions


def predictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``sample_id, learner, t, pred, confidence, label``: three learners on the labels of
    ``embeddings``, right with shares that change over time; a third is unlabelled."""
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), F.col("label").cast("int").alias("truth"))
    rows = v.select("*", F.explode(F.array(*[F.lit(k) for k in ("a", "b", "c")])).alias("learner"))
    u = hash_unit(F.concat("learner", F.lit(":"), F.col("sample_id").cast("string")))
    t = F.floor(F.col("sample_id") / 50)
    good = F.when(F.col("learner") == "a", 0.8).when((F.col("learner") == "b") & (t > 4), 0.95).otherwise(0.4)
    other = (F.col("truth") + 1 + F.floor(u * 7)) % 10
    return rows.select(
        "sample_id", "learner", t.alias("t"), F.when(u <= good, F.col("truth")).otherwise(other).cast("int").alias("pred"),
        u.alias("confidence"), F.when(F.col("sample_id") % 3 != 0, F.col("truth")).alias("label"),
    )


PRED_SQL = f"""pr as (select sample_id, learner, t, (case when u <= good then truth else (truth + 1 + floor(u * 7)) % 10 end)::int as pred, u as confidence,
  case when sample_id % 3 <> 0 then truth end as label from (select *, case when learner = 'a' then 0.8 when learner = 'b' and t > 4 then 0.95 else 0.4 end as good from (
  select vec_id as sample_id, label::int as truth, learner, vec_id // 50 as t, {unit_sql("learner || ':' || vec_id::varchar")} as u
  from embeddings, (values ('a'), ('b'), ('c')) v(learner))))"""

BARS_SQL = """select class, bin, role, count(*)::bigint as n, round(count(*) / (select count(*) from {0} where label is not null), 6) as share from (
  select pred as class, least(9, floor(confidence * 10))::int as bin, case when pred = label then 'TP' else 'FP' end as role from {0} where label is not null
  union all select label, least(9, floor(confidence * 10))::int, 'FN' from {0} where label is not null and pred <> label) group by 1, 2, 3"""


@query(f"with {PRED_SQL} {BARS_SQL.format('pr')}")
def performance_bars(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(views.performance_bars(predictions(spark, sf_dir)), "share")


@query(
    f"""with {PRED_SQL}, pa as (select * from pr where learner = 'a'), pb as (select * from pr where learner = 'b'), x as ({BARS_SQL.format("pa")}), y as ({BARS_SQL.format("pb")})
select class, bin, role, coalesce(x.n, 0)::bigint as n_before, coalesce(y.n, 0)::bigint as n_after, (coalesce(y.n, 0) - coalesce(x.n, 0))::bigint as delta from x full join y using (class, bin, role)"""
)
def performance_compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = predictions(spark, sf_dir)
    return views.performance_compare(p.where("learner = 'a'"), p.where("learner = 'b'"))


WEIGHTS_SQL = """wt as (select t, learner, w / sum(w) over (partition by t) as weight from (
  select t, learner, power(0.5, coalesce(sum(bad) over (partition by learner order by t rows between unbounded preceding and 1 preceding), 0)) as w from (
    select t, learner, sum((label is not null and pred <> label)::int) as bad from pr group by 1, 2)))"""


@query(f"with {PRED_SQL}, {WEIGHTS_SQL} select t, learner, round(weight, 6) as weight from wt")
def weights_majority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(ensemble.majority_weights(predictions(spark, sf_dir), "t"), "weight")


VOTE_SQL = f"""{PRED_SQL}, {WEIGHTS_SQL}, s as (select sample_id, t, pred, sum(weight) as w from pr join wt using (t, learner) group by 1, 2, 3),
vo as (select *, row_number() over (partition by sample_id order by w desc, pred) as r, w / sum(w) over (partition by sample_id) as confidence from s)"""


@query(f"with {VOTE_SQL} select sample_id, t, pred, round(confidence, 6) as confidence from vo where r = 1")
def weighted_vote(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = predictions(spark, sf_dir)
    out = ensemble.vote(p.drop("confidence"), ensemble.majority_weights(p, "t"), ["sample_id", "t"], ["t", "learner"])
    return rounded(out, "confidence")


@query(f"with {PRED_SQL} select learner, t, count(*)::bigint as n, round(avg((pred = label)::int), 6) as accuracy from pr where label is not null group by 1, 2")
def accuracy_by_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(ensemble.accuracy(predictions(spark, sf_dir), ["learner", "t"]), "accuracy")


@query()
def weights_majority_dynamic(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = predictions(spark, sf_dir).where("label is not null")
    return ensemble.policy_series(p, "sample_id", ["a", "b", "c"], ensemble.WeightPolicy("majority")).drop("all_")


@query()
def weights_additive(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = predictions(spark, sf_dir).where("label is not null")
    return ensemble.policy_series(p, "sample_id", ["a", "b", "c"], ensemble.WeightPolicy("additive")).drop("all_")


@query(
    f"""with {PRED_SQL}, n1 as (select learner, sample_id, count(*) over w as n, sum((pred <> label)::int) over w / count(*) over w as p from pr where label is not null
  window w as (partition by learner order by sample_id rows unbounded preceding)),
n2 as (select *, sqrt(p * (1 - p) / n) as s from n1),
n3 as (select *, min(case when n >= 30 then {{'v': p + s, 'p': p, 's': s}} end) over (partition by learner order by sample_id rows unbounded preceding) as low from n2)
select learner, sample_id, n::bigint as n, round(p, 6) as p, case when n >= 30 and low.s > 0 and p + s >= low.p + 3 * low.s then 'drift'
  when n >= 30 and low.s > 0 and p + s >= low.p + 2 * low.s then 'warning' else 'stable' end as level from n3"""
)
def error_rate_drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = detect.error_rate(predictions(spark, sf_dir), "sample_id", key=["learner"])
    return rounded(out.select("learner", "sample_id", "n", "p", "level"), "p")


# ------------------------------------------------------------- learners and sets


def membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``learner_id, sample_id``: each learner's training rows, drawn by digest."""
    v = places(spark, sf_dir).select("sample_id", F.explode(F.array(F.lit("l1"), F.lit("l2"), F.lit("l3"))).alias("learner_id"))
    return v.where(hash_unit(F.concat("learner_id", F.col("sample_id").cast("string"))) < 0.3)


MEMBER_SQL = f"me as (select learner_id, sample_id from pl, (values ('l1'), ('l2'), ('l3')) v(learner_id) where {unit_sql('learner_id || sample_id::varchar')} < 0.3)"


@query(
    f"""with {PLACES_SQL}, {MEMBER_SQL}, g as (select learner_id, comp_id, count(*) as n from me join pl using (sample_id) group by 1, 2)
select learner_id, comp_id, n::bigint as n, round(n / sum(n) over (partition by learner_id), 6) as share from g"""
)
def learner_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(views.shares(membership(spark, sf_dir), places(spark, sf_dir), "learner_id"), "share")


@query(
    f"""with {PLACES_SQL}, se as (select case when is_new then 'new' else 'old' end as set_id, sample_id from pl), g as (select set_id, comp_id, count(*) as n from se join pl using (sample_id) group by 1, 2)
select set_id, comp_id, n::bigint as n, round(n / sum(n) over (partition by set_id), 6) as share from g"""
)
def interest_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    sets = p.select(F.when(F.col("is_new"), "new").otherwise("old").alias("set_id"), "sample_id")
    return rounded(views.shares(sets, p, "set_id"), "share")


@query(
    f"""with {PLACES_SQL}, {PRED_SQL}, {WEIGHTS_SQL}, se as (select case when is_new then 'new' else 'old' end as set_id, sample_id from pl),
g as (select set_id, learner, sum(weight) as total from pr join wt using (t, learner) join se using (sample_id) group by 1, 2)
select set_id, learner, round(total / sum(total) over (partition by set_id), 6) as importance from g"""
)
def model_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    pr, p = predictions(spark, sf_dir), places(spark, sf_dir)
    weights = pr.join(ensemble.majority_weights(pr, "t"), ["t", "learner"]).select("sample_id", "learner", "weight")
    sets = p.select(F.when(F.col("is_new"), "new").otherwise("old").alias("set_id"), "sample_id")
    return rounded(views.model_distribution(weights, sets), "importance")


@query(f"with {PLACES_SQL}, {MEMBER_SQL} select distinct sample_id from me where learner_id in ('l1', 'l3')")
def reference_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    active = spark.createDataFrame([("l1", True), ("l2", False), ("l3", True)], "learner_id string, active boolean")
    return ensemble.reference(membership(spark, sf_dir), active)


@query(
    f"""with {PLACES_SQL}, {MEMBER_SQL}, q as (select distinct sample_id from me where learner_id = 'l2')
select sample_id // 50 as t, count(*)::bigint as arrived, count(q.sample_id)::bigint as asked, round(count(q.sample_id) / count(*), 6) as share from pl left join q using (sample_id) group by 1"""
)
def labelling_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    asked = membership(spark, sf_dir).where("learner_id = 'l2'").select("sample_id").distinct()
    rows = places(spark, sf_dir).withColumn("t", F.floor(F.col("sample_id") / 50))
    return rounded(ensemble.labelling_cost(rows, asked, "t"), "share")


# --------------------------------------------------------------------- selections

POLYGON = [(-0.15, -0.1), (0.12, -0.16), (0.2, 0.05), (0.02, 0.02), (0.05, 0.2), (-0.18, 0.11)]


def _inside_sql(x: str, y: str) -> str:
    terms = []
    for (ax, ay), (bx, by) in zip(POLYGON, POLYGON[1:] + POLYGON[:1], strict=True):
        terms.append(f"((({ay} > {y}) <> ({by} > {y})) and {x} < ({bx} - ({ax})) * ({y} - ({ay})) / ({by} - ({ay})) + ({ax}))::int")
    return f"({' + '.join(terms)}) % 2 = 1"


@query(f"with {PLACES_SQL} select sample_id, comp_id from pl where {_inside_sql('x', 'y')}")
def lasso_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interact.lasso(places(spark, sf_dir), POLYGON).select("sample_id", "comp_id")


@query(
    f"""with {PLACES_SQL}, s as (select * from pl where {_inside_sql("x", "y")}), l as (select unnest(['x', 'y']) as feature, unnest([x, y]) as v from s)
select feature, count(v)::bigint as n, round(avg(v), 6) as mean, round(stddev_pop(v), 6) as sd, round(min(v), 6) as low, round(quantile_cont(v, 0.5), 6) as median, round(max(v), 6) as high from l group by 1"""
)
def selection_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = interact.summary(interact.lasso(places(spark, sf_dir), POLYGON), ["x", "y"])
    return rounded(out, "mean", "sd", "low", "median", "high")


@query(f"with {PLACES_SQL} select sample_id // 50 as t, count(*)::bigint as n from pl where {_inside_sql('x', 'y')} group by 1")
def brush_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    return interact.times_of(p.withColumn("t", F.floor(F.col("sample_id") / 50)), interact.lasso(p, POLYGON), "t")


@query(f"with {PLACES_SQL} select sample_id, comp_id from pl where sample_id // 50 between 2 and 4")
def brush_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = places(spark, sf_dir).withColumn("t", F.floor(F.col("sample_id") / 50))
    return interact.brush(rows, "t", 2, 4).select("sample_id", "comp_id")


@query(f"with {PLACES_SQL}, {MEMBER_SQL} select sample_id, comp_id from pl where sample_id in (select sample_id from me where learner_id = 'l2')")
def training_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interact.training_rows(places(spark, sf_dir), membership(spark, sf_dir), "l2").select("sample_id", "comp_id")


@query(f"with {PLACES_SQL} select p.sample_id, coalesce(d.lang, '') as lang, coalesce(length(d.text), -1)::bigint as chars from pl p left join documents d on d.doc_id = p.sample_id where {_inside_sql('x', 'y')}")
def selection_detail(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir)
    raw = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), "lang", F.char_length("text").cast("long").alias("chars"))
    return interact.detail(p, raw, interact.lasso(p, POLYGON)).select("sample_id", "lang", "chars").fillna({"lang": "", "chars": -1})


@query(f"with {DENSITY_SQL} select i, comp_id from best where r = 1 and comp_id not in (2)")
def hidden_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    hidden = spark.createDataFrame([(2,)], "comp_id int")
    return interact.shown(mixture.assign(points(spark, sf_dir), POINT, COMPONENTS), hidden).select("i", "comp_id")


# ------------------------------------------------------------ scores and baselines

def _scored(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, int, int]:
    """Reports of two runs, the large values of ``events``; nine drifts that cut its rows into ten; a window; the end."""
    e = read(spark, sf_dir, "events")
    n = e.count()
    truth = spark.range(1, 10).select(F.col("id").cast("int").alias("drift_no"), F.floor(F.col("id") * n / 10).alias("t"))
    reports = e.where("value > 240").select((F.col("event_id") % 2).cast("int").alias("run"), F.col("event_id").alias("t"))
    return reports, truth, n // 100, n


SCORE_SQL = """en as (select count(*) as n from events),
tr as (select drift_no, t, coalesce(lead(t) over (order by t), n) as until, n // 100 as w from (select k::int as drift_no, k * n // 10 as t, n from range(1, 10) v(k), en)),
rp as (select (event_id % 2)::int as run, event_id as t from events where value > 240),
sc as (select run, drift_no, min(rp.t - tr.t) as delay, count(*) - 1 as extra from rp join tr on rp.t >= tr.t and rp.t < tr.until group by 1, 2),
al as (select run, drift_no, delay, coalesce(extra, 0) as extra, case when delay is null then 'missed' when delay < w then 'detected' else 'late' end as status
  from (select distinct run from rp) a cross join (select drift_no, w from tr) b left join sc using (run, drift_no))"""


@query(f"with {SCORE_SQL} select run, drift_no, status, coalesce(delay, -1)::bigint as delay, extra::bigint as false_reports from al")
def score_drifts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect.score(*_scored(spark, sf_dir), ["run"]).fillna(-1, ["delay"])


TOTAL_SQL = f"""{SCORE_SQL}, tt as (select run, sum((status = 'detected')::int) as detected, sum((status = 'late')::int) as late, sum((status = 'missed')::int) as missed,
  sum(extra) + (select count(*) from rp r where r.run = al.run and r.t < (select min(t) from tr)) as false_reports from al group by run)"""


@query(f"with {TOTAL_SQL} select run, detected::bigint as detected, late::bigint as late, missed::bigint as missed, false_reports::bigint as false_reports from tt")
def score_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect.totals(*_scored(spark, sf_dir), ["run"])


@query(
    f"""with {TOTAL_SQL} select round((detected + late) / (detected + late + false_reports), 6) as precision, round((detected + late) / (detected + late + missed), 6) as recall,
  round(detected / (detected + late), 6) as on_time, detected::double as detected, late::double as late, missed::double as missed, false_reports::double as false_reports
from (select avg(detected) as detected, avg(late) as late, avg(missed) as missed, avg(false_reports) as false_reports from tt)"""
)
def score_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    scores = detect.totals(*_scored(spark, sf_dir), ["run"]).withColumn("method", F.lit("m"))
    out = detect.summary(detect.mean_over_runs(scores, ["method"])).drop("method")
    return rounded(out, "precision", "recall", "on_time")


def binned(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir)
    side = (F.col("day") >= F.lit("2024-01-16").cast("date")).cast("int")
    return p.select(side.alias("side"), F.floor(F.col("x") * 4).alias("cx"), F.floor((F.col("y") + 1) * 6).alias("cy"))


BINNED_SQL = f"{POINTS_SQL}, bi as (select (day >= date '2024-01-16')::int as side, floor(x * 4) as cx, floor((y + 1) * 6) as cy from pts)"


def _tvd_sql(source: str, cells: str) -> str:
    return f"""select sum(abs(p / tp - q / tq)) / 2 as tvd from (select {cells}, sum((side = 1)::int) as p, sum((side = 0)::int) as q from {source} group by {cells}),
  (select sum((side = 1)::int) as tp, sum((side = 0)::int) as tq from {source})"""


@query(f"with {BINNED_SQL} select round(tvd, 6) as tvd from ({_tvd_sql('bi', 'cx, cy')})")
def tvd_joint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(total_variation.distance(binned(spark, sf_dir), "side", ["cx", "cy"]), "tvd")


@query(f"with {BINNED_SQL} select round(avg(tvd), 6) as tvd from ({_tvd_sql('bi', 'cx')} union all {_tvd_sql('bi', 'cy')})")
def tvd_marginal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(total_variation.marginal(binned(spark, sf_dir), "side", ["cx", "cy"]), "tvd")


@query(
    f"""with {BINNED_SQL}, c as (select cx, cy, sum((side = 1)::int) as p, sum((side = 0)::int) as q from bi group by 1, 2),
s as (select (p + 0.5::double) / (sum(p) over () + 0.5::double * count(*) over ()) as p, (q + 0.5::double) / (sum(q) over () + 0.5::double * count(*) over ()) as q from c)
select round(sum(p * ln(p / q)), 6) as divergence from s"""
)
def kl_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(information.cell_entropy(binned(spark, sf_dir), "side", ["cx", "cy"]), "divergence")


@query(
    f"""with {PLACES_SQL}, k as (select a.sample_id, a.is_new, b.is_new as bn, row_number() over (partition by a.sample_id
    order by sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)), b.sample_id) as r from pl a, pl b)
select sample_id, is_new::int as side, sum((is_new <> bn)::int)::bigint as others, round(sum((is_new <> bn)::int) / greatest(10 - sum((is_new <> bn)::int), 0.5) - 1, 6) as degree
from k where r <= 10 group by 1, 2"""
)
def local_drift_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = places(spark, sf_dir).withColumn("side", F.col("is_new").cast("int"))
    return rounded(local_degree.neighbour_degrees(p, "sample_id", "side", ["x", "y"], 10), "degree")


# ------------------------------------------------------------------ planted streams


@query(f"select i, seg, round(x, 6) as x, round(y, 6) as y from {gaussian_sql('mean')}")
def gaussian_stream_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(gaussian(spark, sf_dir, "mean"), "x", "y")


@query(f"select i, seg, round(x, 6) as x, round(y, 6) as y from {gaussian_sql('sd')}")
def gaussian_stream_sd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(gaussian(spark, sf_dir, "sd"), "x", "y")
