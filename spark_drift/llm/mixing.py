"""Mixing sources to target weights by entropy balancing, with DataFrame operations only.

Documents get rates that meet token constraints while staying as near to 1 as these
allow (least relative entropy over tokens, no rate above ``cap``). The convex dual has one
variable per constrained group; with ``eta`` the sum of the variables of a document's
groups, its rate is ``min(cap, exp(eta))``: the cap is part of the dual, which goes on
linearly beyond it. The gradient in a group is the tilted token mass less the target, the
curvature between two groups the tilted mass that they share below the cap. Newton
steps, never longer than 1 and cut back until the dual falls, run until the largest
relative miss of a target is below ``tol``. Documents enter through sums by
cell (a combination of groups) only, so rounds never scan them. With one margin, as for sources,
the Hessian is diagonal and the rounds stay in the rows of the groups; with several, the
sums of all pairs of groups, of a checked number, give the linear system of a step.

Rounding. Rates become whole copies cell by cell, a cell being the documents of one
source and one size, ordered by falling size: the cumulated count times the rate is
rounded and differenced, which keeps the token error below about one document. Four
correction rounds then add or take single copies of the largest sizes that still
fit the remaining error. Inside a cell the first documents by a digest of id and text
get the extra copy. Ranks come from counts by digest prefixes plus ranks within
a prefix; there are as many prefixes as keep a prefix's rows of one cell few, so a cell that
holds a third of all rows, or an id that many rows share, is never sorted in one task.

Edge cases: null text has size 0 and is never worth tokens; a null source is a
source of its own, last in order; a source without words has target 0; repeated
rows are separate documents; an empty table gives an empty result; targets that no rates meet end at
the nearest capped ones; other columns are ignored or, in
``mixed_documents``, repeated with their rows.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spark_drift.plans.lineage import cut

WORD = "[^\\x20\\x09-\\x0D]+"
CAP = 3
CORRECTIONS = 4


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def sized(docs: DataFrame, carry: bool = False) -> DataFrame:
    """``doc_id, source, size, digest`` and, with ``carry``, the whole ``row``."""
    name = F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary")))
    digest = F.conv(F.substring(F.md5(name.cast("binary")), 1, 15), 16, 10)
    columns = [
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").cast("string").alias("source"),
        words_in(F.col("text")).alias("size"),
        digest.cast("long").alias("digest"),
    ]
    if carry:
        columns.append(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return docs.select(*columns)


def source_targets(cells: DataFrame, cap: int = CAP, weights: int = 3) -> DataFrame:
    """``source, source_size, target``: weights 1, 2, ... repeat over the sources in
    code-point order, null last; targets share all sizes, none above ``cap`` times
    its source. One row per source enters the two ordered windows."""
    by = cells.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))
    by = by.withColumn("weight", (place - 1) % weights + 1)
    limit = F.col("source_size") * cap
    by = by.withColumn("ratio", limit / F.col("weight"))
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    after = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.orderBy("ratio", F.col("source").asc_nulls_last()).rowsBetween(
        Window.unboundedPreceding, Window.unboundedFollowing
    )
    # the level at which a source would be filled if all with smaller ratios were full
    level = (F.sum("source_size").over(everything) - F.coalesce(F.sum(limit).over(before), F.lit(0))) / F.sum(
        "weight"
    ).over(after)
    by = by.withColumn("level", level).withColumn("open", F.col("ratio") >= F.col("level"))
    settled = F.min(F.when(F.col("open"), F.struct("ratio", "source", "level"))).over(everything)["level"]
    target = F.least(limit.cast("double"), settled * F.col("weight"))
    return by.select("source", "source_size", F.coalesce(target, F.lit(0.0)).alias("target"))


# ------------------------------------------------------------- entropy balancing

#: Newton rounds of one margin per job, between two measurements
INNER = 8


def balance(
    docs: DataFrame, size: str, margins: dict[str, DataFrame], cap: float = CAP, tol: float = 1e-12, rounds: int = 100, most: int = 512
) -> DataFrame:
    """Rates that meet token constraints: one row per cell with its ``tokens, rate, gap``.

    ``margins``: column -> ``(column, target)``; groups without a target are free. A cell is a
    combination of the margin columns. ``gap``: the largest relative miss of a target
    at the end, above ``tol`` only if the targets cannot be met. With several margins at
    most ``most`` groups are allowed in all.
    """
    names = list(margins)
    cells = cut(docs.groupBy(*names).agg(F.sum(size).cast("double").alias("tokens")))
    if len(names) == 1:
        name = names[0]
        want = margins[name].select(F.col(name).alias("key"), F.col("target").cast("double").alias("want"))
        groups = cells.join(want, F.col(name).eqNullSafe(F.col("key")), "left").drop("key")
        return balance_groups(groups, float(cap), tol, rounds).drop("want")
    return _several(cells, names, margins, float(cap), tol, rounds, most)


def _tilt(eta: Column, cap: float) -> Column:
    return F.least(F.lit(cap), F.exp(eta))


def _missed(target: Column, mass: Column) -> Column:
    return F.abs(target - mass) / F.greatest(target, F.lit(1.0))


def balance_groups(groups: DataFrame, cap: float = CAP, tol: float = 1e-12, rounds: int = 100) -> DataFrame:
    """``groups`` (one row each, with ``tokens`` and the tokens that it should have, ``want``) plus ``rate, gap``.

    With one margin the dual separates: each group's variable iterates in the group's own row, in the
    partitions that ``groups`` has."""
    names = groups.columns
    reachable = F.least(F.coalesce("want", "tokens"), F.col("tokens") * cap)
    state = cut(groups.select(*names, reachable.alias("goal_"), F.lit(0.0).alias("eta_")))

    def step(eta: Column) -> Column:
        mass = F.col("tokens") * _tilt(eta, cap)
        curve = F.when(eta < math.log(cap), mass)
        newton = F.coalesce(F.try_divide(F.col("goal_") - mass, curve), F.signum(F.col("goal_") - mass))
        return eta + F.greatest(F.lit(-1.0), F.least(F.lit(1.0), newton))

    settled = F.col("goal_") <= 0  # no tokens wanted: the rate's limit is 0
    mass = F.when(settled, 0.0).otherwise(F.col("tokens") * _tilt(F.col("eta_"), cap))
    for _ in range(-(-rounds // INNER)):
        if (state.agg(F.max(_missed(F.col("goal_"), mass))).first()[0] or 0.0) <= tol:
            break
        eta = F.aggregate(F.sequence(F.lit(1), F.lit(INNER)), F.col("eta_"), lambda acc, _: step(acc))
        state = cut(state.withColumn("eta_", F.when(settled, F.col("eta_")).otherwise(eta)))
    rate = F.when(settled, 0.0).otherwise(_tilt(F.col("eta_"), cap))
    gap = state.agg(F.coalesce(F.max(_missed(F.coalesce("want", "tokens"), mass)), F.lit(0.0))).first()[0]
    return state.select(*names, rate.alias("rate"), F.lit(float(gap)).alias("gap"))


def _several(cells: DataFrame, names: list[str], margins: dict[str, DataFrame], cap: float, tol: float, rounds: int, most: int) -> DataFrame:
    """Newton steps over all groups of all margins together."""
    spark = cells.sparkSession
    found = {m: margins[m].select(m, F.col("target").cast("double").alias("target")).limit(most + 1).collect() for m in names}
    groups = [(m, r[0]) for m in names for r in found[m]]
    if len(groups) > most:
        raise ValueError(f"{len(groups)} constrained groups; several margins allow {most}")
    place = {g: k for k, g in enumerate(groups)}
    want = np.array([r[1] for m in names for r in found[m]])

    def tilted(eta: np.ndarray) -> DataFrame:
        out = cells.withColumn("eta", F.lit(0.0))
        for m in names:
            rows = [(key, float(eta[k])) for (own, key), k in place.items() if own == m]
            table = spark.createDataFrame(rows, f"key {cells.schema[m].dataType.simpleString()}, add double")
            out = out.join(F.broadcast(table), F.col(m).eqNullSafe(F.col("key")), "left")
            out = out.withColumn("eta", F.col("eta") + F.coalesce("add", F.lit(0.0))).drop("key", "add")
        return out

    def measured(eta: np.ndarray):
        """Masses, curvature and the dual's value: one aggregate per pair of margins."""
        top = math.log(cap)
        rows = tilted(eta)
        mass = F.col("tokens") * _tilt(F.col("eta"), cap)
        curve = F.when(F.col("eta") < top, mass).otherwise(0.0)
        value = F.when(F.col("eta") <= top, mass).otherwise(F.col("tokens") * cap * (1 + F.col("eta") - top))
        masses, hessian, total = np.zeros(len(groups)), np.zeros((len(groups), len(groups))), 0.0
        for i, a in enumerate(names):
            for b in names[i + 1 :]:
                pairs = rows.groupBy(a, b).agg(F.sum(mass).alias("m"), F.sum(curve).alias("w"), F.sum(value).alias("v")).collect()
                for r in pairs:
                    g, h = place.get((a, r[0])), place.get((b, r[1]))
                    if g is not None and h is not None:
                        hessian[g, h] += r["w"]
                        hessian[h, g] += r["w"]
                    first = (i, b) == (0, names[1])
                    total += r["v"] if first else 0.0
                    # each margin's own sums are taken from one pair it is in
                    if g is not None and b == names[-1]:
                        masses[g] += r["m"]
                        hessian[g, g] += r["w"]
                    if h is not None and i == 0 and b == names[-1]:
                        masses[h] += r["m"]
                        hessian[h, h] += r["w"]
        return masses, hessian, total - float(eta @ want)

    eta = np.zeros(len(groups))
    masses, hessian, value = measured(eta)
    missed = lambda m: float((np.abs(want - m) / np.maximum(want, 1.0)).max(initial=0.0))
    for _ in range(rounds):
        if missed(masses) <= tol:
            break
        # margins share their total, so the system is singular; the least solution serves
        way = np.linalg.lstsq(hessian, want - masses, rcond=1e-12)[0]
        way /= max(1.0, float(np.abs(way).max()))
        slope, share = float((masses - want) @ way), 1.0
        while share > 1e-6:
            trial = measured(eta + share * way)
            if trial[2] <= value + 1e-4 * share * slope + 1e-12 * abs(value):
                break
            share /= 2
        else:
            break
        eta = eta + share * way
        if trial[2] >= value and missed(trial[0]) >= missed(masses):
            masses, hessian, value = trial
            break
        masses, hessian, value = trial
    return tilted(eta).select(*names, "tokens", _tilt(F.col("eta"), cap).alias("rate"), F.lit(missed(masses)).alias("gap"))


def cell_copies(cells: DataFrame, targets: DataFrame, cap: int = CAP) -> DataFrame:
    """``source, size, n, copies`` (copies of a cell altogether), source size and target."""
    named = targets.select(F.col("source").alias("of"), "source_size", "target", F.col("source_size").cast("double").alias("tokens"), F.col("target").alias("want"))
    rates = balance_groups(named, float(cap)).select("of", "source_size", "target", F.round("rate", 12).alias("rate"))
    c = cells.join(rates, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    falling = Window.partitionBy("source").orderBy(F.col("size").desc())
    upto = F.sum("n").over(falling.rowsBetween(Window.unboundedPreceding, 0))
    whole = lambda n: F.floor(n * F.col("rate") + 0.5)
    c = c.withColumn("upto", upto).withColumn("copies", whole(F.col("upto")) - whole(F.col("upto") - F.col("n")))
    # all rows of a source, in the order used throughout, so that one sort serves
    source = falling.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    earlier = falling.rowsBetween(Window.unboundedPreceding, -1)
    for _ in range(CORRECTIONS):
        c = c.withColumn("gap", F.round("target").cast("long") - F.sum(F.col("copies") * F.col("size")).over(source))
        room = F.when(F.col("gap") > 0, F.col("n") * cap - F.col("copies")).otherwise(F.col("copies"))
        fits = (F.col("size") > 0) & (F.col("size") <= F.abs("gap"))
        c = c.withColumn("room", F.when(fits, room).otherwise(F.lit(0)))
        used = F.coalesce(F.sum(F.col("room") * F.col("size")).over(earlier), F.lit(0))
        left = F.floor(F.try_divide(F.abs("gap") - used, F.col("size")))
        take = F.greatest(F.lit(0), F.least(F.col("room"), F.coalesce(left, F.lit(0))))
        c = c.withColumn("take", take).withColumn("copies", F.col("copies") + F.signum("gap").cast("long") * F.col("take"))
    return c.select("source", "size", "n", "copies", "source_size", "target")


#: rows of one cell that a digest prefix holds, about, at most
PREFIX_ROWS = 50_000


def mix(sizes: DataFrame, light: DataFrame | None = None, cap: int = CAP) -> DataFrame:
    """``sizes`` (from ``sized``) with ``source_size, target, copies, taken``.

    ``light``: the same rows without the carried ones, where those are costly.
    """
    light = light if light is not None else sizes
    bits = min(40, max(8, (light.count() // PREFIX_ROWS).bit_length()))
    # a null source has a name of its own, so that joins and windows share one partitioning
    keyed = lambda df: df.withColumns({
        "cell_": F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n")), "salt": F.shiftright("digest", 60 - bits)
    })
    keys = ["cell_", "size", "salt"]
    counts = cut(keyed(light).groupBy(*keys, "source").agg(F.count(F.lit(1)).alias("m")))
    cells = cut(counts.groupBy("source", "size").agg(F.sum("m").alias("n")))
    planned = cell_copies(cells, source_targets(cells, cap), cap)
    planned = cut(planned.withColumn("cell_", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))).drop("source"))
    order = Window.partitionBy("cell_", "size").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.withColumn("start", F.coalesce(F.sum("m").over(order), F.lit(0))).join(planned, ["cell_", "size"])
    starts = starts.select(*keys, "start", "n", "copies", "source_size", "target")
    ranked = keyed(sizes).join(starts, keys)
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy("digest", "doc_id")) + F.col("start")
    each = F.floor(F.col("copies") / F.col("n")) + F.when(rank <= F.col("copies") % F.col("n"), 1).otherwise(0)
    out = ranked.withColumn("each", each.cast("long"))
    keep = [c for c in sizes.columns if c != "digest"]
    return out.select(
        *keep, "source_size", "target", F.col("each").alias("copies"), (F.col("each") * F.col("size")).alias("taken")
    )


def mixed_documents(docs: DataFrame, cap: int = CAP) -> DataFrame:
    """``docs`` with each row repeated by its copies, none included; columns stay."""
    done = mix(sized(docs, carry=True), sized(docs), cap)
    return done.select(F.explode(F.array_repeat("row", F.col("copies").cast("int"))).alias("row")).select("row.*")


def oracle(table: str = "documents", cap: int = CAP) -> str:
    """The same mix in SQL for an independent engine."""
    steps = []
    for k in range(CORRECTIONS):
        steps.append(
            f"""g{k} as (select *, cast(round(target) as bigint) - sum(copies * size) over (partition by source) as gap from c{k}),
r{k} as (select *, case when size > 0 and size <= abs(gap) then case when gap > 0 then n * {cap} - copies else copies end else 0 end as room from g{k}),
u{k} as (select *, coalesce(sum(room * size) over (partition by source order by size desc rows between unbounded preceding and 1 preceding), 0) as used from r{k}),
c{k + 1} as (select source, size, n, source_size, target, copies + sign(gap) * greatest(0, least(room,
  case when size > 0 then cast(floor((abs(gap) - used) / size) as bigint) else 0 end)) as copies from u{k})"""
        )
    return f"""
with d as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::bigint as size,
  ('0x' || substr(md5(coalesce(doc_id::varchar, '') || ':' || md5(coalesce(text, ''))), 1, 15))::bigint as digest from {table}),
cells as (select source, size, count(*)::bigint as n from d group by all),
s1 as (select source, sum(size * n)::bigint as source_size from cells group by source),
s2 as (select *, (row_number() over (order by source nulls last) - 1) % 3 + 1 as weight from s1),
s3 as (select *, {cap} * source_size as lim, ({cap} * source_size)::double / weight as ratio from s2),
s4 as (select *, ((select sum(source_size) from s1) - coalesce(sum(lim) over (order by ratio, source nulls last rows between unbounded preceding and 1 preceding), 0))::double
  / sum(weight) over (order by ratio, source nulls last rows between current row and unbounded following) as level from s3),
s5 as (select *, (select arg_min(level, ratio) from s4 where ratio >= level) as settled from s4),
t as (select source, source_size, least(lim::double, settled * weight) as target from s5),
rated as (select *, case when source_size > 0 and target > 0 then least({cap}.0, round(target / source_size, 12)) else 0.0 end::double as rate from t),
b as (select c.*, source_size, target, rate, sum(n) over (partition by c.source order by size desc rows unbounded preceding)::bigint as upto
  from cells c join rated r on c.source is not distinct from r.source),
c0 as (select source, size, n, source_size, target,
  cast(floor(upto * rate + 0.5) as bigint) - cast(floor((upto - n) * rate + 0.5) as bigint) as copies from b),
{", ".join(steps)},
k as (select d.*, c.n, c.copies, c.source_size, c.target,
  row_number() over (partition by d.source, d.size order by digest, doc_id) as rk
  from d join c{CORRECTIONS} c on d.source is not distinct from c.source and d.size = c.size),
e as (select *, (copies // n + case when rk <= copies % n then 1 else 0 end)::bigint as each from k)
select doc_id, size, source_size, target, each as copies, (each * size)::bigint as taken from e
"""
