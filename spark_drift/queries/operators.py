"""Relational building blocks on the given tables: scans, joins, aggregates, windows, sets,
scalar functions, the SQL surface, and batch twins of the streaming windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spark_drift.operators import views
from spark_drift.queries.base import DAYS_SQL, days, query, rounded
from spark_drift.queries.displays import BOX, CELLS, _halo_sql, places
from spark_drift.sources.tables import read, standardise
from spark_drift.streaming import monitors

# ---------------------------------------------------------------------- sources


@query("select l_linenumber::bigint as line, count(*)::bigint as n, round(avg(l_quantity), 6) as quantity, round(avg(l_discount), 6) as discount from lineitem where l_shipdate >= timestamp '1997-01-01' group by 1")
def io_scan_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns and a pushed filter of a wide table."""
    li = read(spark, sf_dir, "lineitem").where(F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz"))
    out = li.groupBy(F.col("l_linenumber").cast("long").alias("line")).agg(
        F.count(F.lit(1)).alias("n"), F.avg("l_quantity").alias("quantity"), F.avg("l_discount").alias("discount")
    )
    return rounded(out, "quantity", "discount")


@query("select (props->>'k')::bigint as k, count(*)::bigint as n, round(avg(value), 6) as mean from events group by 1")
def io_json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events").select(F.from_json("props", "k long").alias("p"), "value")
    return rounded(e.groupBy(F.col("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean")), "mean")


# -------------------------------------------------------------- projection, filter


@query("select event_id, round((value - avg(value) over ()) / stddev_pop(value) over (), 6) as z from events")
def op_standardise(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events").select("event_id", F.col("value").alias("z"))
    return rounded(standardise(e, ["z"]), "z")


@query("select event_id, event_type from events where ts >= timestamp '2024-01-10' and ts < timestamp '2024-01-12'")
def op_timeslice(spark: SparkSession, sf_dir: str) -> DataFrame:
    low, high = (F.lit(d).cast("timestamp_ntz") for d in ("2024-01-10", "2024-01-12"))
    return read(spark, sf_dir, "events").where((F.col("ts") >= low) & (F.col("ts") < high)).select("event_id", "event_type")


# ----------------------------------------------------------------------- joins


@query("select c_mktsegment as segment, count(*)::bigint as n, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey group by 1")
def op_join_equi(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = read(spark, sf_dir, "orders"), read(spark, sf_dir, "customer")
    out = o.join(c, o.o_custkey == c.c_custkey).groupBy(F.col("c_mktsegment").alias("segment"))
    return rounded(out.agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("total")), "total", digits=2)


@query("select r_name, count(*)::bigint as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")
def op_join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed tables of at most 25 rows on the small sides."""
    c, n, r = (read(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    small = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return c.join(F.broadcast(small), c.c_nationkey == small.n_nationkey).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("select doc_id, lang from documents where doc_id in (select doc_id from labels)")
def op_join_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id", "left_semi").select("doc_id", "lang")


@query("select doc_id, lang from documents where doc_id not in (select doc_id from labels)")
def op_join_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


@query("select lang, count(*)::bigint as n, count(quality)::bigint as labelled, round(avg(quality), 6) as good from documents left join labels using (doc_id) group by 1")
def op_join_left(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id", "left")
    return rounded(both.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count("quality").alias("labelled"), F.avg("quality").alias("good")), "good")


@query(
    """with a as (select l_shipdate::date as day, count(*) as items from lineitem group by 1), b as (select o_orderdate::date as day, count(*) as orders from orders group by 1)
select coalesce(a.day, b.day) as day, coalesce(items, 0)::bigint as items, coalesce(orders, 0)::bigint as orders from a full join b on a.day = b.day"""
)
def op_join_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = read(spark, sf_dir, "lineitem").groupBy(F.to_date("l_shipdate").alias("day")).agg(F.count(F.lit(1)).alias("items"))
    b = read(spark, sf_dir, "orders").groupBy(F.to_date("o_orderdate").alias("day")).agg(F.count(F.lit(1)).alias("orders"))
    return a.join(b, "day", "full").fillna(0, ["items", "orders"])


@query(
    """select e.event_id, p.low from events e join (select k * 20.0::double as low, (k + 1) * 20.0::double as high from range(0, 30) r(k)) p on e.value >= p.low and e.value < p.high"""
)
def op_join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A range join as an equi-join on the bucket that the range falls in."""
    bands = spark.range(30).select((F.col("id") * 20.0).alias("low"), ((F.col("id") + 1) * 20.0).alias("high"), F.col("id").alias("bucket"))
    e = read(spark, sf_dir, "events").withColumn("bucket", F.floor(F.col("value") / 20))
    return e.join(F.broadcast(bands), "bucket").where((F.col("value") >= F.col("low")) & (F.col("value") < F.col("high"))).select("event_id", "low")


@query(
    """with v as (select ts as since, event_id as version from events where event_type = 'purchase'), q as (select event_id, user_id, ts from events where event_type = 'view' or event_type = 'click')
select q.event_id, coalesce(max(v.version), -1)::bigint as version from q left join (select e.user_id, e.ts as since, e.event_id as version from events e where event_type = 'purchase') v on v.user_id = q.user_id and v.since <= q.ts group by 1"""
)
def op_join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Latest purchase of the user not after each view or click: a union, ordered, the
    last version carried forward; events are numbered in time order."""
    e = read(spark, sf_dir, "events").where(F.col("event_type").isin("purchase", "view", "click"))
    v = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    upto = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id")
    upto = upto.rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("version", F.max(v).over(upto)).where("event_type <> 'purchase'").select("event_id", F.coalesce("version", F.lit(-1)).alias("version"))


@query("select a.event_id, b.event_id as follows from events a join events b on a.event_id = b.event_id + 1")
def op_join_self(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events").select("event_id")
    return e.join(e.select((F.col("event_id") + 1).alias("event_id"), F.col("event_id").alias("follows")), "event_id")


# ------------------------------------------------------------------- aggregates


@query("select coalesce(event_type, 'all') as event_type, coalesce(day, -1)::int as day, count(*)::bigint as n, round(sum(value), 4) as total from (select event_type, day(ts) as day, value from events) group by cube (event_type, day)")
def op_agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events").select("event_type", F.dayofmonth("ts").alias("day"), "value")
    out = e.cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return rounded(out.fillna("all", ["event_type"]).fillna(-1, ["day"]), "total", digits=4)


@query("select coalesce(l_returnflag, 'all') as flag, coalesce(l_linestatus, 'all') as status, count(*)::bigint as n from lineitem group by rollup (l_returnflag, l_linestatus)")
def op_agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status"))
    return li.rollup("flag", "status").agg(F.count(F.lit(1)).alias("n")).fillna("all", ["flag", "status"])


@query("select coalesce(lang, 'all') as lang, coalesce(source, 'all') as source, count(*)::bigint as n from documents group by grouping sets ((lang), (source), ())")
def op_agg_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    read(spark, sf_dir, "documents").select("lang", "source").createOrReplaceTempView("sd_documents")
    return spark.sql("select lang, source, count(*) as n from sd_documents group by grouping sets ((lang), (source), ())").fillna("all", ["lang", "source"])


@query("select event_type, count(distinct user_id)::bigint as users, count(*)::bigint as n from events group by 1")
def op_agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count(F.lit(1)).alias("n"))


@query("select event_type, abs(count(distinct user_id) - count(distinct user_id)) < 1 as near from events group by 1")
def op_agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketched distinct counts lie within a tenth of the exact ones."""
    by = read(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("e"))
    return by.select("event_type", (F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("near"))


@query("select l_returnflag as flag, round(covar_pop(l_quantity, l_extendedprice), 3) as cov, round(var_pop(l_quantity), 6) as var, round(corr(l_quantity, l_extendedprice), 6) as corr from lineitem group by 1")
def op_cov(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("flag"))
    out = li.agg(F.covar_pop("l_quantity", "l_extendedprice").alias("cov"), F.var_pop("l_quantity").alias("var"), F.corr("l_quantity", "l_extendedprice").alias("corr"))
    return rounded(rounded(out, "var", "corr"), "cov", digits=3)


@query("select event_type, round(quantile_cont(value, 0.5), 6) as median, round(quantile_cont(value, 0.9), 6) as p90 from events group by 1")
def op_agg_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = read(spark, sf_dir, "events").groupBy("event_type").agg(F.percentile("value", 0.5).alias("median"), F.percentile("value", 0.9).alias("p90"))
    return rounded(by, "median", "p90")


@query("select lang, sum((quality = 0)::int)::bigint as q0, sum((quality = 1)::int)::bigint as q1 from documents join labels using (doc_id) group by 1")
def op_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id")
    return both.groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1))).select("lang", F.col("0").alias("q0"), F.col("1").alias("q1")).fillna(0)


@query("select l_returnflag as flag, name, round(avg(v), 6) as mean from (select l_returnflag, unnest(['quantity', 'discount', 'tax']) as name, unnest([l_quantity, l_discount, l_tax]) as v from lineitem) group by 1, 2")
def op_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read(spark, sf_dir, "lineitem").select(
        F.col("l_returnflag").alias("flag"), F.col("l_quantity").alias("quantity"), F.col("l_discount").alias("discount"), F.col("l_tax").alias("tax")
    )
    return rounded(li.unpivot("flag", ["quantity", "discount", "tax"], "name", "v").groupBy("flag", "name").agg(F.avg("v").alias("mean")), "mean")


# --------------------------------------------------------------------- windows


@query(
    """select event_id, rank() over w as r, dense_rank() over w as d, ntile(4) over (partition by event_type order by value, event_id) as q, lag(event_id, 1, -1) over (partition by event_type order by event_id)::bigint as before
from events window w as (partition by event_type order by user_id)"""
)
def op_win_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = Window.partitionBy("event_type")
    return read(spark, sf_dir, "events").select(
        "event_id", F.rank().over(by.orderBy("user_id")).cast("long").alias("r"), F.dense_rank().over(by.orderBy("user_id")).cast("long").alias("d"),
        F.ntile(4).over(by.orderBy("value", "event_id")).cast("long").alias("q"), F.lag("event_id", 1, -1).over(by.orderBy("event_id")).alias("before"),
    )


@query("select event_id, round(sum(value) over (partition by user_id order by event_id), 6) as running, round(avg(value) over (partition by user_id order by event_id rows between 4 preceding and current row), 6) as recent from events")
def op_win_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = Window.partitionBy("user_id").orderBy("event_id")
    out = read(spark, sf_dir, "events").select(
        "event_id", F.sum("value").over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.avg("value").over(by.rowsBetween(-4, 0)).alias("recent")
    )
    return rounded(out, "running", "recent")


@query("select event_id, count(*) over (partition by user_id order by epoch(ts)::bigint range between 86400 preceding and current row)::bigint as last_day from events")
def op_win_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events").withColumn("s", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1000000 + 0.5).cast("long"))
    by = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)
    return e.select("event_id", F.count(F.lit(1)).over(by).alias("last_day"))


@query("select event_id, first_value(event_id) over w as opened, last_value(event_id) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as closed from events window w as (partition by user_id order by event_id)")
def op_win_first_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(spark, sf_dir, "events").select("event_id", F.first("event_id").over(by).alias("opened"), F.last("event_id").over(by).alias("closed"))


@query("select o_orderkey, round(o_totalprice, 2) as price from orders order by o_totalprice desc, o_orderkey limit 25")
def op_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(read(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", F.col("o_totalprice").alias("price")), "price", digits=2)


# ------------------------------------------------------------------- set operators


def _sides(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    e = read(spark, sf_dir, "events")
    return e.where("event_type = 'click'").select("user_id"), e.where("value > 120").select("user_id")


_SIDES = "a as (select user_id from events where event_type = 'click'), b as (select user_id from events where value > 120)"


@query(f"with {_SIDES} select user_id, count(*)::bigint as n from (select * from a union all select * from b) group by 1")
def op_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    return a.unionByName(b).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query(f"with {_SIDES} select * from a intersect select * from b")
def op_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    return a.intersect(b)


@query(f"with {_SIDES} select * from a except all select * from b")
def op_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    return a.exceptAll(b)


@query("select event_id from events where ('0x' || substr(md5(event_id::varchar), 1, 8))::bigint < 0.3 * 4294967296")
def op_sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A 30 % split by id digest, the same in every run."""
    digest = F.conv(F.substring(F.md5(F.col("event_id").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    return read(spark, sf_dir, "events").where(digest < F.lit(0.3 * 4294967296)).select("event_id")


# --------------------------------------------------------------- scalar functions


@query("select event_id, round(ln(1 + value), 6) as l, round(exp(-value / 50), 6) as e, round(sqrt(value), 6) as s, floor(value / 7)::bigint as f, (event_id % 13)::bigint as m from events")
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    out = read(spark, sf_dir, "events").select(
        "event_id", F.log(1 + v).alias("l"), F.exp(-v / 50).alias("e"), F.sqrt(v).alias("s"), F.floor(v / 7).alias("f"), F.pmod("event_id", F.lit(13)).alias("m")
    )
    return rounded(out, "l", "e", "s")


@query("select doc_id, length(text)::bigint as chars, upper(lang) || '-' || source as tag, len(string_split(text, chr(10)))::bigint as lines, substr(text, 1, 20) as head from documents")
def fn_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select(
        "doc_id", F.char_length("text").cast("long").alias("chars"), F.concat_ws("-", F.upper("lang"), "source").alias("tag"),
        F.size(F.split("text", "\n")).cast("long").alias("lines"), F.substring("text", 1, 20).alias("head"),
    )


@query("select o_orderkey, year(o_orderdate)::bigint as y, dayofyear(o_orderdate)::bigint as d, date_trunc('month', o_orderdate)::date as month, datediff('day', date '1995-01-01', o_orderdate::date)::bigint as age from orders")
def fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return read(spark, sf_dir, "orders").select(
        "o_orderkey", F.year(d).cast("long").alias("y"), F.dayofyear(d).cast("long").alias("d"), F.to_date(F.date_trunc("month", d.cast("timestamp"))).alias("month"),
        F.datediff(F.to_date(d), F.lit("1995-01-01").cast("date")).cast("long").alias("age"),
    )


@query("select vec_id, round(list_sum(list_transform(embedding, lambda v: v::double * v::double)), 4) as norm, round(list_max(embedding)::double, 6) as top, len(list_filter(embedding, lambda v: v > 0))::bigint as positive from embeddings")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.transform("embedding", lambda x: x.cast("double"))
    out = read(spark, sf_dir, "embeddings").select(
        "vec_id", F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x).alias("norm"), F.array_max(v).alias("top"),
        F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"),
    )
    return rounded(rounded(out, "norm", digits=4), "top")


@query("select lang, count(distinct source)::bigint as sources, max(n)::bigint as most from (select lang, source, count(*) as n from documents group by 1, 2) group by 1")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = read(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return maps.select("lang", F.size("m").cast("long").alias("sources"), F.array_max(F.map_values("m")).alias("most"))


@query("select event_id, (props->>'k')::bigint * 2 as twice, json_object('id', event_id, 'type', event_type)::varchar as payload from events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events")
    payload = F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("type")))
    return e.select("event_id", (F.get_json_object("props", "$.k").cast("long") * 2).alias("twice"), payload.alias("payload"))


# -------------------------------------------------------------------- SQL surface


@query(f"with {DAYS_SQL} select month, count(*)::bigint as n, round(avg(x1), 6) as x1 from days group by 1")
def sql_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    days(spark, sf_dir).createOrReplaceTempView("sd_days")
    return rounded(spark.sql("select month, count(*) as n, avg(x1) as x1 from sd_days group by month"), "x1")


@query(
    """with r as (select event_type, value as x from events where event_id % 2 = 0), c as (select event_type, value as x from events where event_id % 2 = 1),
b as (select event_type, avg(abs(r.x - c.x)) as b from r join c using (event_type) group by 1), w as (select r.event_type, avg(abs(r.x - s.x)) as w from r join r s using (event_type) group by 1),
v as (select c.event_type, avg(abs(c.x - s.x)) as v from c join c s using (event_type) group by 1)
select event_type, round(greatest(0, 1 - (w + v) / (2 * b)), 6) as distance from b join w using (event_type) join v using (event_type)"""
)
def sql_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grouped aggregate called from SQL text (groups must fit a task)."""
    from spark_drift.functions import sqlfuncs

    sqlfuncs.register(spark)
    read(spark, sf_dir, "events").createOrReplaceTempView("sd_events")
    return rounded(spark.sql("select event_type, energy_distance(value, event_id % 2) as distance from sd_events group by event_type"), "distance")


@query(_halo_sql("0.7", "0.3 / 24").replace("as density from g, o", "as value from g, o"))
def sql_halo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table function called with LATERAL."""
    from spark_drift.functions import sqlfuncs

    sqlfuncs.register(spark)
    views.grid(places(spark, sf_dir), "x", "y", BOX, CELLS).createOrReplaceTempView("sd_cells")
    text = "select h.row, h.col, sum(h.value) as value from sd_cells as g, lateral halo(g.row, g.col, g.density) as h group by h.row, h.col"
    return rounded(spark.sql(text), "value")


@query("select event_id, round(-0.5 * ((value / 50 - 0.5) ** 2 / 0.25 + ln(0.25::double) + ln(2 * pi())), 6) as logpdf from events")
def sql_logpdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spark_drift.functions import sqlfuncs

    sqlfuncs.register(spark)
    read(spark, sf_dir, "events").createOrReplaceTempView("sd_events")
    text = "select event_id, gauss_logpdf(array(value / 50), array(0.5D), array(0.25D)) as logpdf from sd_events"
    return rounded(spark.sql(text), "logpdf")


# --------------------------------------------------------- twins of stream windows


def _stream_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _epoch(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.unix_timestamp(c) for c in columns})


@query("select epoch(date_trunc('day', ts))::bigint as start, event_type, count(*)::bigint as n, round(avg(value), 6) as mean from events group by 1, 2")
def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_epoch(monitors.tumbling(_stream_rows(spark, sf_dir), "1 day"), "start"), "mean")


@query(
    """select s as start, count(*)::bigint as n, round(avg(value), 6) as mean from (select value, unnest([floor(epoch(ts) / 21600)::bigint * 21600, floor(epoch(ts) / 21600)::bigint * 21600 - 21600,
  floor(epoch(ts) / 21600)::bigint * 21600 - 43200, floor(epoch(ts) / 21600)::bigint * 21600 - 64800]) as s from events) group by 1"""
)
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_epoch(monitors.sliding(_stream_rows(spark, sf_dir), "1 day", "6 hours"), "start"), "mean")


@query(
    """with g as (select user_id, ts, case when lag(ts) over (partition by user_id order by ts) > ts - interval 6 hours then 0 else 1 end as opens from events),
s as (select *, sum(opens) over (partition by user_id order by ts, opens desc rows unbounded preceding) as no from g)
select user_id, count(*)::bigint as n, round(epoch(max(ts)) - epoch(min(ts)), 2) as seconds from s group by user_id, no"""
)
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = monitors.sessions(_stream_rows(spark, sf_dir), "6 hours")
    seconds = (F.unix_micros("stop") - F.unix_micros("start")) / 1000000.0 - 21600.0
    return rounded(out.select("user_id", "n", seconds.alias("seconds")), "seconds", digits=2)


