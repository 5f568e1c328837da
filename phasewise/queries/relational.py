"""Queries of the operators around the method, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.shared import stored
from ..sources.tables import events_points, table
from .core import EV, FIXED, fixed_medians

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def cents():
    return F.round(F.col("value") * 100).cast("long")


@query("scan_parquet", "select event_type, count(*) as points from events where value > 50 group by 1")
def scan_parquet(spark, sf):
    return table(spark, sf, "events").where("value > 50").groupBy("event_type").agg(F.count("*").alias("points"))


@query("filter_project", "select event_id, cast(round(value * 100) as bigint) as cents, event_type = 'error' as is_error from events where value is not null and not isnan(value) and event_type <> 'view'")
def filter_project(spark, sf):
    return table(spark, sf, "events").where(F.col("value").isNotNull() & ~F.isnan("value") & (F.col("event_type") != "view")).select("event_id", cents().alias("cents"), (F.col("event_type") == "error").alias("is_error"))


@query("join_orders_customer", "select c_mktsegment, count(*) as orders, round(sum(o_totalprice), 2) as price from orders join customer on o_custkey = c_custkey group by 1")
def join_orders_customer(spark, sf):
    j = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("c_mktsegment").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("price"))


@query("outer_join", "select n_nationkey, count(s_suppkey) as suppliers from nation left join supplier on n_nationkey = s_nationkey group by 1")
def outer_join(spark, sf):
    j = table(spark, sf, "nation").join(table(spark, sf, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "left")
    return j.groupBy("n_nationkey").agg(F.count("s_suppkey").alias("suppliers"))


@query("semi_join", "select count(*) as customers from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'F')")
def semi_join(spark, sf):
    o = table(spark, sf, "orders").where("o_orderstatus = 'F'")
    return table(spark, sf, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").agg(F.count("*").alias("customers"))


@query("range_join", f"with {EV} select count(*) as pairs from e a join e b on b.ordinal > a.ordinal and b.ordinal <= a.ordinal + 5 and abs(a.cents - b.cents) <= 10")
def range_join(spark, sf):
    """Neighbours within five places: buckets of five ordinals, then the residual condition."""
    p = events_points(spark, sf, scale=100.0).select("ordinal", F.col("vec")[0].alias("c"))
    a = p.select(F.col("ordinal").alias("i"), F.col("c").alias("a"), F.explode(F.array(*(F.floor(F.col("ordinal") / 5) + s for s in (0, 1)))).alias("bucket"))
    b = p.select(F.col("ordinal").alias("j"), F.col("c").alias("b"), F.floor(F.col("ordinal") / 5).alias("bucket"))
    return a.join(b, "bucket").where("j > i and j <= i + 5 and abs(a - b) <= 10").agg(F.count("*").alias("pairs"))


@query("asof_model", "select e.event_id, m.event_id as model_id from events e asof join (select event_id, ts from events where event_id % 100 = 0) m on e.ts >= m.ts")
def asof_model(spark, sf):
    """Latest model (every 100th event) at each event's time: a union and a window by day, with the
    last model of the days before carried over."""
    e = table(spark, sf, "events").select("event_id", "ts", F.date_format("ts", "yyyyMMdd").cast("int").alias("day"))
    models = e.where("event_id % 100 = 0")
    last = models.groupBy("day").agg(F.max_by("event_id", "ts").alias("m"))
    days = e.select("day").distinct().join(last, "day", "left")
    before = days.withColumn("before", F.last("m", ignorenulls=True).over(W.orderBy("day").rowsBetween(W.unboundedPreceding, -1))).select("day", "before")
    both = e.withColumn("m", F.when(F.col("event_id") % 100 == 0, F.col("event_id")))
    inside = F.last("m", ignorenulls=True).over(W.partitionBy("day").orderBy("ts", F.col("m").asc_nulls_last()).rowsBetween(W.unboundedPreceding, 0))
    return both.withColumn("in_day", inside).join(F.broadcast(before), "day").select("event_id", F.coalesce("in_day", "before").alias("model_id"))


@query("lateral_nearest", f"with {EV}, {FIXED} select x.id as point_id, arg_min(m.median_id, (abs(x.value - m.mv), m.median_id)) as median_id from e x, m group by 1")
def lateral_nearest(spark, sf):
    """A point meets the medians in its cell of values and the nearest on either side of it: all others are beyond."""
    events_points(spark, sf).createOrReplaceTempView("lateral_points")
    stored(fixed_medians(spark, sf).selectExpr("vec[0] as x", "median_id").groupBy("x").agg(F.min("median_id").alias("median_id")), "medians").createOrReplaceTempView("lateral_medians")
    cells = spark.sql("select floor(vec[0] / 0.25) as cell from lateral_points group by 1")
    stored(cells, "cells").createOrReplaceTempView("lateral_cells")
    # of each cell, the places of medians from the last below it to the first above it
    ends = spark.sql("select c.cell, coalesce(max(case when m.x < c.cell * 0.25D then m.x end), min(m.x)) as lo, coalesce(min(case when m.x > (c.cell + 1) * 0.25D then m.x end), max(m.x)) as hi from lateral_cells c cross join lateral_medians m group by c.cell")
    stored(ends, "ends").createOrReplaceTempView("lateral_ends")
    near = spark.sql("select e.cell, collect_list(struct(m.median_id, m.x)) as ms from lateral_ends e join lateral_medians m on m.x between e.lo and e.hi group by e.cell")
    stored(near, "near").createOrReplaceTempView("lateral_near")
    return spark.sql("select p.point_id, n.m.median_id as median_id from lateral_points p join lateral_near a on a.cell = floor(p.vec[0] / 0.25), lateral (select array_min(transform(a.ms, x -> struct(abs(p.vec[0] - x.x) as gap, x.median_id as median_id))) as m) n")


@query("agg_phase", f"with {EV} select (ordinal - 1) // 1000 as phase, count(*) as points, sum(cents)::bigint as cents, count(distinct user_id) as users from e group by 1")
def agg_phase(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", cents().alias("cents"))
    p = events_points(spark, sf).select(F.col("point_id").alias("event_id"), F.floor((F.col("ordinal") - 1) / 1000).alias("phase"))
    return e.join(p, "event_id").groupBy("phase").agg(F.count("*").alias("points"), F.sum("cents").alias("cents"), F.countDistinct("user_id").alias("users"))


@query("distinct_points", "select count(distinct cast(round(value * 100) as bigint)) as points from events")
def distinct_points(spark, sf):
    return table(spark, sf, "events").agg(F.countDistinct(cents()).alias("points"))


@query("distinct_approx")
def distinct_approx(spark, sf):
    return table(spark, sf, "events").agg(F.approx_count_distinct(cents(), 0.02).alias("points"))


_G = "select user_id % 3 as u, event_type, count(*) as points, sum(cast(round(value * 100) as bigint))::bigint as cents from events group by "
for _name, _by in (("cost_rollup", "rollup (user_id % 3, event_type)"), ("cost_cube", "cube (user_id % 3, event_type)"), ("grouping_sets", "grouping sets ((user_id % 3), (event_type))")):
    SQL[_name] = _G + _by


def _grouped(df):
    return df.agg(F.count("*").alias("points"), F.sum(cents()).alias("cents"))


def _users(spark, sf):
    return table(spark, sf, "events").withColumn("u", F.col("user_id") % 3)


Q["cost_rollup"] = lambda spark, sf: _grouped(_users(spark, sf).rollup("u", "event_type"))
Q["cost_cube"] = lambda spark, sf: _grouped(_users(spark, sf).cube("u", "event_type"))
Q["grouping_sets"] = lambda spark, sf: _grouped(_users(spark, sf).groupingSets([("u",), ("event_type",)], "u", "event_type"))


@query("percentiles", "select user_id, round(quantile_cont(value, 0.5), 6) as median, round(quantile_cont(value, 0.95), 6) as high from events group by 1")
def percentiles(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("value", F.lit(0.95)), 6).alias("high"))


@query("verdict_pivot", "select phase, count(*) filter (v = 'inlier') as inlier, count(*) filter (v = 'outlier') as outlier from (select event_id // 1000 as phase, case when value > 150 then 'outlier' else 'inlier' end as v from events) group by 1")
def verdict_pivot(spark, sf):
    v = table(spark, sf, "events").select(F.floor(F.col("event_id") / 1000).alias("phase"), F.when(F.col("value") > 150, "outlier").otherwise("inlier").alias("v"))
    return v.groupBy("phase").pivot("v", ["inlier", "outlier"]).agg(F.count("v")).select("phase", F.coalesce("inlier", F.lit(0)).alias("inlier"), F.coalesce("outlier", F.lit(0)).alias("outlier"))


@query("rank_outliers", "select event_id, rank() over w as r, dense_rank() over w as dr, ntile(4) over (partition by user_id order by value desc, event_id) as quarter, round(percent_rank() over w, 6) as pr from events window w as (partition by user_id order by cast(round(value) as bigint) desc)")
def rank_outliers(spark, sf):
    w = W.partitionBy("user_id").orderBy(F.desc(F.round("value").cast("long")))
    return table(spark, sf, "events").select("event_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(W.partitionBy("user_id").orderBy(F.desc("value"), "event_id")).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("weight_delta", "select event_id, cast(round(value * 100) as bigint) - lag(cast(round(value * 100) as bigint)) over w as delta, lead(event_id) over w as next_id from events window w as (partition by user_id order by event_id)")
def weight_delta(spark, sf):
    w = W.partitionBy("user_id").orderBy("event_id")
    return table(spark, sf, "events").select("event_id", (cents() - F.lag(cents()).over(w)).alias("delta"), F.lead("event_id").over(w).alias("next_id"))


@query("running_cost", "select event_id, sum(cast(round(value * 100) as bigint)) over (partition by user_id order by event_id rows unbounded preceding)::bigint as cost, count(*) over (partition by user_id order by event_id range between 500 preceding and current row) as near from events")
def running_cost(spark, sf):
    w = W.partitionBy("user_id").orderBy("event_id")
    return table(spark, sf, "events").select("event_id", F.sum(cents()).over(w.rowsBetween(W.unboundedPreceding, 0)).alias("cost"), F.count("*").over(w.rangeBetween(-500, 0)).alias("near"))


@query("topk_global", "select event_id, value from events order by value desc, event_id limit 10")
def topk_global(spark, sf):
    return table(spark, sf, "events").select("event_id", "value").orderBy(F.desc("value"), "event_id").limit(10)


@query("topk_per_key", "select user_id, event_id, r from (select user_id, event_id, row_number() over (partition by user_id order by value desc, event_id) as r from events) where r <= 3")
def topk_per_key(spark, sf):
    r = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))
    return table(spark, sf, "events").select("user_id", "event_id", r.alias("r")).where("r <= 3")


@query("set_ops", "select user_id from events where value > 150 intersect select user_id from events where event_type = 'error'")
def set_ops(spark, sf):
    e = table(spark, sf, "events")
    return e.where("value > 150").select("user_id").intersect(e.where("event_type = 'error'").select("user_id"))


TEXT = "with t as (select doc_id, coalesce(text, '') as t from documents) select doc_id, length(t)::bigint as chars, ascii(t)::bigint as first_code, (length(t) - length(regexp_replace(t, '[0-9]', '', 'g')))::bigint as digits, (length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')))::bigint as capitals, len(list_distinct(string_split(t, '')))::bigint as distinct_chars from t"


def text_numbers(spark, sf):
    """Character counts of documents (text as codes)."""
    t = F.coalesce("text", F.lit(""))
    gone = lambda p: (F.length(t) - F.length(F.regexp_replace(t, p, ""))).cast("long")
    return table(spark, sf, "documents").select("doc_id", F.length(t).cast("long").alias("chars"), F.ascii(t).cast("long").alias("first_code"), gone("[0-9]").alias("digits"), gone("[A-Z]").alias("capitals"), F.size(F.array_distinct(F.split(t, ""))).cast("long").alias("distinct_chars"))


Q["text_features"], SQL["text_features"] = text_numbers, TEXT


@query("time_features", "select event_id, date_diff('day', date '1970-01-01', ts::date)::bigint as day, (epoch_us(ts) // 1000000 % 86400)::bigint as second, (epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by event_id))::bigint as gap_us from events")
def time_features(spark, sf):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    gap = us - F.lag(us).over(W.partitionBy("user_id").orderBy("event_id"))
    return table(spark, sf, "events").select("event_id", F.datediff("ts", F.lit("1970-01-01")).cast("long").alias("day"), (F.floor(us / 1_000_000) % 86400).cast("long").alias("second"), gap.alias("gap_us"))


@query("math_functions", "select event_id, round(ln(value + 1), 6) as l, round(log2(value + 1), 6) as l2, round(sqrt(value), 6) as root, greatest(value, 50) as up, least(value, 50) as down from events")
def math_functions(spark, sf):
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", F.round(F.log(v + 1), 6).alias("l"), F.round(F.log2(v + 1), 6).alias("l2"), F.round(F.sqrt(v), 6).alias("root"), F.greatest(v, F.lit(50.0)).alias("up"), F.least(v, F.lit(50.0)).alias("down"))


@query("vector_ops", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as squared, len(embedding)::int as d from embeddings")
def vector_ops(spark, sf):
    v = F.col("embedding").cast("array<double>")
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 4).alias("squared"), F.size("embedding").alias("d"))


@query("json_feature", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def json_feature(spark, sf):
    return table(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("window_tumbling", "select strftime(time_bucket(interval '6 hours', ts), '%Y-%m-%d %H') as start, count(*) as points from events group by 1")
def window_tumbling(spark, sf):
    w = F.window(F.col("ts").cast("timestamp"), "6 hours")
    return table(spark, sf, "events").groupBy(w.alias("w")).agg(F.count("*").alias("points")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "points")


@query("window_sliding", "select strftime(time_bucket(interval '1 day', ts) - to_days(o), '%Y-%m-%d') as start, count(*) as points from events, range(0, 2) t(o) group by 1")
def window_sliding(spark, sf):
    w = F.window(F.col("ts").cast("timestamp"), "2 days", "1 day")
    return table(spark, sf, "events").groupBy(w.alias("w")).agg(F.count("*").alias("points")).select(F.date_format("w.start", "yyyy-MM-dd").alias("start"), "points")


@query("window_session", "with g as (select user_id, event_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) >= interval '12 hours' or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as n from events), s as (select *, sum(n) over (partition by user_id order by ts rows unbounded preceding) as s from g) select user_id, min(event_id) as first_id, count(*) as points from s group by user_id, s")
def window_session(spark, sf):
    s = F.session_window(F.col("ts").cast("timestamp"), "12 hours")
    return table(spark, sf, "events").groupBy("user_id", s.alias("s")).agg(F.min("event_id").alias("first_id"), F.count("*").alias("points")).drop("s")


@query("dedup", "select user_id, event_type, min(event_id) as event_id from events group by 1, 2")
def dedup(spark, sf):
    r = F.row_number().over(W.partitionBy("user_id", "event_type").orderBy("event_id"))
    return table(spark, sf, "events").withColumn("r", r).where("r = 1").select("user_id", "event_type", "event_id")


@query("hash_sample", "select event_id from events where cast(('0x' || substr(md5('7|' || event_id), 1, 8)) as bigint) < 429496729")
def hash_sample(spark, sf):
    h = F.conv(F.substring(F.md5(F.concat(F.lit("7|"), F.col("event_id").cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")
    return table(spark, sf, "events").where(h < 429496729).select("event_id")


@query("conversation_turns", "select conv_id, count(*) as turns, sum(length(text))::bigint as chars, round(avg(length(text)), 4) as mean_chars from conversations group by 1")
def conversation_turns(spark, sf):
    n = F.length("text")
    return table(spark, sf, "conversations").groupBy("conv_id").agg(F.count("*").alias("turns"), F.sum(n).alias("chars"), F.round(F.avg(n), 4).alias("mean_chars"))


@query("page_features", "select page_id, length(html)::bigint as chars, (length(html) - length(replace(html, '<', '')))::bigint as tags, length(url)::bigint as url_chars from pages")
def page_features(spark, sf):
    h = F.col("html")
    return table(spark, sf, "pages").select("page_id", F.length(h).cast("long").alias("chars"), (F.length(h) - F.length(F.replace(h, F.lit("<"), F.lit("")))).cast("long").alias("tags"), F.length("url").cast("long").alias("url_chars"))


@query("customer_gaps", "select o_orderkey, o_custkey, round(o_totalprice * 100)::bigint as cents, date_diff('day', lag(o_orderdate) over w, o_orderdate)::bigint as gap from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def customer_gaps(spark, sf):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf, "orders").select("o_orderkey", "o_custkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"), F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).cast("long").alias("gap"))


@query("supplier_prices", "select l_suppkey, count(*) as lines, round(avg(l_extendedprice / l_quantity), 4) as unit_price, round(avg(l_discount), 6) as discount from lineitem where l_quantity > 0 group by 1")
def supplier_prices(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity > 0").groupBy("l_suppkey").agg(F.count("*").alias("lines"), F.round(F.avg(F.col("l_extendedprice") / F.col("l_quantity")), 4).alias("unit_price"), F.round(F.avg("l_discount"), 6).alias("discount"))
