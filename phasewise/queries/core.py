"""Queries of the core method, each with its SQL.  Keys follow the inventory (M...)."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.distance import KINDS, distance_expr, vector
from ..functions.draws import draw_expr
from ..operators import miner as mn
from ..operators.engine import Settings
from ..operators.points import chunk, chunk_by_window, scale, with_ordinal
from ..plans import schedule as sc
from ..sources.shared import stored
from .miner_sql import EVENTS, MEDIANS, PHASE_LOG, USERS, VERDICTS, miner_sql
from ..sources.tables import LINEITEM_KEYS, events_points, lineitem_points, orders_points, table

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


EV = "e as (select event_id as id, row_number() over (order by event_id) as ordinal, value, cast(round(value * 100) as bigint) as cents, user_id, ts from events)"
DRAW = "cast(('0x' || substr(md5('1|0|1|' || id), 1, 8)) as bigint) / 4294967296.0"


@query("points_lineitem", "select row_number() over (order by " + ", ".join(LINEITEM_KEYS) + ") as ordinal, round(l_quantity + l_extendedprice + l_discount + l_tax, 6) as money, l_linenumber::double as line, date_diff('day', date '1970-01-01', l_shipdate::date)::double as day, ascii(l_returnflag)::double as flag, ascii(l_linestatus)::double as status from lineitem")
def points_lineitem(spark, sf):
    v = F.col("vec")
    return lineitem_points(spark, sf).select("ordinal", F.round(v[0] + v[1] + v[2] + v[3], 6).alias("money"), v[4].alias("line"), v[5].alias("day"), v[6].alias("flag"), v[7].alias("status"))


@query("points_orders", "select row_number() over (order by o_orderkey) as ordinal, o_orderkey as point_id, ascii(o_orderstatus)::double as status, list_position(['1-URGENT', '2-HIGH', '3-MEDIUM', '4-NOT SPECIFIED', '5-LOW'], o_orderpriority)::double as priority, o_totalprice as price, month(o_orderdate)::double as month, ((dayofweek(o_orderdate) + 6) % 7)::double as weekday from orders")
def points_orders(spark, sf):
    v = F.col("vec")
    return orders_points(spark, sf).select("ordinal", "point_id", v[0].alias("status"), v[1].alias("priority"), v[2].alias("price"), v[3].alias("month"), v[4].alias("weekday"))


@query("scale_minmax", "select row_number() over (order by o_orderkey) as ordinal, round((o_totalprice - min(o_totalprice) over ()) / (max(o_totalprice) over () - min(o_totalprice) over ()), 6) as x from orders")
def scale_minmax(spark, sf):
    return scale(orders_points(spark, sf), "minmax", 5).select("ordinal", F.round(F.col("vec")[2], 6).alias("x"))


@query("scale_zscore", "select event_id as point_id, round((value - avg(value) over ()) / stddev_samp(value) over (), 6) as x from events")
def scale_zscore(spark, sf):
    return scale(events_points(spark, sf), "zscore", 1).select("point_id", F.round(F.col("vec")[0], 6).alias("x"))


@query("scale_robust", "with q as (select quantile_cont(value, 0.5) as m, quantile_cont(value, 0.75) - quantile_cont(value, 0.25) as w from events) select event_id as point_id, round((value - m) / w, 6) as x from events, q")
def scale_robust(spark, sf):
    return scale(events_points(spark, sf), "robust", 1).select("point_id", F.round(F.col("vec")[0], 6).alias("x"))


@query("ordinal_events", "select event_id, row_number() over (order by ts, event_id) as ordinal from events")
def ordinal_events(spark, sf):
    return with_ordinal(table(spark, sf, "events").select("event_id", "ts"), ["ts", "event_id"]).select("event_id", "ordinal")


@query("ordinal_per_user", "select event_id, user_id, row_number() over (partition by user_id order by event_id) as ordinal from events")
def ordinal_per_user(spark, sf):
    return with_ordinal(table(spark, sf, "events").select("event_id", "user_id"), ["event_id"], "user_id")


@query("chunk_stats", f"with {EV} select (ordinal - 1) // 500 as chunk_id, count(*) as points, sum(cents)::bigint as cents, min(cents) as lo, max(cents) as hi from e group by 1")
def chunk_stats(spark, sf):
    c = F.col("vec")[0].cast("long")
    return chunk(events_points(spark, sf, scale=100.0), 500).groupBy("chunk_id").agg(F.count("*").alias("points"), F.sum(c).alias("cents"), F.min(c).alias("lo"), F.max(c).alias("hi"))


@query("chunk_days", "select strftime(ts, '%Y-%m-%d') as day, count(*) as points, sum(cast(round(value * 100) as bigint))::bigint as cents from events group by 1")
def chunk_days(spark, sf):
    df = chunk_by_window(table(spark, sf, "events"), "ts", "1 day")
    return df.groupBy(F.date_format("window_start", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("points"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


@query("initial_floor_events", f"with {EV}, h as (select * from e where ordinal <= 3) select round(min(abs(a.value - b.value)), 6) as closest, round(min(abs(a.value - b.value)) / 34, 9) as floor from h a join h b on a.ordinal < b.ordinal")
def initial_floor_events(spark, sf):
    return sc.initial_floor(events_points(spark, sf), 2, 34, d=1, zero_floor="error").select(F.round("closest", 6).alias("closest"), F.round("floor", 9).alias("floor"))


@query("initial_floor_multi", f"with {EV}, o as (select *, row_number() over (partition by user_id order by id) as r from e), h as (select * from o where r <= 4) select a.user_id::varchar as stream_key, min(abs(a.cents - b.cents))::bigint as closest from h a join h b on a.user_id = b.user_id and a.r < b.r group by 1")
def initial_floor_multi(spark, sf):
    out = sc.initial_floor(events_points(spark, sf, stream_key="user_id", scale=100.0), 3, 34, d=1, zero_floor="allow")
    return out.select("stream_key", F.col("closest").cast("long").alias("closest"))


@query("initial_floor_distinct", f"with {EV}, o as (select *, row_number() over (partition by user_id order by id) as r from e), f as (select user_id, cents, min(r) as r from o group by 1, 2), h as (select *, row_number() over (partition by user_id order by r) as q from f qualify q <= 4) select a.user_id::varchar as stream_key, min(abs(a.cents - b.cents))::bigint as closest, round(min(abs(a.cents - b.cents)) / 34, 9) as floor from h a join h b on a.user_id = b.user_id and a.q < b.q group by 1")
def initial_floor_distinct(spark, sf):
    out = sc.initial_floor(events_points(spark, sf, stream_key="user_id", scale=100.0), 3, 34, d=1)
    return out.select("stream_key", F.col("closest").cast("long").alias("closest"), F.round("floor", 9).alias("floor"))


@query("phase_schedule", f"with {EV}, h as (select * from e where ordinal <= 3), n as (select count(value) as n from e), c as (select min(abs(a.value - b.value)) / 34 as l1, 1 + ln(any_value(n)) as a, 273 as m, any_value(n) as n from h a join h b on a.ordinal < b.ordinal, n) select i as phase, round(l1 * pow(34, i - 1), 6) as floor, round(l1 * pow(34, i - 1) / (2 * a), 6) as price, round(4 * m * l1 * pow(34, i - 1), 3) as cost_cap, round(8 * a * m, 6) as median_cap, ceil(2 * ln(n))::bigint as runs from c, range(1, 6) t(i)")
def phase_schedule(spark, sf):
    """The schedule of ``events``: from its first floor and its length."""
    p = events_points(spark, sf)
    floor, n = sc.initial_floor(p, 2, 34, d=1, zero_floor="error").head()["floor"], p.agg(F.count("vec")).head()[0]
    out = sc.phase_schedule(spark, floor, k=2, n=n)
    return out.select("phase", F.round("floor", 6).alias("floor"), F.round("price", 6).alias("price"), F.round("cost_cap", 3).alias("cost_cap"), F.round("median_cap", 6).alias("median_cap"), "runs")


@query("constants_grid", "with v as (select distinct floor(value)::bigint as v from events where value >= 1 and value < 181) select g as gamma, b as beta from v x(g), v y(b) where g + 4 * (1 + 4 * (b + g)) <= g * b and b >= 2 * (1 + g) + g")
def constants_grid(spark, sf):
    """The pairs of constants that are feasible among the whole values of ``events``."""
    return sc.feasible_constants(table(spark, sf, "events").select("value"), 1.0, 180)


@query("draws_hash", f"select event_id as id, {DRAW.replace('id)', 'event_id)')} as u from events")
def draws_hash(spark, sf):
    return table(spark, sf, "events").select(F.col("event_id").alias("id"), draw_expr(1, 0, 1, F.col("event_id")).alias("u"))


@query("distance_kinds", "with p as (select l_quantity as a, l_discount as b, l_tax as c from lineitem) select round(sum(sqrt((a - 25) * (a - 25) + (b - 0.05) * (b - 0.05) + (c - 0.04) * (c - 0.04))), 4) as euclidean, round(sum((a - 25) * (a - 25) + (b - 0.05) * (b - 0.05) + (c - 0.04) * (c - 0.04)), 4) as sqeuclidean, round(sum(abs(a - 25) + abs(b - 0.05) + abs(c - 0.04)), 4) as manhattan, round(sum(greatest(abs(a - 25), abs(b - 0.05), abs(c - 0.04))), 4) as chebyshev from p")
def distance_kinds(spark, sf):
    df = table(spark, sf, "lineitem")
    a, b = [F.col(c) for c in ("l_quantity", "l_discount", "l_tax")], [F.lit(25.0), F.lit(0.05), F.lit(0.04)]
    return df.agg(*(F.round(F.sum(distance_expr(k, a, b)), 4).alias(k) for k in KINDS))


def pass_sql(opens: str, weight: str = "1", cost_cap: float | None = None) -> str:
    """CTEs up to ``done(p)``: one facility pass over all events, as a fold over their list."""
    near = "list_transform([list_transform(a.x, lambda v: abs(v - e.x))], lambda d: {'t': list_min(d), 'at': list_position(d, list_min(d))})"
    opened = "{'x': list_append(a.x, e.x), 'id': list_append(a.id, e.id), 'w': list_append(a.w, e.w), 'service': a.service, 'read': a.read + 1, 'over': false}"
    joined = "{'x': a.x, 'id': a.id, 'w': list_transform(a.w, lambda v, j: case when j = q.at then v + e.w else v end), 'service': a.service + q.t * e.w, 'read': a.read + 1, 'over': false}"
    stop = "{'x': a.x, 'id': a.id, 'w': a.w, 'service': a.service, 'read': a.read, 'over': true}"
    total = "(q2.service + 2000 * len(q2.x)) > %s" % cost_cap if cost_cap else "false"
    step = f"list_transform({near}, lambda q: case when len(a.x) = 0 or e.u < {opens} then {opened} else {joined} end)[1]"
    fold = f"case when a.over then a else list_transform([{step}], lambda q2: case when {total} then {stop} else q2 end)[1] end"
    return f"""with {EV}, l as (select list({{'id': id, 'x': cents, 'w': ({weight})::bigint, 'u': {DRAW}}} order by ordinal) as es from e),
done as (select list_reduce(es, lambda a, e: {fold}, {{'x': []::bigint[], 'id': []::bigint[], 'w': []::bigint[], 'service': 0::bigint, 'read': 0::bigint, 'over': false}}) as p from l)"""


PASS_ROWS = " select unnest(p.id) as median_id, unnest(p.w) as weight, p.service as service_cost from done"
PRICED, UNPRICED = "least(q.t * e.w / 2000.0, 1)", "least(q.t * e.w * 1.0, 1)"


def _pass(spark, sf, rule: str = "priced", weighted: bool = False, price: float = 2000.0):
    p = events_points(spark, sf, scale=100.0)
    if weighted:
        p = p.withColumn("weight", (F.col("point_id") % 3 + 1).cast("double"))
    done = mn.pass_stream(p, price, Settings(opening_rule=rule))
    # the pass is run once: its sums by median are written
    held = stored(done.groupBy("median_id").agg(F.sum("weight").cast("long").alias("weight"), F.sum(F.col("dist") * F.col("weight")).alias("service")), "pass")
    return held.select("median_id", "weight").join(F.broadcast(held.agg(F.sum("service").cast("long").alias("service_cost"))))


@query("facility_pass", pass_sql(PRICED) + PASS_ROWS)
def facility_pass(spark, sf):
    return _pass(spark, sf)


@query("facility_pass_unpriced", pass_sql(UNPRICED) + PASS_ROWS)
def facility_pass_unpriced(spark, sf):
    return _pass(spark, sf, "unpriced")


@query("facility_pass_weighted", pass_sql(PRICED, "id % 3 + 1") + PASS_ROWS)
def facility_pass_weighted(spark, sf):
    return _pass(spark, sf, weighted=True)


@query("facility_pass_keyed", f"with {EV} select sum(1)::bigint as weight, count(distinct user_id) as streams from e")
def facility_pass_keyed(spark, sf):
    done = mn.pass_assignments(events_points(spark, sf, stream_key="user_id", scale=100.0), 2000.0)
    return done.agg(F.sum("weight").cast("long").alias("weight"), F.countDistinct("stream_key").alias("streams"))


@query("stop_audit", pass_sql(PRICED, cost_cap=60000) + " select case when p.over then p.read + 1 end as first_over from done")
def stop_audit(spark, sf):
    done = mn.pass_stream(events_points(spark, sf, scale=100.0), 2000.0, Settings())
    return mn.stop_audit(done, 2000.0, 60000.0).select("first_over")


RUNS_SQL = "select stream_key, l.phase, {} as runs, round(l.least, 4) as least, round(l.most, 4) as most, l.fewest, l.most_medians from (select stream_key, unnest(log) as l from result)"


@query("runs_compare", miner_sql(USERS, k=2, num=10, runs=6) + RUNS_SQL.format("6::bigint"))
def runs_compare(spark, sf):
    """The independent runs of each phase of each user's stream."""
    r = mn.mine_outliers(events_points(spark, sf, stream_key="user_id"), Settings(k=2, num=10, runs=6))
    return r.run_log.groupBy("stream_key", "phase").agg(F.count("*").alias("runs"), F.round(F.min("total_cost"), 4).alias("least"), F.round(F.max("total_cost"), 4).alias("most"), F.min("medians").alias("fewest"), F.max("medians").alias("most_medians"))


RUNS = "r as (select user_id % 7 as phase, user_id as run, count(*) as points_read, sum(cast(round(value * 100) as bigint))::bigint as cost from events group by user_id)"


@query("pick_winner", f"with {RUNS} select phase, arg_max(run, (points_read, -cost, -run)) as winner from r group by phase")
def pick_winner(spark, sf):
    runs = table(spark, sf, "events").groupBy("user_id").agg(F.count("*").alias("points_read"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cost"))
    runs = runs.select((F.col("user_id") % 7).alias("phase"), F.col("user_id").alias("run"), "points_read", "cost")
    return runs.groupBy("phase").agg(F.max_by("run", F.struct("points_read", -F.col("cost"), -F.col("run"))).alias("winner"))


@query("read_split", f"with {EV} select ordinal + 7 <= 400 as is_read, count(*) as points, min(id) as first_id from e group by 1")
def read_split(spark, sf):
    return mn.split_read(events_points(spark, sf), 400, 7).groupBy("is_read").agg(F.count("*").alias("points"), F.min("point_id").alias("first_id"))


CARRIED = "m as (select min(id) as id, arg_min(cents, id) as cents, count(*) as weight from e where ordinal <= 500 group by cents // 1000)"


def carried(spark, sf):
    """Weighted medians of a first chunk: one per ten units of value."""
    p = events_points(spark, sf, scale=100.0).where("ordinal <= 500")
    return p.groupBy(F.floor(F.col("vec")[0] / 1000).alias("g")).agg(F.min("point_id").alias("median_id"), F.min_by("vec", "point_id").alias("vec"), F.sum("weight").alias("weight")).drop("g")


@query("carry_union", f"with {EV}, {CARRIED} select 0 as rank, id as point_id, cents, weight::bigint as weight from m union all select 1, id, cents, 1 from e where ordinal > 500")
def carry_union(spark, sf):
    """The input of the second phase: the first chunk's medians, then all that is unread."""
    unread = events_points(spark, sf, scale=100.0).where("ordinal > 500")
    return mn.next_input(carried(spark, sf), unread).select("rank", "point_id", F.col("vec")[0].cast("long").alias("cents"), F.col("weight").cast("long").alias("weight"))


GROUPED = "g as (select cents // 1000 as b, ordinal > (select count(*) // 2 from e) as late, min(id) as id, count(*) as w from e group by 1, 2), x as (select b, min(id) as median_id, sum(case when not late then w end) as wb, sum(w) as wa from g group by b)"


def before_after(spark, sf):
    p = events_points(spark, sf, scale=100.0).withColumn("b", F.floor(F.col("vec")[0] / 1000))
    half = p.agg(F.floor(F.count("*") / 2).alias("half"))
    p = p.join(F.broadcast(half))  # one row
    early = F.when(F.col("ordinal") <= F.col("half"), 1.0)
    x = p.groupBy("b").agg(F.min("point_id").alias("median_id"), F.sum(early).alias("wb"), F.count("*").cast("double").alias("wa"))
    return x.where("wb is not null").select("median_id", F.col("wb").alias("weight")), x.select("median_id", F.col("wa").alias("weight"), F.lit(1.0).alias("own"))


def _marked(rule):
    def run(spark, sf):
        b, a = before_after(spark, sf)
        out = mn.mark_candidates(b, a, rule, 1.0)
        return out.select("median_id", F.col("weight_before").cast("long").alias("weight_before"), F.col("weight_after").cast("long").alias("weight_after"), "is_new", "is_candidate")

    return run


Q["candidates_mark"], Q["candidates_light"] = _marked("stalled"), _marked("stalled_light")
SQL["candidates_mark"] = f"with {EV}, {GROUPED} select median_id, wb::bigint as weight_before, wa::bigint as weight_after, wb is null as is_new, wa = coalesce(wb, 1) as is_candidate from x"
SQL["candidates_light"] = f"with {EV}, {GROUPED} select median_id, wb::bigint as weight_before, wa::bigint as weight_after, wb is null as is_new, wa = coalesce(wb, 1) and wa <= 1 as is_candidate from x"

STALLS = "c as (select (ordinal - 1) // 500 as phase, cents // 500 as m from e), d as (select distinct phase, m from c), born as (select m, min(phase) as b from d group by m), s as (select born.m as median_id, p.phase, d.m is null as stalled from born cross join (select distinct phase from c) p left join d on d.m = born.m and d.phase = p.phase where p.phase >= born.b)"
SETTLE = f"with {EV}, {STALLS}, f as (select median_id, min(phase) as first_phase from s where stalled group by 1) select s.median_id, first_phase, count(*) as age, sum(stalled::int)::bigint as score, case when count(*) < 3 then 'pending' when sum(stalled::int) = 3 then 'outlier' else 'inlier' end as verdict from s join f using (median_id) where phase >= first_phase and phase < first_phase + 3 group by 1, 2"


def stalls(spark, sf):
    """(median_id, phase, stalled) of value cells over chunks of 500 events."""
    c = chunk(events_points(spark, sf, scale=100.0), 500).select(F.col("chunk_id").alias("phase"), F.floor(F.col("vec")[0] / 500).cast("long").alias("m")).distinct()
    born = c.groupBy("m").agg(F.min("phase").alias("b"))
    last = c.agg(F.max("phase").alias("last"))
    every = born.join(F.broadcast(last)).select("m", F.explode(F.sequence("b", "last")).alias("phase"))
    return every.join(c.withColumn("hit", F.lit(True)), ["m", "phase"], "left").select(F.col("m").alias("median_id"), "phase", F.col("hit").isNull().alias("stalled"))


@query("settle_window", SETTLE)
def settle_window(spark, sf):
    return mn.settle(stalls(spark, sf), 3)


@query("settle_pending", f"select verdict, count(*) as medians, min(first_phase) as first_phase from ({SETTLE}) group by verdict")
def settle_pending(spark, sf):
    return mn.settle(stalls(spark, sf), 3).groupBy("verdict").agg(F.count("*").alias("medians"), F.min("first_phase").alias("first_phase"))


@query("retire_antijoin", f"with {EV}, {STALLS} select distinct median_id from s where median_id not in (select median_id from ({SETTLE}) where verdict = 'outlier')")
def retire_antijoin(spark, sf):
    v = mn.settle(stalls(spark, sf), 3).where("verdict = 'outlier'")
    return mn.retire(stalls(spark, sf).select("median_id").distinct(), v)


def events_miner(spark, sf, keep=tuple(mn.KINDS), **more):
    return mn.mine_single_stream(events_points(spark, sf), Settings(**{"k": 3, "outlier_phases": 2, "num": 500, "runs": 3, "floor_growth": "on_breach"} | more), keep=keep)


def phase_log(r) -> object:
    """The phase log with costs rounded as in the SQL."""
    keep = ["stream_key", "phase", "winner_run", "points_in", "points_read", "unread", "medians_out", "new_medians", "stop_reason"]
    return r.phase_log.select(*keep, *(F.round(c, n).alias(c) for c, n in (("floor", 2), ("price", 2), ("service_cost", 4), ("total_cost", 2), ("ssq", 5), ("max_dist", 6))))


@query("miner_chunked_events", miner_sql(EVENTS, k=3, num=500, runs=3, growth="on_breach") + PHASE_LOG)
def miner_chunked_events(spark, sf):
    return phase_log(events_miner(spark, sf, ("phase_log",)))


@query("miner_limit_driven", miner_sql(EVENTS, k=2, num=None, runs=2, gamma=2, beta=4) + PHASE_LOG)
def miner_limit_driven(spark, sf):
    s = Settings(k=2, mode="limit_driven", gamma=2, beta=4, runs=2)
    return phase_log(mn.mine_single_stream(events_points(spark, sf), s))


def users_miner(spark, sf, **more):
    p = events_points(spark, sf, stream_key="user_id")
    return mn.mine_outliers(p, Settings(**{"k": 2, "num": 10, "runs": 2} | more))


USERS_SQL = miner_sql(USERS, k=2, num=10, runs=2)


@query("miner_per_user", USERS_SQL + VERDICTS)
def miner_per_user(spark, sf):
    return users_miner(spark, sf).verdicts


@query("miner_per_user_phases", USERS_SQL + PHASE_LOG)
def miner_per_user_phases(spark, sf):
    return phase_log(users_miner(spark, sf))


@query("miner_per_user_medians", USERS_SQL + MEDIANS)
def miner_per_user_medians(spark, sf):
    return users_miner(spark, sf).final()[0].select("stream_key", "median_id", F.col("vec")[0].alias("x"), F.col("weight_after").alias("weight"))


@query("miner_single_stream", miner_sql(EVENTS, k=3, num=1000, runs=2) + VERDICTS)
def miner_single_stream(spark, sf):
    """Verdicts of the whole stream, read in stretches that hand their state on."""
    return mn.mine_single_stream(events_points(spark, sf), Settings(k=3, num=1000, runs=2), stretch=3000).verdicts


PHASES = "with e as (select row_number() over (order by event_id) as ordinal from events) select (ordinal - 1) // 500 + 1 as phase, count(*) as points_in from e group by 1"


@query("phase_progress", f"select phase::int as phase, points_in, points_in as points_read, 0::bigint as unread from ({PHASES})")
def phase_progress(spark, sf):
    return events_miner(spark, sf, ("phase_log",), runs=1, num=500).phase_log.select("phase", "points_in", "points_read", "unread")


@query("weight_conservation", "select count(*) as weight from events")
def weight_conservation(spark, sf):
    """Final medians' weights and those of retired outliers add up to the points read."""
    r = events_miner(spark, sf, ("phase_log", "verdicts", mn.LAST_MEDIANS), runs=1, num=1000)
    last = r.phase_log.agg(F.max("phase").alias("last"))
    held = r.medians.join(F.broadcast(last)).where("phase = last")
    gone = r.verdicts.where("verdict = 'outlier'").select("median_id", "weight", "settled_phase").join(F.broadcast(last)).where("settled_phase < last")
    return held.select(F.col("weight_after").alias("w")).union(gone.select("weight")).agg(F.sum("w").cast("long").alias("weight"))


@query("sharded_weights", "select count(*) as weight from events")
def sharded_weights(spark, sf):
    return mn.sharded_medians(events_points(spark, sf), shards=16, price=50.0, fan_in=4).agg(F.sum("weight").cast("long").alias("weight"))


#: One shard is one pass, so its medians can be written in SQL; the confirming scan and the ageing are the same for more.
SHARD_SQL = pass_sql(PRICED).replace("'1|0|1|'", "'1|0|0|'") + """,
m as (select unnest(p.id) as median_id, unnest(p.x) as mx from done),
f as (select arg_min(median_id, (abs(cents - mx), median_id)) as median_id, e.id, (e.ordinal - 1) // 500 + 1 as phase from e, m group by e.id, e.ordinal),
hits as (select distinct median_id, phase from f where id <> median_id),
born as (select id as median_id, (ordinal - 1) // 500 + 1 as born from e where id in (select median_id from m)),
st as (select b.median_id, ph.phase, h.phase is null as stalled from born b join (select distinct phase from f) ph on ph.phase >= b.born left join hits h on h.median_id = b.median_id and h.phase = ph.phase),
ff as (select median_id, min(phase) as first_phase from st where stalled group by 1)
select st.median_id, first_phase::int as first_phase, count(*) as age, sum(stalled::int)::bigint as score, case when count(*) < 2 then 'pending' when sum(stalled::int) = 2 then 'outlier' else 'inlier' end as verdict
from st join ff using (median_id) where phase >= first_phase and phase < first_phase + 2 group by 1, 2"""


@query("sharded_verdicts", SHARD_SQL)
def sharded_verdicts(spark, sf):
    """A sharded stream's candidates, settled by a confirming scan."""
    p = events_points(spark, sf, scale=100.0)
    return mn.mine_shards(p, 1, Settings(outlier_phases=2, num=500), shards=1, price=2000.0)["verdicts"]


FIXED = "m as (select ordinal as median_id, value as mv from e where ordinal % 1000 = 1)"


def fixed_medians(spark, sf):
    return events_points(spark, sf).where("ordinal % 1000 = 1").select(F.col("ordinal").alias("median_id"), "vec")


NEAR = f"with {EV}, {FIXED}, a as (select id, value, arg_min(median_id, (abs(value - mv), median_id)) as median_id, min(abs(value - mv)) as dist from e, m group by id, value)"


@query("assign_nearest", NEAR + " select id as point_id, median_id, round(dist, 6) as dist from a")
def assign_nearest(spark, sf):
    return mn.assign(events_points(spark, sf), fixed_medians(spark, sf), 1).select("point_id", "median_id", F.round("dist", 6).alias("dist"))


@query("assign_keyed", "with e as (select user_id::varchar as stream_key, event_id as id, value, row_number() over (partition by user_id order by event_id) as r from events), m as (select stream_key, id as median_id, value as mv from e where r <= 3), a as (select e.stream_key, id, value, arg_min(median_id, (abs(value - mv), median_id)) as median_id, min(abs(value - mv)) as dist from e join m using (stream_key) group by 1, 2, 3) select stream_key, id as point_id, median_id, round(dist, 6) as dist from a")
def assign_keyed(spark, sf):
    """Points of many streams, each to a median of its own stream."""
    p = events_points(spark, sf, stream_key="user_id")
    medians = p.where("ordinal <= 3").select("stream_key", F.col("point_id").alias("median_id"), "vec")
    return mn.assign(p, medians, 1).select("stream_key", "point_id", "median_id", F.round("dist", 6).alias("dist"))


@query("score_static", NEAR + " select id as point_id, median_id, dist > 50 as is_far from a")
def score_static(spark, sf):
    return mn.assign(events_points(spark, sf), fixed_medians(spark, sf), 1).select("point_id", "median_id", (F.col("dist") > 50).alias("is_far"))


@query("explain_dims", "with p as (select row_number() over (order by o_orderkey) as o, o_orderkey as id, o_totalprice / 1000 as a, month(o_orderdate)::double as b from orders), x as (select * from p where o % 500 = 7), m as (select * from p where o % 400 = 1), d as (select x.id as median_id, m.id as near_id, sqrt((x.a - m.a) * (x.a - m.a) + (x.b - m.b) * (x.b - m.b)) as dist, (x.a - m.a) * (x.a - m.a) as s from x join m on x.id <> m.id) select median_id, arg_min(near_id, (dist, near_id)) as near_id, round(min(dist), 6) as dist, round(arg_min(s / (dist * dist), (dist, near_id)), 6) as share_0 from d group by 1")
def explain_dims(spark, sf):
    p = orders_points(spark, sf).select("ordinal", F.col("point_id").alias("median_id"), F.array(F.col("vec")[2] / 1000, F.col("vec")[3]).alias("vec"))
    out = mn.explain_outliers(p.where("ordinal % 500 = 7"), p.where("ordinal % 400 = 1"), 2)
    return out.select("median_id", "near_id", F.round("dist", 6).alias("dist"), F.round("share_0", 6).alias("share_0"))


@query("window_flip", "with e as (select event_id as id, strftime(ts, '%Y-%m-%d') as day, cast(round(value * 100) as bigint) as c from events), n as (select a.id, a.day, count(b.id) as near from e a left join e b on a.day = b.day and a.id <> b.id and abs(a.c - b.c) <= 100 group by 1, 2), f as (select day, count(*) as points, sum((near < 2)::int)::bigint as sparse from n group by day) select day, points, sparse, sparse - lag(sparse) over (order by day) as change from f")
def window_flip(spark, sf):
    """Points with fewer than two neighbours in their day's window, and the change between windows."""
    df = chunk_by_window(table(spark, sf, "events"), "ts", "1 day").select(F.col("event_id").alias("id"), F.date_format("window_start", "yyyy-MM-dd").alias("day"), F.round(F.col("value") * 100).cast("long").alias("c"))
    near = F.count("*").over(W.partitionBy("day").orderBy("c").rangeBetween(-100, 100)) - 1
    f = df.withColumn("near", near).groupBy("day").agg(F.count("*").alias("points"), F.sum((F.col("near") < 2).cast("int")).alias("sparse"))
    return f.withColumn("change", F.col("sparse") - F.lag("sparse").over(W.orderBy("day")))


@query("final_medians", "select max((ordinal - 1) // 1000 + 1)::int as phase from (select row_number() over (order by event_id) as ordinal from events)")
def final_medians(spark, sf):
    return events_miner(spark, sf, ("phase_log", "verdicts", mn.LAST_MEDIANS), runs=1, num=1000).final()[0].select("phase").distinct()
