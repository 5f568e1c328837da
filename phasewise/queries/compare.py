"""Queries of baselines (B...) and measures (C...), each with its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..baselines import means as bm
from ..baselines import neighbours as bn
from ..baselines import statistics as bs
from ..operators import measures as ms
from ..operators import miner as mn
from ..operators.engine import Settings
from ..plans.schedule import multiplier
from ..sources.shared import stored
from ..sources.tables import customer_points, events_points, lineitem_points, nation_points, orders_points, table
from .core import EV, NEAR, PRICED, USERS_SQL, events_miner, fixed_medians, pass_sql, users_miner
from .miner_sql import EVENTS, USERS, VERDICTS, miner_sql

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


CUSTOMERS = "q as (select c_custkey as id, c_acctbal / 100 as x, c_nationkey::double as y from customer)"
PLANE_GAP = "sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))"
KNN = f"with {CUSTOMERS}, d as (select a.id, {PLANE_GAP} as g, row_number() over (partition by a.id order by {PLANE_GAP}) as r from q a join q b on a.id <> b.id), k as (select id as point_id, g from d where r = 3) select point_id, round(g, 6) as dist from k order by g desc, point_id limit 7"


def plane(spark, sf):
    """Quantity and price (in thousands) of all lineitems."""
    return lineitem_points(spark, sf).withColumn("vec", F.array(F.col("vec")[0], F.col("vec")[1] / 1000))


def _knn(method):
    return lambda spark, sf: bn.knn_rank(customer_points(spark, sf), 3, 7, d=2, method=method).select("point_id", F.round("dist", 6).alias("dist"))


for _m, _name in (("join", "knn_rank_top"), ("block", "knn_rank_block"), ("pruned", "knn_rank_pruned")):
    Q[_name], SQL[_name] = _knn(_m), KNN


@query("knn_rank_cells", KNN)
def knn_rank_cells(spark, sf):
    return bn.knn_rank_cells(customer_points(spark, sf), 3, 7, d=2).select("point_id", F.round("dist", 6).alias("dist"))


@query("knn_rank_lineitem")
def knn_rank_lineitem(spark, sf):
    """The same over all lineitems: too many pairs for SQL, tested against all pairs on a small table."""
    return bn.knn_rank_cells(plane(spark, sf), 3, 7, d=2)


DB = f"with {CUSTOMERS}, n as (select a.id, count(b.id) as near from q a left join q b on a.id <> b.id and {PLANE_GAP} <= 3 group by 1) select id as point_id, near from n where near <= (select floor(count(*) * (1 - 0.99) + 1e-9) from q)"


def _db(method):
    return lambda spark, sf: bn.db_outliers(customer_points(spark, sf), 3.0, 0.99, d=2, method=method)


Q["db_nested"], SQL["db_nested"] = _db("nested"), DB
Q["db_grid"], SQL["db_grid"] = _db("grid"), DB


@query("db_grid_lineitem")
def db_grid_lineitem(spark, sf):
    """Distance-fraction outliers of all lineitems: too many pairs for SQL, tested on a small table."""
    return bn.db_outliers(plane(spark, sf), 3.0, 0.998, d=2, method="grid")


@query("window_knn", f"with {EV}, n as (select a.id, count(b.id) as near from e a left join e b on a.id <> b.id and abs(a.ordinal - b.ordinal) <= 50 and abs(a.cents - b.cents) <= 100 group by 1) select id as point_id, near, near < 2 as is_outlier from n")
def window_knn(spark, sf):
    return bn.window_knn(events_points(spark, sf, scale=100.0), 100.0, 2, 50, d=1)


@query("window_knn_approx")
def window_knn_approx(spark, sf):
    return bn.window_knn(events_points(spark, sf, scale=100.0), 100.0, 2, 50, d=1, approx=0.5)


@query("lof", "with s as (select c_custkey as id, cast(round(c_acctbal * 100) as bigint) as c from customer), d as (select a.id as a, b.id as b, abs(a.c - b.c)::double as g, row_number() over (partition by a.id order by abs(a.c - b.c), b.id) as r from s a join s b on a.id <> b.id), n as (select * from d where r <= 5), k as (select a, max(g) as kd from n group by a), l as (select n.a, 1.0 / greatest(avg(greatest(n.g, k.kd)), 1e-12) as lrd from n join k on k.a = n.b group by n.a) select n.a as point_id, round(avg(y.lrd) / any_value(x.lrd), 6) as lof from n join l x on x.a = n.a join l y on y.a = n.b group by n.a")
def lof(spark, sf):
    p = customer_points(spark, sf).withColumn("vec", F.array(F.round(F.col("vec")[0] * 10_000)))
    return bn.lof(p, 5, d=1).select("point_id", F.round("lof", 6).alias("lof"))


STAT = {"zscore": "with s as (select avg(value) as c, stddev_samp(value) as w from events) select event_id as point_id, round(abs(value - c) / w, 6) as score from events, s where abs(value - c) / w > 3",
        "iqr": "with s as (select quantile_cont(value, 0.25) as lo, quantile_cont(value, 0.75) as hi from events) select event_id as point_id, round(greatest(lo - value, value - hi) / (hi - lo), 6) as score from events, s where greatest(lo - value, value - hi) / (hi - lo) > 1.5",
        "mad": "with m as (select quantile_cont(value, 0.5) as c from events), s as (select any_value(c) as c, quantile_cont(abs(value - c), 0.5) as w from events, m) select event_id as point_id, round(abs(value - c) / w, 6) as score from events, s where abs(value - c) / w > 5"}
CUTS = {"zscore": 3.0, "iqr": 1.5, "mad": 5.0}


def _stat(kind):
    return lambda spark, sf: bs.stat_outliers(events_points(spark, sf), kind, CUTS[kind]).select("point_id", F.round("score", 6).alias("score"))


for _k in STAT:
    Q[_k], SQL[_k] = _stat(_k), STAT[_k]


@query("deviation_top", 'with s as (select avg(value) as m, count(*) as n from events) select event_id as point_id, round((value - m) * (value - m) * n / (n - 1), 4) as "drop" from events, s order by (value - m) * (value - m) desc, event_id limit 7')
def deviation_top(spark, sf):
    return bs.deviation_outliers(events_points(spark, sf), 7, 1).select("point_id", F.round("drop", 4).alias("drop"))


def _lloyd_sql(iters: int) -> str:
    steps = ["with p as (select o_orderkey as id, row_number() over (order by o_orderkey) as o, o_totalprice / 1000 as x, month(o_orderdate)::double as y from orders), c0 as (select (o - 1)::int as cluster, x, y from p where o <= 3)"]
    for i in range(iters):
        gap = "(p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y)"
        steps.append(f"a{i} as (select id, any_value(p.x) as x, any_value(p.y) as y, arg_min(cluster, ({gap}, cluster)) as cluster from p, c{i} c group by id), c{i + 1} as (select cluster, count(*) as weight, avg(x) as x, avg(y) as y from a{i} group by cluster)")
    return ", ".join(steps) + f" select cluster, weight::bigint as weight, round(x, 4) as c0, round(y, 4) as c1 from c{iters}"


def _lloyd(iters):
    def run(spark, sf):
        p = orders_points(spark, sf).withColumn("vec", F.array(F.col("vec")[2] / 1000, F.col("vec")[3]))
        return bm.lloyd(p, 3, iters, 2).select("cluster", F.col("weight").cast("long").alias("weight"), F.round("c0", 4).alias("c0"), F.round("c1", 4).alias("c1"))

    return run


for _n, _name in ((1, "lloyd_one_step"), (3, "lloyd_3")):
    Q[_name], SQL[_name] = _lloyd(_n), _lloyd_sql(_n)


@query("mean_miner")
def mean_miner(spark, sf):
    return bm.mean_miner(events_points(spark, sf, stream_key="user_id"), 2, 10, 2, rule="farthest", farthest=1)


@query("mean_miner_light")
def mean_miner_light(spark, sf):
    return bm.mean_miner(events_points(spark, sf, stream_key="user_id"), 3, 10, 2, rule="light", min_weight=3.0)


SMALL = "with s as (select n_nationkey as id, (n_nationkey * n_nationkey * 7 + n_nationkey * 3) % 101 as c from nation), g as (select a.id as p, b.id as m, abs(a.c - b.c) as g from s a, s b)"


@query("exact_kmedian_k1", SMALL + " select sum(g)::bigint as cost, m::bigint as m1 from g group by m order by cost, m1 limit 1")
def exact_kmedian_k1(spark, sf):
    return bm.exact_kmedian(nation_points(spark, sf), 1, 1, "manhattan").select(F.col("cost").cast("long").alias("cost"), "m1")


@query("exact_kmedian_k2", SMALL + " select sum(least(a.g, b.g))::bigint as cost, a.m::bigint as m1, b.m::bigint as m2 from g a join g b on a.p = b.p and a.m < b.m group by a.m, b.m order by cost, m1, m2 limit 1")
def exact_kmedian_k2(spark, sf):
    return bm.exact_kmedian(nation_points(spark, sf), 2, 1, "manhattan").select(F.col("cost").cast("long").alias("cost"), "m1", "m2")


def _cost(column):
    return lambda spark, sf: ms.clustering_cost(events_points(spark, sf), fixed_medians(spark, sf), 1).select(F.round(column, 3).alias(column))


for _c, _sql in (("kmedian_cost", "sum(dist)"), ("ssq", "sum(dist * dist)"), ("max_dist", "max(dist)")):
    Q[_c], SQL[_c] = _cost(_c), f"{NEAR} select round({_sql}, 3) as {_c} from a"


CHARGES = {"service_cost": "p.service / 100.0", "facility_cost": "20.0 * len(p.x)", "total_cost": "p.service / 100.0 + 20.0 * len(p.x)"}
for _c, _sql in CHARGES.items():
    Q[_c] = lambda spark, sf, c=_c: ms.online_cost(mn.pass_stream(events_points(spark, sf, scale=100.0), 2000.0), 2000.0).select(F.round(F.col(c) / 100, 2).alias(c))
    SQL[_c] = pass_sql(PRICED) + f" select round(({_sql})::double, 2) as {_c} from done"


OUT = "o as (select stream_key, v.id as median_id, v.w as weight, v.first as first_phase, v.settled as settled_phase from (select stream_key, unnest(verdicts) as v from result) where v.verdict = 'outlier')"


@query("outlier_count", USERS_SQL + f", {OUT} select count(distinct median_id) as outliers, coalesce(sum(weight), 0)::double as outlier_weight from o")
def outlier_count(spark, sf):
    return ms.outlier_count(users_miner(spark, sf).verdicts)


@query("miner_outliers", USERS_SQL + f", {OUT} select o.stream_key, median_id, round(x, 6) as x, weight, first_phase, settled_phase from o join points on points.stream_key = o.stream_key and points.id = median_id")
def miner_outliers(spark, sf):
    return users_miner(spark, sf).outliers.select("stream_key", "median_id", F.round(F.col("vec")[0], 6).alias("x"), "weight", "first_phase", "settled_phase")


@query("miner_outliers_stream", miner_sql(EVENTS, k=3, num=500, runs=3, growth="on_breach") + VERDICTS + " where v.verdict = 'outlier'")
def miner_outliers_stream(spark, sf):
    return events_miner(spark, sf, ("verdicts",)).verdicts.where("verdict = 'outlier'")


LOGS = "g as (select stream_key, unnest(log) as l from result)"


@query("space_vs_caps", USERS_SQL + f", {LOGS} select stream_key, max(l.medians_out)::bigint as medians_max, 2::bigint as k, round(2 * ln(10000), 6) as k_log_n, round(4 * 2 * (1 + ln(10000)) * 273, 3) as cap, (max(l.medians_out) * 24)::bigint as bytes from g group by 1")
def space_vs_caps(spark, sf):
    out = ms.space_report(users_miner(spark, sf).phase_log, k=2, n=10_000, gamma=34, beta=34)
    return out.select("stream_key", "medians_max", "k", F.round("k_log_n", 6).alias("k_log_n"), F.round("cap", 3).alias("cap"), F.col("bytes").cast("long").alias("bytes"))


@query("progress", USERS_SQL + f", {LOGS} select stream_key, count(*) as phases, min(l.points_read) as min_new_points, round(avg(l.points_read), 6) as mean_new_points, sum((l.stop_reason <> 'end')::int)::bigint as breaches from g group by 1")
def progress(spark, sf):
    return ms.progress(users_miner(spark, sf).phase_log).withColumn("mean_new_points", F.round("mean_new_points", 6))


@query("ratio_tiny", SMALL + ", o as (select min(c) as optimum from (select sum(least(a.g, b.g)) as c from g a join g b on a.p = b.p and a.m < b.m group by a.m, b.m)), c as (select sum(d) as cost from (select p, min(g) as d from g where m in (0, 12) group by p)) select cost::bigint as cost, optimum::bigint as optimum, round(cost / optimum, 6) as ratio from c, o")
def ratio_tiny(spark, sf):
    p = nation_points(spark, sf)
    out = ms.approx_ratio(p, p.where("point_id in (0, 12)").select(F.col("point_id").alias("median_id"), "vec"), 2, 1)
    return out.select(F.col("cost").cast("long").alias("cost"), F.col("optimum").cast("long").alias("optimum"), F.round("ratio", 6).alias("ratio"))


SEEDS = (1, 2, 3, 4)


def seeded(seed: int) -> str:
    sql = miner_sql(USERS, k=2, num=10, runs=1, growth="on_breach", seed=seed)
    return f"select {seed} as seed, coalesce(list(v.id) filter (v.verdict = 'outlier'), []) as ids, any_value(cost) as cost, any_value(medians) as medians from (select unnest(verdicts) as v, sum(list_sum(list_transform(log, lambda l: l.total_cost))) over () as cost, sum(len(cid)) over ()::bigint as medians from ({sql} select * from result))"


SEED_ROWS = "r as (" + " union all ".join(seeded(s) for s in SEEDS) + ")"


def seed_runs(spark, sf):
    """(seed, median_ids, cost, medians): the outliers of all users' streams, the sum of costs, the medians held."""
    points = events_points(spark, sf, stream_key="user_id")
    rows = None
    for seed in SEEDS:
        r = stored(mn.mine_outliers(points, Settings(k=2, num=10, runs=1, seed=seed, floor_growth="on_breach")).tagged, "seeds")
        r = mn.MinerResult(r)
        ids = r.verdicts.agg(F.collect_list(F.when(F.col("verdict") == "outlier", F.col("median_id"))).alias("median_ids"))
        last = r.final()[0].agg(F.count("*").alias("medians"))
        one = ids.join(F.broadcast(r.phase_log.agg(F.sum("total_cost").alias("cost"))), F.lit(True)).join(F.broadcast(last), F.lit(True)).select(F.lit(seed).alias("seed"), "median_ids", "cost", "medians")  # one row each
        rows = one if rows is None else rows.unionByName(one)
    return rows


@query("stability", f"with {SEED_ROWS}, p as (select avg(case when len(list_distinct(list_concat(a.ids, b.ids))) = 0 then 1.0 else len(list_intersect(a.ids, b.ids))::double / len(list_distinct(list_concat(a.ids, b.ids))) end) as j from r a join r b on a.seed < b.seed) select count(*) as seeds, round(any_value(j), 6) as mean_jaccard, round(stddev_samp(len(ids)), 6) as sd_outliers, round(stddev_samp(cost), 2) as sd_cost, round(stddev_samp(medians), 6) as sd_medians from r, p")
def stability(spark, sf):
    """Outlier sets, costs and median counts over seeds."""
    out = ms.seed_table(seed_runs(spark, sf))
    return out.select("seeds", *(F.round(c, n).alias(c) for c, n in (("mean_jaccard", 6), ("sd_outliers", 6), ("sd_cost", 2), ("sd_medians", 6))))


@query("success_share", f"with {SEED_ROWS}, b as (select min(cost) as least from r) select count(*) as seeds, 1.05::double as bound, round(avg((cost <= 1.05 * least)::int), 6) as share from r, b")
def success_share(spark, sf):
    """Share of seeds whose cost is within 1.05 of the best."""
    costs = {r.seed: r.cost for r in seed_runs(spark, sf).select("seed", "cost").collect()}  # one row a seed
    return spark.createDataFrame([ms.success_share(costs, 1.05)], "seeds long, bound double, share double")


@query("miner_overlap", USERS_SQL + f", {OUT}, z as (select event_id as id from events, (select avg(value) as c, stddev_samp(value) as w from events) where abs(value - c) / w > 3), u as (select x.median_id as a, z.id as b from (select distinct median_id from o) x full join z on x.median_id = z.id) select count(*) filter (a = b) as both, count(*) filter (b is null) as only_a, count(*) filter (a is null) as only_b, round(count(*) filter (a = b) / count(*), 6) as jaccard from u")
def miner_overlap(spark, sf):
    """The miner's outliers and those of the z-score baseline (C14)."""
    mine = users_miner(spark, sf).verdicts.where("verdict = 'outlier'").select(F.col("median_id").alias("point_id"))
    out = ms.overlap(mine, bs.stat_outliers(events_points(spark, sf), "zscore", 3.0))
    return out.select("both", "only_a", "only_b", F.round("jaccard", 6).alias("jaccard"))


A_B = "a as (select event_id as id from events, (select avg(value) as c, stddev_samp(value) as w from events) where abs(value - c) / w > 3), b as (select event_id as id from events, (select quantile_cont(value, 0.25) as lo, quantile_cont(value, 0.75) as hi from events) where greatest(lo - value, value - hi) / (hi - lo) > 1.5)"


@query("overlap", f"with {A_B}, u as (select a.id as x, b.id as y from a full join b on a.id = b.id) select count(*) filter (x = y) as both, count(*) filter (y is null) as only_a, count(*) filter (x is null) as only_b, round(count(*) filter (x = y) / count(*), 6) as jaccard from u")
def overlap(spark, sf):
    p = events_points(spark, sf)
    out = ms.overlap(bs.stat_outliers(p, "zscore", 3.0), bs.stat_outliers(p, "iqr", 1.5))
    return out.select("both", "only_a", "only_b", F.round("jaccard", 6).alias("jaccard"))


@query("except_outliers", f"with {A_B} select id as point_id from b except select id from a")
def except_outliers(spark, sf):
    p = events_points(spark, sf)
    return bs.stat_outliers(p, "iqr", 1.5).select("point_id").exceptAll(bs.stat_outliers(p, "zscore", 3.0).select("point_id"))


@query("balance", NEAR + ", c as (select median_id, count(*) as c from a group by 1) select count(*) as clusters, min(c) as smallest, max(c) as largest, round(max(c) / min(c), 6) as ratio from c")
def balance(spark, sf):
    a = mn.assign(events_points(spark, sf), fixed_medians(spark, sf), 1)
    return ms.balance(a).select("clusters", "smallest", "largest", F.round("ratio", 6).alias("ratio"))


@query("prf", "with s as (select avg(value) as c, stddev_samp(value) as w from events), r as (select event_id as id, abs(value - c) / w as score, (event_type = 'error')::int as hit from events, s where abs(value - c) / w > 2), t as (select count(*) as positives from events where event_type = 'error'), o as (select *, row_number() over w1 as i, sum(hit) over w1 as hits from r window w1 as (order by score desc, id rows unbounded preceding)), x as (select coalesce(sum(hit), 0)::bigint as tp, count(*) as found, coalesce(sum(case when hit = 1 then hits / i end), 0) as ap from o) select tp, found - tp as fp, positives - tp as fn, round(tp / found, 6) as precision, round(tp / positives, 6) as recall, round(2.0 * tp / (found + positives), 6) as f1, round(ap / positives, 6) as average_precision from x, t")
def prf(spark, sf):
    ranked = bs.stat_outliers(events_points(spark, sf), "zscore", 2.0)
    truth = table(spark, sf, "events").where("event_type = 'error'").select(F.col("event_id").alias("point_id"))
    out = ms.detection_quality(ranked, truth)
    return out.select("tp", "fp", "fn", *(F.round(c, 6).alias(c) for c in ("precision", "recall", "f1", "average_precision")))


@query("delay", USERS_SQL + f", {OUT} select round(avg(settled_phase - first_phase), 6) as mean_phases, max(settled_phase - first_phase) as max_phases, round(avg(settled_phase - first_phase) * 10, 4) as mean_points from o")
def delay(spark, sf):
    """From the first flag of an outlier of the miner to its verdict (C17)."""
    out = ms.detection_delay(users_miner(spark, sf).verdicts, 10)
    return out.select(F.round("mean_phases", 6).alias("mean_phases"), "max_phases", F.round("mean_points", 4).alias("mean_points"))


@query("sparse_gap", USERS_SQL + f", {OUT}, c as (select event_id as id, cast(round(value * 100) as bigint) as cents from events), n as (select id, least(cents - lag(cents) over w, lead(cents) over w - cents) as g from c window w as (order by cents, id)), r as (select *, percent_rank() over (order by g) as q from n) select id as point_id, g::double as nn_dist, round(q, 6) as dataset_quantile from r where id in (select median_id from o)")
def sparse_gap(spark, sf):
    """How far the miner's outliers lie from their nearest event, among all events."""
    mine = users_miner(spark, sf).verdicts.where("verdict = 'outlier'").select(F.col("median_id").alias("point_id"))
    out = ms.sparse_gap(events_points(spark, sf, scale=100.0), mine, 1)
    return out.select("point_id", "nn_dist", F.round("dataset_quantile", 6).alias("dataset_quantile"))


@query("caps_grid", "select k::bigint as k, event_type, n, round(4 * k * (1 + ln(n)) * 273, 3) as cap from range(1, 11) a(k), (select event_type, count(value) as n from events group by event_type) b")
def caps_grid(spark, sf):
    """State cap against k and the length of each type's stream: it grows with log n only."""
    n = table(spark, sf, "events").groupBy("event_type").agg(F.count("value").alias("n"))
    k = spark.range(1, 11).withColumnRenamed("id", "k")
    return n.join(F.broadcast(k), F.lit(True)).select("k", "event_type", "n", F.round(4 * F.col("k") * (1 + F.log("n")) * multiplier(34, 34), 3).alias("cap"))
