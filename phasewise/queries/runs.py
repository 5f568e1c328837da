"""Queries of workloads, streaming twins and the SQL surface (rows only: sequential or sampled)."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import sqlapi
from ..operators.engine import Settings
from ..plans import workloads as wl
from ..sources.tables import events_points, table
from .miner_sql import USERS, miner_sql

Q: dict = {}
PHASES = "select stream_key, l.phase, l.points_read, l.points_in - l.points_read as unread, l.medians_out, l.stop_reason from (select stream_key, unnest(log) as l from result)"
NEAR_DAYS = "select a.event_id, strftime(a.day, '%Y-%m-%d') as day, count(*) filter (b.day = a.day) as near, count(*) filter (b.day = a.day + 1) as near_next_day from e a left join e b on b.day in (a.day, a.day + 1) and a.event_id <> b.event_id and abs(a.value - b.value) <= 10 and abs(a.s - b.s) <= 3600 group by 1, 2"
SQL: dict[str, str] = {
    "evolving_windows": f"with e as (select event_id, ts::date as day, value, hour(ts) * 3600 + minute(ts) * 60 + second(ts) as s from events), n as ({NEAR_DAYS}) select *, near_next_day >= 2 as dense_next_day from n where near < 2",
    "handover_phases": miner_sql(USERS, k=2, num=5, runs=1, growth="none", floor=40.0) + "select stream_key, l.phase, l.points_read::int as points_read, l.new_medians, l.medians_out from (select stream_key, unnest(log) as l from result)",
    "miner_limits": miner_sql(USERS, k=2, num=10, runs=2, caps=(None, 8.0)) + PHASES,
    "sweep_constants": "with a as (" + " union all ".join(f"select {i} as cell, * from ({miner_sql(USERS, k=2, num=10, runs=1, gamma=g, beta=b)} select * from result)" for i, (g, b) in enumerate((g, b) for g in (18.0, 20.0, 22.0, 34.0) for b in (34.0, 68.0, 104.0, 170.0))) + ") select cell, count(*) as streams, sum(phase)::bigint as phases, sum(len(list_filter(verdicts, lambda v: v.verdict = 'outlier')))::bigint as outliers, sum(len(cid))::bigint as medians from a group by 1",
}


def query(f):
    Q[f.__name__] = f
    return f


@query
def evolving_windows(spark, sf):
    return wl.evolving_windows(spark, sf).withColumn("day", F.date_format("day", "yyyy-MM-dd"))


@query
def handover_phases(spark, sf):
    """What every phase of a user's stream reads, opens and hands to the next."""
    return wl.handover_trace(spark, sf, ("phase_log",))["phase_log"].select("stream_key", "phase", F.col("points_read").cast("int").alias("points_read"), "new_medians", "medians_out")


@query
def mixed_table(spark, sf):
    return wl.mixed_table(spark, sf, runs=3)["phase_log"]


@query
def mixed_table_cost(spark, sf):
    """Outliers, squared distance and cost of the mixed table (the first published table's outputs)."""
    return wl.mixed_table(spark, sf, runs=1)["table"]


@query
def three_class_table(spark, sf):
    return wl.three_class_table(spark, sf, runs=3, num=500)["phase_log"]


@query
def three_class_cost(spark, sf):
    """Outliers, squared distance and cost of the three-class table (the second published table's outputs)."""
    return wl.three_class_table(spark, sf, runs=1, num=500)["table"]


@query
def published_sizes(spark, sf):
    """Both published tables at their own sizes, one row each."""
    one = wl.mixed_table(spark, sf, rows=4177, runs=3)["table"].withColumn("rows", F.lit(4177))
    return one.unionByName(wl.three_class_table(spark, sf, rows=151, runs=3)["table"].withColumn("rows", F.lit(151)))


@query
def method_timing(spark, sf):
    """CPU seconds of the four methods at the published sizes and parameters."""
    return wl.method_timing(spark, sf)


@query
def three_class_balance(spark, sf):
    return wl.three_class_table(spark, sf, runs=1, num=500)["balance"]


@query
def sweep_constants(spark, sf):
    return wl.constant_sweep(spark, sf).select("cell", "streams", "phases", "outliers", "medians")


@query
def sweep_settings(spark, sf):
    return wl.setting_sweep(spark, sf)


@query
def text_codes_quality(spark, sf):
    return wl.text_codes(spark, sf)["quality"]


@query
def vector_purity(spark, sf):
    return wl.vector_clusters(spark, sf)["purity"]


@query
def customer_spend(spark, sf):
    return wl.customer_spend(spark, sf).verdicts


@query
def supplier_price_streams(spark, sf):
    return wl.supplier_prices(spark, sf).verdicts


@query
def sql_facility(spark, sf):
    sqlapi.register(spark)
    events_points(spark, sf, stream_key="user_id").createOrReplaceTempView("facility_points")
    return spark.sql("select * from facility_scan(table(select * from facility_points), 50.0D, 1)")


@query
def sql_summary(spark, sf):
    sqlapi.register(spark)
    table(spark, sf, "events").createOrReplaceTempView("summary_events")
    return spark.sql("select user_id, weighted_median_summary(value, 1.0D) as median from summary_events group by user_id")


@query
def miner_limits(spark, sf):
    """Every user's stream under a cap of eight medians: phases end early, and the rest heads the next one."""
    from ..operators.miner import mine_outliers

    r = mine_outliers(events_points(spark, sf, stream_key="user_id"), Settings(k=2, num=10, runs=2, median_cap=8, max_stalled_phases=50))
    return r.phase_log.select("stream_key", "phase", "points_read", "unread", "medians_out", "stop_reason")


@query
def compaction(spark, sf):
    """Re-passes over the medians of each user's stream until both limits hold."""
    from ..operators.miner import mine_outliers

    s = Settings(k=2, num=10, runs=1, repass=True, median_cap=6, cost_cap=1e60, max_stalled_phases=50)
    return mine_outliers(events_points(spark, sf, stream_key="user_id"), s).phase_log.select("stream_key", "phase", "points_read", "unread", "medians_out", "stop_reason")
