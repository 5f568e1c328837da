"""The experiment workloads on the given tables, and parameter sweeps.  (W1-W11, M29)

Each function takes (spark, sf_dir, ...) and returns named DataFrames.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import replace
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.means import lloyd_kernel, mean_miner
from ..baselines.neighbours import db_outliers, knn_rank
from ..functions.coding import Feature, feature_columns
from ..functions.distance import block_distances
from ..operators import measures as ms
from ..operators.engine import Miner, Settings
from ..operators.miner import MinerResult, assign, mine_outliers, mine_single_stream
from ..operators.points import chunk_by_window, scale, to_points
from ..operators.sweeping import streams, sweep_stream
from ..sources.shared import stored
from ..sources.tables import embedding_points, events_points, lineitem_points, orders_points, table


def _report(points: DataFrame, r: MinerResult, d: int) -> dict[str, DataFrame]:
    held = r.final()[0].select("stream_key", "median_id", "vec")
    cost, counts = ms.clustering_cost(points, held, d), ms.outlier_count(r.verdicts)
    paid = r.phase_log.groupBy("stream_key").agg(F.sum("total_cost").alias("online_cost"), F.max("phase").alias("phases"))
    table = paid.join(cost, "stream_key").join(F.broadcast(counts), F.lit(True))  # one row each
    table = table.select("phases", "outliers", "outlier_weight", F.col("ssq").alias("squared_distance"), F.col("kmedian_cost").alias("cost"), "online_cost")
    return {"points": points, "phase_log": r.phase_log, "run_log": r.run_log, "verdicts": r.verdicts, "outliers": r.outliers, "cost": cost, "balance": ms.balance(assign(points, held, d)), "outlier_count": counts, "table": table}


def mixed_table(spark: SparkSession, sf_dir: str, num: int = 500, rows: int | None = None, **more) -> dict[str, DataFrame]:
    """Mixed rows of eight attributes, scaled to 0..1; k = 2, O = 2.  ``rows`` = 4177 is the size of the
    first published table, None takes all.  "table" holds outliers, squared distance and cost together."""
    points = scale(lineitem_points(spark, sf_dir, rows), "minmax", 8)
    return _report(points, mine_single_stream(points, Settings(**{"k": 2, "outlier_phases": 2, "num": num} | more)), 8)


def three_class_table(spark: SparkSession, sf_dir: str, num: int = 50, rows: int | None = None, **more) -> dict[str, DataFrame]:
    """Rows of five attributes; k = 3, O = 3.  ``rows`` = 151 is the size of the second published table."""
    points = scale(orders_points(spark, sf_dir, rows), "minmax", 5)
    return _report(points, mine_single_stream(points, Settings(**{"k": 3, "outlier_phases": 3, "num": num} | more)), 5)


#: Fixed values of the published timing: neighbours and ranks, share and radius.
RANKED, NEIGHBOURS, SHARE, RADIUS = 7, 3, 0.95, 0.45


def method_timing(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (151, 4177), num: int = 500) -> DataFrame:
    """(method, n, wall_s, cpu_s) of the four methods at the published sizes and parameters, with the
    executors' CPU time; the methods' kernels are also timed alone, in one thread without Spark."""
    rows = []
    for n in sizes:
        made = lineitem_points(spark, sf_dir, n) if n > 1000 else orders_points(spark, sf_dir, n)
        d = 8 if n > 1000 else 5
        points = stored(scale(made, "minmax", d), "timed")
        k = 2 if n > 1000 else 3
        methods = {
            "phased miner": lambda p=points, k=k: mine_outliers(p, Settings(k=k, outlier_phases=k, num=num)).phase_log.collect(),
            "chunked mean miner": lambda p=points, k=k: mean_miner(p, k, num, k).collect(),
            "kNN-rank": lambda p=points, d=d: knn_rank(p, NEIGHBOURS, RANKED, d=d, method="block").collect(),
            "distance-fraction": lambda p=points, d=d: db_outliers(p, RADIUS, SHARE, d=d).collect(),
        }
        for name, action in methods.items():
            rows += ms.timed(spark, name, n, action)
        local = points.orderBy("ordinal").toPandas()
        rows += kernel_timing(np.stack(local["vec"].to_numpy()), k, num)
    return spark.createDataFrame(rows, "method string, n long, wall_s double, cpu_s double")


def kernel_timing(x: np.ndarray, k: int, num: int = 500) -> list[tuple]:
    """(method, n, None, CPU seconds) of the four methods on one thread."""
    n, w, out = len(x), np.ones(len(x)), []

    def take(name: str, action) -> None:
        began = time.thread_time()
        action()
        out.append((f"{name}, kernel", n, None, time.thread_time() - began))

    for runs in (1, None):
        take(f"phased miner, {'all' if runs is None else runs} runs", lambda runs=runs: Miner(Settings(k=k, outlier_phases=k, num=num, runs=runs), x.shape[1]).run(np.arange(n), x, w))
    take("chunked mean miner", lambda: [lloyd_kernel(x[at : at + num], w[at : at + num], k, 10) for at in range(0, n, num)])

    def ranked():
        for at in range(0, n, 256):
            gap = block_distances("euclidean", x[at : at + 256], x)
            gap[np.arange(len(gap)), np.arange(at, at + len(gap))] = np.inf
            np.partition(gap, NEIGHBOURS - 1, axis=1)

    take("kNN-rank", ranked)
    take("distance-fraction", lambda: [(block_distances("euclidean", x[at : at + 256], x) <= RADIUS).sum(1) for at in range(0, n, 256)])
    return out


def evolving_windows(spark: SparkSession, sf_dir: str, radius: float = 10.0, seconds: int = 3600, fewest: int = 2) -> DataFrame:
    """(event_id, day, near, near_next_day, dense_next_day) of the points of a day with fewer than
    ``fewest`` neighbours on (value, second of day), and whether the next day has made their place dense.
    A range join by cells: a point meets the cells around it, then distances decide."""
    t = F.col("ts").cast("timestamp")
    e = chunk_by_window(table(spark, sf_dir, "events"), "ts", "1 day").select("event_id", "value", (F.hour(t) * 3600 + F.minute(t) * 60 + F.second(t)).alias("second"), F.to_date("window_start").alias("day"))
    e = e.withColumn("cv", F.floor(F.col("value") / radius)).withColumn("cs", F.floor(F.col("second") / seconds))
    around = lambda c: F.explode(F.array(*(F.col(c) + s for s in (-1, 0, 1)))).alias(c)
    mine = e.select("event_id", F.col("value").alias("v"), F.col("second").alias("s"), "day", around("cv"), "cs").select("event_id", "v", "s", "day", "cv", around("cs"))
    mine = mine.withColumn("at", F.explode(F.array("day", F.date_add("day", 1))))
    others = e.select(F.col("event_id").alias("other"), "value", "second", F.col("day").alias("at"), "cv", "cs")
    met = mine.join(others, ["at", "cv", "cs"]).where((F.col("event_id") != F.col("other")) & (F.abs(F.col("v") - F.col("value")) <= radius) & (F.abs(F.col("s") - F.col("second")) <= seconds))
    counts = met.groupBy("event_id").agg(F.count(F.when(F.col("at") == F.col("day"), 1)).alias("near"), F.count(F.when(F.col("at") != F.col("day"), 1)).alias("near_next_day"))
    out = e.join(counts, "event_id", "left").select("event_id", "day", F.coalesce("near", F.lit(0)).alias("near"), F.coalesce("near_next_day", F.lit(0)).alias("near_next_day"))
    return out.where(F.col("near") < fewest).withColumn("dense_next_day", F.col("near_next_day") >= fewest)


def handover_trace(spark: SparkSession, sf_dir: str, keep: tuple[str, ...] = ("medians", "phase_log", "verdicts"), **more) -> dict[str, DataFrame]:
    """Medians handed from phase to phase on every user's events, under one floor that stays; the tables in ``keep``."""
    r = mine_outliers(events_points(spark, sf_dir, stream_key="user_id"), Settings(**{"k": 2, "num": 5, "runs": 1, "floor_growth": "none", "floor": 40.0} | more), keep=keep)
    return {name: r.table(name) for name in keep}


def sweep(points: DataFrame, base: Settings, grid: dict[str, list]) -> DataFrame:
    """(cell, settings, streams, phases, outliers, total_cost, medians): every stream under every setting, sums over
    streams.  Points move once; a stream's task does all cells, and cells that decide alike are done once.  (M29)"""
    spark = points.sparkSession
    cells = [dict(zip(grid, values, strict=True)) for values in product(*grid.values())]
    settings = [replace(base, **c) for c in cells]
    schema = "cell int, streams long, phases long, outliers long, total_cost double, medians long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = [[0, 0, 0, 0.0, 0] for _ in settings]
        for stream in streams(batches):
            for one, found in zip(sums, sweep_stream(settings, *stream), strict=True):
                one[:] = [a + b for a, b in zip(one, (1, *found), strict=True)]
        if sums and sums[0][0]:
            rows = [pa.array(range(len(sums)), pa.int32()), *(pa.array(c) for c in zip(*sums, strict=True))]
            yield pa.RecordBatch.from_arrays(rows, names=[c.split()[0] for c in schema.split(", ")])

    placed = points.select("stream_key", "ordinal", "point_id", "vec", "weight").repartition("stream_key").sortWithinPartitions("stream_key", "ordinal")
    each = placed.mapInArrow(run, schema)
    names = spark.createDataFrame([(i, str(c)) for i, c in enumerate(cells)], "cell int, settings string")
    total = each.groupBy("cell").agg(*(F.sum(c).alias(c) for c in ("streams", "phases", "outliers", "total_cost", "medians")))
    return total.join(F.broadcast(names), "cell").select("cell", "settings", "streams", "phases", "outliers", "total_cost", "medians")


def constant_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The constants gamma and beta, with feasible pairs among them, on every user's events."""
    points = events_points(spark, sf_dir, stream_key="user_id", ranked=False)  # a sweep needs the order only
    return sweep(points, Settings(k=2, num=10, runs=1), {"gamma": [18.0, 20.0, 22.0, 34.0], "beta": [34.0, 68.0, 104.0, 170.0]})


def setting_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """K, O and the chunk size, on every user's events."""
    points = events_points(spark, sf_dir, stream_key="user_id", ranked=False)  # a sweep needs the order only
    return sweep(points, Settings(runs=1, floor_growth="on_breach"), {"k": [1, 2, 5, 10], "outlier_phases": [1, 2, 3], "num": [5, 10, 20]})


def live_events(spark: SparkSession, source: str, schema, settings: Settings, **more) -> DataFrame:
    """Verdicts of per-user streams from a folder of event files."""
    from ..sources.tables import read_stream
    from ..streaming.live import live_points, mine_outliers_stream

    return mine_outliers_stream(live_points(read_stream(spark, source, schema)), settings, 1, **more)


def text_codes(spark: SparkSession, sf_dir: str, **more) -> dict[str, DataFrame]:
    """Documents as six character statistics of their whole texts; both labels as weak truth."""
    t = F.coalesce("text", F.lit(""))
    n = F.greatest(F.length(t), F.lit(1))
    share = lambda p: F.length(F.regexp_replace(t, p, "")) / n
    kinds = Feature(t, "mean", coding="ascii_mean")
    docs = table(spark, sf_dir, "documents")
    mean = feature_columns(docs, [kinds])[0] / 255.0
    df = docs.select("doc_id", F.log(n.cast("double")).alias("size"), mean.alias("mean"), share("[^0-9]").alias("digits"), share("[^A-Z]").alias("capitals"), share(r"[\p{L}\p{N}\s]").alias("marks"), (F.size(F.array_distinct(F.split(t, ""))) / n).alias("distinct"))
    points = scale(to_points(df, ["doc_id"], ["size", "mean", "digits", "capitals", "marks", "distinct"], point_id="doc_id"), "minmax", 6)
    r = mine_single_stream(points, Settings(**{"k": 4, "outlier_phases": 2, "num": 100, "floor_growth": "on_breach", "runs": 3} | more))
    labels = table(spark, sf_dir, "labels")
    ranked = r.verdicts.where("verdict = 'outlier'").select(F.col("median_id").alias("point_id"), F.col("score").cast("double").alias("score"))
    truth = {"quality": labels.where("quality = 0"), "toxic": labels.where("toxic = 1")}
    scored = [ms.detection_quality(ranked, rows.select(F.col("doc_id").alias("point_id"))).withColumn("label", F.lit(name)) for name, rows in truth.items()]
    return {"points": points, "verdicts": r.verdicts, "quality": scored[0].unionByName(scored[1])}


def vector_clusters(spark: SparkSession, sf_dir: str, k: int = 10, **more) -> dict[str, DataFrame]:
    """64-dimensional vectors; purity of the labels by nearest median."""
    points = embedding_points(spark, sf_dir)
    r = mine_single_stream(points, Settings(**{"k": k, "num": 250, "runs": 1, "floor_growth": "on_breach"} | more))
    near = assign(points, r.final()[0].select("stream_key", "median_id", "vec"), 64)
    labels = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("point_id"), "label")
    c = near.join(labels, "point_id").groupBy("median_id", "label").agg(F.count("*").alias("c"))
    best = c.groupBy("median_id").agg(F.max("c").alias("best"), F.sum("c").alias("all"))
    return {"phase_log": r.phase_log, "purity": best.agg((F.sum("best") / F.sum("all")).alias("purity"), F.count("*").alias("medians"))}


def customer_spend(spark: SparkSession, sf_dir: str, **more) -> MinerResult:
    """Every customer's orders as a stream of total prices."""
    points = to_points(table(spark, sf_dir, "orders"), ["o_orderdate", "o_orderkey"], ["o_totalprice"], point_id="o_orderkey", stream_key="o_custkey")
    return mine_outliers(points, Settings(**{"k": 1, "num": 5, "runs": 1} | more))


def supplier_prices(spark: SparkSession, sf_dir: str, **more) -> MinerResult:
    """Every supplier's lines as a stream of (unit price, discount)."""
    df = table(spark, sf_dir, "lineitem").where("l_quantity > 0").withColumn("unit", F.col("l_extendedprice") / F.col("l_quantity"))
    points = to_points(df, ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "unit", "l_discount"], ["unit", "l_discount"], stream_key="l_suppkey")
    return mine_outliers(points, Settings(**{"k": 2, "num": 50, "runs": 1} | more))


def planted(points: DataFrame, at: list[int], value: float, d: int) -> DataFrame:
    """``points`` with the vectors at these ordinals moved far away (truth for detection measures)."""
    far = F.array(*(F.lit(value) for _ in range(d)))
    return points.withColumn("vec", F.when(F.col("ordinal").isin(at), far).otherwise(F.col("vec")))
