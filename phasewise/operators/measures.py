"""Cost and accuracy measures; each returns a small DataFrame with typed columns.  (C1-C18)"""

from __future__ import annotations

import time
from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.schedule import log, multiplier
from .miner import assign


def clustering_cost(points: DataFrame, medians: DataFrame, d: int, distance: str = "euclidean") -> DataFrame:
    """(stream_key, kmedian_cost, ssq, max_dist) at the nearest medians.  (C1, C2, C9)"""
    a = assign(points, medians, d, distance)
    return a.groupBy("stream_key").agg(F.sum(F.col("weight") * F.col("dist")).alias("kmedian_cost"), F.sum(F.col("weight") * F.col("dist") * F.col("dist")).alias("ssq"), F.max("dist").alias("max_dist"))


def online_cost(assignments: DataFrame, price: float) -> DataFrame:
    """(stream_key, service_cost, facility_cost, total_cost) as charged while reading.  (C3-C5)"""
    service, opened = F.sum(F.when(~F.col("opens"), F.col("dist") * F.col("weight")).otherwise(0.0)), F.sum(F.col("opens").cast("int"))
    return assignments.groupBy("stream_key").agg(service.alias("service_cost"), (opened * price).alias("facility_cost"), (service + opened * price).alias("total_cost"))


def outlier_count(verdicts: DataFrame) -> DataFrame:
    """(outliers, outlier_weight).  (C6)"""
    return verdicts.where("verdict = 'outlier'").agg(F.countDistinct("median_id").alias("outliers"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("outlier_weight"))


def executor_cpu(spark) -> float:
    """CPU seconds that tasks of this application have used in the JVMs so far, by Spark's own metrics."""
    store = spark._jsc.sc().statusStore()
    stages = store.stageList(None, False, False, spark._sc._gateway.new_array(spark._jvm.double, 0), None)
    return sum(stages.apply(i).executorCpuTime() for i in range(stages.size())) / 1e9


def _python_cpu() -> float:
    """CPU seconds of this process and of its ended children, with those of live Python workers (local mode)."""
    import os

    tick, me, total = os.sysconf("SC_CLK_TCK"), os.getpid(), 0.0
    parents, times = {}, {}
    for pid in filter(str.isdigit, os.listdir("/proc")):
        try:
            with open(f"/proc/{pid}/stat") as f:
                name, rest = f.read().rsplit(")", 1)
        except OSError:
            continue
        fields = rest.split()
        parents[int(pid)], times[int(pid)] = int(fields[1]), (sum(map(int, fields[11:15])) / tick, "java" in name)
    for pid, (seconds, java) in times.items():
        up = pid
        while up not in (0, 1, me) and up in parents:
            up = parents[up]
        if up == me and not java:
            total += seconds
    return total


def timed(spark, label: str, n: int, action: Callable, repeats: int = 1) -> list[tuple[str, int, float, float]]:
    """(label, n, wall seconds, CPU seconds of tasks and Python workers) of each repeat.  (C7)"""
    out = []
    for _ in range(repeats):
        wall, cpu, python = time.perf_counter(), executor_cpu(spark), _python_cpu()
        action()
        out.append((label, n, time.perf_counter() - wall, executor_cpu(spark) - cpu + _python_cpu() - python))
    return out


def space_report(phase_log: DataFrame, *, k: int, n: float, gamma: float, beta: float, d: int = 1, log_base: str = "e") -> DataFrame:
    """(stream_key, medians_max, k, k_log_n, cap, bytes).  (C8)"""
    logn = log(n, log_base)
    cap = 4 * k * (1 + logn) * multiplier(gamma, beta)
    most = F.max("medians_out")
    return phase_log.groupBy("stream_key").agg(most.cast("long").alias("medians_max")).select("stream_key", "medians_max", F.lit(k).cast("long").alias("k"), F.lit(k * logn).alias("k_log_n"), F.lit(float(cap)).alias("cap"), (F.col("medians_max") * (8 * (d + 2))).alias("bytes"))


def progress(phase_log: DataFrame) -> DataFrame:
    """(stream_key, phases, min_new_points, mean_new_points, breaches).  (C10)"""
    return phase_log.groupBy("stream_key").agg(F.count("*").alias("phases"), F.min("points_read").alias("min_new_points"), F.avg("points_read").alias("mean_new_points"), F.sum((F.col("stop_reason") != "end").cast("int")).alias("breaches"))


def approx_ratio(points: DataFrame, medians: DataFrame, k: int, d: int) -> DataFrame:
    """(cost, optimum, ratio) against the exact optimum.  (C11)"""
    from ..baselines.means import exact_kmedian

    cost = clustering_cost(points, medians, d).select(F.col("kmedian_cost").alias("cost"))
    best = exact_kmedian(points, k, d).select(F.col("cost").alias("optimum"))
    return cost.join(F.broadcast(best), F.lit(True)).select("cost", "optimum", (F.col("cost") / F.col("optimum")).alias("ratio"))


def success_share(costs: dict[int, float], bound: float) -> dict[str, float]:
    """Share of the seeds whose cost is within ``bound`` times the least.  (C12)"""
    best = min(costs.values())
    return {"seeds": len(costs), "bound": bound, "share": sum(c <= bound * best for c in costs.values()) / len(costs)}


def stability(results: dict[int, set], costs: dict[int, float], medians: dict[int, int]) -> dict[str, float]:
    """Mean pairwise Jaccard of outlier sets and deviations over seeds.  (C13)"""
    pairs = list(combinations(results, 2))
    jaccard = [len(results[a] & results[b]) / len(results[a] | results[b]) if results[a] | results[b] else 1.0 for a, b in pairs]

    def sd(values) -> float:
        values = list(values)
        m = sum(values) / len(values)
        return (sum((v - m) ** 2 for v in values) / max(len(values) - 1, 1)) ** 0.5

    return {"pairs": len(pairs), "mean_jaccard": sum(jaccard) / len(jaccard) if jaccard else 1.0, "sd_outliers": sd(len(r) for r in results.values()), "sd_cost": sd(costs.values()), "sd_medians": sd(medians.values())}


def seed_table(runs: DataFrame) -> DataFrame:
    """(seeds, mean_jaccard, sd_outliers, sd_cost, sd_medians) from (seed, median_ids, cost, medians), one row a
    seed, inside Spark: pairs of seeds are joined, their sets compared.  (C13)"""
    a, b = (runs.select(F.col("seed").alias(f"seed_{s}"), F.col("median_ids").alias(f"ids_{s}")) for s in ("a", "b"))
    union = F.size(F.array_union("ids_a", "ids_b"))
    pairs = a.join(F.broadcast(b), F.col("seed_a") < F.col("seed_b")).agg(F.avg(F.when(union == 0, 1.0).otherwise(F.size(F.array_intersect("ids_a", "ids_b")) / union)).alias("mean_jaccard"))  # one row a seed
    spread = runs.agg(F.count("*").alias("seeds"), F.stddev_samp(F.size("median_ids")).alias("sd_outliers"), F.stddev_samp("cost").alias("sd_cost"), F.stddev_samp("medians").alias("sd_medians"))
    return spread.join(F.broadcast(pairs), F.lit(True)).select("seeds", "mean_jaccard", "sd_outliers", "sd_cost", "sd_medians")


def overlap(a: DataFrame, b: DataFrame, key: str = "point_id") -> DataFrame:
    """(both, only_a, only_b, jaccard) of two sets of ids.  (C14)"""
    x, y = a.select(key).distinct().withColumn("in_a", F.lit(1)), b.select(key).distinct().withColumn("in_b", F.lit(1))
    u = x.join(y, key, "full_outer")
    both = F.count(F.when(F.col("in_a").isNotNull() & F.col("in_b").isNotNull(), 1))
    return u.agg(both.alias("both"), F.count(F.when(F.col("in_b").isNull(), 1)).alias("only_a"), F.count(F.when(F.col("in_a").isNull(), 1)).alias("only_b"), (both / F.greatest(F.count("*"), F.lit(1))).alias("jaccard"))


def balance(assignments: DataFrame) -> DataFrame:
    """(clusters, smallest, largest, ratio) of members by median.  (C15)"""
    c = assignments.groupBy("median_id").agg(F.count("*").alias("c"))
    return c.agg(F.count("*").alias("clusters"), F.min("c").alias("smallest"), F.max("c").alias("largest"), (F.max("c") / F.min("c")).alias("ratio"))


def detection_quality(ranked: DataFrame, truth: DataFrame, key: str = "point_id") -> DataFrame:
    """(tp, fp, fn, precision, recall, f1, average_precision) of (key, score) rows against true ids.  (C16)"""
    t = truth.select(key).distinct().withColumn("is_true", F.lit(1))
    r = ranked.join(t, key, "left").withColumn("hit", F.coalesce("is_true", F.lit(0)))
    n_true = t.agg(F.count("*").alias("positives"))
    order = W.orderBy(F.desc("score"), key)
    at = r.withColumn("i", F.row_number().over(order)).withColumn("hits", F.sum("hit").over(order.rowsBetween(W.unboundedPreceding, 0)))
    s = at.agg(F.coalesce(F.sum("hit"), F.lit(0)).alias("tp"), F.count("*").alias("found"), F.coalesce(F.sum(F.when(F.col("hit") == 1, F.col("hits") / F.col("i"))), F.lit(0.0)).alias("ap"))
    s = s.join(F.broadcast(n_true), F.lit(True))
    precision, recall = F.col("tp") / F.greatest("found", F.lit(1)), F.col("tp") / F.greatest("positives", F.lit(1))
    f1 = F.when(precision + recall > 0, 2 * precision * recall / (precision + recall)).otherwise(0.0)
    return s.select("tp", (F.col("found") - F.col("tp")).alias("fp"), (F.col("positives") - F.col("tp")).alias("fn"), precision.alias("precision"), recall.alias("recall"), f1.alias("f1"), (F.col("ap") / F.greatest("positives", F.lit(1))).alias("average_precision"))


def detection_delay(verdicts: DataFrame, num: int) -> DataFrame:
    """(mean_phases, max_phases, mean_points) from the first flag to the verdict.  (C17)"""
    wait = F.col("settled_phase") - F.col("first_phase")
    return verdicts.where("verdict = 'outlier'").agg(F.avg(wait).alias("mean_phases"), F.max(wait).alias("max_phases"), (F.avg(wait) * num).alias("mean_points"))


def sparse_gap(points: DataFrame, outlier_ids: DataFrame, d: int) -> DataFrame:
    """(point_id, nn_dist, dataset_quantile): nearest-neighbour distance of outliers among all points'.  One
    dimension takes tables of any size, more dimensions the guard of the all-pairs baselines.  (C18)"""
    from ..baselines.neighbours import kth_distances, nearest_gaps
    from .points import with_ordinal

    nn = nearest_gaps(points) if d == 1 else kth_distances(points, 1, d, method="block")
    ranked = with_ordinal(nn, ["dist", "point_id"], name="o")
    # equal distances share their first place
    first = ranked.groupBy("dist").agg(F.min("o").alias("first"))
    n = ranked.agg(F.count("*").alias("n"))
    some = ranked.join(F.broadcast(outlier_ids.select("point_id").distinct()) if outlier_ids.count() <= 100_000 else outlier_ids.select("point_id").distinct(), "point_id")
    share = F.when(F.col("n") > 1, (F.col("first") - 1) / (F.col("n") - 1)).otherwise(0.0)
    return some.join(first, "dist").join(F.broadcast(n), F.lit(True)).select("point_id", F.col("dist").alias("nn_dist"), share.alias("dataset_quantile"))
