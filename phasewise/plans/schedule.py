"""Floors, prices, limits and numbers of runs; checks of the constants.  (M5-M7, M17)"""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.distance import distance_expr, vector

LOGS = {"e": math.log, "2": math.log2, "10": math.log10}


def log(n: float, base: str = "e") -> float:
    return LOGS[base](max(n, 1))


def multiplier(gamma: float, beta: float) -> float:
    """What both limits hold: 1 + 4 (gamma + beta)."""
    return 1 + 4 * (gamma + beta)


def check_constants(gamma: float, beta: float, c: float = 1.0, strict: bool = False) -> tuple[float, float]:
    """Slacks of the two conditions on the constants (negative: not met)."""
    first = gamma * beta - gamma - 4 * multiplier(gamma, beta)
    second = beta - 2 * c * (1 + gamma) - gamma
    if first < 0 or second < 0:
        said = f"gamma={gamma}, beta={beta}, c={c}: slacks {first:g} and {second:g}"
        if strict:
            raise ValueError(said)
        warnings.warn(said, stacklevel=2)
    return first, second


def feasible_constants(candidates: DataFrame, c: float, most: int) -> DataFrame:
    """(gamma, beta) that meet both conditions, both from the whole parts of the column ``value``, 1 to ``most``."""
    whole = candidates.where((F.col("value") >= 1) & (F.col("value") < most + 1)).select(F.floor("value").alias("gamma")).distinct()
    gamma, beta = F.col("gamma"), F.col("beta")
    ok = (gamma + 4 * (1 + 4 * (beta + gamma)) <= gamma * beta) & (beta >= 2 * c * (1 + gamma) + gamma)
    return whole.join(F.broadcast(whole.withColumnRenamed("gamma", "beta")), F.lit(True)).where(ok).select("gamma", "beta")


@dataclass(frozen=True)
class PhasePlan:
    phase: int
    floor: float
    price: float
    cost_cap: float
    median_cap: float
    runs: int


def plan_phase(phase: int, floor: float, *, k: int, n: float, gamma: float, beta: float, log_base: str = "e", runs: int | None = None) -> PhasePlan:
    m, logn = multiplier(gamma, beta), log(n, log_base)
    return PhasePlan(phase, floor, floor / (k * (1 + logn)), 4 * floor * m, 4 * k * (1 + logn) * m, runs or max(1, math.ceil(2 * logn)))


def grow(floor: float, beta: float, policy: str, breached: bool) -> float:
    """The next phase's floor."""
    if policy == "every_phase" or policy == "on_breach" and breached:
        return floor * beta
    if policy in ("on_breach", "none"):
        return floor
    raise ValueError(f"unknown floor growth {policy!r}")


def phase_schedule(spark: SparkSession, floor1: float | Column, *, k: int, n: int, gamma: float = 34, beta: float = 34, log_base: str = "e", phases: int = 5) -> DataFrame:
    """(phase, floor, price, cost_cap, median_cap, runs) under literal growth."""
    plan, m, logn = spark.range(1, phases + 1), multiplier(gamma, beta), log(n, log_base)
    floor = F.lit(floor1) * F.pow(F.lit(float(beta)), F.col("id") - 1)
    return plan.select(F.col("id").alias("phase"), floor.alias("floor"), (floor / (k * (1 + logn))).alias("price"), (4 * m * floor).alias("cost_cap"), F.lit(4.0 * k * (1 + logn) * m).alias("median_cap"), F.lit(math.ceil(2 * logn)).cast("long").alias("runs"))


def initial_floor(points: DataFrame, k: int, beta: float, *, d: int, distance: str = "euclidean", zero_floor: str = "distinct") -> DataFrame:
    """(stream_key, closest, floor): the closest pair of the first k + 1 points, over beta.

    ``zero_floor="distinct"`` takes the first k + 1 different points, "error" fails on a zero, "allow" keeps it."""
    if zero_floor == "distinct":
        firsts = points.groupBy("stream_key", "vec").agg(F.min("ordinal").alias("ordinal"))
        head = firsts.withColumn("r", F.row_number().over(W.partitionBy("stream_key").orderBy("ordinal"))).where(F.col("r") <= k + 1)
    elif zero_floor in ("error", "allow"):
        head = points.where(F.col("ordinal") <= k + 1)
    else:
        raise ValueError(f"unknown zero_floor {zero_floor!r}")
    a = head.select("stream_key", F.col("ordinal").alias("i"), F.col("vec").alias("a"))
    b = head.select("stream_key", F.col("ordinal").alias("j"), F.col("vec").alias("b"))
    pairs = a.join(b, "stream_key").where("i < j").select("stream_key", distance_expr(distance, vector("a", d), vector("b", d)).alias("dist"))
    out = pairs.groupBy("stream_key").agg(F.min("dist").alias("closest"))
    if zero_floor == "error":
        out = out.withColumn("closest", F.when(F.col("closest") == 0, F.raise_error(F.lit("the first points repeat: zero floor")).cast("double")).otherwise(F.col("closest")))
    return out.withColumn("floor", F.col("closest") / beta)
