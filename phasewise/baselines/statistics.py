"""Statistical and deviation baselines.  (B6, B7)"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("zscore", "iqr", "mad")


def stat_outliers(points: DataFrame, kind: str, cut: float) -> DataFrame:
    """(stream_key, point_id, score) of one-dimensional points whose score is above ``cut``; one or two
    aggregations by stream, joined back."""
    x = F.col("vec")[0]
    if kind == "zscore":
        stats = points.groupBy("stream_key").agg(F.avg(x).alias("c"), F.stddev_samp(x).alias("w"))
        score = F.abs(x - F.col("c")) / F.col("w")
    elif kind == "iqr":
        stats = points.groupBy("stream_key").agg(F.percentile(x, F.lit(0.25)).alias("lo"), F.percentile(x, F.lit(0.75)).alias("hi"))
        score = F.greatest(F.col("lo") - x, x - F.col("hi")) / (F.col("hi") - F.col("lo"))
    elif kind == "mad":
        centre = points.groupBy("stream_key").agg(F.percentile(x, F.lit(0.5)).alias("c"))
        stats = points.join(centre, "stream_key").groupBy("stream_key").agg(F.first("c").alias("c"), F.percentile(F.abs(x - F.col("c")), F.lit(0.5)).alias("w"))
        score = F.abs(x - F.col("c")) / F.col("w")
    else:
        raise ValueError(f"kind must be one of {KINDS}, not {kind!r}")
    return points.join(stats, "stream_key").select("stream_key", "point_id", score.alias("score")).where(F.col("score") > cut)


def deviation_outliers(points: DataFrame, top_n: int, d: int) -> DataFrame:
    """(point_id, drop): the points whose removal lowers the sum of squared deviations most.  Leaving
    x out lowers it by n / (n - 1) * |x - mean|^2.  (B7)"""
    v = [F.col("vec")[i] for i in range(d)]
    stats = points.groupBy("stream_key").agg(F.count("*").alias("n"), *(F.avg(c).alias(f"m{i}") for i, c in enumerate(v)))
    drop = sum(((c - F.col(f"m{i}")) * (c - F.col(f"m{i}")) for i, c in enumerate(v)), F.lit(0.0)) * F.col("n") / (F.col("n") - 1)
    return points.join(stats, "stream_key").select("point_id", drop.alias("drop")).orderBy(F.desc("drop"), "point_id").limit(top_n)
