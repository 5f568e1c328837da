"""Points of a stream: vectors, total order, chunks, scaling.  (M1-M4)

A point table has the columns stream_key (string), ordinal (from 1), point_id, vec (array of
doubles) and weight.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.coding import Feature, feature_columns
from ..sources.shared import stored

NULLS = ("error", "drop", "impute")


def with_ordinal(df: DataFrame, keys: list, stream_key: str | None = None, name: str = "ordinal", keep: list | None = None) -> DataFrame:
    """A dense ordinal from 1 in the order of ``keys``.

    Per stream it is a window over the stream's own rows.  A single stream is never ranked in one task:
    rows are range-partitioned by all keys, sorted within their part, and written once with their place
    in it; each part starts at the sum of the counts before it (one number a part, broadcast).  Plan
    it over the columns that are needed: they are what is written, or ``keep`` (columns of ``df``) is, if given.
    """
    if stream_key:
        return df.withColumn(name, F.row_number().over(W.partitionBy(stream_key).orderBy(*keys)).cast("long"))
    at = "_at"
    while at in df.columns:
        at += "_"
    placed = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn(at, F.monotonically_increasing_id())
    placed = stored(placed if keep is None else placed.select(*keep, at), "ordered")
    part, inside = F.shiftright(at, 33), F.col(at).bitwiseAND(F.lit((1 << 33) - 1))
    counts = placed.groupBy(part.alias(f"{at}p")).agg(F.count("*").alias(f"{at}n"))
    before = counts.select(f"{at}p", F.coalesce(F.sum(f"{at}n").over(W.orderBy(f"{at}p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias(f"{at}b"))
    out = placed.join(F.broadcast(before), part == F.col(f"{at}p"))
    return out.withColumn(name, (F.col(f"{at}b") + inside + 1).cast("long")).drop(at, f"{at}p", f"{at}b")


def to_points(df: DataFrame, order_by: list, features: list[Feature | str] | None = None, *, vector: str | None = None, point_id: str | None = None, stream_key: str | Column | None = None, weight: str | None = None, nulls: str = "error", impute: float = 0.0, ranked: bool = True) -> DataFrame:
    """A point table of ``df``.  Null coordinates: "error" fails the query, "drop" leaves the row
    out, "impute" takes the given value; NaN and infinity always fail.  Without ``ranked`` the ordinal is the one
    whole number in ``order_by`` as it is: in order, with gaps."""
    if nulls not in NULLS:
        raise ValueError(f"nulls must be one of {NULLS}, not {nulls!r}")
    if (features is None) == (vector is None):
        raise ValueError("give either features or a vector column")
    parts = feature_columns(df, features) if features else None
    vec = F.array(*parts) if parts else F.col(vector).cast("array<double>")
    key = F.lit("all") if stream_key is None else (F.col(stream_key) if isinstance(stream_key, str) else stream_key)
    order = [(F.col(k) if isinstance(k, str) else k).alias(f"_k{i}") for i, k in enumerate(order_by)]
    ident = [F.col(point_id).cast("long").alias("_id")] if point_id else []
    out = df.select(*order, *ident, vec.alias("_vec"), key.cast("string").alias("_key"), (F.col(weight).cast("double") if weight else F.lit(1.0)).alias("_weight"))
    missing = F.col("_vec").isNull() | F.exists("_vec", lambda x: x.isNull())
    if nulls == "drop":
        out = out.where(~missing)
    elif nulls == "impute":
        out = out.withColumn("_vec", F.transform("_vec", lambda x: F.coalesce(x, F.lit(impute))))
    bad = F.coalesce(missing, F.lit(True)) | F.exists("_vec", lambda x: F.isnan(x) | (F.abs(x) == float("inf")))
    out = out.withColumn("_vec", F.when(bad, F.raise_error(F.lit("a coordinate is null, NaN or infinite")).cast("array<double>")).otherwise(F.col("_vec")))
    if ranked:
        out = with_ordinal(out, [f"_k{i}" for i in range(len(order))], "_key" if stream_key is not None else None, "_ordinal")
    elif len(order) > 1:
        raise ValueError("points that are not ranked have one key of order")
    else:
        out = out.withColumn("_ordinal", F.col("_k0").cast("long"))
    return out.select(
        F.col("_key").alias("stream_key"),
        F.col("_ordinal").alias("ordinal"),
        F.col("_id" if point_id else "_ordinal").alias("point_id"),
        F.col("_vec").alias("vec"),
        F.col("_weight").alias("weight"),
    )


def chunk(points: DataFrame, num: int) -> DataFrame:
    """chunk_id (from 0): ``num`` consecutive points each."""
    return points.withColumn("chunk_id", F.floor((F.col("ordinal") - 1) / num).cast("long"))


def chunk_by_window(df: DataFrame, ts: str, width: str) -> DataFrame:
    """window_start: the event-time window that a row belongs to."""
    return df.withColumn("window_start", F.window(F.col(ts).cast("timestamp"), width)["start"])


def scale(points: DataFrame, kind: str, d: int) -> DataFrame:
    """Coordinates scaled by stream: "none", "minmax" (to 0..1), "zscore" or "robust" (median and
    interquartile range).  A constant coordinate becomes 0.  One aggregation, joined by stream."""
    if kind == "none":
        return points
    x = [F.col("vec")[i] for i in range(d)]
    if kind == "minmax":
        centre, width = [F.min(c) for c in x], [F.max(c) - F.min(c) for c in x]
    elif kind == "zscore":
        centre, width = [F.avg(c) for c in x], [F.stddev_samp(c) for c in x]
    elif kind == "robust":
        centre = [F.percentile(c, F.lit(0.5)) for c in x]
        width = [F.percentile(c, F.lit(0.75)) - F.percentile(c, F.lit(0.25)) for c in x]
    else:
        raise ValueError(f"unknown scaling {kind!r}")
    stats = points.groupBy("stream_key").agg(*(c.alias(f"_c{i}") for i, c in enumerate(centre)), *(w.alias(f"_w{i}") for i, w in enumerate(width)))
    scaled = F.array(*(F.when(F.coalesce(F.col(f"_w{i}"), F.lit(0.0)) == 0, 0.0).otherwise((F.col("vec")[i] - F.col(f"_c{i}")) / F.col(f"_w{i}")) for i in range(d)))
    return points.join(stats, "stream_key").select("stream_key", "ordinal", "point_id", scaled.alias("vec"), "weight")
