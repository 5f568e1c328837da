"""Sources and sinks: the given tables as points, files, streams, and phase-wise state folders."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.coding import Feature, feature_columns
from ..operators.points import to_points, with_ordinal

FORMATS = ("parquet", "csv", "json", "orc", "text")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A file source; row formats need a schema (nothing is inferred by reading the data twice)."""
    if kind not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}, not {kind!r}")
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_points(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """A load source: points (stream_key, point_id, ts, vec) at a steady rate."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rate.select(F.lit("all").alias("stream_key"), F.col("value").alias("point_id"), F.col("timestamp").alias("ts"), F.array(F.rand(1)).alias("vec"))


def write_phases(df: DataFrame, path: str, column: str = "phase") -> None:
    """State by phase: one folder a phase, only the phases at hand are replaced."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(column).parquet(path)


def events_points(spark: SparkSession, sf_dir: str, *, upto: int | None = None, stream_key=None, scale: float = 1.0, ranked: bool = True) -> DataFrame:
    """``events`` in the order of event_id; the vector is (value * scale)."""
    df = table(spark, sf_dir, "events").select("event_id", "user_id", "value")
    df = df.where(F.col("event_id") < upto) if upto else df
    value = F.col("value") if scale == 1.0 else F.round(F.col("value") * scale)
    return to_points(df, ["event_id"], [Feature(value, "value")], point_id="event_id", stream_key=stream_key, ranked=ranked)


LINEITEM_KEYS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
LINEITEM_FEATURES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "l_shipdate", "l_returnflag", "l_linestatus"]


def lineitem_points(spark: SparkSession, sf_dir: str, rows: int | None = None) -> DataFrame:
    """Eight mixed attributes of ``lineitem`` in full-row order (text by character code)."""
    df = table(spark, sf_dir, "lineitem").select(*LINEITEM_KEYS).withColumn("l_shipdate", F.to_date("l_shipdate"))
    # the keys hold the features, so rows are moved with the keys only; coordinates are checked and written one a column
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    parts = [F.when(bad(x), F.raise_error(F.lit("a coordinate is null, NaN or infinite")).cast("double")).otherwise(x).alias(f"x{i}") for i, x in enumerate(feature_columns(df, LINEITEM_FEATURES))]
    ranked = with_ordinal(df, LINEITEM_KEYS, keep=parts)
    points = ranked.select(F.lit("all").alias("stream_key"), "ordinal", F.col("ordinal").alias("point_id"), F.array(*(F.col(f"x{i}") for i in range(len(parts)))).alias("vec"), F.lit(1.0).alias("weight"))
    return points.where(F.col("ordinal") <= rows) if rows else points


def orders_points(spark: SparkSession, sf_dir: str, rows: int | None = None) -> DataFrame:
    """Five attributes of ``orders``: status code, priority rank, total price, month, weekday."""
    df = table(spark, sf_dir, "orders").where(F.col("o_orderkey").isNotNull())
    features = ["o_orderstatus", Feature("o_orderpriority", coding="ordinal", levels=PRIORITIES), "o_totalprice", Feature(F.month("o_orderdate"), "month"), Feature(F.weekday("o_orderdate"), "weekday")]
    points = to_points(df, ["o_orderkey"], features, point_id="o_orderkey")
    return points.where(F.col("ordinal") <= rows) if rows else points


def embedding_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return to_points(table(spark, sf_dir, "embeddings"), ["vec_id"], vector="embedding", point_id="vec_id")


def customer_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Account balance (in hundreds) and nation of ``customer``."""
    return to_points(table(spark, sf_dir, "customer"), ["c_custkey"], [Feature(F.col("c_acctbal") / 100, "balance"), "c_nationkey"], point_id="c_custkey")


def nation_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A small table of whole numbers: squares modulo 101 of ``nation``'s keys."""
    key = F.col("n_nationkey")
    return to_points(table(spark, sf_dir, "nation"), ["n_nationkey"], [Feature((key * key * 7 + key * 3) % 101, "place")], point_id="n_nationkey")
