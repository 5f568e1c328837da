"""Everything by ``spark.sql``: a table function for the facility pass, a scalar distance to fixed
medians, and temporary views."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult, OrderingColumn, PartitioningColumn

from .functions.draws import draws
from .operators.kernel import facility_pass


class FacilityScan:
    """facility_scan(TABLE(points), price, seed): medians and weights of one pass per stream key."""

    def __init__(self):
        self.rows: list[tuple[str, int, list[float], float]] = []
        self.price, self.seed = 1.0, 1

    @staticmethod
    def analyze(points: AnalyzeArgument, price: AnalyzeArgument, seed: AnalyzeArgument) -> AnalyzeResult:
        from pyspark.sql.types import ArrayType, LongType, StringType, StructType

        schema = StructType().add("stream_key", StringType()).add("median_id", LongType()).add("vec", ArrayType(DoubleType())).add("weight", DoubleType()).add("service_cost", DoubleType())
        return AnalyzeResult(schema, partitionBy=[PartitioningColumn("stream_key")], orderBy=[OrderingColumn("ordinal")])

    def eval(self, row, price: float, seed: int) -> None:
        self.price, self.seed = float(price), int(seed)
        self.rows.append((row["stream_key"], row["point_id"], row["vec"], row["weight"]))

    def terminate(self) -> Iterator[tuple]:
        if not self.rows:
            return
        ids = np.array([r[1] for r in self.rows], np.int64)
        x, w = np.array([r[2] for r in self.rows], float), np.array([r[3] for r in self.rows], float)
        p = facility_pass(x, w, draws("hash", self.seed, 0, 1, ids), self.price)
        for i, row in enumerate(p.rows):
            yield self.rows[0][0], int(ids[row]), x[row].tolist(), float(p.weight[i]), float(p.service)


def register(spark: SparkSession) -> None:
    """Registers ``facility_scan`` and ``weighted_median_summary``."""
    spark.udtf.register("facility_scan", F.udtf(FacilityScan))

    def summary(v: pd.Series, w: pd.Series) -> float:
        order = np.argsort(v.to_numpy(), kind="stable")
        values, weights = v.to_numpy()[order], w.to_numpy()[order]
        return float(values[np.searchsorted(np.cumsum(weights), weights.sum() / 2)]) if len(values) else float("nan")

    summary.__annotations__ = {"v": pd.Series, "w": pd.Series, "return": float}
    spark.udf.register("weighted_median_summary", F.pandas_udf(summary, "double"))


def nearest_distance(medians: np.ndarray):
    """An Arrow-batched scalar function: distance of a vector column to the nearest of these medians."""
    held = np.asarray(medians, float)

    def gap(v: pd.Series) -> pd.Series:
        x = np.stack(v.to_numpy()).astype(float)
        return pd.Series(np.sqrt(((x[:, None, :] - held[None]) ** 2).sum(2)).min(1))

    gap.__annotations__ = {"v": pd.Series, "return": pd.Series}
    return F.pandas_udf(gap, "double")


def views(points: DataFrame, prefix: str = "stream") -> None:
    points.createOrReplaceTempView(f"{prefix}_points")
