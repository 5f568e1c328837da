"""Typed columns to numbers: the features of a point.  (M1)"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DecimalType)
CODINGS = ("ascii_first", "ascii_mean", "length", "ordinal")


@dataclass(frozen=True)
class Feature:
    """One coordinate: ``source`` is a column name or a Column; ``coding`` how text becomes a number;
    ``levels`` the order of values for coding="ordinal"; ``key`` the entry of a map column."""

    source: str | Column
    name: str | None = None
    coding: str = "ascii_first"
    levels: tuple[str, ...] = ()
    key: str | None = None


def numeric(column: Column, kind: T.DataType, feature: Feature = Feature("")) -> Column:
    """``column`` of type ``kind`` as a double."""
    if isinstance(kind, NUMERIC):
        return column.cast("double")
    if isinstance(kind, T.BooleanType):
        return column.cast("int").cast("double")
    if isinstance(kind, T.DateType):
        return F.datediff(column, F.lit("1970-01-01").cast("date")).cast("double")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(column.cast("timestamp")) / F.lit(1e6)
    if isinstance(kind, T.DayTimeIntervalType):
        return column.cast("interval second").cast("double")
    if isinstance(kind, T.MapType):
        return column.getItem(feature.key).cast("double")
    if isinstance(kind, T.StringType):
        if feature.coding == "ascii_first":
            return F.ascii(column).cast("double")
        if feature.coding == "length":
            return F.length(column).cast("double")
        if feature.coding == "ascii_mean":
            codes = F.transform(F.split(column, ""), lambda c: F.ascii(c))
            return F.aggregate(codes, F.lit(0), lambda a, c: a + c).cast("double") / F.greatest(F.length(column), F.lit(1))
        if feature.coding == "ordinal":
            places = F.array(*(F.lit(x) for x in feature.levels))
            return F.nullif(F.array_position(places, column), F.lit(0)).cast("double")
        raise ValueError(f"coding must be one of {CODINGS}, not {feature.coding!r}")
    raise TypeError(f"no numeric coding of {kind.simpleString()}")


def feature_columns(df: DataFrame, features: list[Feature | str]) -> list[Column]:
    out = []
    for i, f in enumerate(features):
        f = Feature(f) if isinstance(f, str) else f
        column = F.col(f.source) if isinstance(f.source, str) else f.source
        kind = df.select(column).schema[0].dataType
        if isinstance(kind, T.ArrayType):
            raise TypeError("an array column is a vector already: pass it as ``vector``")
        out.append(numeric(column, kind, f).alias(f.name or (f.source if isinstance(f.source, str) else f"f{i}")))
    return out
