"""Relational operators around the engine: ordered, range and interval joins, tops, rollups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], on: str, value: str) -> DataFrame:
    """Each left row with the latest right value at or before it, by one sort of both sides instead of a range join."""
    l_ = left.withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).withColumn("__left", F.lit(1))
    r_ = right.select(*by, on, F.col(value).alias("__v"), F.lit(0).alias("__left"))
    both = l_.unionByName(r_, allowMissingColumns=True)
    w = Window.partitionBy(*by).orderBy(on, "__left").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn(f"{value}_asof", F.last("__v", ignorenulls=True).over(w)).where("__left = 1")
    return out.select(*left.columns, f"{value}_asof")


def interval_join(left: DataFrame, right: DataFrame, by: list[str], l_time: str, r_time: str, seconds: int) -> DataFrame:
    """Pairs whose times lie within `seconds`: both sides fall into buckets of that width, the right into both neighbours too."""
    sec = lambda c: F.unix_timestamp(c)
    l_ = left.withColumn("__b", F.floor(sec(l_time) / seconds))
    r_ = right.withColumn("__b", F.explode(F.array(*[F.floor(sec(r_time) / seconds) + d for d in (-1, 0, 1)])))
    return l_.join(r_, [*by, "__b"]).where(F.abs(sec(l_time) - sec(r_time)) <= seconds).drop("__b")


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """Points within [low, high): ranges go to each bucket they touch, so a point meets only ranges near it."""
    p = points.withColumn("__b", F.floor(F.col(value) / width))
    r = ranges.withColumn("__b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return p.join(r, "__b").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__b")


def top_per_group(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def salted_count(df: DataFrame, by: list[str], salts: int = 16) -> DataFrame:
    """Distinct-heavy counts in two levels, so that one hot key spreads over `salts` tasks."""
    part = df.groupBy(*by, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("__s")).agg(F.count("*").alias("n"))
    return part.groupBy(*by).agg(F.sum("n").alias("n"))
