"""Joins that need more than an equality: ranges, intervals, latest-before, salted keys, top-k per row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 8, how: str = "inner") -> DataFrame:
    """An equality join whose left rows of one key spread over ``salts`` tasks; right rows repeat once per salt."""
    spread = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    copied = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return spread.join(copied, [key, "_salt"], how).drop("_salt")


def range_join(points: DataFrame, ranges: DataFrame, value: Column, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high) of ranges, by an equality join on cells of ``width`` and a filter."""
    cells = ranges.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    placed = points.withColumn("_value", value).withColumn("_cell", F.floor(F.col("_value") / width))
    return placed.join(cells, "_cell").where((F.col("_value") >= F.col(low)) & (F.col("_value") < F.col(high))).drop("_cell", "_value")


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str, out: str) -> DataFrame:
    """Adds ``out`` to left: the value of right's latest row of the key at or before left's time.

    Both sides run through one window per key; of rows at the same time right's come first.
    """
    names = [c for c in left.columns if c not in (key, time)]
    x = left.select(key, time, F.struct(*names).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    y = right.select(key, time, F.lit(None).cast(x.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    met = x.unionByName(y).withColumn(out, F.last("_v", ignorenulls=True).over(w))
    return met.where("_side = 1").select(key, time, "_row.*", out)


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of a key whose right time lies within ``seconds`` after the left time, by cells of that width."""
    cell = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    x = left.withColumn("_cell", F.explode(F.array(cell(left_time), cell(left_time) + 1)))
    y = right.withColumn("_cell", cell(right_time))
    gap = F.unix_micros(F.col(right_time).cast("timestamp")) - F.unix_micros(F.col(left_time).cast("timestamp"))
    return x.join(y, [key, "_cell"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_cell")


def salted_count(df: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Rows per key in two phases, for engines or plans without partial aggregation."""
    salted = df.groupBy(key, F.pmod(F.monotonically_increasing_id(), F.lit(salts)).alias("_salt")).agg(F.count(F.lit(1)).alias("n"))
    return salted.groupBy(key).agg(F.sum("n").alias("n"))
