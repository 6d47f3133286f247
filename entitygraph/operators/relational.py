"""Joins and samples that Spark has no operator of its own for, as compositions of those that it has."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, left_value: str, right_value: str, reach: float, keys: tuple[str, ...] = ()) -> DataFrame:
    """Rows of both sides (no common column names but the keys) whose values differ by at most ``reach``: an equi-join on buckets of that width, the right
    side in its own bucket and the two beside it, and the exact condition on what meets. Nulls meet nothing."""
    width = float(reach) if reach > 0 else 1.0
    bucket = lambda c: F.floor(F.col(c) / F.lit(width))
    near = right.withColumn("_bucket", F.explode(F.array(*[bucket(right_value) + d for d in (-1, 0, 1)])))
    met = left.withColumn("_bucket", bucket(left_value)).join(near, ["_bucket", *keys])
    return met.where(F.abs(F.col(left_value) - F.col(right_value)) <= reach).drop("_bucket")


def as_of_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str, name: str) -> DataFrame:
    """The left rows with the right side's latest ``value`` of the same key at or before their time, as ``name``; null where there is none. One sort by key and time, no join."""
    columns = left.columns
    both = left.withColumn("_side", F.lit(1)).withColumn(name, F.lit(None).cast(right.schema[value].dataType)).unionByName(
        right.select(key, time, F.col(value).alias(name)).withColumn("_side", F.lit(0)), allowMissingColumns=True
    )
    upto = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(name, F.last(F.when(F.col("_side") == 0, F.col(name)), ignorenulls=True).over(upto)).where("_side = 1").select(*columns, name)


def interval_pairs(rows: DataFrame, key: str, time: str, id_col: str, seconds: int) -> DataFrame:
    """key, a, b of rows of one key at most so many seconds apart, a before b (by time, then id)."""
    one = rows.select(F.col(key).alias(key), F.col(id_col), F.unix_micros(F.col(time).cast("timestamp")).alias("t"))
    left, right = one.select(key, F.col(id_col).alias("a"), F.col("t").alias("ta")), one.select(key, F.col(id_col).alias("b"), F.col("t").alias("tb"))
    met = range_join(left, right, "ta", "tb", seconds * 1_000_000, (key,))
    return met.where((F.col("ta") < F.col("tb")) | ((F.col("ta") == F.col("tb")) & (F.col("a") < F.col("b")))).select(key, "a", "b")


def entity_sample(records: DataFrame, entity: str, percent: int, seed: int = 0) -> DataFrame:
    """All records of a share of the entities, drawn by a hash of seed and entity: the same on every run, and no entity is cut."""
    number = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col(entity).cast("string"))), 1, 8), 16, 10).cast("long")
    return records.where(number % 100 < percent)


def top_k(rows: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group."""
    return rows.withColumn("_rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_rank") <= k).drop("_rank")
