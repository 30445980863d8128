"""Global ranks and prefix sums without a single-partition window: partial sums by range, then local order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def with_rank(df: DataFrame, size: str, tie: list[str], name: str = "rank_pos", keys: tuple[str, ...] = (), salts: int = 64) -> DataFrame:
    """Position 1 = largest, ties by hash. Counts by (size, salt) give offsets; rows are ordered only inside a pair."""
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(*tie), F.lit(salts)))
    counts = salted.groupBy(*keys, size, "_salt").agg(F.count(F.lit(1)).alias("_n"))
    ahead = Window.partitionBy(*keys).orderBy(F.desc(size), "_salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*keys, size, "_salt", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_ahead"))
    inside = Window.partitionBy(*keys, size, "_salt").orderBy(*tie)
    return salted.withColumn("_in", F.row_number().over(inside)).join(offsets, [*keys, size, "_salt"]).withColumn(name, (F.col("_in") + F.col("_ahead")).cast("long")).drop("_salt", "_in", "_ahead", "_n")


def with_prefix(df: DataFrame, amount: Column, order: str, name: str = "prefix_before", buckets: int = 64) -> DataFrame:
    """Sum of amounts before each row, in the order of (salt of the key, key)."""
    salted = df.withColumn("_amount", amount.cast("long")).withColumn("_salt", F.pmod(F.xxhash64(order), F.lit(buckets)))
    sums = salted.groupBy("_salt").agg(F.sum("_amount").alias("_sum"))
    ahead = Window.orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("_salt", F.coalesce(F.sum("_sum").over(ahead), F.lit(0)).alias("_ahead"))
    inside = Window.partitionBy("_salt").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    local = salted.withColumn("_in", F.coalesce(F.sum("_amount").over(inside), F.lit(0)))
    return local.join(F.broadcast(offsets), "_salt").withColumn(name, (F.col("_in") + F.col("_ahead")).cast("long")).drop("_salt", "_in", "_ahead", "_amount")


def with_position(df: DataFrame, key: str, name: str = "position", width: int = 4096) -> DataFrame:
    """Position from 0 in the order of a whole-number key: counts by ranges of ``width`` keys, then order inside a range."""
    ranged = df.withColumn("_range", F.expr(f"{key} div {width}"))
    ahead = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    counts = ranged.groupBy("_range").agg(F.count(F.lit(1)).alias("_n"))
    offsets = counts.select("_range", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_ahead"))
    inside = Window.partitionBy("_range").orderBy(key)
    local = ranged.withColumn("_in", F.row_number().over(inside) - 1)
    return local.join(offsets, "_range").withColumn(name, (F.col("_in") + F.col("_ahead")).cast("long")).drop("_range", "_in", "_ahead")
