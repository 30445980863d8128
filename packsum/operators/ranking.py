"""Ranks by packing: a rank query becomes a packing instance whose optimum is 2N plus the rank."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packsum.operators.rounding import grid_steps, sizes_only, steps_to_instance
from packsum.functions.units import octave
from packsum.operators.solvers import bins, solve_ffd
from packsum.params import Eps, octave_step


def reduction(values: DataFrame, column: str, low: int, high: int) -> tuple[DataFrame, int, int]:
    """Numbers on a denominator where all lie strictly between one half and two thirds: (histogram, capacity, shift)."""
    h = high - low + 2
    mapped = values.groupBy((F.col(column) - low + 1 + 3 * h).cast("long").alias("size_units")).agg((2 * F.count(F.lit(1))).alias("n"))
    return mapped, 6 * h, 3 * h + 1 - low


def rank_exact(values: DataFrame, column: str, queries: list[int]) -> DataFrame:
    """Numbers larger than each query, and the optimum 2N + rank of its packing instance."""
    q = F.explode(F.array(*(F.lit(x).cast("long") for x in queries))).alias("q")
    counted = values.groupBy(column).agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col(column), "n", q).groupBy("q").agg(F.sum("n").alias("n_total"), F.coalesce(F.sum(F.when(F.col(column) > F.col("q"), F.col("n"))), F.lit(0)).alias("rank")).select("q", "n_total", "rank", (2 * F.col("n_total") + F.col("rank")).alias("optimum"))


def rank_by_packing(spark: SparkSession, values: DataFrame, column: str, queries: list[int], eps: Eps) -> DataFrame:
    """Rank estimates from the summary of the doubled numbers alone: each query adds 2N items of one size.

    One summary serves all queries, as the reduction promises; only its few sizes come to the driver.
    """
    low, high, n = values.agg(F.min(column), F.max(column), F.count(F.lit(1))).first()
    hist, cap, shift = reduction(values, column, low, high)
    hist = hist.withColumn("group_j", octave(F.col("size_units"), cap, eps))
    instance = steps_to_instance(grid_steps(hist, octave_step("n_j", eps)))
    summary = [(r["size_units"], r["multiplicity"]) for r in sizes_only(instance).collect()]
    rows = []
    for q in queries:
        inside = min(max(q, low - 1), high)
        solution = solve_ffd([*summary, (cap - (inside + shift), 2 * n)], cap)
        rows.append((q, n, bins(solution) - 2 * n, len(summary)))
    return spark.createDataFrame(rows, "q long, n_total long, rank_estimate long, stored int")


def rank_report(spark: SparkSession, values: DataFrame, column: str, queries: list[int], eps: Eps) -> DataFrame:
    """Estimate, exact rank, and whether the error is within 4 eps N, plus one step of the summary."""
    got = rank_by_packing(spark, values, column, queries, eps)
    both = got.join(rank_exact(values, column, queries).select("q", "rank"), "q")
    error = F.col("rank_estimate") - F.col("rank")
    limit = 4 * eps.num * F.col("n_total") / eps.den
    return both.select("q", "n_total", "rank", "rank_estimate", ((error >= 0) & (error <= limit + 1)).alias("within"))


def quantile_by_rank(spark: SparkSession, values: DataFrame, column: str, phi: float, eps: Eps) -> int:
    """Binary search on rank estimates; the value found need not occur in the data."""
    low, high, n = values.agg(F.min(column), F.max(column), F.count(F.lit(1))).first()
    hist, cap, shift = reduction(values, column, low, high)
    hist = hist.withColumn("group_j", octave(F.col("size_units"), cap, eps))
    summary = [(r["size_units"], r["multiplicity"]) for r in sizes_only(steps_to_instance(grid_steps(hist, octave_step("n_j", eps)))).collect()]
    a, b = int(low), int(high)
    while a < b:
        mid = (a + b) // 2
        rank = bins(solve_ffd([*summary, (cap - (mid + shift), 2 * n)], cap)) - 2 * n
        a, b = (a, mid) if rank <= (1 - phi) * n else (mid + 1, b)
    return a
