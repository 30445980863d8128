"""Checks of what a rounded instance must satisfy, on exact ranks: test-scale tools, one row of flags and slacks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packsum.operators.rounding import histogram
from packsum.params import Eps
from packsum.sources.tables import Items


def _cumulated(df: DataFrame, n: str) -> DataFrame:
    down = Window.partitionBy("group_j").orderBy(F.desc("size_units")).rowsBetween(Window.unboundedPreceding, 0)
    c1 = F.sum(n).over(down)
    return df.withColumn("c1", c1).withColumn("c0", F.col("c1") - F.col(n))


def rank_ranges(items: Items, eps: Eps, instance: DataFrame, grouped: bool = True) -> DataFrame:
    """Overlaps of rank ranges of true and rounded values: no item is expanded."""
    if not grouped:
        instance = instance.groupBy("size_units").agg(F.sum("multiplicity").alias("multiplicity")).withColumn("group_j", F.lit(0))
    true = _cumulated(histogram(items, eps, grouped), "n").select("group_j", F.col("size_units").alias("true_size"), F.col("c0").alias("a0"), F.col("c1").alias("a1"))
    up = _cumulated(instance, "multiplicity").select(F.col("group_j").alias("g"), F.col("size_units").alias("up_size"), F.col("c0").alias("b0"), F.col("c1").alias("b1"))
    return true.join(up, (F.col("group_j") == F.col("g")) & (F.col("a0") < F.col("b1")) & (F.col("b0") < F.col("a1")))


def check_properties(items: Items, eps: Eps, instance: DataFrame, grouped: bool = True, slack: int = 1) -> DataFrame:
    """Flags of the four properties. The third is checked by the fact behind it: after the h = floor(4 delta n) largest
    rounded items of an octave are set aside, the rest is dominated by the true items."""
    both = rank_ranges(items, eps, instance, grouped)
    # The largest shift needed: some rounded value at rank r exceeds the true value at r - h.
    ahead = both.groupBy("group_j", "up_size").agg(F.max("b1").alias("last"))
    true = _cumulated(histogram(items, eps, grouped), "n")
    counts = true.groupBy("group_j").agg(F.sum("n").alias("n_j"))
    reach = ahead.join(true.select(F.col("group_j").alias("g"), F.col("size_units").alias("t"), "c1"), (F.col("group_j") == F.col("g")) & (F.col("t") >= F.col("up_size")), "left")
    reach = reach.groupBy("group_j", "up_size").agg(F.max("last").alias("last"), F.coalesce(F.max("c1"), F.lit(0)).alias("covered"))
    shift = reach.groupBy("group_j").agg(F.max(F.greatest(F.lit(0), F.col("last") - F.col("covered"))).alias("shift")).join(counts, "group_j")
    den, num = (2 * eps.den, eps.num) if grouped else (eps.den**2, eps.num**2)
    allowed = F.expr(f"(n_j * {num}L) div {den}L")
    shifts = shift.agg(F.max("shift").alias("worst_shift"), F.bool_and(F.col("shift") <= allowed + slack).alias("p3"))
    p2 = both.agg(F.bool_and(F.col("up_size") >= F.col("true_size")).alias("p2"))
    total = histogram(items, eps, grouped).agg(F.sum(F.col("size_units") * F.col("n")).alias("true_total"), F.sum("n").alias("n_big"), F.count(F.lit(1)).alias("values"))
    up_total = instance.agg(F.sum(F.col("size_units") * F.col("multiplicity")).alias("up_total"), F.sum("multiplicity").alias("n_up"), F.count_distinct("size_units").alias("sigma"), F.min("size_units").alias("least"))
    one = p2.crossJoin(shifts).crossJoin(total).crossJoin(up_total)
    p1 = (F.col("least") * eps.den > eps.num * items.cap) & (F.col("n_up") == F.col("n_big"))
    p4 = F.col("up_total") * eps.den <= F.col("true_total") * (eps.den + eps.num)
    return one.select(p1.alias("p1"), "p2", "p3", p4.alias("p4"), F.col("n_big").cast("long").alias("n_big"), F.col("true_total").cast("long").alias("true_total"), F.col("up_total").cast("long").alias("up_total"), F.col("sigma").cast("long").alias("sigma"), F.col("worst_shift").cast("long").alias("worst_shift"))


def extra_bins(items: Items, eps: Eps) -> DataFrame:
    """Bins for the items set aside in every octave, against eps times the size bound plus the octaves."""
    hist = histogram(items, eps)
    n = hist.groupBy("group_j").agg(F.sum("n").alias("n_j"))
    aside = F.expr(f"(n_j * {eps.num}L) div {2 * eps.den}L")
    each = n.withColumn("h", aside).withColumn("extra", F.expr("(h + shiftleft(1L, group_j) - 1) div shiftleft(1L, group_j)"))
    size = hist.agg(F.sum(F.col("size_units") * F.col("n")).alias("total"))
    out = each.agg(F.coalesce(F.sum("extra"), F.lit(0)).cast("long").alias("extra_bins")).crossJoin(size)
    bound = F.col("total") * eps.num / (eps.den * items.cap) + eps.octaves
    return out.select("extra_bins", (F.col("extra_bins") <= bound).alias("within"))


def rank_errors(items: Items, eps: Eps, steps: DataFrame) -> DataFrame:
    """Exact rank ranges of stored values against their bounds: the worst miss of each octave."""
    true = _cumulated(histogram(items, eps), "n").select(F.col("group_j").alias("g"), F.col("size_units").alias("s"), "c0", "c1")
    both = steps.join(true, (F.col("group_j") == F.col("g")) & (F.col("size_units") == F.col("s")))
    below = F.greatest(F.lit(0), F.col("c0") + 1 - F.col("rank_hi"))
    return both.groupBy("group_j").agg(F.count(F.lit(1)).alias("stored"), F.max(below).cast("long").alias("too_early"), F.max(F.greatest(F.lit(0), F.col("rank_hi") - F.col("c1"))).cast("long").alias("too_late"))
