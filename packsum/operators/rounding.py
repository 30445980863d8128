"""Big items rounded up to few sizes, as Spark plans over value histograms.

A histogram has rows (keys, group_j, size_units, n). Rank 1 is the largest item of a group. A summary is a list of
steps (keys, group_j, size_units, rank_hi): the value, and an upper bound of its rank. A rounded instance has rows
(keys, group_j, size_units, multiplicity).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from packsum.functions.units import is_big, octave
from packsum.params import Eps, check_packing, octave_step, simple_step
from packsum.sources.tables import Items

SMALL = -1


def split_small(items: Items, eps: Eps) -> DataFrame:
    """Small total and counts on both sides, in one pass."""
    big = is_big(F.col("size_units"), items.cap, eps)
    return items.df.groupBy(*items.keys).agg(
        F.coalesce(F.sum(F.when(~big, F.col("size_units"))), F.lit(0)).cast("long").alias("small_total"),
        F.count_if(~big).alias("n_small"),
        F.count_if(big).alias("n_big"),
        F.coalesce(F.sum(F.when(big, F.col("size_units"))), F.lit(0)).cast("long").alias("big_total"),
        F.coalesce(F.max(F.when(~big, F.col("size_units"))), F.lit(0)).cast("long").alias("small_max"),
    )


def last_piece(items: Items) -> Column:
    """What an item leaves for a bin of its own choice: one over the capacity fills whole bins first."""
    size = F.col("size_units")
    return F.when(size > items.cap, (size - 1) % items.cap + 1).otherwise(size) if items.over else size


def within_capacity(items: Items) -> Items:
    """Items with their last pieces for sizes; the same where none is over the capacity."""
    return Items(items.df.withColumn("size_units", last_piece(items)), items.cap, items.keys) if items.over else items


def split_pieces(items: Items, eps: Eps) -> DataFrame:
    """The split of whole items, beside it the small last pieces and the bins that larger items fill, in one pass."""
    if not items.over:
        same = split_small(items, eps)
        return same.withColumn("small_pieces", F.col("small_total")).withColumn("largest_piece", F.col("small_max")).withColumn("full_bins", F.lit(0).cast("long"))
    pieces = items.df.withColumn("piece", last_piece(items))
    big, small = is_big(F.col("size_units"), items.cap, eps), ~is_big(F.col("piece"), items.cap, eps)
    whole = F.expr(f"(size_units - 1) div {items.cap}L")
    return pieces.groupBy(*items.keys).agg(
        F.coalesce(F.sum(F.when(~big, F.col("size_units"))), F.lit(0)).cast("long").alias("small_total"),
        F.count_if(~big).alias("n_small"),
        F.count_if(big).alias("n_big"),
        F.coalesce(F.sum(F.when(big, F.col("size_units"))), F.lit(0)).cast("long").alias("big_total"),
        F.coalesce(F.sum(F.when(small, F.col("piece"))), F.lit(0)).cast("long").alias("small_pieces"),
        F.coalesce(F.max(F.when(small, F.col("piece"))), F.lit(0)).cast("long").alias("largest_piece"),
        F.coalesce(F.sum(F.when(F.col("size_units") > items.cap, whole)), F.lit(0)).cast("long").alias("full_bins"),
    )


def with_octave(items: Items, eps: Eps) -> DataFrame:
    return items.df.withColumn("group_j", octave(F.col("size_units"), items.cap, eps))


def octave_profile(items: Items, eps: Eps) -> DataFrame:
    """Items, range and total of each octave; octave -1 holds the small items, so one aggregate serves both."""
    return (
        with_octave(items, eps)
        .groupBy(*items.keys, "group_j")
        .agg(F.count(F.lit(1)).alias("n_j"), F.min("size_units").alias("lo"), F.max("size_units").alias("hi"), F.sum("size_units").cast("long").alias("total"))
    )


def octave_inequality(items: Items, eps: Eps) -> DataFrame:
    """The sum of n_j / 2**(j+1) stays below the total size of big items: both sides times 2**k, in units."""
    k = eps.octaves
    big = octave_profile(items, eps).filter(F.col("group_j") >= 0)
    left = F.sum(F.col("n_j") * F.expr(f"shiftleft(1L, {k} - group_j - 1)") * F.lit(items.cap))
    return big.agg(left.cast("long").alias("octave_sum"), (F.sum("total") * (1 << k)).cast("long").alias("size_sum")).withColumn("holds", F.col("octave_sum") < F.col("size_sum"))


def histogram(items: Items, eps: Eps, grouped: bool = True) -> DataFrame:
    """Values of big items with counts. Partial aggregation before the shuffle absorbs common values."""
    df = with_octave(items, eps).filter(is_big(F.col("size_units"), items.cap, eps))
    if not grouped:
        df = df.withColumn("group_j", F.lit(0))
    return df.groupBy(*items.keys, "group_j", "size_units").agg(F.count(F.lit(1)).alias("n"))


def _ranked(hist: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    group = [*keys, "group_j"]
    down = Window.partitionBy(*group).orderBy(F.desc("size_units"))
    whole = Window.partitionBy(*group)
    out = hist.withColumn("c1", F.sum("n").over(down.rowsBetween(Window.unboundedPreceding, 0)))
    return out.withColumn("c0", F.col("c1") - F.col("n")).withColumn("n_j", F.sum("n").over(whole)).withColumn("least", F.min("size_units").over(whole))


def grid_steps(hist: DataFrame, step: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """Exact summary: stored positions 1, 1 + t, 1 + 2t, ... and the last; ``step`` is SQL of t over the group size n_j."""
    r = _ranked(hist, keys).withColumn("t", F.expr(step).cast("long"))
    r = r.withColumn("b0", F.expr("(c0 + t - 1) div t")).withColumn("b1", F.expr("(c1 + t - 1) div t"))
    starts = r.filter("b1 > b0").select(*keys, "group_j", "size_units", (F.col("b0") * F.col("t") + 1).alias("rank_hi"))
    last = r.filter("size_units = least").select(*keys, "group_j", "size_units", F.col("n_j").alias("rank_hi"))
    return starts.unionByName(last).groupBy(*keys, "group_j", "rank_hi").agg(F.max("size_units").alias("size_units")).select(*keys, "group_j", "size_units", "rank_hi")


def steps_to_instance(steps: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """A stored value covers the positions from its rank bound to before the next; the last covers one."""
    order = Window.partitionBy(*keys, "group_j").orderBy("rank_hi")
    m = F.coalesce(F.lead("rank_hi").over(order) - F.col("rank_hi"), F.lit(1))
    return compact(steps.withColumn("multiplicity", m).filter("multiplicity > 0"), keys)


def compact(instance: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    return instance.groupBy(*keys, "group_j", "size_units").agg(F.sum("multiplicity").cast("long").alias("multiplicity"))


def sizes_only(instance: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Distinct sizes over all octaves."""
    return instance.groupBy(*keys, "size_units").agg(F.sum("multiplicity").cast("long").alias("multiplicity"))


def round_simple(items: Items, eps: Eps) -> DataFrame:
    """One exact summary of precision eps**2 / 4 over all big items."""
    check_packing(eps)
    return steps_to_instance(grid_steps(histogram(items, eps, grouped=False), simple_step("n_j", eps), items.keys), items.keys)


def round_octaves(items: Items, eps: Eps, wide: bool = False) -> DataFrame:
    """One exact summary of precision eps / 8 for each octave; the key makes their union."""
    check_packing(eps)
    return steps_to_instance(grid_steps(histogram(items, eps), octave_step("n_j", eps, wide), items.keys), items.keys)


def round_histogram(items: Items, eps: Eps) -> DataFrame:
    """A small explicit universe: every value is kept, nothing is rounded."""
    return histogram(items, eps).withColumnRenamed("n", "multiplicity")


def merge_rounded(instances: DataFrame, step: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Union of rounded parts, rounded again by a weighted exact grid if a step is given.

    Rank dominance survives disjoint union and composition, and shifts add, so halving the precision at both levels
    keeps the whole within the original one.
    """
    union = compact(instances, keys)
    if step is None:
        return union
    return steps_to_instance(grid_steps(union.withColumnRenamed("multiplicity", "n"), step, keys), keys)


def round_in_parts(items: Items, eps: Eps, parts: int) -> DataFrame:
    """Two-level rounding: hash parts with half the precision, then their union with the other half."""
    half = octave_step("n_j", Eps(eps.num, 2 * eps.den))
    salted = Items(items.df.withColumn("part", F.pmod(F.xxhash64(*items.df.columns), F.lit(parts))), items.cap, (*items.keys, "part"))
    leaves = steps_to_instance(grid_steps(histogram(salted, eps), half, salted.keys), salted.keys)
    return merge_rounded(leaves.drop("part"), half, items.keys)


def linear_grouping(items: Items, eps: Eps, keys: tuple[str, ...] = ()) -> DataFrame:
    """Offline baseline: groups of floor(eps * SIZE) items from the largest down, each rounded up to its largest."""
    hist = histogram(items, eps, grouped=False)
    total = items.df.groupBy(*keys).agg(F.sum("size_units").alias("all_units"))
    hist = hist.crossJoin(F.broadcast(total)) if not keys else hist.join(F.broadcast(total), list(keys))
    r = _ranked(hist, keys).withColumn("t", F.expr(f"greatest(1L, (cast(all_units as bigint) * {eps.num}L) div {eps.den * items.cap}L)"))
    r = r.withColumn("b0", F.expr("(c0 + t - 1) div t")).withColumn("b1", F.expr("(c1 + t - 1) div t"))
    m = F.least("n_j", F.col("b1") * F.col("t")) - F.least("n_j", F.col("b0") * F.col("t"))
    return r.select(*keys, "group_j", "size_units", m.cast("long").alias("multiplicity")).filter("multiplicity > 0")


def fixed_grid(items: Items, eps: Eps, per_bin: int) -> DataFrame:
    """Ablation: sizes up to multiples of cap / per_bin, without ranks. Pairs of half-size items may stop fitting."""
    step = max(1, items.cap // per_bin)
    up = F.least(F.expr(f"((size_units + {step - 1}) div {step}) * {step}"), F.lit(items.cap)).cast("long")
    hist = histogram(items, eps)
    return hist.withColumn("size_units", up).groupBy(*items.keys, "group_j", "size_units").agg(F.sum("n").cast("long").alias("multiplicity"))


def dyadic_fixed(items: Items, eps: Eps, level: int) -> DataFrame:
    """Bounded universe at one fixed level: up to the top leaf of the node of 2**level units, held to the octave's maximum."""
    hist = histogram(items, eps)
    top = F.max("size_units").over(Window.partitionBy(*items.keys, "group_j"))
    up = F.least(F.expr(f"(size_units div {1 << level}) * {1 << level} + {(1 << level) - 1}"), top).cast("long")
    return hist.withColumn("size_units", up).groupBy(*items.keys, "group_j", "size_units").agg(F.sum("n").cast("long").alias("multiplicity"))


def quantile(steps: DataFrame, phi: float, keys: tuple[str, ...] = ()) -> DataFrame:
    """Stored value of the last rank bound at or before phi * n."""
    whole = Window.partitionBy(*keys, "group_j")
    at = steps.withColumn("n_j", F.max("rank_hi").over(whole)).filter(F.col("rank_hi") <= F.greatest(F.lit(1), F.floor(F.col("n_j") * phi)))
    return at.groupBy(*keys, "group_j").agg(F.max_by("size_units", "rank_hi").alias("size_units"))


def rank_bounds(steps: DataFrame, q: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """Bounds of the number of items larger than q: below the first stored value at most q, from the last above it."""
    over = F.col("size_units") > q
    return steps.groupBy(*keys, "group_j").agg(
        F.coalesce(F.max(F.when(over, F.col("rank_hi"))), F.lit(0)).alias("at_least"),
        F.coalesce(F.min(F.when(~over, F.col("rank_hi") - 1)), F.max("rank_hi")).alias("at_most"),
    )


def size_of(instance: DataFrame) -> Column:
    return F.sum(F.col("size_units") * F.col("multiplicity"))
