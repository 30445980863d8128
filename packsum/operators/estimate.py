"""From a rounded instance and the small total to a number of bins, its description, and an assignment."""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.functions.ranks import with_prefix, with_rank
from packsum.functions.units import is_big
from packsum.operators import rounding, solvers, summaries
from packsum.params import Eps, check_packing, packing_eps
from packsum.sources.tables import Items

REPORT = (
    "eps_num long, eps_den long, n_small long, n_big long, small_total long, big_total long, sigma long, rounded_total long, rounded_bins long, free_space double, "
    "fits boolean, alg long, size_bound long, pair_bound long, words long, log_term long, certificate string"
)


def free_space(solution: solvers.Solution, cap: int, eps: Eps) -> int:
    """Units of free space below 1 - eps, times the denominator of eps, over all bins."""
    return sum(max(0, cap * (eps.den - eps.num) - solvers.load(p) * eps.den) * n for p, n in solution)


def estimate_bins(n_bins: int, w_scaled: int, small_total: int, cap: int, eps: Eps) -> tuple[bool, int]:
    """(whether small items fit, bins): otherwise what is left fills further bins up to 1 - eps."""
    over = small_total * eps.den - w_scaled
    if over <= 0:
        return True, n_bins
    return False, n_bins + -(-over // (cap * (eps.den - eps.num)))


def observed_cap(small_max: int, cap: int) -> Eps:
    """Small items are at most the largest one seen, a bound at least as good as eps."""
    return Eps(small_max, cap)


def rounded(items: Items, eps: Eps, how: str = "octaves", summary: str = "exact", **options) -> DataFrame:
    """Few sizes for the items that fit a bin, and for the last pieces of larger ones."""
    items = rounding.within_capacity(items)
    if how == "simple":
        return rounding.round_simple(items, eps)
    if summary == "exact":
        return rounding.round_octaves(items, eps, **options)
    return summaries.SUMMARIES[summary](items, eps, **options)


@dataclass(frozen=True)
class PackHow:
    rounding: str = "octaves"
    summary: str = "exact"
    solver: str = "lp"
    small_cap: str = "eps"


def report(items: Items, eps: Eps, instance: DataFrame, how: PackHow = PackHow()) -> DataFrame:
    """One row for each stream. Solving is one task a stream, on its few rounded sizes.

    An item over the capacity is one item in counts and totals; it fills whole bins, and its last piece is packed.
    """
    check_packing(eps)
    keys, cap = list(items.keys), items.cap
    totals = rounding.split_pieces(items, eps)
    if not keys:
        totals, instance = totals.withColumn("_one", F.lit(0)), instance.withColumn("_one", F.lit(0))
        keys = ["_one"]
    sizes = rounding.sizes_only(instance, tuple(keys))
    totals = totals.select(*(F.col(c).alias(c) for c in totals.columns))  # both sides stem from one table: names apart
    sizes = sizes.select(*(F.col(c).alias(c) for c in sizes.columns))

    def solve(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left):
            return pd.DataFrame(columns=[*keys, *(f.split()[0] for f in REPORT.split(", "))])
        row = left.iloc[0]
        pairs = [(int(s), int(n)) for s, n in zip(right["size_units"], right["multiplicity"], strict=True)]
        certificate = how.solver
        if how.solver == "lp":
            solution, _, certificate = solvers.solve_lp(pairs, cap)
        else:
            solution = solvers.SOLVERS[how.solver](pairs, cap)
        use = eps if how.small_cap == "eps" else observed_cap(int(row["largest_piece"]), cap)
        w = free_space(solution, cap, use)
        full = int(row["full_bins"])
        fits, alg = estimate_bins(solvers.bins(solution), w, int(row["small_pieces"]), cap, use)
        total = int(row["small_total"]) + int(row["big_total"])
        one = {k: row[k] for k in keys} | {
            "eps_num": eps.num, "eps_den": eps.den, "n_small": int(row["n_small"]), "n_big": int(row["n_big"]), "small_total": int(row["small_total"]), "big_total": int(row["big_total"]),
            "sigma": len(pairs), "rounded_total": sum(s * n for s, n in pairs), "rounded_bins": solvers.bins(solution) + full, "free_space": w / use.den / cap, "fits": fits, "alg": alg + full,
            "size_bound": -(-total // cap), "pair_bound": sum(n for s, n in pairs if 2 * s > cap) + full, "words": 3 * len(pairs) + 1, "log_term": eps.octaves, "certificate": certificate,
        }
        return pd.DataFrame([one])

    fields = "".join(f"{f.name} {f.dataType.simpleString()}, " for f in totals.schema if f.name in keys)
    out = totals.groupBy(*keys).cogroup(sizes.groupBy(*keys)).applyInPandas(solve, fields + REPORT)
    return out.drop("_one")


def pack(items: Items, eps_target: Eps, how: PackHow = PackHow(), **options) -> DataFrame:
    """End to end for a wanted factor 1 + eps_target."""
    eps = packing_eps(eps_target)
    return report(items, eps, rounded(items, eps, how.rounding, how.summary, **options), how)


def with_guarantee(df: DataFrame) -> DataFrame:
    """Whether the estimate is within (1 + 3 eps) of the lower bound, plus the sizes and the logarithmic term."""
    bound = F.greatest("size_bound", F.lit(1))
    limit = (1 + 3 * F.col("eps_num") / F.col("eps_den")) * bound + F.col("sigma") + F.col("log_term")
    return df.withColumn("ratio", F.col("alg") / bound).withColumn("above_lower", F.col("alg") >= F.col("size_bound")).withColumn("within_upper", F.col("alg") <= limit + 1)


def solution_of(items: Items, eps: Eps, instance: DataFrame) -> solvers.Solution:
    """The solution of a single stream, on the driver: the rounded sizes are few whatever the data."""
    rows = rounding.sizes_only(instance).collect()
    return solvers.solve_lp([(r["size_units"], r["multiplicity"]) for r in rows], items.cap)[0]


def describe(items: Items, eps: Eps, instance: DataFrame) -> DataFrame:
    """Patterns with their repeats and loads."""
    spark = items.df.sparkSession
    rows = [(k, [(s, c) for s, c in p], solvers.load(p), n) for k, (p, n) in enumerate(solution_of(items, eps, instance))]
    return spark.createDataFrame(rows, "pattern_id int, pattern array<struct<size_units:long,count:int>>, load_units long, bins long")


def assign(items: Items, eps: Eps, instance: DataFrame, item_id: str = "item_id") -> DataFrame:
    """A bin for every item, in one further pass: rounding keeps the order, so the r-th largest big item takes the r-th
    largest slot; a small item goes where the running total of small sizes meets the free space of the bins.
    """
    spark, cap = items.df.sparkSession, items.cap
    solution = solution_of(items, eps, instance)
    room = cap * (eps.den - eps.num) // eps.den
    patterns, gaps, first, free = [], [], 0, 0
    for p, n in solution:
        for s, c in p:
            patterns.append((s, first, n, c))
        gap = max(0, room - solvers.load(p))
        if gap:
            gaps.append((free, free + gap * n, gap, first))
            free += gap * n
        first += n
    slots = spark.createDataFrame(patterns, "slot_size long, first_bin long, n_bins long, per_bin long")
    slots = slots.withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_bins") * F.col("per_bin") - 1)))
    slots = slots.select("slot_size", (F.col("first_bin") + F.expr("k div per_bin")).alias("bin"), "k")
    slots = with_rank(slots, "slot_size", ["bin", "k"], "slot_rank").select("slot_rank", "bin")
    own = items.df.select(F.col(item_id).alias("item_id"), "size_units")
    big = with_rank(own.filter(is_big(F.col("size_units"), cap, eps)), "size_units", ["item_id"], "slot_rank")
    placed = big.join(slots, "slot_rank").select("item_id", "size_units", "bin")
    small = with_prefix(own.filter(~is_big(F.col("size_units"), cap, eps)), F.col("size_units"), "item_id")
    holes = spark.createDataFrame(gaps, "lo long, hi long, gap long, hole_bin long") if gaps else spark.createDataFrame([], "lo long, hi long, gap long, hole_bin long")
    at = small.join(F.broadcast(holes), (F.col("prefix_before") >= F.col("lo")) & (F.col("prefix_before") < F.col("hi")), "left")
    where = F.when(F.col("lo").isNotNull(), F.col("hole_bin") + F.expr("(prefix_before - lo) div gap")).otherwise(F.lit(first) + F.expr(f"(prefix_before - {free}L) div {max(room, 1)}L"))
    return placed.unionByName(at.select("item_id", "size_units", where.cast("long").alias("bin")))


def assignment_check(items: Items, eps: Eps, instance: DataFrame) -> DataFrame:
    loads = assign(items, eps, instance).groupBy("bin").agg(F.sum("size_units").alias("load"), F.count(F.lit(1)).alias("n"))
    return loads.agg(F.count(F.lit(1)).alias("bins"), F.sum("n").alias("items"), F.max("load").alias("fullest"), (F.max("load") <= items.cap).alias("feasible"))
