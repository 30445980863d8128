"""Rank summaries other than the exact grid: built-in deterministic, randomised, bounded universe, and sequential."""

from __future__ import annotations

import bisect
import math


import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.functions.units import is_big
from packsum.operators.rounding import grid_steps, histogram, steps_to_instance, with_octave
from packsum.params import Eps, octave_step
from packsum.sources.tables import Items


def builtin_steps(items: Items, eps: Eps) -> DataFrame:
    """Deterministic summary from one aggregate: a percentile grid, the exact ends, and rank bounds by its accuracy.

    Accuracy 1/A with A = ceil(8 / eps) and rank fractions eps / 4 apart keep every shift within eps * n / 2; octaves of
    fewer than 32 / eps items take the exact grid.
    """
    a, gap = math.ceil(8 / float(eps.fraction)), float(eps.fraction) / 4
    fractions = [k * gap for k in range(1, math.ceil(1 / gap)) if k * gap < 1]
    big = with_octave(items, eps).filter(is_big(F.col("size_units"), items.cap, eps))
    agg = big.groupBy(*items.keys, "group_j").agg(
        F.count(F.lit(1)).alias("n"), F.max("size_units").alias("hi"), F.min("size_units").alias("lo"), F.percentile_approx("size_units", [1 - f for f in fractions], a).alias("q")
    )
    few = math.ceil(32 / float(eps.fraction))
    body = agg.filter(F.col("n") >= few).select(*items.keys, "group_j", "n", F.posexplode("q").alias("i", "size_units"))
    bound = F.least("n", F.ceil((F.element_at(F.array(*map(F.lit, fractions)), F.col("i") + 1) + 1 / a) * F.col("n")) + 1)
    inner = body.select(*items.keys, "group_j", "size_units", bound.cast("long").alias("rank_hi"))
    wide = agg.filter(F.col("n") >= few)
    ends = wide.select(*items.keys, "group_j", F.col("hi").alias("size_units"), F.lit(1).cast("long").alias("rank_hi")).unionByName(wide.select(*items.keys, "group_j", F.col("lo").alias("size_units"), F.col("n").alias("rank_hi")))
    steps = monotone(inner.unionByName(ends), items.keys)
    return steps.unionByName(exact_where_few(items, eps, agg, few))


def exact_where_few(items: Items, eps: Eps, agg: DataFrame, few: int) -> DataFrame:
    """Exact steps of the octaves with fewer than ``few`` items: only their rows leave the scan, at most that many each."""
    small = agg.filter(F.col("n") < few).select(*items.keys, "group_j")
    rows = with_octave(items, eps).join(F.broadcast(small) if not items.keys else small, [*items.keys, "group_j"], "left_semi")
    return grid_steps(histogram(Items(rows.drop("group_j"), items.cap, items.keys), eps), octave_step("n_j", eps), items.keys)


def monotone(steps: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """One step for each rank bound (the larger value is safe) and each value (its least bound)."""
    one = steps.groupBy(*keys, "group_j", "rank_hi").agg(F.max("size_units").alias("size_units"))
    best = one.groupBy(*keys, "group_j", "size_units").agg(F.min("rank_hi").alias("rank_hi"), F.max("rank_hi").alias("top"))
    last = one.groupBy(*keys, "group_j").agg(F.max("rank_hi").alias("n"))
    return best.join(last, [*keys, "group_j"]).select(*keys, "group_j", "size_units", F.explode(F.array_distinct(F.array("rank_hi", F.when(F.col("top") == F.col("n"), F.col("n")).otherwise(F.col("rank_hi"))))).alias("rank_hi"))


def round_builtin(items: Items, eps: Eps) -> DataFrame:
    return steps_to_instance(builtin_steps(items, eps), items.keys)


def sketch_size(error: float, failure: float) -> int:
    """Size of a quantile sketch whose normalised rank error is at most ``error`` but for a share ``failure`` of runs.

    2.296 / k**0.9021 is the published error of the sketch at 1 %; the tail falls like that of a normal distribution.
    """
    tail = math.sqrt(max(1.0, math.log(1 / failure) / math.log(100)))
    return min(65_535, max(8, math.ceil((2.296 * tail / error) ** (1 / 0.9021))))


def random_steps(items: Items, eps: Eps, sketch_k: int | None = None, error: float | None = None, failure: float = 1e-4) -> DataFrame:
    """Randomised summary: a mergeable quantile sketch for each octave; rank bounds move by its rank error.

    The sketch's size follows from the allowed failure, unless it is given; octaves of fewer than 32 / eps items take the
    exact grid, as rank bounds of whole positions are too wide for them.
    """
    gap = float(eps.fraction) / 4
    error = float(eps.fraction) / 16 if error is None else error
    sketch_k = sketch_size(error, failure) if sketch_k is None else sketch_k
    fractions = [k * gap for k in range(1, math.ceil(1 / gap)) if k * gap < 1]
    big = with_octave(items, eps).filter(is_big(F.col("size_units"), items.cap, eps))
    agg = big.groupBy(*items.keys, "group_j").agg(
        F.count(F.lit(1)).alias("n"), F.max("size_units").alias("hi"), F.min("size_units").alias("lo"), F.expr(f"kll_sketch_agg_bigint(size_units, {sketch_k})").alias("sketch")
    )
    ranks = ", ".join(f"{1 - f}D" for f in fractions)
    few = math.ceil(32 / float(eps.fraction))
    wide = agg.filter(F.col("n") >= few)
    body = wide.select(*items.keys, "group_j", "n", F.posexplode(F.expr(f"kll_sketch_get_quantile_bigint(sketch, array({ranks}))")).alias("i", "size_units"))
    bound = F.least("n", F.ceil((F.element_at(F.array(*map(F.lit, fractions)), F.col("i") + 1) + error) * F.col("n")) + 1)
    inner = body.select(*items.keys, "group_j", "size_units", bound.cast("long").alias("rank_hi"))
    ends = wide.select(*items.keys, "group_j", F.col("hi").alias("size_units"), F.lit(1).cast("long").alias("rank_hi")).unionByName(wide.select(*items.keys, "group_j", F.col("lo").alias("size_units"), F.col("n").alias("rank_hi")))
    return monotone(inner.unionByName(ends), items.keys).unionByName(exact_where_few(items, eps, agg, few))


def round_random(items: Items, eps: Eps, sketch_k: int | None = None, failure: float = 1e-4) -> DataFrame:
    return steps_to_instance(random_steps(items, eps, sketch_k, failure=failure), items.keys)


def round_universe(items: Items, eps: Eps, bits: int = 24) -> DataFrame:
    """Bounded universe: a dyadic tree over units, compressed from the leaves with delta = eps / 2.

    Work is on the histogram of an octave, which the universe bounds. A node that stays rounds its items up to its top
    leaf, held to the octave's maximum, so ranks dominate; one root path bounds the shift.
    """
    if items.cap >= 1 << bits:
        raise ValueError("the universe is larger than its stated bits")
    keys, num, den = list(items.keys), eps.num, 2 * eps.den

    def compress(pdf: pd.DataFrame) -> pd.DataFrame:
        total, top = int(pdf["n"].sum()), int(pdf["size_units"].max())
        keep = total * num // (den * bits)
        level = dict(zip(pdf["size_units"].astype(int), pdf["n"].astype(int), strict=True))
        out: dict[int, int] = {}
        for height in range(bits):
            parents: dict[int, int] = {}
            for node, n in level.items():
                parents[node >> 1] = parents.get(node >> 1, 0) + n
            up: dict[int, int] = {}
            for node, n in level.items():
                if parents[node >> 1] <= keep:
                    up[node >> 1] = parents[node >> 1]
                else:
                    value = min(top, ((node + 1) << height) - 1)
                    out[value] = out.get(value, 0) + n
            level = up
        for n in level.values():
            out[top] = out.get(top, 0) + n
        head = {k: pdf[k].iloc[0] for k in [*keys, "group_j"]}
        return pd.DataFrame([{**head, "size_units": v, "multiplicity": n} for v, n in out.items()])

    hist = histogram(items, eps)
    fields = "".join(f"{f.name} {f.dataType.simpleString()}, " for f in hist.schema if f.name in keys)
    return hist.groupBy(*keys, "group_j").applyInPandas(compress, fields + "group_j int, size_units long, multiplicity long")


class SequentialSummary:
    """Deterministic one-pass summary of ranks in non-increasing order: tuples (value, gap, spread).

    Prefix sums of gaps bound ranks from below, and with the spread from above; gap + spread stays within 2 delta n.
    """

    def __init__(self, delta: float):
        self.delta, self.n, self.most = delta, 0, 0
        self.values: list[int] = []  # negated, so that order is ascending
        self.gaps: list[int] = []
        self.spreads: list[int] = []
        self.period = max(1, int(1 / (2 * delta)))

    def add(self, value: int) -> None:
        at = bisect.bisect_left(self.values, -value)
        edge = at == 0 or at == len(self.values)
        self.values.insert(at, -value)
        self.gaps.insert(at, 1)
        self.spreads.insert(at, 0 if edge else max(0, int(2 * self.delta * self.n) - 1))
        self.n += 1
        if self.n % self.period == 0:
            self.compress()
        self.most = max(self.most, len(self.values))

    def compress(self) -> None:
        limit = int(2 * self.delta * self.n)
        i = len(self.values) - 2
        while i >= 1:
            if self.gaps[i] + self.gaps[i + 1] + self.spreads[i + 1] <= limit:
                self.gaps[i + 1] += self.gaps[i]
                del self.values[i], self.gaps[i], self.spreads[i]
            i -= 1

    def bounds(self) -> list[tuple[int, int, int]]:
        """(value, least rank, greatest rank) of every stored value."""
        out, low = [], 0
        for v, g, s in zip(self.values, self.gaps, self.spreads, strict=True):
            low += g
            out.append((-v, low, low + s))
        return out

    def steps(self) -> list[tuple[int, int]]:
        """(value, rank bound): bounds in order, ends exact, one value for each bound."""
        best: dict[int, int] = {}
        for value, _, high in self.bounds():
            best[min(high, self.n)] = max(value, best.get(min(high, self.n), 0))
        if self.values:
            best[1] = -self.values[0]
            best[self.n] = max(best.get(self.n, 0), -self.values[-1])
        return sorted((r, v) for r, v in best.items())


def round_sequential(items: Items, eps: Eps, parts: int = 8) -> DataFrame:
    """The sequential summary in hash parts with precision eps / 16, rounded again with as much after the union."""
    keys = list(items.keys)
    delta = float(eps.fraction) / 16
    big = with_octave(items, eps).filter(is_big(F.col("size_units"), items.cap, eps)).select(*keys, "group_j", "size_units")
    salted = big.withColumn("part", F.pmod(F.monotonically_increasing_id(), F.lit(parts)))

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        s = SequentialSummary(delta)
        for x in pdf["size_units"]:
            s.add(int(x))
        head = {k: pdf[k].iloc[0] for k in [*keys, "group_j", "part"]}
        return pd.DataFrame([{**head, "size_units": v, "rank_hi": r, "most": s.most} for r, v in s.steps()])

    fields = "".join(f"{f.name} {f.dataType.simpleString()}, " for f in big.schema if f.name in keys)
    steps = salted.groupBy(*keys, "group_j", "part").applyInPandas(fold, fields + "group_j int, part long, size_units long, rank_hi long, most int")
    own = (*items.keys, "part")
    leaves = steps_to_instance(steps.select(*own, "group_j", "size_units", "rank_hi"), own)
    union = leaves.groupBy(*keys, "group_j", "size_units").agg(F.sum("multiplicity").alias("n"))
    return steps_to_instance(grid_steps(union, octave_step("n_j", Eps(eps.num, 2 * eps.den)), items.keys), items.keys)


def sequential_report(items: Items, eps: Eps) -> DataFrame:
    """Rank error and memory of one sequential summary for each octave, read in table order; exact ranks beside it."""
    delta = float(eps.fraction) / 8
    big = with_octave(items, eps).filter(is_big(F.col("size_units"), items.cap, eps)).select("group_j", "size_units")

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        s = SequentialSummary(delta)
        for x in pdf["size_units"]:
            s.add(int(x))
        ordered = sorted((-int(x) for x in pdf["size_units"]))
        allowed = int(2 * delta * s.n)
        off = 0
        for value, low, high in s.bounds():
            first, last = bisect.bisect_left(ordered, -value) + 1, bisect.bisect_right(ordered, -value)
            off = max(off, first - high, low - last, high - low)
        return pd.DataFrame([{"group_j": pdf["group_j"].iloc[0], "n_j": s.n, "stored": len(s.values), "most_stored": s.most, "words": 3 * s.most, "worst": max(0, off), "allowed": allowed, "ok": off <= max(allowed, 1)}])

    return big.groupBy("group_j").applyInPandas(fold, "group_j int, n_j long, stored int, most_stored int, words int, worst long, allowed long, ok boolean")




SUMMARIES = {"exact": None, "builtin": round_builtin, "random": round_random, "universe": round_universe, "sequential": round_sequential}
