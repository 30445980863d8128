"""Makespan of scalar jobs from geometric counters and a small total."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.functions.units import exponent
from packsum.operators.solvers import bisect_capacity, list_schedule, longest_first
from packsum.params import Eps, geometric_count, geometric_grid

TOP = 1 << 60  # the largest size that tables admit; the grid ends there


def with_exponent(df: DataFrame, eps: Eps, size: str = "size_units", top: int = TOP) -> DataFrame:
    """Jobs of size 0 have no exponent."""
    return df.withColumn("exp_i", F.when(F.col(size) > 0, exponent(F.col(size), eps, top)))


def counters(df: DataFrame, eps: Eps, keys: tuple[str, ...] = (), top: int = TOP) -> DataFrame:
    """Count and total of every exponent of the absolute grid, in one pass; any later cut needs only these rows."""
    return with_exponent(df, eps, top=top).filter("exp_i is not null").groupBy(*keys, "exp_i").agg(F.count(F.lit(1)).alias("n"), F.sum("size_units").cast("long").alias("total"), F.max("size_units").alias("largest"))


def cut(rows: DataFrame, eps: Eps, keys: tuple[str, ...] = ()) -> DataFrame:
    """(exp_i, n) of big jobs, and one row with a null exponent for the small total."""
    k = geometric_count(eps)
    top = rows.groupBy(*keys).agg(F.max("exp_i").alias("q"))
    marked = rows.join(F.broadcast(top), list(keys)) if keys else rows.crossJoin(F.broadcast(top))
    big = F.col("exp_i") >= F.col("q") - k
    return marked.groupBy(*keys, F.when(big, F.col("exp_i")).alias("exp_i")).agg(F.sum("n").cast("long").alias("n"), F.sum("total").cast("long").alias("total"))


def summary_two_pass(df: DataFrame, eps: Eps) -> DataFrame:
    """The same, with the largest job known from a first pass: small jobs are summed without an exponent."""
    k = geometric_count(eps)
    biggest = df.agg(F.max("size_units")).first()[0] or 1
    grid = geometric_grid(eps, TOP)
    q = max(i for i, g in enumerate([0, *grid]) if g < biggest) - 1
    low = grid[q - k] if q - k >= 0 else 0
    big = F.col("size_units") > low
    out = df.filter("size_units > 0").withColumn("exp_i", F.when(big, exponent(F.col("size_units"), eps, TOP)))
    return out.groupBy("exp_i").agg(F.count(F.lit(1)).alias("n"), F.sum("size_units").cast("long").alias("total"))


class GeometricStream:
    """Order-faithful summary: when the largest exponent grows, buckets that fall behind enter the small total at their
    rounded size, so the total drifts up by at most 1 + eps."""

    def __init__(self, eps: Eps):
        self.grid, self.k = geometric_grid(eps, TOP), geometric_count(eps)
        self.q: int | None = None
        self.counts: dict[int, int] = {}
        self.small = 0
        self.most = 0

    def exponent(self, p: int) -> int:
        import bisect

        return bisect.bisect_left(self.grid, p) - 1

    def add(self, p: int) -> None:
        if p <= 0:
            return
        i = self.exponent(p)
        if self.q is None or i > self.q:
            self.q = i
            for j in [j for j in self.counts if j < i - self.k]:
                self.small += self.counts.pop(j) * self.grid[j + 1]
        if i >= self.q - self.k:
            self.counts[i] = self.counts.get(i, 0) + 1
        else:
            self.small += p
        self.most = max(self.most, len(self.counts) + 1)


def estimate(counts: list[tuple[int, int]], small: int, m: int, grid: list[int], peak_share: int) -> int:
    """Rounded big jobs longest first, then small jobs on the least loaded machine."""
    big = [(grid[i + 1], n) for i, n in counts]
    top = longest_first(big, m) if big else 0
    total = sum(s * n for s, n in big) + small
    return max(top, -(-total // m) + peak_share)


def makespan_rows(summary: DataFrame, eps: Eps, machines: list[int]) -> list[tuple]:
    """One summary answers for any number of machines."""
    rows = summary.collect()
    grid = geometric_grid(eps, TOP)
    counts = [(r["exp_i"], r["n"]) for r in rows if r["exp_i"] is not None]
    small = sum(r["total"] for r in rows if r["exp_i"] is None)
    true = sum(r["total"] for r in rows)
    out = []
    for m in machines:
        peak = grid[max(i for i, _ in counts) + 1] if counts else 0
        value = estimate(counts, small, m, grid, -(-peak * eps.num // eps.den) if small else 0)
        big = [(grid[i + 1], n) for i, n in counts]
        low = max(-(-sum(s * n for s, n in big) // m), max((s for s, _ in big), default=0)) if big else 0
        packed = bisect_capacity(big, m, low, longest_first(big, m)) if big else 0
        out.append((m, eps.num, eps.den, len(counts) + 1, value, max(packed, -(-(sum(s * n for s, n in big) + small) // m)), -(-true // m), small))
    return out


MAKESPAN = "machines int, eps_num int, eps_den int, words int, estimate long, by_packing long, load_bound long, small_total long"


def makespan_report(df: DataFrame, eps: Eps, machines: list[int]) -> DataFrame:
    spark = df.sparkSession
    summary = cut(counters(df, eps), eps)
    peak = df.agg(F.max("size_units")).first()[0] or 0
    rows = [(*r, max(int(r[6]), int(peak))) for r in makespan_rows(summary, eps, machines)]
    out = spark.createDataFrame(rows, MAKESPAN + ", lower_bound long")
    limit = (1 + 3 * float(eps.fraction)) * 4 / 3
    return out.withColumn("ratio", F.col("estimate") / F.greatest("lower_bound", F.lit(1))).withColumn("valid", (F.col("estimate") >= F.col("lower_bound")) & (F.col("ratio") <= limit + 1e-9))


def drift_report(df: DataFrame, eps: Eps, key: str, order: list[str]) -> DataFrame:
    """Per stream, in its order: the drifted small total against the exact one, which drift must keep within 1 + eps."""

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        s = GeometricStream(eps)
        sizes = [int(x) for x in pdf.sort_values(order)["size_units"]]
        for p in sizes:
            s.add(p)
        exact = sum(p for p in sizes if p > 0 and s.exponent(p) < (s.q or 0) - s.k)
        ok = exact <= s.small <= exact * (1 + float(eps.fraction)) + len(sizes)
        return pd.DataFrame([{key: pdf[key].iloc[0], "n": len(sizes), "small_drift": s.small, "small_exact": exact, "most_words": s.most, "within": ok}])

    kind = df.schema[key].dataType.simpleString()
    return df.groupBy(key).applyInPandas(fold, f"{key} {kind}, n long, small_drift long, small_exact long, most_words int, within boolean")


def by_list(df: DataFrame, m: int, longest: bool) -> int:
    """Baseline on all jobs, at test scale."""
    jobs = [r[0] for r in df.select("size_units").collect()]
    return list_schedule(sorted(jobs, reverse=True) if longest else jobs, m)


def modulo_assignment(df: DataFrame, ident: str, m: int) -> DataFrame:
    """Baseline without fallback: jobs by identifier modulo the machines."""
    return df.groupBy((F.col(ident) % m).cast("int").alias("machine")).agg(F.sum("size_units").cast("long").alias("load"), F.count(F.lit(1)).alias("n"))
