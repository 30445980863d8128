"""Vector scheduling in few dimensions: jobs counted by geometric type.

A big job's type is the exponent of every coordinate; a small job's type is the exponent of every coordinate relative
to its norm. Null stands for a zero coordinate. Coordinates of at most delta times the norm are zeroed first, with
delta = eps / d.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packsum.functions.units import exponent
from packsum.operators.containers import greedy_place
from packsum.operators.makespan import TOP
from packsum.params import Eps, geometric_grid, typed_allowed
from packsum.sources.tables import Vectors

KINDS = "kind string, type array<int>, n long, norm_sum long"


def drop_tiny(vectors: Vectors, eps: Eps) -> Vectors:
    """Keeps v_k > delta * norm."""
    top = F.array_max("v")
    v = F.transform("v", lambda x: F.when(x * (eps.den * vectors.dims) > top * eps.num, x).otherwise(F.lit(0).cast("long")))
    return Vectors(vectors.df.withColumn("v", v), vectors.dims, vectors.cap)


def relative_steps(eps: Eps, dims: int) -> list[Fraction]:
    """(1 + eps)**-t for t = 0, 1, ... down to delta."""
    out, base, t = [], 1 + eps.fraction, Fraction(1)
    while t >= eps.fraction / dims:
        out.append(t)
        t = t / base
    return [*out, t]


def relative_exponent(x: Column, top: Column, eps: Eps, dims: int) -> Column:
    """Largest t >= 0 with x <= top * (1 + eps)**-t; null where x is 0. Powers are fractions rounded to 2**-40."""
    steps = [int(s * (1 << 40)) for s in relative_steps(eps, dims)]
    table = F.array(*(F.lit(s).cast("decimal(20,0)") for s in steps))
    scaled = x.cast("decimal(20,0)") * F.lit(1 << 40).cast("decimal(14,0)")
    fits = F.filter(table, lambda s: scaled <= top.cast("decimal(17,0)") * s)
    return F.when(x > 0, F.greatest(F.size(fits) - 1, F.lit(0)).cast("int"))


def with_types(vectors: Vectors, eps: Eps) -> DataFrame:
    """Norm, exponent of the norm, and both types of every job."""
    own = drop_tiny(vectors, eps)
    parts = range(vectors.dims)
    df = own.df.withColumn("norm", F.array_max("v")).filter("norm > 0")
    big = F.array(*(F.when(F.get("v", F.lit(k)) > 0, exponent(F.get("v", F.lit(k)), eps, TOP)) for k in parts))
    small = F.array(*(relative_exponent(F.get("v", F.lit(k)), F.col("norm"), eps, vectors.dims) for k in parts))
    return df.withColumn("big_type", big).withColumn("small_type", small)


def big_threshold(vectors: Vectors, eps: Eps) -> int:
    """Jobs are big if their norm exceeds delta times the largest one."""
    top = vectors.df.agg(F.max(F.array_max("v"))).first()[0] or 0
    return eps.num * int(top) // (eps.den * vectors.dims)


def typed_summary(vectors: Vectors, eps: Eps, limit: int | None = None) -> DataFrame:
    """Two passes: the largest norm, then counts of big types and norm sums of small types in one aggregate."""
    if not typed_allowed(eps, vectors.dims):
        raise ValueError("too many types for this precision and dimension")
    limit = big_threshold(vectors, eps) if limit is None else limit
    df = with_types(vectors, eps)
    big = F.col("norm") > limit
    kind, own = F.when(big, "big").otherwise("small"), F.when(big, F.col("big_type")).otherwise(F.col("small_type"))
    return df.groupBy(kind.alias("kind"), own.alias("type")).agg(F.count(F.lit(1)).alias("n"), F.sum("norm").cast("long").alias("norm_sum"))


def typed_report(vectors: Vectors, eps: Eps) -> DataFrame:
    from packsum.params import typed_bound

    s = typed_summary(vectors, eps)
    return s.agg(F.count_if(F.col("kind") == "big").alias("big_types"), F.count_if(F.col("kind") == "small").alias("small_types"), F.sum("n").cast("long").alias("jobs")).withColumn("type_bound", F.lit(typed_bound(eps, vectors.dims))).withColumn("within", F.col("big_types") <= F.col("type_bound") + F.lit(2**vectors.dims))


class TypedStream:
    """Order-faithful summary: a big type that falls behind the largest exponent turns into a small type at its rounded
    norm."""

    def __init__(self, eps: Eps, dims: int):
        self.eps, self.dims = eps, dims
        self.grid = geometric_grid(eps, TOP)
        self.steps = relative_steps(eps, dims)
        self.reach = next(k for k in range(10_000) if (1 + eps.fraction) ** k >= dims / eps.fraction)
        self.q: int | None = None
        self.big: dict[tuple, int] = {}
        self.small: dict[tuple, int] = {}

    def exponent(self, p: int) -> int:
        import bisect

        return bisect.bisect_left(self.grid, p) - 1

    def relative(self, v: tuple[int, ...]) -> tuple:
        top = max(v)
        return tuple(None if x == 0 else max(sum(1 for s in self.steps if x <= top * s) - 1, 0) for x in v)

    def add(self, v: tuple[int, ...]) -> None:
        top = max(v)
        if top == 0:
            return
        v = tuple(x if x * self.eps.den * self.dims > top * self.eps.num else 0 for x in v)
        i = self.exponent(top)
        if self.q is None or i > self.q:
            self.q = i
            for t in [t for t in self.big if max(x for x in t if x is not None) < i - self.reach]:
                n, peak = self.big.pop(t), max(x for x in t if x is not None)
                own = tuple(None if x is None else peak - x for x in t)
                self.small[own] = self.small.get(own, 0) + n * self.grid[peak + 1]
        if i >= self.q - self.reach:
            t = tuple(None if x == 0 else self.exponent(x) for x in v)
            self.big[t] = self.big.get(t, 0) + 1
        else:
            t = self.relative(v)
            self.small[t] = self.small.get(t, 0) + top


def typed_drift(vectors: Vectors, eps: Eps, order: str = "job_id") -> DataFrame:
    """Sequential against batch, in one order: norm sums of small jobs within 1 + eps of the exact ones, and the loads of
    every coordinate, as their types tell them, within (1 + eps)**2. Roundings to whole units are one for each job."""
    dims = vectors.dims

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        s = TypedStream(eps, dims)
        rows = [tuple(int(x) for x in v) for v in pdf.sort_values("place", kind="stable")["v"]]
        for v in rows:
            s.add(v)
        small = [v for v in rows if max(v) > 0 and s.exponent(max(v)) < s.q - s.reach]
        exact = sum(max(v) for v in small)
        got = sum(s.small.values())
        base = 1 + float(eps.fraction)
        ok = exact <= got <= exact * base + len(rows)
        kept = [[x if x * eps.den * dims > max(v) * eps.num else 0 for x in v] for v in small]
        true = [sum(v[k] for v in kept) for k in range(dims)]
        told = [sum(total * base ** -t[k] for t, total in s.small.items() if t[k] is not None) for k in range(dims)]
        loads = all(x - len(rows) <= y <= x * base**2 + len(rows) for x, y in zip(true, told, strict=True))
        worst = max((y / x for x, y in zip(true, told, strict=True) if x), default=1.0)
        return pd.DataFrame([{"n": len(rows), "big_types": len(s.big), "small_types": len(s.small), "norm_drift": got, "norm_exact": exact, "within": ok, "n_small": len(small), "load_drift": worst, "loads_within": loads}])

    one = vectors.df.select(F.col(order).alias("place"), "v", F.lit(0).alias("g"))
    return one.groupBy("g").applyInPandas(fold, "n long, big_types int, small_types int, norm_drift long, norm_exact long, within boolean, n_small long, load_drift double, loads_within boolean").drop("g")


def typed_estimate(vectors: Vectors, eps: Eps, m: int) -> DataFrame:
    """Makespan of representatives: big types at their upper corner, small types cut into pieces of delta times the peak."""
    spark = vectors.df.sparkSession
    grid, rows = geometric_grid(eps, TOP), typed_summary(vectors, eps).collect()
    limit = max(1, big_threshold(vectors, eps))
    out: list[tuple[int, ...]] = []
    for r in rows:
        if r["kind"] == "big":
            out += [tuple(0 if t is None else grid[t + 1] for t in r["type"])] * r["n"]
        else:
            base = 1 + float(eps.fraction)
            left = r["norm_sum"]
            while left > 0:
                piece = min(limit, left)
                out.append(tuple(0 if t is None else int(np.ceil(piece / base**t)) for t in r["type"]))
                left -= piece
    every = np.array(sorted(out, key=max, reverse=True), np.int64).reshape(-1, vectors.dims)
    value = int(greedy_place(every, m).max()) if len(every) else 0
    sums = vectors.df.agg(*(F.coalesce(F.sum(F.get("v", F.lit(k))), F.lit(0)).alias(f"l{k}") for k in range(vectors.dims)), F.coalesce(F.max(F.array_max("v")), F.lit(0)).alias("peak")).first()
    low = max(max(-(-int(sums[f"l{k}"]) // m) for k in range(vectors.dims)), int(sums["peak"]))
    return spark.createDataFrame([(m, len(rows), len(every), value, low, value / max(low, 1))], "machines int, types int, pieces int, estimate long, lower_bound long, ratio double")
