"""Vector scheduling: big jobs are kept, small ones are combined into containers of bounded norm.

Thresholds are shares of T, the largest load over the machines, so no data is rescaled. All amounts are whole units.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from packsum.sources.tables import Vectors

SUMMARY = "kind string, vec array<long>, norm long, n_jobs long"


def norm(v: str = "v") -> Column:
    return F.array_max(v)


def loads(vectors: Vectors, m: int) -> DataFrame:
    """Load of every dimension, jobs, and the largest norm: one row."""
    sums = [F.coalesce(F.sum(F.get("v", F.lit(k))), F.lit(0)).cast("long").alias(f"load_{k}") for k in range(vectors.dims)]
    out = vectors.df.agg(F.count(F.lit(1)).alias("n_jobs"), F.coalesce(F.max(norm()), F.lit(0)).alias("largest_norm"), *sums)
    return out.withColumn("largest_load", F.greatest(*(F.col(f"load_{k}") for k in range(vectors.dims))) if vectors.dims > 1 else F.col("load_0")).withColumn("machines", F.lit(m))


def load_bound(vectors: Vectors, m: int) -> int:
    """m * T: the largest load of a dimension."""
    return int(loads(vectors, m).first()["largest_load"])


def is_small(size: Column, gamma: Fraction, load: int, m: int) -> Column:
    """norm <= gamma * load / m."""
    return size <= F.lit(gamma.numerator * load // (gamma.denominator * m))


def prefix_buckets(vectors: Vectors, m: int, gamma: Fraction, load: int, salts: int = 16) -> DataFrame:
    """Small jobs with their container: within a salt, running norm totals are cut every gamma * T.

    Jobs of a bucket start within one gamma * T and the last adds at most as much, so the container's norm is at most
    2 gamma T; buckets are at most d m / gamma plus one for each salt.
    """
    small = vectors.df.withColumn("norm", norm()).filter(is_small(F.col("norm"), gamma, load, m)).withColumn("salt", F.pmod(F.col("job_id"), F.lit(salts)))
    before = Window.partitionBy("salt").orderBy("job_id", "norm", "v").rowsBetween(Window.unboundedPreceding, -1)
    prefix = F.coalesce(F.sum("norm").over(before), F.lit(0)).cast("decimal(38,0)")
    return small.withColumn("prefix", prefix).withColumn("bucket", F.expr(f"cast((prefix * {m * gamma.denominator}) div {max(1, gamma.numerator * load)} as bigint)"))


def containers_prefix(vectors: Vectors, m: int, gamma: Fraction, salts: int = 16, load: int | None = None) -> DataFrame:
    """Summary in built-in expressions alone: one row for each big job or container."""
    load = load_bound(vectors, m) if load is None else load
    sums = [F.sum(F.get("v", F.lit(k))).cast("long") for k in range(vectors.dims)]
    packed = prefix_buckets(vectors, m, gamma, load, salts).groupBy("salt", "bucket").agg(F.array(*sums).alias("vec"), F.count(F.lit(1)).alias("n_jobs"))
    small = packed.select(F.lit("container").alias("kind"), "vec", F.array_max("vec").alias("norm"), "n_jobs")
    return big_jobs(vectors, m, gamma, load).unionByName(small)


def big_jobs(vectors: Vectors, m: int, gamma: Fraction, load: int) -> DataFrame:
    return vectors.df.filter(~is_small(norm(), gamma, load, m)).select(F.lit("big").alias("kind"), F.col("v").alias("vec"), norm().alias("norm"), F.lit(1).cast("long").alias("n_jobs"))


@dataclass
class ContainerStream:
    """One pass with a growing T: jobs that were big turn small, closed containers open again, opens are combined."""

    m: int
    gamma: Fraction
    dims: int
    first_fit: bool = False
    load: np.ndarray = None
    n: int = 0
    big: list = field(default_factory=list)  # heaps by norm
    closed: list = field(default_factory=list)
    open: tuple | None = None  # (vector, jobs)
    most: int = 0
    tick: int = 0  # keeps heap entries apart

    def __post_init__(self):
        self.load = np.zeros(self.dims, np.int64)

    @property
    def small(self) -> int:
        """Largest norm of a small job now."""
        return self.gamma.numerator * int(self.load.max()) // (self.gamma.denominator * self.m)

    def add(self, v: np.ndarray) -> None:
        self.load += v
        self.n += 1
        limit = self.small
        while self.big and self.big[0][0] <= limit:
            self._put(heapq.heappop(self.big)[2], 1, limit)
        while self.closed and self.closed[0][0] <= limit:
            _, _, vec, jobs = heapq.heappop(self.closed)
            self._put(vec, jobs, limit)
        if int(v.max()) <= limit:
            self._put(v, 1, limit)
        else:
            heapq.heappush(self.big, (int(v.max()), self.n, v))
        self.most = max(self.most, len(self.big) + len(self.closed) + (self.open is not None))

    def _put(self, v: np.ndarray, jobs: int, limit: int) -> None:
        if self.first_fit:
            for i, (_, order, vec, n) in enumerate(self.closed):
                both = vec + v
                if int(both.max()) <= 2 * limit:
                    self.closed[i] = (int(both.max()), order, both, n + jobs)
                    heapq.heapify(self.closed)
                    return
        vec, n = self.open if self.open else (np.zeros(self.dims, np.int64), 0)
        vec, n = vec + v, n + jobs
        if int(vec.max()) > limit:
            self.tick += 1
            heapq.heappush(self.closed, (int(vec.max()), self.tick, vec, n))
            self.open = None
        else:
            self.open = (vec, n)

    def rows(self) -> list[tuple]:
        out = [("big", x[2].tolist(), x[0], 1) for x in self.big] + [("container", x[2].tolist(), x[0], x[3]) for x in self.closed]
        if self.open:
            out.append(("container", self.open[0].tolist(), int(self.open[0].max()), self.open[1]))
        return out


def containers_sequential(vectors: Vectors, m: int, gamma: Fraction, order: str = "job_id", first_fit: bool = False) -> DataFrame:
    """The one-pass algorithm in the order of a column: sequential by nature, one task."""
    dims = vectors.dims

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        s = ContainerStream(m, gamma, dims, first_fit)
        for v in pdf.sort_values("place", kind="stable")["v"]:
            s.add(np.asarray(v, np.int64))
        return pd.DataFrame([(*r, s.most) for r in s.rows()], columns=["kind", "vec", "norm", "n_jobs", "most"])

    one = vectors.df.select(F.col(order).alias("place"), "v", F.lit(0).alias("g"))
    return one.groupBy("g").applyInPandas(fold, SUMMARY + ", most long").drop("g")


def next_fit_containers(rows: Iterator[tuple[np.ndarray, int]], limit: int) -> Iterator[tuple[np.ndarray, int, bool]]:
    """Containers of at most twice the limit: (vector, jobs, whether closed)."""
    vec, n = None, 0
    for v, jobs in rows:
        vec, n = (v if vec is None else vec + v), n + jobs
        if int(vec.max()) > limit:
            yield vec, n, True
            vec, n = None, 0
    if vec is not None:
        yield vec, n, False


def containers_parallel(vectors: Vectors, m: int, gamma: Fraction, load: int | None = None) -> DataFrame:
    """Two passes: loads first, then next fit in every partition with the final T; the opens are combined at the end.

    Any packing of small jobs under twice gamma T keeps the guarantee.
    """
    load = load_bound(vectors, m) if load is None else load
    limit = gamma.numerator * load // (gamma.denominator * m)

    def fold(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def rows() -> Iterator[tuple[np.ndarray, int]]:
            for pdf in batches:
                for v in pdf["v"]:
                    yield np.asarray(v, np.int64), 1

        out = [("container" if closed else "open", vec.tolist(), int(vec.max()), n) for vec, n, closed in next_fit_containers(rows(), limit)]
        yield pd.DataFrame(out, columns=["kind", "vec", "norm", "n_jobs"])

    small = vectors.df.filter(is_small(norm(), gamma, load, m)).select("v").mapInPandas(fold, SUMMARY)
    return big_jobs(vectors, m, gamma, load).unionByName(combine_open(small, limit))


def combine_open(summary: DataFrame, limit: int) -> DataFrame:
    """Open containers, one a partition at most, are combined in one task; closed ones stay where they are."""

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = ((np.asarray(v, np.int64), int(n)) for v, n in zip(pdf["vec"], pdf["n_jobs"], strict=True))
        return pd.DataFrame([("container", vec.tolist(), int(vec.max()), n) for vec, n, _ in next_fit_containers(rows, limit)], columns=["kind", "vec", "norm", "n_jobs"])

    merged = summary.filter("kind = 'open'").groupBy(F.lit(0).alias("g")).applyInPandas(fold, SUMMARY)
    return summary.filter("kind <> 'open'").unionByName(merged)


def merge_containers(a: DataFrame, b: DataFrame, dims: int, m: int, gamma: Fraction) -> DataFrame:
    """Two summaries under the load of both: jobs no longer big are combined, small containers with them."""
    both = a.unionByName(b)
    load = int(both.agg(*(F.coalesce(F.sum(F.get("vec", F.lit(k))), F.lit(0)).alias(f"l{k}") for k in range(dims))).select(F.greatest(*(F.col(f"l{k}") for k in range(dims))) if dims > 1 else F.col("l0")).first()[0])
    limit = gamma.numerator * load // (gamma.denominator * m)
    stay = both.filter(F.col("norm") > limit)
    small = both.filter(F.col("norm") <= limit).select(F.lit("open").alias("kind"), "vec", "norm", "n_jobs")
    return combine_open(stay.unionByName(small), limit)


def container_report(summary: DataFrame, vectors: Vectors, m: int, gamma: Fraction, extra: int = 1) -> DataFrame:
    """Counts, space bound, capacity, and whether all load is still there."""
    load = load_bound(vectors, m)
    limit = gamma.numerator * load // (gamma.denominator * m)
    kept = [F.coalesce(F.sum(F.get("vec", F.lit(k))), F.lit(0)).cast("long").alias(f"load_{k}") for k in range(vectors.dims)]
    got = summary.agg(F.count_if(F.col("kind") == "big").alias("n_big"), F.count_if(F.col("kind") != "big").alias("n_containers"), F.sum("n_jobs").alias("jobs"), F.coalesce(F.max(F.when(F.col("kind") != "big", F.col("norm"))), F.lit(0)).alias("fullest"), *kept)
    true = loads(vectors, m).select("n_jobs", *(F.col(f"load_{k}").alias(f"true_{k}") for k in range(vectors.dims)))
    same = F.lit(True)
    for k in range(vectors.dims):
        same &= F.col(f"load_{k}") == F.col(f"true_{k}")
    bound = int(vectors.dims * m / gamma) + extra
    one = got.crossJoin(F.broadcast(true))
    return one.select("n_big", "n_containers", F.col("jobs").cast("long").alias("jobs"), "fullest", (F.col("fullest") <= 2 * limit + 2).alias("capacity_ok"), (same & (F.col("jobs") == F.col("n_jobs"))).alias("load_kept"), F.lit(bound).alias("space_bound"), (F.col("n_big") + F.col("n_containers") <= bound).alias("space_ok"), ((F.col("n_big") + F.col("n_containers")) * vectors.dims + vectors.dims).alias("words"))


def containers_grouped(vectors: Vectors, group: str) -> DataFrame:
    """One container for each group that is given with the jobs; a group below 0 is a big job."""
    sums = [F.sum(F.get("v", F.lit(k))).cast("long") for k in range(vectors.dims)]
    packed = vectors.df.groupBy(group).agg(F.array(*sums).alias("vec"), F.count(F.lit(1)).alias("n_jobs"))
    return packed.select(F.when(F.col(group) < 0, "big").otherwise("container").alias("kind"), "vec", F.array_max("vec").alias("norm"), "n_jobs")


def greedy_place(vectors: np.ndarray, m: int, start: np.ndarray | None = None) -> np.ndarray:
    """Loads after giving each vector to the machine whose largest load ends least."""
    used = np.zeros((m, vectors.shape[1]), np.int64) if start is None else start.copy()
    for v in vectors:
        k = int((used + v).max(axis=1).argmin())
        used[k] += v
    return used


def random_then_greedy(containers: np.ndarray, m: int, eps: float, scale: float, seed: int) -> tuple[np.ndarray, float]:
    """Random machines, each refusing what takes it over its share plus eps; refused ones are placed greedily among
    themselves. Returns loads and the share handed over. scale is T."""
    rng = np.random.default_rng(seed)
    d = containers.shape[1]
    share = np.maximum(0.5, containers.sum(axis=0) / (m * scale)) + eps
    first, second, handed = np.zeros((m, d)), np.zeros((m, d)), 0.0
    full = np.zeros(m, bool)
    for v in containers / scale:
        k = int(rng.integers(m))
        if full[k] or (first[k] > share).any():
            full[k] = True
            j = int((second + v).max(axis=1).argmin())
            second[j] += v
            handed += float(v.sum())
        else:
            first[k] += v
    return (first + second) * scale, handed / max(1e-12, float(containers.sum()) / scale)


def placement(summary: DataFrame, dims: int, m: int, gamma: Fraction, eps: float, tries: int = 20) -> DataFrame:
    """Containers placed at random with greedy repair, seed after seed until the proved load holds."""
    spark = summary.sparkSession
    rows = [r["vec"] for r in summary.filter("kind <> 'big'").collect()]
    every = [r["vec"] for r in summary.collect()]
    c = np.array(rows, np.int64).reshape(-1, dims)
    scale = np.array(every, np.int64).reshape(-1, dims).sum(axis=0).max() / m
    share = np.maximum(0.5, c.sum(axis=0) / (m * scale)) if len(c) else np.full(dims, 0.5)
    out = (0, 0.0, 0.0, False)
    for seed in range(tries):
        used, handed = random_then_greedy(c, m, eps, scale, seed)
        slack = float((used / scale - share).max()) if len(c) else 0.0
        ok = slack <= 2 * eps + 4 * float(gamma) + 1e-9
        out = (seed, slack, float(handed), bool(ok))
        if ok:
            break
    return spark.createDataFrame([(m, len(c), *out)], "machines int, n_containers int, seed int, worst_slack double, handed_share double, within boolean")


def makespan_estimate(summary: DataFrame, dims: int, m: int, gamma: Fraction, eps: float, seeds: int = 5) -> tuple[int, int]:
    """(estimate, lower bound) from the summary alone: the best of three placements of the big jobs and containers."""
    rows = summary.select("kind", "vec").collect()
    big = np.array([r["vec"] for r in rows if r["kind"] == "big"], np.int64).reshape(-1, dims)
    small = np.array([r["vec"] for r in rows if r["kind"] != "big"], np.int64).reshape(-1, dims)
    every = np.concatenate([big, small])
    if not len(every):
        return 0, 0
    order = every[np.argsort(-every.max(axis=1), kind="stable")]
    low = max(-(-int(every.sum(axis=0).max()) // m), int(big.max()) if len(big) else 0)
    best = min(int(greedy_place(order, m).max()), int(greedy_place(every, m).max()))
    base = greedy_place(big[np.argsort(-big.max(axis=1), kind="stable")], m) if len(big) else np.zeros((m, dims), np.int64)
    scale = every.sum(axis=0).max() / m
    for seed in range(seeds):
        used, _ = random_then_greedy(small, m, eps, scale, seed)
        best = min(best, int(np.ceil((base + used).max())))
    return best, low


def schedule_report(summary: DataFrame, vectors: Vectors, m: int, gamma: Fraction, eps: float) -> DataFrame:
    spark = summary.sparkSession
    value, low = makespan_estimate(summary, vectors.dims, m, gamma, eps)
    top = int(loads(vectors, m).first()["largest_norm"])
    low = max(low, top)
    factor = 2 - 1 / m + 3 * eps
    return spark.createDataFrame([(m, vectors.dims, value, low, value / max(low, 1), factor)], "machines int, dims int, estimate long, lower_bound long, ratio double, proved_factor double")


def optimum_exact(vectors: list[tuple[int, ...]], m: int, limit: int = 14) -> int:
    """Optimal makespan of a tiny instance: depth-first, equal machines tried once."""
    if len(vectors) > limit:
        raise ValueError("too many jobs for exact search")
    order = sorted(vectors, key=lambda v: (max(v), sum(v)), reverse=True)
    dims = len(order[0]) if order else 1
    best = int(greedy_place(np.array(order, np.int64).reshape(-1, dims), m).max()) if order else 0

    def go(k: int, used: list[tuple[int, ...]]) -> None:
        nonlocal best
        if k == len(order):
            best = min(best, max(max(u) for u in used))
            return
        seen = set()
        for i, u in enumerate(used):
            new = tuple(a + b for a, b in zip(u, order[k], strict=True))
            if u in seen or max(new) >= best:
                continue
            seen.add(u)
            used[i] = new
            go(k + 1, used)
            used[i] = u

    go(0, [(0,) * dims] * m)
    return best
