"""Comparisons and measures beside the estimates: baselines on raw items at test scale, the average-fill argument, failures
of the randomised summary over repeats, types against containers, and what a plan has read and shuffled."""

from __future__ import annotations

import bisect
from fractions import Fraction

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.functions.units import is_big
from packsum.operators import containers, estimate, rounding, solvers, summaries, typed
from packsum.operators.properties import _cumulated
from packsum.params import Eps, container_gamma
from packsum.sources.tables import Items, Vectors

SMALL = "n_small long, small_total long, rounded_bins long, executed long, alg long, fits boolean"


def best_fit(sizes: list[int], cap: int) -> int:
    """Bins of Best Fit in the given order."""
    gaps, used = [], 0
    for s in sizes:
        at = bisect.bisect_left(gaps, s)
        used += at == len(gaps)
        left = (gaps.pop(at) if at < len(gaps) else cap) - s
        bisect.insort(gaps, left)
    return used


def raw_baselines(items: Items, order: str = "item_id") -> DataFrame:
    """Next Fit and First Fit in arrival order, First and Best Fit by decreasing size: all items in one task."""
    cap = items.cap

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        sizes = pdf.sort_values("place", kind="stable")["size_units"].astype(int).tolist()
        down = sorted(sizes, reverse=True)
        row = {"n": len(sizes), "size_bound": -(-sum(sizes) // cap), "next_fit": solvers.next_fit(sizes, cap), "first_fit": len(solvers.first_fit(sizes, cap)), "ffd": len(solvers.first_fit(down, cap)), "bfd": best_fit(down, cap)}
        return pd.DataFrame([row])

    one = items.df.select(F.col(order).alias("place"), "size_units", F.lit(0).alias("g"))
    return one.groupBy("g").applyInPandas(run, "n long, size_bound long, next_fit long, first_fit long, ffd long, bfd long")


def small_by_first_fit(items: Items, eps: Eps, order: str = "item_id") -> DataFrame:
    """Small items put one by one, by First Fit, into the bins of the rounded solution, beside the estimate of their
    number of bins: all small items in one task."""
    cap = items.cap
    solution = estimate.solution_of(items, eps, estimate.rounded(items, eps))
    small = items.df.filter(~is_big(F.col("size_units"), cap, eps))
    total, many = small.agg(F.coalesce(F.sum("size_units"), F.lit(0)).cast("long"), F.count(F.lit(1))).first()
    fits, alg = estimate.estimate_bins(solvers.bins(solution), estimate.free_space(solution, cap, eps), int(total), cap, eps)
    start = [solvers.load(p) for p, n in solution for _ in range(n)]

    if not many:
        return items.df.sparkSession.createDataFrame([(0, 0, len(start), len(start), alg, fits)], SMALL)

    def run(batches):
        sizes = [s for pdf in batches for s in pdf["size_units"].astype(int).tolist()]
        yield pd.DataFrame([{"n_small": len(sizes), "small_total": sum(sizes), "rounded_bins": len(start), "executed": len(solvers.first_fit(sizes, cap, start)), "alg": alg, "fits": fits}])

    own = small.select(F.col(order).alias("place"), "size_units").repartition(1).sortWithinPartitions("place", "size_units").select("size_units")
    return own.mapInPandas(run, SMALL)


def average_fill(report: DataFrame, cap: int) -> DataFrame:
    """Where small items open further bins, all bins but one are filled beyond 1 - eps on average, which bounds the
    estimate by (1 + eps) / (1 - eps) times the total size and one bin."""
    room = F.col("eps_den") - F.col("eps_num")
    held = F.col("rounded_total") + F.col("small_total")
    size = F.col("big_total") + F.col("small_total")
    least = (F.col("alg") - 1) * room * cap < held * F.col("eps_den")
    most = (F.col("alg") - 1) * room * cap <= (F.col("eps_den") + F.col("eps_num")) * size
    return report.withColumn("average_fill", held / (F.col("alg") * F.lit(float(cap)))).withColumn("filled", F.col("fits") | least).withColumn("bounded", F.col("fits") | most)


def failure_frequency(items: Items, eps: Eps, repeats: int = 8, failure: float = 1e-4) -> DataFrame:
    """Runs of the randomised summary, and how many of them state a rank bound that a true rank breaks. A few
    runs cannot measure a rare failure: ``within`` lets one run fail where less than one is expected."""
    runs = Items(items.df.withColumn("run", F.explode(F.sequence(F.lit(1), F.lit(repeats)))), items.cap, ("run",))
    steps = summaries.random_steps(runs, eps, failure=failure)
    true = _cumulated(rounding.histogram(items, eps), "n").select(F.col("group_j").alias("g"), F.col("size_units").alias("s"), "c0")
    both = steps.join(true, (F.col("group_j") == F.col("g")) & (F.col("size_units") == F.col("s")))
    each = both.groupBy("run").agg(F.max(F.greatest(F.lit(0), F.col("c0") + 1 - F.col("rank_hi"))).cast("long").alias("miss"))
    out = each.agg(F.count(F.lit(1)).alias("runs"), F.count_if(F.col("miss") > 0).alias("failed"), F.max("miss").alias("worst_miss"))
    return out.withColumn("allowed", F.lit(failure * eps.octaves)).withColumn("within", F.col("failed") <= F.ceil(F.col("allowed") * F.col("runs") * 3))


def types_against_containers(vectors: Vectors, eps: Eps, m: int) -> DataFrame:
    """Rows that both summaries store in one, two, ... dimensions: types grow with the power of the dimension."""
    spark, rows = vectors.df.sparkSession, []
    for d in range(1, vectors.dims + 1):
        v = Vectors(vectors.df.withColumn("v", F.slice("v", 1, d)), d, vectors.cap)
        gamma: Fraction = container_gamma(eps, d)
        r = typed.typed_report(v, eps).first()
        stored = containers.containers_prefix(v, m, gamma).count()
        rows.append((d, int(r["big_types"]), int(r["small_types"]), int(r["type_bound"]), stored, int(r["jobs"]), bool(r["within"])))
    return spark.createDataFrame(rows, "dims int, big_types long, small_types long, type_bound long, containers long, jobs long, within boolean")


def measured(df: DataFrame) -> dict[str, int]:
    """Runs a plan and reads its own metrics: table scans, rows scanned, rows returned, bytes written to shuffles. The
    result comes to the driver, so this is for plans that return a report."""
    returned = len(df.collect())
    out, seen, todo = {"scans": 0, "rows_scanned": 0, "shuffle_bytes": 0, "rows_returned": returned}, set(), [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        name, metrics = node.getClass().getSimpleName(), node.metrics()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if name.endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        if name == "ReusedExchangeExec" or node.id() in seen:
            continue
        seen.add(node.id())
        if name in ("FileSourceScanExec", "BatchScanExec"):
            out["scans"] += 1
            out["rows_scanned"] += metrics.apply("numOutputRows").value()
        if name == "ShuffleExchangeExec":
            out["shuffle_bytes"] += metrics.apply("shuffleBytesWritten").value()
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return out


def passes(plans: dict[str, DataFrame], rows: int) -> DataFrame:
    """Passes over a table of so many rows, and bytes shuffled, of named plans."""
    spark = next(iter(plans.values())).sparkSession
    found = {k: measured(df) for k, df in plans.items()}
    table = [(k, m["scans"], m["rows_scanned"], m["rows_scanned"] / max(rows, 1), m["shuffle_bytes"], m["rows_returned"]) for k, m in found.items()]
    return spark.createDataFrame(table, "plan string, scans long, rows_scanned long, passes double, shuffle_bytes long, rows_returned long")
