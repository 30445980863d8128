"""Comparisons and measures beside the estimates."""

import numpy as np
from pyspark.sql import functions as F

from packsum.operators import comparisons, solvers, typed
from packsum.params import Eps
from packsum.sources.tables import Items, Vectors


def items_of(spark, sizes, cap):
    return Items(spark.createDataFrame([(i, int(s)) for i, s in enumerate(sizes)], "item_id long, size_units long"), cap)


def slow(sizes, cap, best, start=()):
    gaps = [cap - x for x in start]
    for s in sizes:
        fit = [i for i, g in enumerate(gaps) if g >= s]
        if not fit:
            gaps.append(cap)
            fit = [len(gaps) - 1]
        at = min(fit, key=lambda i: gaps[i]) if best else fit[0]
        gaps[at] -= s
    return [cap - g for g in gaps]


def test_raw_rules_equal_slow_twins(spark):
    rng = np.random.default_rng(3)
    for _ in range(100):
        sizes, start = rng.integers(1, 101, rng.integers(0, 40)).tolist(), rng.integers(0, 101, rng.integers(0, 9)).tolist()
        assert comparisons.best_fit(sizes, 100) == len(slow(sizes, 100, True))
        assert solvers.first_fit(sizes, 100) == slow(sizes, 100, False)
        assert solvers.first_fit(sizes, 100, start) == slow(sizes, 100, False, start)
    sizes = rng.integers(1, 101, 300).tolist()
    r = comparisons.raw_baselines(items_of(spark, sizes, 100)).first()
    down = sorted(sizes, reverse=True)
    assert (r["first_fit"], r["ffd"], r["bfd"]) == (len(slow(sizes, 100, False)), len(slow(down, 100, False)), len(slow(down, 100, True)))


def test_small_items_by_first_fit_stay_within_the_estimate(spark):
    rng = np.random.default_rng(5)
    for share in (0.0, 0.5, 0.95, 1.0):
        sizes = np.where(rng.random(400) < share, rng.integers(1, 200, 400), rng.integers(201, 1001, 400))
        r = comparisons.small_by_first_fit(items_of(spark, sizes, 1000), Eps(1, 5)).first()
        assert r["rounded_bins"] <= r["executed"] <= r["alg"] and r["n_small"] == (sizes <= 200).sum()


def test_loads_told_by_types_drift_little(spark):
    rng = np.random.default_rng(6)
    v = np.maximum(1, (10 ** rng.uniform(1, 6, (600, 1)) * rng.uniform(0, 1, (600, 3))).astype(int))
    frame = spark.createDataFrame([(i, [int(x) for x in r]) for i, r in enumerate(v)], "job_id long, v array<long>")
    for eps in (Eps(1, 1), Eps(1, 2), Eps(1, 4)):
        r = typed.typed_drift(Vectors(frame, 3, 10**6), eps).first()
        assert r["n_small"] > 50 and r["within"] and r["loads_within"] and 1 <= r["load_drift"] <= (1 + float(eps.fraction)) ** 2 + 0.05


def test_failures_and_passes_are_counted(spark, tmp_path):
    rng = np.random.default_rng(7)
    items = items_of(spark, rng.integers(1, 10**6, 3000), 10**6)
    r = comparisons.failure_frequency(items, Eps(1, 5), repeats=3).first()
    assert (r["runs"], r["failed"], r["within"]) == (3, 0, True)
    path = str(tmp_path / "t.parquet")
    items.df.write.parquet(path)
    table = spark.read.parquet(path)
    one = comparisons.measured(table.groupBy((F.col("size_units") % 7).alias("k")).count())
    two = comparisons.measured(table.select("size_units").union(table.select("item_id")))
    assert (one["scans"], one["rows_scanned"], one["rows_returned"]) == (1, 3000, 7) and one["shuffle_bytes"] > 0
    assert (two["scans"], two["rows_scanned"], two["shuffle_bytes"]) == (2, 6000, 0)
