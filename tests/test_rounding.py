"""Rounding, summaries and estimates against exact ranks, brute force and hand values."""

import random
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from packsum.operators import estimate, properties, rounding, solvers, summaries
from packsum.params import Eps, container_gamma, geometric_count, packing_eps, typed_bound
from packsum.sources.tables import Items, items, size_list

EPS = Eps(1, 5)


def collect(df):
    return {(r["group_j"], r["size_units"]): r["multiplicity"] for r in df.collect()}


def test_constants():
    assert [Eps(1, d).octaves for d in (3, 5, 10, 20)] == [2, 3, 4, 5]
    assert [geometric_count(Eps(1, d)) for d in (3, 5, 10, 20)] == [4, 9, 25, 62]
    assert float(container_gamma(Eps(1, 2), 4)) == pytest.approx(0.00601, abs=1e-5)
    assert [typed_bound(Eps(1, 2), d) for d in (2, 3, 4)] == [49, 729, 14641]
    assert packing_eps(Eps(3, 5)).fraction == Fraction(1, 5)


def test_boundary_sizes(spark):
    cap = 100
    sizes = [0, 20, 21, 25, 26, 50, 51, 100]
    got = {r["size_units"]: r["group_j"] for r in rounding.with_octave(size_list(spark, sizes, cap), EPS).collect()}
    assert got == {0: -1, 20: -1, 21: 2, 25: 2, 26: 1, 50: 1, 51: 0, 100: 0}


def expanded(sizes, cap, eps, wide=False):
    """Rounding by the definition, on a list."""
    out = {}
    for j in range(eps.octaves):
        low = cap / 2 ** (j + 1) if j < eps.octaves - 1 else 0
        own = sorted((s for s in sizes if s * eps.den > eps.num * cap and low < s <= cap / 2**j), reverse=True)
        n = len(own)
        t = max(1, n * eps.num // ((2 if wide else 4) * eps.den))
        for i in range(n):
            v = own[i] if i == n - 1 else own[i // t * t]
            out[j, v] = out.get((j, v), 0) + 1
    return out


@pytest.mark.parametrize("seed", range(3))
def test_octave_rounding_by_definition(spark, seed):
    rng = random.Random(seed)
    sizes = [rng.choice([rng.randint(1, 1000), 500, 501]) for _ in range(400)]
    got = collect(rounding.round_octaves(size_list(spark, sizes, 1000), EPS))
    assert got == expanded(sizes, 1000, EPS)


def test_empty_and_single(spark):
    empty = Items(size_list(spark, [1], 10).df.limit(0), 10)
    assert rounding.round_octaves(empty, EPS).count() == 0
    assert estimate.report(empty, EPS, rounding.round_octaves(empty, EPS)).count() <= 1
    one = size_list(spark, [7], 10)
    assert collect(rounding.round_octaves(one, EPS)) == {(0, 7): 1}
    assert estimate.report(one, EPS, rounding.round_octaves(one, EPS)).first()["alg"] == 1


def test_invalid_sizes(spark):
    df = spark.createDataFrame([(5.0,), (None,), (-1.0,), (20.0,)], "x double")
    assert items(df, F.col("x"), 10, on_bad="drop").df.count() == 1
    assert sorted(r[0] for r in items(df, F.col("x"), 10, on_bad="clamp").df.collect()) == [0, 5, 10]
    with pytest.raises(Exception, match="size is null"):
        items(df, F.col("x"), 10).df.collect()


@pytest.mark.parametrize("build", ["builtin", "random", "universe", "sequential"])
def test_summaries_keep_the_properties(spark, build):
    rng = random.Random(5)
    it = size_list(spark, [rng.randint(1, 60_000) for _ in range(6000)], 65_000)
    inst = summaries.SUMMARIES[build](it, EPS)
    r = properties.check_properties(it, EPS, inst).first()
    assert r["p1"] and r["p2"] and r["p3"] and r["p4"], r


@pytest.mark.parametrize("parts", [1, 2, 8, 64])
def test_union_of_parts(spark, parts):
    rng = random.Random(parts)
    it = size_list(spark, [rng.randint(1, 9999) for _ in range(4000)], 10_000)
    r = properties.check_properties(it, EPS, rounding.round_in_parts(it, EPS, parts)).first()
    assert r["p1"] and r["p2"] and r["p3"] and r["p4"], r


def test_fixed_grid_is_not_rank_rounding(spark):
    """Halves no longer pair once rounded up past a half."""
    it = size_list(spark, [50] * 20, 100)
    up = rounding.fixed_grid(it, EPS, 3).first()
    assert 2 * up["size_units"] > 100


def test_both_cases_of_the_estimate():
    eps = Eps(1, 4)
    assert estimate.estimate_bins(3, estimate.free_space([(((50, 1),), 2), (((75, 1),), 1)], 100, eps), 50, 100, eps) == (True, 3)
    w = estimate.free_space([(((50, 1),), 2)], 100, eps)
    assert w == 2 * 25 * 4
    assert estimate.estimate_bins(2, w, 50, 100, eps) == (True, 2)
    assert estimate.estimate_bins(2, w, 51, 100, eps) == (False, 3)
    assert estimate.estimate_bins(2, w, 50 + 76, 100, eps) == (False, 4)
    assert estimate.estimate_bins(0, 0, 0, 100, eps) == (True, 0)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 30), min_size=1, max_size=9), st.sampled_from(["ffd", "bfd", "nfd", "lp"]))
def test_solvers_against_brute_force(sizes, name):
    instance = [(s, 1) for s in sizes]
    best = solvers.solve_exact(instance, 30)
    solution = solvers.SOLVERS[name](instance, 30)
    assert solvers.covers(solution, instance, 30)
    assert solvers.bins(solution) >= best >= solvers.lower_bound(instance, 30)
    if name != "nfd":
        assert solvers.bins(solution) <= best + len(set(sizes))


def test_linear_program_on_many_equal_items():
    instance = [(35, 1000), (21, 2000), (14, 1500)]
    solution, value, _ = solvers.solve_lp(instance, 100)
    assert solvers.covers(solution, instance, 100)
    assert solvers.bins(solution) == 1000  # no pattern fills more than 98 of 100, and all items are 98,000
    assert value is None or value <= solvers.bins(solution) <= value + 3


def test_sandwich_on_a_table(spark, tiny):
    from packsum.sources.tables import quantity_items

    for target in (Eps(1, 1), Eps(3, 5), Eps(3, 10)):
        r = estimate.with_guarantee(estimate.pack(quantity_items(spark, tiny), target)).first()
        assert r["above_lower"] and r["within_upper"]


def test_assignment_is_feasible(spark, tiny):
    from packsum.sources.tables import document_items, event_items

    for it in (document_items(spark, tiny), event_items(spark, tiny)):
        r = estimate.assignment_check(it, EPS, rounding.round_octaves(it, EPS)).first()
        assert r["feasible"] and r["items"] == it.df.count()


def test_sequential_summary_bounds():
    rng = random.Random(1)
    data = [rng.randint(1, 500) for _ in range(3000)]
    s = summaries.SequentialSummary(0.02)
    for x in data:
        s.add(x)
    ordered = sorted(data, reverse=True)
    assert sum(s.gaps) == len(data)
    assert s.most < 400
    for value, low, high in s.bounds():
        first, last = ordered.index(value) + 1, len(data) - ordered[::-1].index(value)
        assert low <= last and high >= first
        assert high - low <= 2 * 0.02 * len(data)


@pytest.mark.parametrize("kind", ["builtin", "random"])
def test_properties_hold_for_few_items(spark, kind):
    rng = random.Random(3)
    for eps in (Eps(1, 3), Eps(1, 10)):
        for n in (1, 2, 40, 110, 330, 700):
            items = size_list(spark, [rng.randint(1, 1000) for _ in range(n)], 1000)
            flags = properties.check_properties(items, eps, summaries.SUMMARIES[kind](items, eps)).first()
            assert not flags["n_big"] or (flags["p1"] and flags["p2"] and flags["p3"] and flags["p4"]), (eps, n)


def test_sketch_size_follows_from_failure():
    sizes = [summaries.sketch_size(1 / 80, f) for f in (1e-2, 1e-4, 1e-8)]
    assert sizes == sorted(sizes) and sizes[0] >= 300
