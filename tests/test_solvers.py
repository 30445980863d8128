"""Solvers on counted sizes against item-by-item rules and known optima."""

import random
from collections import Counter

import pytest

from packsum.operators import solvers


def by_items(sizes, cap, best):
    gaps = []
    for s in sorted(sizes, reverse=True):
        fit = [i for i, g in enumerate(gaps) if g >= s]
        if not fit:
            gaps.append(cap - s)
        else:
            gaps[min(fit, key=lambda i: (gaps[i], i)) if best else fit[0]] -= s
    return len(gaps)


def instances(count):
    rng = random.Random(1)
    for t in range(count):
        cap = rng.choice([20, 50, 100, 1000])
        values = [rng.randint(0 if t % 5 == 0 else 1, cap) for _ in range(rng.randint(1, 10))]
        yield cap, [rng.choice(values) for _ in range(rng.randint(0, 60))]


def test_decreasing_rules_equal_item_by_item():
    for cap, items in instances(2000):
        counted = list(Counter(items).items())
        for best, solve in ((False, solvers.solve_ffd), (True, solvers.solve_bfd)):
            solution = solve(counted, cap)
            assert solvers.covers(solution, counted, cap)
            assert solvers.bins(solution) == by_items(items, cap, best), (cap, items, best)


def test_first_fit_decreasing_keeps_the_order_of_bins():
    assert solvers.bins(solvers.solve_ffd([(68, 7), (67, 10), (60, 8), (57, 1), (39, 7), (34, 1), (25, 10), (21, 7), (20, 2)], 100)) == 26


def test_linear_program_states_only_what_it_proved():
    rng = random.Random(4)
    hard = [(rng.randint(10**6, 5 * 10**6), rng.randint(50, 400)) for _ in range(40)]
    solution, bound, certificate = solvers.solve_lp(hard, 10**7)
    assert solvers.covers(solution, hard, 10**7)
    assert bound <= solvers.bins(solution) and (certificate != "linear program" or solvers.bins(solution) <= bound + len(hard) + 1)
    assert solvers.solve_lp(hard, 10**7) == (solution, bound, certificate)
    cut = solvers.solve_lp(hard, 10**7, steps=200)
    assert cut[2] != "linear program" and cut[1] <= bound + 1


def test_lower_bounds_of_cut_pricing_hold():
    for cap, items in instances(300):
        counted = [(s, n) for s, n in Counter(items).items() if s]
        if not counted or len(items) > 12:
            continue
        best = solvers.solve_exact(counted, cap)
        for steps in (1, 50, 10_000):
            solution, bound, _ = solvers.solve_lp(counted, cap, steps)
            assert best <= solvers.bins(solution) and (bound is None or bound <= best + 1e-6)


@pytest.mark.parametrize("rule", ["ffd", "bfd", "nfd", "lp"])
def test_no_items(rule):
    assert solvers.bins(solvers.SOLVERS[rule]([], 10)) == 0
