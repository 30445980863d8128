"""Packing rounded instances: first, best and next fit decreasing, a pattern linear program, and exact search.

These run after the data has been summarised, on at most a few thousand (size, multiplicity) pairs, in the driver or in
one task for each stream. A solution is a list of (pattern, repeats); a pattern is a list of (size, count).
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Sequence

import numpy as np

Instance = list[tuple[int, int]]
Pattern = tuple[tuple[int, int], ...]
Solution = list[tuple[Pattern, int]]


def tidy(instance: Instance) -> Instance:
    total: Counter[int] = Counter()
    for size, n in instance:
        total[int(size)] += int(n)
    return sorted(((s, n) for s, n in total.items() if n > 0), reverse=True)


def bins(solution: Solution) -> int:
    return sum(n for _, n in solution)


def load(pattern: Pattern) -> int:
    return sum(s * c for s, c in pattern)


def _gather(found: dict[Pattern, int]) -> Solution:
    return sorted(found.items(), reverse=True)


def _with(pattern: Pattern, size: int, count: int) -> Pattern:
    return (*pattern, (size, count))


def solve_bfd(instance: Instance, cap: int) -> Solution:
    """Best fit decreasing on whole classes of equal bins: each step moves a run of bins, never one item."""
    open_bins: dict[tuple[int, Pattern], int] = {}
    done: dict[Pattern, int] = {}

    def put(gap: int, pattern: Pattern, many: int) -> None:
        if not many:
            return
        if gap < smallest:
            done[pattern] = done.get(pattern, 0) + many
        else:
            open_bins[gap, pattern] = open_bins.get((gap, pattern), 0) + many

    items = tidy(instance)
    smallest = items[-1][0] if items else 1
    for size, left in items:
        while left:
            key = min((k for k in open_bins if k[0] >= size), key=lambda k: k[0], default=None)
            if key is None:
                per = cap // max(size, 1) if size else left
                per = min(max(per, 1), left)
                many = max(1, left // per)
                put(cap - per * size, ((size, per),), many)
                left -= per * many
                continue
            gap, pattern = key
            many = open_bins.pop(key)
            per = gap // size if size else left
            full, rest = _filled(many, per, left)
            put(gap - per * size, _with(pattern, size, per), full)
            if rest:
                put(gap - rest * size, _with(pattern, size, rest), 1)
            put(gap, pattern, many - full - (rest > 0))
            left -= full * per + rest
    for (_, pattern), many in open_bins.items():
        done[pattern] = done.get(pattern, 0) + many
    return _gather(done)


def _filled(many: int, per: int, left: int) -> tuple[int, int]:
    """Of a run of equal bins that take ``per`` items each: how many are filled, and what one more bin takes."""
    full = min(many, left // per)
    return full, left - full * per if full < many else 0


def solve_ffd(instance: Instance, cap: int) -> Solution:
    """First fit decreasing on runs of equal bins, kept in the order in which bins were opened."""
    items = tidy(instance)
    runs: list[tuple[int, Pattern, int]] = []
    done: dict[Pattern, int] = {}
    for k, (size, left) in enumerate(items):
        least = items[k + 1][0] if k + 1 < len(items) else cap + 1  # a bin with less room than the next size is closed
        out: list[tuple[int, Pattern, int]] = []

        def keep(gap: int, pattern: Pattern, many: int, out: list = out, least: int = least) -> None:
            if many and gap < min(least, items[-1][0]):
                done[pattern] = done.get(pattern, 0) + many
            elif many:
                out.append((gap, pattern, many))

        for gap, pattern, many in runs:
            if not left or gap < size:
                keep(gap, pattern, many)
                continue
            per = gap // size if size else left
            full, rest = _filled(many, per, left)
            keep(gap - per * size, _with(pattern, size, per), full)
            if rest:
                keep(gap - rest * size, _with(pattern, size, rest), 1)
            keep(gap, pattern, many - full - (rest > 0))
            left -= full * per + rest
        if left:
            per = max(cap // size, 1) if size else left
            keep(cap - per * size, ((size, per),), left // per)
            if left % per:
                keep(cap - left % per * size, ((size, left % per),), 1)
        runs = out
    for _, pattern, many in runs:
        done[pattern] = done.get(pattern, 0) + many
    return _gather(done)


def solve_nfd(instance: Instance, cap: int) -> Solution:
    """Next fit decreasing: only the last bin stays open."""
    done: dict[Pattern, int] = {}
    gap, pattern = 0, ()
    for size, left in tidy(instance):
        while left:
            if not pattern or gap < size:
                if pattern:
                    done[pattern] = done.get(pattern, 0) + 1
                per = cap // size if size else left
                if left >= per > 0:
                    many = left // per
                    left -= many * per
                    if left or cap - per * size >= 0:
                        done[((size, per),)] = done.get(((size, per),), 0) + many - 1
                        gap, pattern = cap - per * size, ((size, per),)
                    continue
                gap, pattern = cap, ()
            per = min(left, gap // size if size else left)
            gap, pattern, left = gap - per * size, _with(pattern, size, per), left - per
    if pattern:
        done[pattern] = done.get(pattern, 0) + 1
    return _gather({p: n for p, n in done.items() if n})


def first_fit(sizes: list[int], cap: int, start: Sequence[int] = ()) -> list[int]:
    """Loads of First Fit in the given order, after bins of loads ``start``, for baselines at test scale: a tournament tree
    over free space."""
    width = 1
    while width < max(len(sizes) + len(start), 1):
        width *= 2
    tree = [0] * width + [cap - x for x in start] + [cap] * (width - len(start))
    for at in range(width - 1, 0, -1):
        tree[at] = max(tree[2 * at], tree[2 * at + 1])
    used = len(start)
    for s in sizes:
        at = 1
        while at < width:
            at = 2 * at if tree[2 * at] >= s else 2 * at + 1
        tree[at] -= s
        used = max(used, at - width + 1)
        at //= 2
        while at:
            tree[at] = max(tree[2 * at], tree[2 * at + 1])
            at //= 2
    return [cap - x for x in tree[width : width + used]]


def next_fit(sizes: list[int], cap: int) -> int:
    count, gap = 0, -1
    for s in sizes:
        if s > gap:
            count, gap = count + 1, cap
        gap -= s
    return count


def lower_bound(instance: Instance, cap: int) -> int:
    """Total size, and for thresholds up to half: items over cap - t are alone, the middle ones by size."""
    items = tidy(instance)
    total = sum(s * n for s, n in items)
    best = -(-total // cap)
    for t in {s for s, _ in items if 2 * s <= cap} | {0}:
        alone = sum(n for s, n in items if s > cap - t)
        half = sum(n for s, n in items if cap - t >= s and 2 * s > cap)
        room = half * cap - sum(s * n for s, n in items if cap - t >= s and 2 * s > cap)
        small = sum(s * n for s, n in items if t <= s and 2 * s <= cap)
        best = max(best, alone + half + max(0, -(-(small - room) // cap)))
    return best


def _price(sizes: list[int], value: np.ndarray, limit: list[int], cap: int, steps: int) -> tuple[float, list[int], float, int]:
    """Most valuable pattern found, by depth-first search over counts in order of value per size, cut by the fractional
    bound: (value, counts, upper bound of any pattern's value, steps used). The bound is the value where the search ended."""
    order = sorted(range(len(sizes)), key=lambda i: (-value[i] / sizes[i], i))
    best, best_counts = 0.0, [0] * len(sizes)
    counts = [0] * len(sizes)
    used, missed = 0, 0.0

    def go(k: int, room: int, got: float) -> None:
        nonlocal best, best_counts, used, missed
        if got > best + 1e-12:
            best, best_counts = got, counts.copy()
        if k == len(order):
            return
        i = order[k]
        reach = got + room * value[i] / sizes[i]
        if value[i] <= 0 or reach <= best + 1e-9:
            return
        if used >= steps:
            missed = max(missed, reach)
            return
        used += 1
        for c in range(min(limit[i], room // sizes[i]), -1, -1):
            counts[i] = c
            go(k + 1, room - c * sizes[i], got + c * value[i])
        counts[i] = 0

    go(0, cap, 0.0)
    return best, best_counts, max(best, missed), used


def solve_lp(instance: Instance, cap: int, steps: int = 2_000_000) -> tuple[Solution, float | None, str]:
    """Pattern linear program by column generation, rounded: (solution, lower bound of its value, certificate).

    First-fit-decreasing comes first, and ends the search where it is within the number of sizes of a lower bound,
    which is all that the estimate asks of a solver. Otherwise the better of rounding all columns up, and of rounding
    down and packing the rest by first fit, competes with it. Basic solutions have as many columns as sizes. Work is
    bounded by steps, so reruns agree. "linear program" is stated only where pricing was complete; otherwise the dual
    values over the bound of what pricing may have missed are still a lower bound.
    """
    items = tidy(instance)
    greedy = solve_ffd(items, cap)
    if not items or bins(greedy) - lower_bound(items, cap) <= len(items):
        return greedy, None, "greedy within the number of sizes of the lower bound"
    sizes, need = [s for s, _ in items], np.array([n for _, n in items], float)
    basis = [[0] * i + [min(cap // s, int(need[i]))] + [0] * (len(sizes) - i - 1) for i, s in enumerate(sizes)]
    inverse = np.diag([1.0 / c[i] for i, c in enumerate(basis)])
    x = inverse @ need
    certificate, value = "steps ran out", None
    while steps > 0:
        duals = np.maximum(np.ones(len(sizes)) @ inverse, 0)
        worth, column, most, used = _price(sizes, duals, [int(min(n, cap // s)) for s, n in items], cap, min(steps, 250_000))
        steps -= max(used, 1) + len(sizes) ** 2 // 64
        value = max(value or 0.0, float(duals @ need) / max(most, 1.0))
        if worth <= 1 + 1e-7:
            certificate = "linear program" if most <= 1 + 1e-7 else "linear program, pricing cut short"
            break
        direction = inverse @ np.array(column, float)
        ratios = np.where(direction > 1e-9, x / np.where(direction > 1e-9, direction, 1), np.inf)
        out = int(ratios.argmin())
        if not np.isfinite(ratios[out]):
            break
        step = ratios[out]
        pivot = inverse[out] / direction[out]
        inverse = inverse - np.outer(direction, pivot)
        inverse[out] = pivot
        x = np.maximum(x - step * direction, 0)
        x[out] = step
        basis[out] = column
    patterns = [tuple((s, c) for s, c in zip(sizes, col, strict=True) if c) for col in basis]
    up = Counter({p: int(np.ceil(v - 1e-9)) for p, v in zip(patterns, x, strict=True) if v > 1e-9})
    down = Counter({p: int(np.floor(v + 1e-9)) for p, v in zip(patterns, x, strict=True) if v >= 1 - 1e-9})
    rest = dict(items)
    for p, n in down.items():
        for s, c in p:
            rest[s] -= n * c
    floor = down + Counter(dict(solve_ffd([(s, n) for s, n in rest.items() if n > 0], cap)))
    choices = [(bins(list(c.items())), k, list(c.items())) for k, c in enumerate((up, floor)) if c] + [(bins(greedy), 2, greedy)]
    best = min(choices, key=lambda c: c[:2])
    return sorted(best[2], reverse=True), value, certificate


def covers(solution: Solution, instance: Instance, cap: int) -> bool:
    """Every pattern fits, and the patterns have a slot for every item."""
    slots: Counter[int] = Counter()
    for p, n in solution:
        if load(p) > cap:
            return False
        for s, c in p:
            slots[s] += c * n
    return all(slots[s] >= n for s, n in tidy(instance))


def solve_exact(instance: Instance, cap: int, limit: int = 16) -> int:
    """Optimal number of bins of a tiny instance, by branch and bound."""
    sizes = [s for s, n in tidy(instance) for _ in range(n)]
    if len(sizes) > limit:
        raise ValueError("too many items for exact search")
    best = bins(solve_ffd(instance, cap))
    floor = lower_bound(instance, cap)

    def go(k: int, loads: list[int]) -> None:
        nonlocal best
        if best == floor or len(loads) >= best:
            return
        if k == len(sizes):
            best = len(loads)
            return
        seen = set()
        for i, used in enumerate(loads):
            if used + sizes[k] <= cap and used not in seen:
                seen.add(used)
                loads[i] += sizes[k]
                go(k + 1, loads)
                loads[i] -= sizes[k]
        loads.append(sizes[k])
        go(k + 1, loads)
        loads.pop()

    go(0, [])
    return best


def solve_exact_vectors(vectors: list[tuple[int, ...]], cap: int, limit: int = 10) -> int:
    """Optimal number of bins of a tiny vector instance."""
    if len(vectors) > limit:
        raise ValueError("too many vectors for exact search")
    order = sorted(vectors, key=max, reverse=True)
    best = len(order)

    def go(k: int, loads: list[tuple[int, ...]]) -> None:
        nonlocal best
        if len(loads) >= best:
            return
        if k == len(order):
            best = len(loads)
            return
        for i, used in enumerate(loads):
            new = tuple(a + b for a, b in zip(used, order[k], strict=True))
            if max(new) <= cap:
                loads[i] = new
                go(k + 1, loads)
                loads[i] = used
        loads.append(order[k])
        go(k + 1, loads)
        loads.pop()

    if order:
        go(0, [])
    return best


SOLVERS = {"ffd": solve_ffd, "bfd": solve_bfd, "nfd": solve_nfd, "lp": lambda i, c: solve_lp(i, c)[0]}


def list_schedule(jobs: list[int], m: int) -> int:
    """Greedy on the least loaded machine, in the given order."""
    loads = [0] * m
    for p in jobs:
        k = min(range(m), key=loads.__getitem__)
        loads[k] += p
    return max(loads)


def longest_first(counts: Instance, m: int) -> int:
    """Longest processing time first on counted jobs: runs of equal jobs go round the machines."""
    import heapq

    heap = [(0, k) for k in range(m)]
    for size, n in tidy(counts):
        if n > 50 * m:  # equal jobs level the machines; only the last rounds need care
            rounds = n // m - 2 * (max(h[0] for h in heap) - min(h[0] for h in heap)) // max(size, 1) - 2
            if rounds > 0:
                heap = [(used + rounds * size, k) for used, k in heap]
                n -= rounds * m
        for _ in range(n):
            used, k = heapq.heappop(heap)
            heapq.heappush(heap, (used + size, k))
    return max(h[0] for h in heap)


def bisect_capacity(counts: Instance, m: int, low: int, high: int) -> int:
    """Least capacity, by search, for which first fit decreasing needs at most m bins: the multifit rule."""
    items = tidy(counts)
    while low < high:
        mid = (low + high) // 2
        if all(s <= mid for s, _ in items) and bins(solve_ffd(items, mid)) <= m:
            high = mid
        else:
            low = mid + 1
    return low


