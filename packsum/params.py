"""Parameters as exact fractions, and the constants that follow from them."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction


@dataclass(frozen=True)
class Eps:
    """Precision num/den: comparisons with sizes in whole units stay exact."""

    num: int
    den: int

    @property
    def fraction(self) -> Fraction:
        return Fraction(self.num, self.den)

    @property
    def octaves(self) -> int:
        """Least k with 2**-k <= eps."""
        k = 0
        while self.num * (1 << k) < self.den:
            k += 1
        return k

    @property
    def label(self) -> str:
        return f"{self.num}/{self.den}"

    @staticmethod
    def of(value: Fraction) -> Eps:
        return Eps(value.numerator, value.denominator)


def packing_eps(target: Eps, dims: int = 1) -> Eps:
    """Internal precision for a wanted factor 1 + target (d + target for vectors): the proved factor is 1 + 3 eps."""
    return Eps.of(target.fraction / (3 * dims))


def check_packing(eps: Eps) -> None:
    if not 0 < eps.fraction <= Fraction(1, 3):
        raise ValueError("packing precision must be in (0, 1/3]")


def simple_step(n: str, eps: Eps) -> str:
    """SQL of the block length max(1, floor(2 delta n)) with delta = eps**2 / 4."""
    return f"greatest(1L, ({n} * {eps.num**2}L) div {2 * eps.den**2}L)"


def octave_step(n: str, eps: Eps, wide: bool = False) -> str:
    """The same with delta = eps / 8; wide: floor(4 delta n), enough where ranks are exact."""
    return f"greatest(1L, ({n} * {eps.num}L) div {(2 if wide else 4) * eps.den}L)"


def geometric_count(eps: Eps) -> int:
    """Least k with (1 + eps)**k >= 1 / eps."""
    k, power, base = 0, Fraction(1), 1 + eps.fraction
    while power < 1 / eps.fraction:
        power, k = power * base, k + 1
    return k


def geometric_grid(eps: Eps, top: int) -> list[int]:
    """floor((1 + eps)**i) for i = 0, 1, ... until it is at least ``top``: whole sizes compare with these exactly."""
    out, power, base = [], Fraction(1), 1 + eps.fraction
    limit = 1 << 80
    while True:
        out.append(math.floor(power))
        if out[-1] >= top:
            return out
        power *= base
        if power.denominator > limit:  # keep numbers short; the floor stays a valid boundary, the same everywhere
            power = Fraction(math.floor(power * (1 << 64)), 1 << 64)


def container_gamma(eps: Eps, dims: int) -> Fraction:
    """Share of the load bound that is still a small job: min(eps/4, eps**2 / (12 ln(d**2 / eps))), rounded down."""
    log = math.log(dims * dims / float(eps.fraction))
    free = float(eps.fraction) ** 2 / (12 * log) if log > 0 else float("inf")
    value = min(float(eps.fraction) / 4, free)
    return Fraction(max(1, math.floor(value * 1_000_000)), 1_000_000)


def linear_gamma(eps: Eps) -> Fraction:
    """The open variant, proportional to eps: no guarantee is claimed for it."""
    return eps.fraction / 4


def typed_bound(eps: Eps, dims: int) -> int:
    """Bound on the number of types of big jobs."""
    delta = float(eps.fraction) / dims
    return math.ceil(math.log(1 / delta**2) / math.log(1 + float(eps.fraction)) - 1e-12) ** dims


def typed_allowed(eps: Eps, dims: int, limit: int = 1_000_000) -> bool:
    return typed_bound(eps, dims) <= limit


def lower_bound_comparison(eps: Eps, n: int) -> float:
    """Stored items that any deterministic comparison-based summary needs, up to its constant."""
    return float(1 / eps.fraction) * math.log2(max(2.0, float(eps.fraction) * n))


def lower_bound_randomised(eps: Eps, failure: float) -> float:
    return float(1 / eps.fraction) * math.log2(max(2.0, math.log2(1 / failure)))
