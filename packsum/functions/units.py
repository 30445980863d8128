"""Exact size arithmetic as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from packsum.params import Eps, geometric_grid


def is_big(size: Column, cap: int, eps: Eps) -> Column:
    """size > eps * cap. Written on the column itself, so a Parquet scan can skip by it."""
    return size > F.lit(eps.num * cap // eps.den)


def octave(size: Column, cap: int, eps: Eps) -> Column:
    """j with size in (cap / 2**(j+1), cap / 2**j] for big sizes, the last octave cut at eps; -1 for small ones."""
    out = F.when(~is_big(size, cap, eps), F.lit(-1))
    for j in range(max(eps.octaves - 1, 0)):
        out = out.when(size > F.lit(cap // 2 ** (j + 1)), F.lit(j))
    return out.otherwise(F.lit(max(eps.octaves - 1, 0)))


def exponent(size: Column, eps: Eps, top: int) -> Column:
    """i with size in ((1 + eps)**i, (1 + eps)**(i + 1)], from literal boundaries; a logarithm only guesses the place."""
    grid = geometric_grid(eps, top)
    table = F.array(*(F.lit(g).cast("long") for g in grid))
    guess = F.floor(F.log(size.cast("double")) / math.log(1 + float(eps.fraction))).cast("int")
    out = F.lit(None).cast("int")
    for shift in (1, 0, -1, -2):  # the largest i whose boundary is below the size
        i = guess + shift
        below = F.when(i < 0, F.lit(0).cast("long")).otherwise(F.get(table, i))
        out = F.coalesce(out, F.when((i >= -1) & (size > below), i))
    return out
