"""Vectorised words of Arrow text columns: byte spans and 64-bit fingerprints, with no Python loop over words."""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

# Fixed values of the fingerprint: any odd multipliers serve.
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
MIX_A = np.uint64(0xBF58476D1CE4E5B9)
MIX_B = np.uint64(0x94D049BB133111EB)
STEP = np.uint64(0xD6E8FEB86659FD93)

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_VALUE = np.random.default_rng(20240917).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_VALUE_LOWER = _VALUE[_LOWER]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * MIX_A
    x = x ^ (x >> np.uint64(27))
    x = x * MIX_B
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=2)
def _powers_to(bits: int, base: int) -> np.ndarray:
    out = np.ones(1 << bits, np.uint64)
    done = 1
    while done < len(out):
        out[done : 2 * done] = out[:done] * np.uint64(pow(base, done, 1 << 64))
        done *= 2
    return out


def powers(n: int, base: int = BASE) -> np.ndarray:
    return _powers_to(max(16, int(n).bit_length()), base)[:n]


@dataclass
class Words:
    """Words of a batch in order: byte spans in ``data``, the document each is in, and the first word of each document."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    first: np.ndarray  # n_docs + 1 bounds
    code: np.ndarray | None  # uint64 fingerprints


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a string column and its n + 1 bounds; nulls are empty."""
    if pa.types.is_large_string(column.type):
        kind = np.int64
    else:
        column, kind = column.cast(pa.string()), np.int32
    if column.null_count:
        column = pc.fill_null(column, "")
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.empty(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    bounds = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[bounds[0] : bounds[-1]] if data is not None else np.empty(0, np.uint8)
    return raw, bounds - bounds[0]


def words(column: pa.Array, lower: bool = False, codes: bool = True) -> Words:
    """Words are maximal runs of bytes other than 0x20 and 0x09-0x0D; they end where their document ends."""
    data, bounds = text_bytes(column)
    n = len(data)
    solid = ~_SPACE[data]
    begins = solid.copy()
    begins[1:] &= ~solid[:-1]
    cuts = bounds[1:-1]
    cuts = cuts[cuts < n]
    begins[cuts] = solid[cuts]
    start = np.flatnonzero(begins)
    stops = solid.copy()
    stops[:-1] &= ~solid[1:]
    before = cuts[cuts > 0] - 1
    stops[before] = solid[before]
    end = np.flatnonzero(stops) + 1
    first = np.searchsorted(start, bounds)
    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(first))
    code = None
    if codes:
        if len(start):
            value = (_VALUE_LOWER if lower else _VALUE)[data]
            value *= powers(n)
            value[~solid] = 0
            code = np.add.reduceat(value, start)
            code *= powers(n, INVERSE)[start]
            code = mix(code + (end - start).astype(np.uint64) * STEP)
        else:
            code = np.empty(0, np.uint64)
    return Words(data, start, end, doc, first, code)


def runs(code: np.ndarray, length: int) -> np.ndarray:
    """Fingerprint of the ``length`` consecutive words from each position that has so many words after it."""
    n = len(code) - length + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for i in range(length):
        out *= STEP
        out += code[i : i + n]
    return mix(out + np.uint64(length))


def signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)
