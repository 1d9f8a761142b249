"""Distances, boxes and Z-curve codes as Column expressions; all stay inside generated code."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bits of one axis in a 63-bit code, by number of axes.
AXIS_BITS = {1: 62, 2: 31, 3: 21}


def add(terms: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, terms)


def point_d2(a: list[Column], b: list[Column]) -> Column:
    """Squared Euclidean distance; exact for whole-number coordinates."""
    return add([(x - y) * (x - y) for x, y in zip(a, b, strict=True)])


def point_box_d2(p: list[Column], lo: list[Column], hi: list[Column]) -> Column:
    return box_gap_d2(p, p, lo, hi)


def box_gap_d2(alo: list[Column], ahi: list[Column], blo: list[Column], bhi: list[Column]) -> Column:
    """Squared gap between two boxes; zero if they meet."""
    gaps = [F.greatest(a - d, c - b, (a - a)) for a, b, c, d in zip(alo, ahi, blo, bhi, strict=True)]
    return add([g * g for g in gaps])


def box_far_d2(alo: list[Column], ahi: list[Column], blo: list[Column], bhi: list[Column]) -> Column:
    """Squared distance that no two points of the boxes exceed."""
    wide = [F.greatest(d - a, b - c) for a, b, c, d in zip(alo, ahi, blo, bhi, strict=True)]
    return add([g * g for g in wide])


def comb(step: int, axes: int, bits: int) -> int:
    """Mask of ``bits`` bits in groups of ``step``, a group every ``step * axes`` bits."""
    mask, at, left = 0, 0, bits
    while left > 0:
        mask |= ((1 << min(step, left)) - 1) << at
        at, left = at + step * axes, left - step
    return mask & ((1 << 63) - 1)


def spread(x: Column, axes: int, bits: int) -> Column:
    """Puts ``axes - 1`` empty bits between the low ``bits`` of x, by halving: each step moves the upper
    half of every group of bits away from the lower half."""
    if axes == 1:
        return x
    step = 1 << (bits - 1).bit_length()
    while step > 1:
        step //= 2
        x = x.bitwiseOR(F.shiftleft(x, step * (axes - 1))).bitwiseAND(F.lit(comb(step, axes, bits)))
    return x


def morton(axes: list[Column], bits: int | None = None) -> Column:
    """Z-curve code of non-negative whole numbers below 2 ** bits; axis 0 has the lowest bit."""
    d = len(axes)
    bits = bits or AXIS_BITS[d]
    return reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(spread(x.cast("bigint"), d, bits), i) if i else spread(x.cast("bigint"), d, bits) for i, x in enumerate(axes)])


def morton_array(axes: list[np.ndarray]) -> np.ndarray:
    """The same codes of arrays, for kernels."""
    d, bits = len(axes), AXIS_BITS[len(axes)]
    out = np.zeros(len(axes[0]), np.int64)
    for k, x in enumerate(axes):
        step = 1 << (bits - 1).bit_length()  # halve groups as ``spread`` does
        x = x.astype(np.int64)
        while d > 1 and step > 1:
            step //= 2
            x = (x | (x << (step * (d - 1)))) & comb(step, d, bits)
        out |= x << k
    return out


def morton_wide(axes: list[Column]) -> tuple[Column, Column]:
    """Code of twice the width, as (high, low): the codes of the upper and of the lower half of each axis."""
    half = AXIS_BITS[len(axes)]
    return morton([F.shiftright(x.cast("bigint"), half) for x in axes]), morton([x.cast("bigint").bitwiseAND(F.lit((1 << half) - 1)) for x in axes])
