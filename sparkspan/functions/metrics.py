"""Metrics for the tree. Any metric that is never smaller than Euclid works with the same boxes and bounds: these
stay Euclidean, and only the weight of a pair of points is measured anew.

A metric gives the square of a distance, from the gaps along the axes (arrays) or from two array columns.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


class Metric(Protocol):
    def squared(self, gaps: list[np.ndarray]) -> np.ndarray: ...

    def columns(self, a: Column, b: Column, zero: Column) -> Column: ...


@dataclass(frozen=True)
class Euclid:
    def squared(self, gaps: list[np.ndarray]) -> np.ndarray:
        out = gaps[0] * gaps[0]
        for g in gaps[1:]:
            out = out + g * g
        return out

    def columns(self, a: Column, b: Column, zero: Column) -> Column:
        return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), zero, lambda s, x: s + x)


@dataclass(frozen=True)
class Manhattan:
    """Sum of the gaps, as along streets."""

    def squared(self, gaps: list[np.ndarray]) -> np.ndarray:
        out = np.abs(gaps[0])
        for g in gaps[1:]:
            out = out + np.abs(g)
        return out * out

    def columns(self, a: Column, b: Column, zero: Column) -> Column:
        way = F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), zero, lambda s, x: s + x)
        return way * way


@dataclass(frozen=True)
class Stretched:
    """Euclid with each axis drawn out by a whole factor of at least one."""

    factors: tuple[int, ...]

    def __post_init__(self):
        if min(self.factors) < 1:
            raise ValueError("a metric must not be smaller than Euclid")

    def squared(self, gaps: list[np.ndarray]) -> np.ndarray:
        return Euclid().squared([g * f for g, f in zip(gaps, self.factors, strict=True)])

    def columns(self, a: Column, b: Column, zero: Column) -> Column:
        f = F.array(*[F.lit(x) for x in self.factors])
        return Euclid().columns(F.zip_with(a, f, lambda x, y: x * y), F.zip_with(b, f, lambda x, y: x * y), zero)


EUCLID = Euclid()


def no_smaller(metric: Metric, gaps: list[np.ndarray]) -> bool:
    """What a metric has to keep: whether it is nowhere below Euclid on these gaps."""
    return bool((metric.squared(gaps) >= EUCLID.squared(gaps)).all())
