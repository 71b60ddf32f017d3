"""Distances and bounds as Column expressions, unrolled over the dimensions.

Vectors are flat columns: a prefix and the number of the dimension (c0, c1 for coordinates, o for centres,
lo and hi for corners), so that every expression stays in generated code and range tests reach the scan.
"""

from __future__ import annotations

import re
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Vector = Sequence[Column]


def dims(df: DataFrame, prefix: str = "c") -> int:
    return sum(bool(re.fullmatch(rf"{prefix}\d+", c)) for c in df.columns)


def vec(prefix: str, d: int, table: str | None = None) -> list[Column]:
    return [F.col(f"{table}.{prefix}{i}" if table else f"{prefix}{i}") for i in range(d)]


def constants(values: Sequence[float]) -> list[Column]:
    return [F.lit(float(v)) for v in values]


def total(parts: Sequence[Column]) -> Column:
    return reduce(lambda a, b: a + b, parts)


def every(parts: Sequence[Column]) -> Column:
    return reduce(lambda a, b: a & b, parts)


def square_distance(a: Vector, b: Vector) -> Column:
    return total([(x - y) * (x - y) for x, y in zip(a, b)])


def euclid(a: Vector, b: Vector) -> Column:
    return F.sqrt(square_distance(a, b))


def ball_lower(oq: Vector, od: Vector, rd: Column) -> Column:
    """Below the directed Hausdorff distance from Q to D, if oq is the mean of Q and the ball of D holds all of D."""
    return F.greatest(euclid(oq, od) - rd, F.lit(0.0))


def ball_upper(oq: Vector, rq: Column, od: Vector, rd: Column) -> Column:
    """Above it, if od is the mean of D."""
    return F.sqrt(square_distance(oq, od) + rd * rd) + rq


def ball_gap(oq: Vector, rq: Column, od: Vector, rd: Column) -> Column:
    """Below the distance of any two points of the two balls; safe under a minimum over parts of D."""
    return F.greatest(euclid(oq, od) - rq - rd, F.lit(0.0))


def box_overlap(lo1: Vector, hi1: Vector, lo2: Vector, hi2: Vector) -> Column:
    """Area (volume) that two boxes share; touching boxes share none."""
    return reduce(lambda a, b: a * b, [F.greatest(F.least(h1, h2) - F.greatest(l1, l2), F.lit(0.0)) for l1, h1, l2, h2 in zip(lo1, hi1, lo2, hi2)])


def boxes_meet(lo1: Vector, hi1: Vector, lo2: Vector, hi2: Vector) -> Column:
    """Closed boxes with a common point."""
    return every([(l1 <= h2) & (l2 <= h1) for l1, h1, l2, h2 in zip(lo1, hi1, lo2, hi2)])


def box_holds(lo: Vector, hi: Vector, lo2: Vector, hi2: Vector) -> Column:
    """The second box lies in the first, borders included."""
    return every([(a <= c) & (d <= b) for a, b, c, d in zip(lo, hi, lo2, hi2)])


def point_inside(p: Vector, lo: Vector, hi: Vector) -> Column:
    return every([(x >= a) & (x <= b) for x, a, b in zip(p, lo, hi)])


def _faces(lo: Vector, hi: Vector):
    for i in range(len(lo)):
        for side in (lo[i], hi[i]):
            yield [side if j == i else x for j, x in enumerate(lo)], [side if j == i else x for j, x in enumerate(hi)]


def box_distance(lo1: Vector, hi1: Vector, lo2: Vector, hi2: Vector) -> Column:
    gaps = [F.greatest(l1 - h2, l2 - h1, F.lit(0.0)) for l1, h1, l2, h2 in zip(lo1, hi1, lo2, hi2)]
    return F.sqrt(total([g * g for g in gaps]))


def box_lower(qlo: Vector, qhi: Vector, dlo: Vector, dhi: Vector) -> Column:
    """Each face of a tight box carries a point, so the farthest face from the other box bounds from below."""
    return F.greatest(*(box_distance(lo, hi, dlo, dhi) for lo, hi in _faces(qlo, qhi)))


def box_upper(qlo: Vector, qhi: Vector, dlo: Vector, dhi: Vector) -> Column:
    """Each face of D carries a point: the best face, seen from the farthest place of Q. The squared distance is a
    sum over dimensions, so the farthest corner is found dimension by dimension."""

    def reach(flo: Vector, fhi: Vector) -> Column:
        parts = [F.greatest(*(F.abs(a - b) for a in (ql, qh) for b in (fl, fh))) for ql, qh, fl, fh in zip(qlo, qhi, flo, fhi)]
        return F.sqrt(total([p * p for p in parts]))

    return F.least(*(reach(lo, hi) for lo, hi in _faces(dlo, dhi)))
