"""Grid cells and bit-interleaved cell ids; dimension 0 takes the lowest bit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import GridSpec
from .geometry import total, vec


def cell_index(x: Column, spec: GridSpec, i: int) -> Column:
    """The number of x's cell along dimension i; the upper edge belongs to the last cell."""
    w = spec.widths[i]
    if w == 0:
        return F.lit(0).cast("long")
    return F.greatest(F.least(F.floor((x - F.lit(spec.lo[i])) / F.lit(w)), F.lit((1 << spec.theta) - 1)), F.lit(0)).cast("long")


def interleave(indexes: list[Column], theta: int) -> Column:
    d = len(indexes)
    return total([F.shiftleft(F.shiftright(x, b).bitwiseAND(F.lit(1).cast("long")), b * d + i) for b in range(theta) for i, x in enumerate(indexes)])


def z_id(point: list[Column], spec: GridSpec) -> Column:
    return interleave([cell_index(x, spec, i) for i, x in enumerate(point)], spec.theta)


def z_decode(cell: Column, spec: GridSpec) -> tuple[list[Column], list[Column]]:
    """The corners of a cell's box."""
    lo, hi = [], []
    for i, w in enumerate(spec.widths):
        index = total([F.shiftleft(F.shiftright(cell, b * spec.d + i).bitwiseAND(F.lit(1).cast("long")), b) for b in range(spec.theta)])
        lo.append(F.lit(spec.lo[i]) + index * F.lit(w))
        hi.append(F.lit(spec.lo[i]) + (index + 1) * F.lit(w))
    return lo, hi


def z_parent(cell: Column, d: int, levels: int = 1) -> Column:
    """The id of the cell on a grid coarser by that many halvings."""
    return F.shiftright(cell, d * levels)


def signatures(points: DataFrame, spec: GridSpec, form: str = "rows", prefix: str = "c") -> DataFrame:
    """The set of cells of each dataset: one row per cell, or a sorted array."""
    rows = points.select("dataset_id", z_id(vec(prefix, spec.d), spec).alias("cell")).distinct()
    if form == "rows":
        return rows
    return rows.groupBy("dataset_id").agg(F.array_sort(F.collect_set("cell")).alias("cells"))
