"""Value types of the engine.

Frames (d = number of dimensions, i = 0..d-1):
  points     dataset_id string, point_id long, c{i} double, any attribute columns
  roots      dataset_id, n, radius, o{i} (mean), lo{i}, hi{i}
  tree       dataset_id, kind (0 node, 1 point), path, point_id, n, radius, is_leaf, split_dim, split_at, o{i}, lo{i}, hi{i};
             of a point, path is its leaf, radius its distance from the leaf's centre and o its coordinates
  upper      path, depth, is_leaf, n_datasets, n, radius, o{i}, lo{i}, hi{i}
  members    path (leaf), dataset_id
  cells      dataset_id, cell;  upper_cells: path, cell
A path is '' for the root and one '0' or '1' more for each level below.
"""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Box:
    lo: tuple[float, ...]
    hi: tuple[float, ...]

    def __post_init__(self):
        if len(self.lo) != len(self.hi) or any(a > b for a, b in zip(self.lo, self.hi)):
            raise ValueError("a box needs corners of equal length, lower one first")

    @property
    def d(self) -> int:
        return len(self.lo)

    @classmethod
    def around(cls, centre, half) -> Box:
        return cls(tuple(c - h for c, h in zip(centre, half)), tuple(c + h for c, h in zip(centre, half)))


@dataclass(frozen=True)
class GridSpec:
    """2**theta equal cells along each dimension of an extent."""

    lo: tuple[float, ...]
    hi: tuple[float, ...]
    theta: int

    def __post_init__(self):
        if not 0 < self.theta * len(self.lo) <= 62:
            raise ValueError("cell ids need 1 to 62 bits")

    @classmethod
    def from_extent(cls, box: Box, theta: int = 5) -> GridSpec:
        return cls(box.lo, box.hi, theta)

    @property
    def d(self) -> int:
        return len(self.lo)

    @property
    def widths(self) -> tuple[float, ...]:
        return tuple((b - a) / float(1 << self.theta) for a, b in zip(self.lo, self.hi))

    def epsilon(self, agg: str = "max") -> float:
        """The cell size as an error bound: of the widest or the narrowest dimension."""
        return (max if agg == "max" else min)(self.widths)
