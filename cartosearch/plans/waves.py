"""Branch and bound in waves: the k-th best so far becomes a literal of the next plan."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field


@dataclass
class WavePlan:
    """leaves: (path, datasets, bound) of nodes that cover all datasets once. score(paths) gives (value, dataset_id) of the best k below them.

    The first wave takes leaves until k datasets are seen; every further one takes all leaves whose bound is not worse
    than the k-th value. Equal bounds are taken, so ties are decided by dataset_id alone.
    """

    leaves: list[tuple[str, int, float]]
    k: int
    largest: bool
    score: Callable[[list[str]], list[tuple[float, str]]]
    visited: int = 0
    rounds: int = 0
    found: list[tuple[float, str]] = field(default_factory=list)

    def _key(self, x: tuple[float, str]) -> tuple[float, str]:
        return (-x[0], x[1]) if self.largest else x

    def run(self) -> list[tuple[float, str]]:
        rest = sorted(self.leaves, key=lambda x: (-x[2] if self.largest else x[2], x[0]))
        while rest:
            if len(self.found) < self.k:
                take, seen = 0, len(self.found)
                while take < len(rest) and seen < self.k:
                    seen += rest[take][1]
                    take += 1
            else:
                limit = self.found[-1][0]
                take = sum(b >= limit if self.largest else b <= limit for _, _, b in rest)
                if not take:
                    break
            wave, rest = rest[:take], rest[take:]
            self.rounds += 1
            self.visited += len(wave)
            self.found = sorted(self.found + self.score([p for p, _, _ in wave]), key=self._key)[: self.k]
        return self.found
