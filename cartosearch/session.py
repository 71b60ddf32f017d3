"""One object for a repository: range, exemplar and point searches in a chain."""

from __future__ import annotations

from pyspark.sql import DataFrame

from .model import Box
from .operators import search_datasets as sd
from .operators import search_points as sp
from .operators.index import SearchIndex, build_index


class SpatialSearch:
    """Datasets of a repository, narrowed step by step; the point searches end the chain."""

    def __init__(self, source: DataFrame | SearchIndex, **options):
        self.index = source if isinstance(source, SearchIndex) else build_index(source, **options)
        self.datasets = self.index.roots.select("dataset_id")

    def _with(self, datasets: DataFrame) -> SpatialSearch:
        new = SpatialSearch(self.index)
        new.datasets = datasets.select("dataset_id")
        return new

    def where(self, datasets: DataFrame) -> SpatialSearch:
        return self._with(self.datasets.join(datasets.select("dataset_id"), "dataset_id", "left_semi"))

    def range(self, box: Box) -> SpatialSearch:
        return self._with(sd.range_datasets(self.index, box).join(self.datasets, "dataset_id", "left_semi"))

    def exemplar(self, query: str | DataFrame, k: int = 10, measure: str = "ia", **options) -> DataFrame:
        return sd.exemplar_search(self.index.where(self.datasets) if self.datasets is not self.index.roots else self.index, query, k, measure, **options)

    def similar(self, query: str | DataFrame, k: int = 10, measure: str = "ia", **options) -> SpatialSearch:
        return self._with(self.exemplar(query, k, measure, **options))

    def points(self, box: Box) -> DataFrame:
        return sp.range_points(self.index, box, self.datasets)

    def nearest(self, query: str | DataFrame, dataset_id: str, k: int = 1, strategy: str = "packed") -> DataFrame:
        return sp.nearest_points(self.index, query, dataset_id, k, strategy)
