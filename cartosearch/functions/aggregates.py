"""Aggregates of datasets: boxes and cell sets from built-in functions, centre distances as grouped pandas aggregates."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType

from ..model import GridSpec
from .zorder import z_id


def dataset_box(coords: list[Column]) -> Column:
    """A struct of the corners, for groupBy().agg()."""
    return F.struct(*(F.min(c).alias(f"lo{i}") for i, c in enumerate(coords)), *(F.max(c).alias(f"hi{i}") for i, c in enumerate(coords)))


def signature(coords: list[Column], spec: GridSpec) -> Column:
    """The sorted set of cells, for groupBy().agg()."""
    return F.array_sort(F.collect_set(z_id(coords, spec)))


@pandas_udf(DoubleType())
def dataset_radius(x: pd.Series, y: pd.Series) -> float:
    """The largest distance of a group's points from their mean; a group has to fit in a task."""
    return float(np.sqrt((x - x.mean()) ** 2 + (y - y.mean()) ** 2).max()) if len(x) else float("nan")


def register(spark: SparkSession) -> None:
    spark.udf.register("dataset_radius", dataset_radius)
