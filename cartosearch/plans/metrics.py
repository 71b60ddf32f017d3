"""Cost and accuracy measures of searches, and trends along a parameter."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

RUN_METRICS = "workload string, repository string, method string, parameter string, value double, wall_ms double, evaluations long, n_results long, accuracy double"


def timed(fn: Callable):
    """What fn returns and the milliseconds it took; a frame is forced into nothing."""
    start = time.perf_counter()
    got = fn()
    if isinstance(got, DataFrame):
        got.write.format("noop").mode("overwrite").save()
    return got, (time.perf_counter() - start) * 1000


def time_queries(fn: Callable[[str], object], query_ids: list[str], reps: int = 1) -> float:
    """Mean milliseconds per query."""
    return sum(timed(lambda q=q: fn(q))[1] for _ in range(reps) for q in query_ids) / max(1, reps * len(query_ids))


def speedup(base_ms: float, own_ms: float) -> float:
    return base_ms / own_ms if own_ms else float("inf")


def overlap_accuracy(rows: list[tuple[float, str]], truth: list[tuple[float, str]], k: int) -> float:
    """Share of the true top-k that was returned."""
    want = {i for _, i in truth[:k]}
    return len(want & {i for _, i in rows[:k]}) / max(1, min(k, len(want)))


def topk_overlap_accuracy(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """The same per query, over frames of (query_id, rank, dataset_id)."""
    top = lambda df: df.filter(F.col("rank") <= k).select("query_id", "dataset_id")
    hits = top(result).join(top(truth), ["query_id", "dataset_id"]).groupBy("query_id").agg(F.count(F.lit(1)).alias("hits"))
    return truth.select("query_id").distinct().join(hits, "query_id", "left").select("query_id", (F.coalesce("hits", F.lit(0)) / k).alias("accuracy"))


def approx_error(result: DataFrame, truth: DataFrame, eps: float) -> DataFrame:
    """Error of approximate distances and whether it is within 2 eps."""
    a, b = result.select("dataset_id", F.col("distance").alias("approx")), truth.select("dataset_id", "distance")
    return a.join(b, "dataset_id").select("dataset_id", F.abs(F.col("approx") - F.col("distance")).alias("error"), (F.abs(F.col("approx") - F.col("distance")) <= 2 * eps).alias("within"))


def scale_distribution(points: DataFrame, bins: int = 16) -> DataFrame:
    """Datasets by the power of two of their size."""
    sizes = points.groupBy("dataset_id").count()
    return sizes.groupBy(F.least(F.floor(F.log2("count")), F.lit(bins)).cast("long").alias("size_log2")).agg(F.count(F.lit(1)).alias("n_datasets"), F.sum("count").alias("n_points"))


def trend(runs: DataFrame, x: str, y: str, by: list[str], tolerance: float = 0.0) -> DataFrame:
    """Per group, whether y never falls (rising) or never rises (falling) along x."""
    along = Window.partitionBy(*by).orderBy(x)
    step = runs.withColumn("_d", F.col(y) - F.lag(y).over(along))
    return step.groupBy(*by).agg(F.coalesce(F.min(F.col("_d") >= -tolerance), F.lit(True)).alias("rising"), F.coalesce(F.min(F.col("_d") <= tolerance), F.lit(True)).alias("falling"), F.count(F.lit(1)).alias("n"))


def run_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUN_METRICS)
