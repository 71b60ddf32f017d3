"""Boxes, summaries and the three measures between datasets, as plain DataFrame plans."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import box_overlap, dims, euclid, vec
from ..functions.zorder import signatures
from ..model import GridSpec


def dataset_boxes(points: DataFrame) -> DataFrame:
    """dataset_id, n, lo, hi."""
    d = dims(points)
    return points.groupBy("dataset_id").agg(F.count(F.lit(1)).alias("n"), *(F.min(f"c{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"c{i}").alias(f"hi{i}") for i in range(d)))


def summarise_nodes(points: DataFrame, keys: list[str]) -> DataFrame:
    """keys, n, radius, o (mean), lo, hi: one aggregate for the means, a second for the distance from them."""
    d = dims(points)
    mean = points.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), *(F.avg(f"c{i}").alias(f"o{i}") for i in range(d)), *(F.min(f"c{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"c{i}").alias(f"hi{i}") for i in range(d)))
    far = points.join(mean, keys).groupBy(*keys).agg(F.max(euclid(vec("c", d), vec("o", d))).alias("radius"))
    return mean.join(far, keys).select(*keys, "n", "radius", *vec("o", d), *vec("lo", d), *vec("hi", d))


def ranked(df: DataFrame, k: int, score: str, largest: bool) -> DataFrame:
    """The k best rows by score, then id, with their rank."""
    from pyspark.sql import Window

    if k < 1:
        raise ValueError("k must be at least 1")
    order = [F.col(score).desc() if largest else F.col(score).asc(), F.col("dataset_id").asc()]
    top = df.orderBy(*order).limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(*order)))


def scan_ia(boxes: DataFrame, query_id: str, k: int = 10, include_zero: bool = False) -> DataFrame:
    """Top-k by shared area over all dataset boxes."""
    d = dims(boxes, "lo")
    q = boxes.filter(F.col("dataset_id") == query_id).select(*(F.col(f"{n}{i}").alias(f"q{n}{i}") for n in ("lo", "hi") for i in range(d)))
    score = box_overlap(vec("qlo", d), vec("qhi", d), vec("lo", d), vec("hi", d))
    scored = boxes.filter(F.col("dataset_id") != query_id).join(F.broadcast(q)).select("dataset_id", score.alias("score"))
    return ranked(scored if include_zero else scored.filter("score > 0"), k, "score", True)


def gbo_rows(query_cells: DataFrame, cells: DataFrame) -> DataFrame:
    """dataset_id and the number of cells shared with the query; a query has at most 4**theta cells."""
    return cells.join(F.broadcast(query_cells.select("cell").distinct()), "cell").groupBy("dataset_id").agg(F.count(F.lit(1)).alias("score"))


def inverted_gbo(cells: DataFrame, query_id: str, k: int = 10) -> DataFrame:
    q = cells.filter(F.col("dataset_id") == query_id)
    return ranked(gbo_rows(q, cells.filter(F.col("dataset_id") != query_id)), k, "score", True)


def scan_gbo(points: DataFrame, spec: GridSpec, query_id: str, k: int = 10) -> DataFrame:
    """The baseline without a tree or postings: intersect the query's array with every dataset's."""
    arrays = signatures(points, spec, "array")
    q = arrays.filter(F.col("dataset_id") == query_id).select(F.col("cells").alias("qcells"))
    scored = arrays.filter(F.col("dataset_id") != query_id).join(F.broadcast(q)).select("dataset_id", F.size(F.array_intersect("cells", "qcells")).cast("long").alias("score"))
    return ranked(scored.filter("score > 0"), k, "score", True)


def hausdorff_scan(points: DataFrame, query_id: str, symmetric: bool = False, block: int = 100_000) -> DataFrame:
    """dataset_id and the directed Hausdorff distance from the query, by all pairs of points: the oracle. Up to `block` query points
    are broadcast; more are dealt into blocks, and every other point meets each block."""
    d = dims(points)
    q = points.filter(F.col("dataset_id") == query_id).select(F.col("point_id").alias("q_id"), *(F.col(f"c{i}").alias(f"q{i}") for i in range(d)))
    others = points.filter(F.col("dataset_id") != query_id)
    n = q.count()
    if n <= block:
        met = others.join(F.broadcast(q))
    else:
        blocks = -(-n // block)
        met = others.withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).join(q.withColumn("b", F.pmod(F.xxhash64("q_id"), F.lit(blocks)).cast("int")), "b")
    pairs = met.select("dataset_id", "point_id", "q_id", euclid(vec("q", d), vec("c", d)).alias("dist"))
    there = pairs.groupBy("dataset_id", "q_id").agg(F.min("dist").alias("near")).groupBy("dataset_id").agg(F.max("near").alias("distance"))
    if not symmetric:
        return there
    back = pairs.groupBy("dataset_id", "point_id").agg(F.min("dist").alias("near")).groupBy("dataset_id").agg(F.max("near").alias("back"))
    return there.join(back, "dataset_id").select("dataset_id", F.greatest("distance", "back").alias("distance"))
