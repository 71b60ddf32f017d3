"""Outlier removal without parameters: the knee of the sorted leaf radii is the threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import dims, vec
from . import bottom_index as bi
from .bottom_index import clean_blocks, tree_points, tree_rows


def leaf_radii(tree: DataFrame) -> DataFrame:
    return tree.filter("kind = 0 AND is_leaf").select("dataset_id", "radius")


def ranked_radii(radii: DataFrame, order: str = "desc", scope: str = "repository") -> DataFrame:
    """radius with its rank from 0 and the length, first and last of the sorted list.

    Ranks of the whole repository need no single ordered task: equal radii are counted first, each partition of
    a range partitioning adds up its counts, and one count per partition goes to the driver.
    """
    keys = ["dataset_id"] if scope == "dataset" else []
    col = F.col("radius")
    way = col.desc() if order == "desc" else col.asc()
    first, last = (F.max, F.min) if order == "desc" else (F.min, F.max)
    if keys:
        w = Window.partitionBy(*keys)
        return radii.withColumn("rank", F.row_number().over(w.orderBy(way)) - 1).withColumn("length", F.count(F.lit(1)).over(w)).withColumn("first", first("radius").over(w)).withColumn("last", last("radius").over(w))
    counted = checkpointed(radii.groupBy("radius").agg(F.count(F.lit(1)).alias("times")).repartitionByRange(way).sortWithinPartitions(way).withColumn("p", F.spark_partition_id()))
    parts = sorted(counted.groupBy("p").agg(F.sum("times"), F.max("radius"), F.min("radius")).collect())
    length = sum(r[1] for r in parts)
    at, starts = 0, {}
    for p, n, _, _ in sorted(parts, key=lambda r: r[0]):
        starts[p], at = at, at + n
    if not parts:
        return counted.select("radius", F.lit(0).cast("long").alias("rank"), F.lit(0).cast("long").alias("length"), "radius", "radius").toDF("radius", "rank", "length", "first", "last")
    top, low = max(r[2] for r in parts), min(r[3] for r in parts)
    begin = F.coalesce(*(F.when(F.col("p") == p, F.lit(n)) for p, n in starts.items())) if len(starts) < 200 else F.element_at(F.create_map(*(F.lit(x) for kv in starts.items() for x in kv)), F.col("p"))
    before = F.coalesce(F.sum("times").over(Window.partitionBy("p").orderBy(way).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    head, tail = (top, low) if order == "desc" else (low, top)
    return counted.select("radius", (begin + before).cast("long").alias("rank"), "times").select("radius", F.explode(F.sequence(F.col("rank"), F.col("rank") + F.col("times") - 1)).alias("rank"), F.lit(length).alias("length"), F.lit(head).alias("first"), F.lit(tail).alias("last"))


def gap_profile(radii: DataFrame, order: str = "desc", chord_span: str = "count", scope: str = "repository") -> DataFrame:
    """rank, radius and how far the radius lies below the chord from the first to the last one."""
    span = F.col("length") if chord_span == "count" else F.greatest(F.col("length") - 1, F.lit(1))
    chord = F.col("first") - F.col("rank") * (F.col("first") - F.col("last")) / span
    return ranked_radii(radii, order, scope).withColumn("gap", chord - F.col("radius"))


def approximate_radii(radii: DataFrame, quantiles: int = 10_000) -> DataFrame:
    """A list of quantiles in place of all radii, for repositories whose leaves are too many to rank."""
    q = F.percentile_approx("radius", [i / quantiles for i in range(quantiles + 1)], 10 * quantiles)
    return radii.agg(q.alias("q")).select(F.explode("q").alias("radius"))


def knee_threshold(radii: DataFrame, order: str = "desc", chord_span: str = "count", approx: bool = False) -> float:
    """The radius of the largest gap, the first one on ties; the first radius itself if the list has no bend."""
    gaps = gap_profile(approximate_radii(radii) if approx else radii, order, chord_span)
    best = gaps.filter("rank >= 1 AND length > 2 AND first != last").agg(F.max_by("radius", F.struct(F.col("gap"), -F.col("rank"))).alias("r")).first()["r"]
    return radii.agg(F.max("radius")).first()[0] if best is None else best


def knee_per_dataset(radii: DataFrame, order: str = "desc", chord_span: str = "count") -> DataFrame:
    gaps = gap_profile(radii, order, chord_span, "dataset")
    bend = (F.col("rank") >= 1) & (F.col("length") > 2) & (F.col("first") != F.col("last"))
    best = F.max_by(F.when(bend, F.col("radius")), F.when(bend, F.struct(F.col("gap"), -F.col("rank"))))
    return gaps.groupBy("dataset_id").agg(F.coalesce(best, F.max("radius")).alias("threshold"))


def mark_outliers(tree: DataFrame, threshold: float | DataFrame) -> DataFrame:
    """Points with `kept`: leaves up to the threshold stay as they are, wider ones lose what lies farther out."""
    leaves = tree.filter("kind = 0 AND is_leaf").select("dataset_id", F.col("path").alias("leaf_path"), F.col("radius").alias("leaf_radius"))
    points = tree_points(tree).join(leaves, ["dataset_id", "leaf_path"])
    if isinstance(threshold, DataFrame):
        points = points.join(threshold, "dataset_id")
        limit = F.col("threshold")
    else:
        limit = F.lit(float(threshold))
    return points.withColumn("kept", (F.col("leaf_radius") <= limit) | (F.col("leaf_distance") <= limit))


def remove_outliers(tree: DataFrame, threshold: float | DataFrame | None = None, scope: str = "repository", on_empty: str = "keep", **knee) -> DataFrame:
    """Tree rows of the points that stay, every node up to the root refreshed from them.

    A dataset that would lose all points keeps them (on_empty="keep") or goes ("drop"). Splits stay where they were;
    emptied nodes go.
    """
    if threshold is None:
        threshold = knee_per_dataset(leaf_radii(tree), **knee) if scope == "dataset" else knee_threshold(leaf_radii(tree), **knee)
    if not isinstance(threshold, DataFrame):
        roots = tree.filter("kind = 0 AND path = ''").select("dataset_id", "n")
        total, largest = roots.agg(F.sum("n"), F.max("n")).first()
        if not total:
            return tree
        if largest <= bi.MOST_BLOCK_POINTS:
            return clean_blocks(tree, float(threshold), on_empty, total)
        wide = checkpointed(roots.filter(F.col("n") > bi.MOST_BLOCK_POINTS).select("dataset_id"))
        small = clean_blocks(tree.join(wide, "dataset_id", "left_anti"), float(threshold), on_empty, total)
        return small.unionByName(_remove(tree.join(wide, "dataset_id", "left_semi"), threshold, on_empty))
    return _remove(tree, threshold, on_empty)


def _remove(tree: DataFrame, threshold: float | DataFrame, on_empty: str) -> DataFrame:
    """The same by joins and aggregates, for datasets of any size."""
    marked = mark_outliers(tree, threshold)
    if on_empty == "keep":
        alive = Window.partitionBy("dataset_id")
        marked = marked.withColumn("kept", F.col("kept") | ~F.max("kept").over(alive))
    d = dims(marked)
    return tree_rows(marked.filter("kept").select("dataset_id", "point_id", F.col("leaf_path").alias("path"), *vec("c", d)))
