"""Hausdorff distance of datasets too large for a task: the pairs of nodes still open are a DataFrame."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import ball_gap, ball_upper, dims, vec


def hausdorff(q_tree: DataFrame, tree: DataFrame, tau: float | None = None, most_rounds: int = 200) -> DataFrame:
    """dataset_id and the distance from the one dataset of q_tree to each of tree.

    A round bounds all open pairs: for each Q part the least upper bound drops the D parts whose gap is beyond it;
    Q parts that can no longer give the maximum, and datasets beyond tau, go; then the wider side is
    replaced by its children, which are joined by their parent's path (a Q part in all its pairs at once). Points are parts of radius 0.
    """
    d = dims(tree, "o")

    def parts(t: DataFrame, x: str) -> DataFrame:
        """Nodes and points, each with a key and its parent's."""
        key = F.when(F.col("kind") == 0, F.col("path")).otherwise(F.concat("path", F.lit("#"), F.col("point_id").cast("string")))
        parent = F.when((F.col("kind") == 0) & (F.col("path") == ""), F.lit(None)).when(F.col("kind") == 0, F.expr("substring(path, 1, length(path) - 1)")).otherwise(F.col("path"))
        own = [F.col("dataset_id")] if x == "d" else []
        return t.select(*own, key.alias(f"{x}_key"), parent.alias(f"{x}_parent"), F.when(F.col("kind") == 0, F.col("radius")).otherwise(F.lit(0.0)).alias(f"{x}_r"), (F.col("kind") == 1).alias(f"{x}_point"), *(F.col(f"o{i}").alias(f"{x}{i}") for i in range(d)))

    q, t = checkpointed(parts(q_tree, "q")), checkpointed(parts(tree, "d"))
    q_cols, d_cols = [c for c in q.columns if c != "q_parent"], [c for c in t.columns if c != "d_parent"]
    pairs = t.filter("d_key = ''").drop("d_parent").join(F.broadcast(q.filter("q_key = ''").drop("q_parent")))
    settled = None
    for _ in range(most_rounds):
        bounded = pairs.withColumn("gap", ball_gap(vec("q", d), F.col("q_r"), vec("d", d), F.col("d_r"))).withColumn("upper", ball_upper(vec("q", d), F.col("q_r"), vec("d", d), F.col("d_r")))
        per_q = bounded.groupBy("dataset_id", "q_key").agg(F.min("upper").alias("q_upper"), F.min("gap").alias("q_lower"))
        per_d = per_q.groupBy("dataset_id").agg(F.max("q_lower").alias("lower"))
        if tau is not None:
            per_d = per_d.filter(F.col("lower") <= tau)
        live = per_q.join(per_d, "dataset_id").filter(F.col("q_upper") >= F.col("lower")).select("dataset_id", "q_key", "q_upper")
        pairs = checkpointed(bounded.join(live, ["dataset_id", "q_key"]).filter(F.col("gap") <= F.col("q_upper")).drop("gap", "upper", "q_upper"))
        open_ = ~(F.col("q_point") & F.col("d_point"))
        if not pairs.filter(open_).limit(1).count():
            settled = pairs
            break
        # All pairs of a Q part move together: its children have to meet every D part that it still has.
        widest = pairs.groupBy("dataset_id", "q_key").agg(F.max("d_r").alias("widest"))
        sized = pairs.join(widest, ["dataset_id", "q_key"])
        split_q = ~F.col("q_point") & (F.col("q_r") >= F.col("widest"))
        split_d = ~split_q & ~F.col("d_point") & (F.col("q_point") | (F.col("d_r") > F.col("q_r")))
        done = sized.filter(~split_q & ~split_d).select(*d_cols, *q_cols)
        by_q = sized.filter(split_q).select(*d_cols, F.col("q_key").alias("q_parent")).join(q, "q_parent").select(*d_cols, *q_cols)
        by_d = sized.filter(split_d).select("dataset_id", F.col("d_key").alias("d_parent"), *q_cols).join(t, ["dataset_id", "d_parent"]).select(*d_cols, *q_cols)
        pairs = done.unionByName(by_q).unionByName(by_d)
    if settled is None:
        raise RuntimeError("the frontier did not settle")
    from ..functions.geometry import euclid

    near = settled.groupBy("dataset_id", "q_key").agg(F.min(euclid(vec("q", d), vec("d", d))).alias("near"))
    return near.groupBy("dataset_id").agg(F.max("near").alias("distance"))
