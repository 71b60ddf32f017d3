"""Top-k by an earth mover's distance between grid histograms (an optional extra, approximate by construction).

Histograms over the index's grid are compared in sliced form: for each axis the one-dimensional transport cost is
the summed difference of the cumulative shares, which needs no linear program; axes are averaged.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.zorder import cell_index
from .index import SearchIndex
from .measures import ranked


def shares(index: SearchIndex) -> DataFrame:
    """dataset_id, axis, bin, share for every bin of every axis that a dataset touches."""
    d = index.d
    axes = F.explode(F.array(*(F.struct(F.lit(i).alias("axis"), cell_index(F.col(f"c{i}"), index.spec, i).alias("bin")) for i in range(d))))
    counts = index.points.select("dataset_id", axes.alias("a")).groupBy("dataset_id", "a.axis", "a.bin").agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("dataset_id", "axis"))).drop("n")


def topk_emd(index: SearchIndex, query: str, k: int = 10) -> DataFrame:
    """dataset_id, distance (in cells), rank."""
    all_shares = shares(index)
    q = F.broadcast(all_shares.filter(F.col("dataset_id") == query).select("axis", "bin", (-F.col("share")).alias("share")))
    others = all_shares.filter(F.col("dataset_id") != query)
    signed = others.unionByName(others.select("dataset_id").distinct().join(q))
    net = signed.groupBy("dataset_id", "axis", "bin").agg(F.sum("share").alias("s"))
    along = Window.partitionBy("dataset_id", "axis").orderBy("bin")
    flow = net.withColumn("carried", F.sum("s").over(along.rowsBetween(Window.unboundedPreceding, 0))).withColumn("steps", F.lead("bin").over(along) - F.col("bin"))
    cost = flow.groupBy("dataset_id").agg((F.sum(F.abs("carried") * F.coalesce("steps", F.lit(0))) / index.d).alias("distance"))
    return ranked(cost, k, "distance", False)
