"""The methods that the index is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import box_lower, box_upper, boxes_meet, constants, dims, euclid, point_inside, vec
from ..functions.zorder import signatures
from ..model import Box, GridSpec
from .bottom_index import build_bottom, dataset_roots, tree_points
from .index import SearchIndex
from .kernels import Tree, all_pairs, early_break, isolation_scores, unpack
from .measures import dataset_boxes, ranked, scan_gbo
from .search_datasets import MOST_QUERY_POINTS, Run, as_query, kernel_frame

__all__ = ["scan_gbo", "box_bound_topk", "box_incremental_topk", "build_rtree", "bulk_tree", "isolation_nn_clean", "raw_hausdorff_topk", "knn_early_break", "scan_range_datasets", "scan_range_points", "separate_indexes", "neighbour_count_clean"]


def box_bound_topk(index: SearchIndex, query: str, k: int = 10) -> Run:
    """Rectangle bounds over all datasets, then all pairs of points of the survivors."""
    q = as_query(index, query)
    d = index.d
    lo, hi = constants(q.lo), constants(q.hi)
    bounds = index.roots.filter(F.col("dataset_id") != q.id).select("dataset_id", "n", box_lower(lo, hi, vec("lo", d), vec("hi", d)).alias("lower"), box_upper(lo, hi, vec("lo", d), vec("hi", d)).alias("upper"))
    first = [r["upper"] for r in bounds.orderBy("upper").limit(k).collect()]
    alive = bounds.filter(F.col("lower") <= first[-1] * (1 + 1e-12)) if len(first) == k else bounds
    qs = index.spark.createDataFrame([(i, *map(float, p)) for i, p in enumerate(q.points)], "q_id long, " + ", ".join(f"q{i} double" for i in range(d)))
    pairs = index.points.join(alive.select("dataset_id"), "dataset_id", "left_semi").join(F.broadcast(qs)).select("dataset_id", "q_id", euclid(vec("q", d), vec("c", d)).alias("dist"))
    top = ranked(pairs.groupBy("dataset_id", "q_id").agg(F.min("dist").alias("near")).groupBy("dataset_id").agg(F.max("near").alias("distance")), k, "distance", False)
    n = alive.agg(F.sum("n")).first()[0] or 0
    return Run([(r["distance"], r["dataset_id"]) for r in top.orderBy("rank").collect()], {"evaluations": int(n) * q.n + index.roots.count() * 2})


def _far_rows(index: SearchIndex, alive: DataFrame, named: DataFrame) -> DataFrame:
    """query_id, dataset_id, score of pairs of datasets of any size: every pair of points is a row."""
    d = index.d
    qs = index.points.join(named, "dataset_id", "left_semi").select(F.col("dataset_id").alias("query_id"), F.col("point_id").alias("q_id"), *(F.col(f"c{i}").alias(f"q{i}") for i in range(d)))
    pairs = index.points.join(alive.select("query_id", "dataset_id"), "dataset_id").join(qs, "query_id").select("query_id", "dataset_id", "q_id", euclid(vec("q", d), vec("c", d)).alias("dist"))
    return pairs.groupBy("query_id", "dataset_id", "q_id").agg(F.min("dist").alias("near")).groupBy("query_id", "dataset_id").agg(F.max("near").alias("score"))


def _far_blocks(index: SearchIndex, alive: DataFrame, query_ids: list[str], most: int) -> DataFrame:
    """The same of datasets that a task takes: every pair of points is compared, block by block; pairs of points are no rows."""
    few = len(query_ids) <= 20
    points = index.packed.filter(F.col("n") <= most).select("dataset_id", "tree")
    queries = points.filter(F.col("dataset_id").isin(query_ids) if few else F.lit(True)).select(F.col("dataset_id").alias("query_id"), F.col("tree").alias("q_tree"))

    def run(batches):
        opened: dict[str, np.ndarray] = {}
        for b in batches:
            out = []
            for q_id, d_id, q, x in zip(*(b.column(i).to_pylist() for i in range(4))):
                if q_id not in opened:
                    opened = {q_id: unpack(q).points}
                out.append((q_id, d_id, all_pairs(opened[q_id], unpack(x).points)))
            cols = list(zip(*out)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.string(), pa.float64()))], names=["query_id", "dataset_id", "score"])

    # Pairs cost by their points and not by their bytes, so they are spread over many tasks.
    spread = max(int(index.spark.conf.get("spark.sql.shuffle.partitions")), 4 * index.spark.sparkContext.defaultParallelism)
    met = alive.select("query_id", "dataset_id").join(points, "dataset_id")
    met = met if few else met.join(queries, "query_id")
    met = met.repartition(spread, "query_id", "dataset_id")
    met = met.join(F.broadcast(queries), "query_id") if few else met
    return met.select("query_id", "dataset_id", "q_tree", "tree").mapInArrow(run, "query_id string, dataset_id string, score double")


def box_bound_batch(index: SearchIndex, query_ids: list[str], k: int = 10, most: int = MOST_QUERY_POINTS) -> DataFrame:
    """The same for many members in one plan: query_id, rank, dataset_id, score, evaluations of the query. Datasets of more than
    `most` points are compared as rows."""
    d = index.d
    named = F.broadcast(index.spark.createDataFrame([(i,) for i in query_ids], "dataset_id string"))
    q = index.roots.join(named, "dataset_id", "left_semi").select(F.col("dataset_id").alias("query_id"), F.col("n").alias("q_n"), *(F.col(f"{n}{i}").alias(f"q{n}{i}") for n in ("lo", "hi") for i in range(d)))
    sides = vec("qlo", d), vec("qhi", d), vec("lo", d), vec("hi", d)
    bounds = index.roots.join(F.broadcast(q)).filter("dataset_id != query_id").select("query_id", "dataset_id", "n", "q_n", box_lower(*sides).alias("lower"), box_upper(*sides).alias("upper"))
    # Bounds over all faces of many dimensions are long expressions; they are planned and computed once.
    bounds = checkpointed(bounds)
    order = Window.partitionBy("query_id").orderBy("upper", "dataset_id")
    tau = bounds.withColumn("r", F.row_number().over(order)).filter(F.col("r") == k).select("query_id", (F.col("upper") * (1 + 1e-12)).alias("tau"))
    alive = bounds.join(F.broadcast(tau), "query_id", "left").filter(F.col("tau").isNull() | (F.col("lower") <= F.col("tau")))
    work = alive.groupBy("query_id").agg(F.sum(F.col("n") * F.col("q_n")).alias("evaluations"))
    far = _far_blocks(index, alive.filter((F.col("n") <= most) & (F.col("q_n") <= most)), query_ids, most)
    if index.roots.filter(F.col("n") > most).limit(1).count():
        far = far.unionByName(_far_rows(index, alive.filter((F.col("n") > most) | (F.col("q_n") > most)), named))
    best = far.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "dataset_id"))).filter(F.col("rank") <= k)
    return best.join(work, "query_id").select("query_id", "rank", "dataset_id", "score", "evaluations")


def bulk_tree(points: np.ndarray, f: int) -> Tree:
    """A box tree by sorting: slabs along the first dimension, runs of f along the second, parents of f nodes each."""
    n, d = points.shape
    order = np.lexsort(points.T[::-1])
    slabs = max(1, int(np.ceil(np.sqrt(np.ceil(n / f)))))
    groups = []
    for slab in np.array_split(order, slabs):
        slab = slab[np.argsort(points[slab, 1], kind="stable")]
        groups += [slab[i : i + f] for i in range(0, len(slab), f)]
    level = [("p", g) for g in groups if len(g)]
    nodes: list[dict] = []

    def add(kind: str, below: np.ndarray) -> int:
        if kind == "p":
            p = points[below]
            lo, hi, count, total = p.min(axis=0), p.max(axis=0), len(p), p.sum(axis=0)
        else:
            parts = [nodes[i] for i in below]
            lo, hi = np.min([x["lo"] for x in parts], axis=0), np.max([x["hi"] for x in parts], axis=0)
            count, total = sum(x["n"] for x in parts), np.sum([x["total"] for x in parts], axis=0)
        nodes.append({"kind": kind, "below": below, "lo": lo, "hi": hi, "n": count, "total": total})
        return len(nodes) - 1

    current = [add(*x) for x in level]
    while len(current) > 1:
        current = [add("n", np.array(current[i : i + max(2, f)])) for i in range(0, len(current), max(2, f))]
    m = len(nodes)
    turn = lambda i: m - 1 - i  # the root first, children of a node side by side
    ordered = nodes[::-1]
    leaf = np.array([x["kind"] == "p" for x in ordered])
    first, last, held, at = np.zeros(m, np.int64), np.zeros(m, np.int64), [], m
    for i, x in enumerate(ordered):
        if x["kind"] == "p":
            first[i], last[i] = at, at + len(x["below"])
            held.append(x["below"])
            at = last[i]
        else:
            first[i], last[i] = turn(x["below"][-1]), turn(x["below"][0]) + 1
    lo, hi = np.array([x["lo"] for x in ordered]), np.array([x["hi"] for x in ordered])
    place = np.concatenate(held)
    half = np.sqrt(((hi - lo) ** 2).sum(axis=1)) / 2
    return Tree([str(i) for i in range(m)], np.array([x["n"] for x in ordered]), half, (lo + hi) / 2, lo, hi, leaf, first, last, points[place], place, np.zeros(n))


def box_incremental_topk(index: SearchIndex, query: str, k: int = 10) -> Run:
    """Two-queue search over box trees: datasets by rectangle bounds, pairs by box distances."""
    q = as_query(index, query)
    d = index.d
    lo, hi = constants(q.lo), constants(q.hi)
    bounds = index.roots.filter(F.col("dataset_id") != q.id).select("dataset_id", box_lower(lo, hi, vec("lo", d), vec("hi", d)).alias("lower"), box_upper(lo, hi, vec("lo", d), vec("hi", d)).alias("upper"))
    first = [r["upper"] for r in bounds.orderBy("upper").limit(k).collect()]
    tau = first[-1] * (1 + 1e-12) if len(first) == k else float("inf")
    part = index.tree.filter("kind = 1").join(bounds.filter(F.col("lower") <= tau), "dataset_id", "left_semi")
    got = kernel_frame(part, bulk_tree(q.points, index.f), tau, "exact", 0.0, "center", "box", index.f).collect()
    rows = sorted((r["distance"], r["dataset_id"]) for r in got if r["distance"] is not None)[:k]
    return Run(rows, {"evaluations": sum(r["evaluations"] for r in got), "kernels": len(got)})


def build_rtree(points: DataFrame, fanout: int = 10) -> DataFrame:
    """A bulk-loaded box tree of every dataset as rows (dataset_id, level, node, n, lo.., hi..): the separate index."""
    d = dims(points)
    n = points.groupBy("dataset_id").agg(F.count(F.lit(1)).alias("_n"))
    sized = points.join(n, "dataset_id")
    slab = F.floor((F.row_number().over(Window.partitionBy("dataset_id").orderBy(*vec("c", d), "point_id")) - 1) / (F.ceil(F.sqrt(F.ceil(F.col("_n") / fanout))) * fanout))
    cut = sized.withColumn("slab", slab)
    run = F.floor((F.row_number().over(Window.partitionBy("dataset_id", "slab").orderBy("c1", "c0", "point_id")) - 1) / fanout)
    placed = cut.withColumn("run", run).groupBy("dataset_id", "slab", "run").agg(F.count(F.lit(1)).alias("n"), *(F.min(f"c{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"c{i}").alias(f"hi{i}") for i in range(d)))
    level = placed.withColumn("node", F.row_number().over(Window.partitionBy("dataset_id").orderBy("slab", "run")) - 1).drop("slab", "run").withColumn("level", F.lit(0))
    out, most = level, (n.agg(F.max("_n")).first()[0] or 1) / fanout
    depth = 0
    while most > 1:
        depth += 1
        level = level.withColumn("node", F.floor(F.col("node") / fanout)).groupBy("dataset_id", "node").agg(F.sum("n").alias("n"), *(F.min(f"lo{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"hi{i}").alias(f"hi{i}") for i in range(d))).withColumn("level", F.lit(depth))
        out, most = out.unionByName(level), most / fanout
    return out


def isolation_nn_scores(points: DataFrame, t: int = 100, psi: int = 8, seed: int = 42) -> DataFrame:
    """points with `score`: t samples of psi points each, drawn from the whole repository by hash."""
    d = dims(points)
    ids = points.select("dataset_id", "point_id", *vec("c", d))
    drawn = ids.orderBy(F.xxhash64("dataset_id", "point_id", F.lit(seed))).limit(t * psi).toPandas()[[f"c{i}" for i in range(d)]].to_numpy()
    samples = [drawn[i::t] for i in range(t) if len(drawn[i::t])]
    schema = ids.schema.simpleString()[7:-1].replace(":", " ").replace(",", ", ") + ", score double"

    def run(batches):
        for b in batches:
            for start in range(0, b.num_rows, 4096):
                part = b.slice(start, 4096)
                p = np.column_stack([part.column(part.schema.get_field_index(f"c{i}")).to_numpy() for i in range(d)])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(isolation_scores(p, samples))], names=[*part.schema.names, "score"])

    return ids.mapInArrow(run, schema)


def isolation_nn_clean(points: DataFrame, contamination: float, t: int = 100, psi: int = 8, seed: int = 42) -> DataFrame:
    """Points whose score is not among the given share of the highest ones."""
    scored = isolation_nn_scores(points, t, psi, seed)
    limit = scored.agg(F.percentile_approx("score", 1 - contamination, 100_000)).first()[0]
    return scored.filter(F.col("score") <= limit).drop("score")


def raw_hausdorff_topk(raw: SearchIndex, query: str, k: int = 10) -> Run:
    """The exact search on an index that was not cleaned."""
    from .search_datasets import topk_hausdorff

    if raw.threshold is not None:
        raise ValueError("this index has been cleaned")
    return topk_hausdorff(raw, query, k)


def knn_early_break(points: DataFrame, query: str, dataset_id: str, k: int = 1, seed: int = 42, block: int = 100_000) -> DataFrame:
    """q_point_id, rank, d_point_id, distance, looked: scan the dataset in a shuffled order for each query point. Query and
    dataset are dealt into blocks of about `block` points that meet in one task each; the k best of the blocks are merged."""
    d = dims(points)
    sizes = {r["dataset_id"]: r["count"] for r in points.filter(F.col("dataset_id").isin([query, dataset_id])).groupBy("dataset_id").count().collect()}
    q_blocks, d_blocks = (max(1, -(-sizes.get(i, 0) // block)) for i in (query, dataset_id))
    schema = "q_point_id long, rank int, d_point_id long, distance double, looked long"

    def run(q_rows: pa.Table, d_rows: pa.Table) -> pa.Table:
        get = lambda t, n: np.column_stack([t.column(f"{n}{i}").to_numpy() for i in range(d)])
        rows = []
        if q_rows.num_rows and d_rows.num_rows:
            order = np.argsort(d_rows.column("shuffled").to_numpy(), kind="stable")
            ids, other, q = d_rows.column("d_id").to_numpy()[order], get(d_rows, "e")[order], get(q_rows, "c")
            index, dist, looked = early_break(q, other, k)
            rows = [(i, r + 1, int(ids[j]), float(x), looked // len(q)) for i, js, xs in zip(q_rows.column("point_id").to_pylist(), index, dist) for r, (j, x) in enumerate(zip(js, xs)) if j >= 0]
        return pa.table([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 5, (pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64()))], names=["q_point_id", "rank", "d_point_id", "distance", "looked"])

    dealt = lambda i, n, x: points.filter(F.col("dataset_id") == i).withColumn(x, F.pmod(F.xxhash64("point_id", F.lit(seed + 1)), F.lit(n)).cast("int"))
    # At least as many blocks of the query as keep a few tasks busy.
    n_q = max(q_blocks, min(8, max(1, sizes.get(query, 0) // 64)))
    q = dealt(query, n_q, "qb").withColumn("db", F.explode(F.sequence(F.lit(0), F.lit(d_blocks - 1)))).select("qb", "db", "point_id", *vec("c", d))
    other = dealt(dataset_id, d_blocks, "db").withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(n_q - 1)))).select(F.col("qb").alias("d_qb"), F.col("db").alias("d_db"), F.col("point_id").alias("d_id"), F.xxhash64("point_id", F.lit(seed)).alias("shuffled"), *(F.col(f"c{i}").alias(f"e{i}") for i in range(d)))
    got = q.groupBy("qb", "db").cogroup(other.groupBy("d_qb", "d_db")).applyInArrow(run, schema)
    if d_blocks == 1:
        return got
    best = Window.partitionBy("q_point_id").orderBy("distance", "d_point_id")
    return got.withColumn("looked", F.sum("looked").over(Window.partitionBy("q_point_id")).cast("long")).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)


def scan_range_datasets(points: DataFrame, box: Box) -> DataFrame:
    boxes, d = dataset_boxes(points), dims(points)
    return boxes.filter(boxes_meet(vec("lo", d), vec("hi", d), constants(box.lo), constants(box.hi))).select("dataset_id", "n")


def scan_range_points(points: DataFrame, box: Box, dataset_id: str) -> DataFrame:
    d = dims(points)
    return points.filter((F.col("dataset_id") == dataset_id) & point_inside(vec("c", d), constants(box.lo), constants(box.hi))).select("dataset_id", "point_id", *vec("c", d))


def separate_indexes(points: DataFrame, spec: GridSpec, f: int = 10) -> dict[str, DataFrame]:
    """One index per kind of query: boxes, postings, a ball tree and a box tree, each from the points."""
    tree = build_bottom(points, f)
    return {"boxes": dataset_boxes(points), "cells": signatures(points, spec), "roots": dataset_roots(tree), "points": tree_points(tree), "rtree": build_rtree(points, f)}


def neighbour_count_clean(points: DataFrame, radius: float, least: int) -> DataFrame:
    """Points with at least `least` others of their dataset within radius; a grid of that width finds the pairs."""
    d = dims(points)
    cell = points.withColumns({f"g{i}": F.floor(F.col(f"c{i}") / radius) for i in range(d)})
    near = cell
    for i in range(d):
        near = near.withColumn(f"g{i}", F.explode(F.array(F.col(f"g{i}") - 1, F.col(f"g{i}"), F.col(f"g{i}") + 1)))
    other = near.select("dataset_id", *vec("g", d), F.col("point_id").alias("other"), *(F.col(f"c{i}").alias(f"q{i}") for i in range(d)))
    pairs = cell.join(other, ["dataset_id", *(f"g{i}" for i in range(d))]).filter((F.col("point_id") != F.col("other")) & (euclid(vec("c", d), vec("q", d)) <= radius))
    enough = pairs.groupBy("dataset_id", "point_id").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= least)
    return points.join(enough, ["dataset_id", "point_id"], "left_semi")
