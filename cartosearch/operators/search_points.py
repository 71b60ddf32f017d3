"""Point search inside found datasets: by rectangle, and the nearest points of a dataset to each query point."""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import ball_gap, ball_upper, box_holds, boxes_meet, constants, euclid, point_inside, vec
from ..model import Box
from .bottom_index import build_bottom
from .index import MOST_TASK_POINTS, SearchIndex
from .kernels import best_first, build_tree, drain, early_break, nearest_in_tree, unpack


def range_points(index: SearchIndex, box: Box, datasets: str | list[str] | DataFrame) -> DataFrame:
    """Points in the rectangle. Leaves apart from it are dropped, leaves inside it are taken whole, only the points of the
    others are compared."""
    d = index.d
    lo, hi = constants(box.lo), constants(box.hi)
    if isinstance(datasets, DataFrame):
        tree = index.tree.join(datasets.select("dataset_id").distinct(), "dataset_id", "left_semi")
    else:
        tree = index.tree.filter(F.col("dataset_id").isin([datasets] if isinstance(datasets, str) else datasets))
    leaves = tree.filter(F.col("is_leaf") & (F.col("kind") == 0) & boxes_meet(vec("lo", d), vec("hi", d), lo, hi)).select("dataset_id", "path", box_holds(lo, hi, vec("lo", d), vec("hi", d)).alias("whole"))
    points = tree.filter("kind = 1").select("dataset_id", "path", "point_id", *vec("o", d))
    got = points.join(leaves, ["dataset_id", "path"]).filter(F.col("whole") | point_inside(vec("o", d), lo, hi))
    return got.select("dataset_id", "point_id", *(F.col(f"o{i}").alias(f"c{i}") for i in range(d)))


def range_points_batch(index: SearchIndex, queries: DataFrame) -> DataFrame:
    """query_id, dataset_id, point_id, c..: the points in many rectangles (query_id, dataset_id, qlo.., qhi..), each of one dataset."""
    d = index.d
    q = queries.select("query_id", "dataset_id", *vec("qlo", d), *vec("qhi", d))
    sides = vec("qlo", d), vec("qhi", d)
    leaves = index.tree.filter(F.col("is_leaf") & (F.col("kind") == 0)).select("dataset_id", "path", *vec("lo", d), *vec("hi", d)).join(q, "dataset_id").filter(boxes_meet(vec("lo", d), vec("hi", d), *sides)).select("dataset_id", "path", "query_id", *sides[0], *sides[1])
    points = index.tree.filter("kind = 1").select("dataset_id", "path", "point_id", *vec("o", d))
    return points.join(leaves, ["dataset_id", "path"]).filter(point_inside(vec("o", d), *sides)).select("query_id", "dataset_id", "point_id", *(F.col(f"o{i}").alias(f"c{i}") for i in range(d)))


def nearest_points_batch(index: SearchIndex, pairs: list[tuple[str, str]], k: int = 1) -> DataFrame:
    """query_id, dataset_id, q_point_id, rank, d_point_id, distance for pairs of members: both packed trees meet in one row.
    Pairs with a dataset of more points than a task takes go through nearest_points."""
    spark = index.spark
    named = spark.createDataFrame(pairs, "query_id string, dataset_id string")
    packed = index.packed.select("dataset_id", "tree").filter("tree IS NOT NULL")
    met = named.join(packed, "dataset_id").join(packed.select(F.col("dataset_id").alias("query_id"), F.col("tree").alias("q_tree")), "query_id")
    schema = "query_id string, dataset_id string, q_point_id long, rank int, d_point_id long, distance double"

    def run(batches):
        for b in batches:
            for q_id, d_id, tree, q_tree in zip(*(b.column(b.schema.get_field_index(c)).to_pylist() for c in ("query_id", "dataset_id", "tree", "q_tree"))):
                q, t = unpack(q_tree), unpack(tree)
                places, far, _ = nearest_in_tree(q.points, t, k)
                n, m = places.shape
                columns = [pa.array([q_id] * (n * m)), pa.array([d_id] * (n * m)), pa.array(np.repeat(q.ids, m)), pa.array(np.tile(np.arange(1, m + 1), n).astype(np.int32)), pa.array(t.ids[places.ravel()]), pa.array(far.ravel())]
                yield pa.RecordBatch.from_arrays(columns, names=[x.split()[0] for x in schema.split(", ")])

    out = met.mapInArrow(run, schema)
    large = {r[0] for r in index.roots.filter(F.col("n") > MOST_TASK_POINTS).select("dataset_id").collect()}
    for q, d in pairs:
        if q in large or d in large:
            got = nearest_points(index, q, d, k)
            out = out.unionByName(got.select(F.lit(q).alias("query_id"), F.lit(d).alias("dataset_id"), "q_point_id", "rank", "d_point_id", "distance"))
    return out


def _query_tree(index: SearchIndex, query: str | DataFrame) -> DataFrame:
    return index.tree.filter(F.col("dataset_id") == query) if isinstance(query, str) else build_bottom(query, index.f)


def nearest_points(index: SearchIndex, query: str | DataFrame, dataset_id: str, k: int = 1, strategy: str = "packed") -> DataFrame:
    """q_point_id, rank, d_point_id, distance: the k nearest points of a dataset for every query point, ties by coordinates,
    then id. packed takes neighbouring query points down the dataset's tree together; leaf_join is a plan of joins, level by
    level; per_point searches the tree point by point; from_hausdorff (k = 1) goes on from where the Hausdorff search of the pair
    stopped; early_break scans. A dataset of more points than a task takes goes through leaf_join whatever the strategy."""
    if k < 1:
        raise ValueError("k must be at least 1")
    if strategy not in ("packed", "leaf_join", "per_point", "from_hausdorff", "early_break"):
        raise ValueError(f"no strategy {strategy}")
    if strategy == "from_hausdorff" and k != 1:
        raise ValueError("the Hausdorff frontier knows one nearest point per query point")
    if strategy != "leaf_join":
        got = index.packed.filter(F.col("dataset_id") == dataset_id).select("n", "tree").first()
        if got is None:
            raise ValueError(f"no dataset {dataset_id}")
        if got["tree"] is not None and got["n"] <= MOST_TASK_POINTS:
            return _kernel_join(index, query, bytes(got["tree"]), k, strategy)
    return _leaf_join(index, _query_tree(index, query), dataset_id, k)


def _leaf_join(index: SearchIndex, q_tree: DataFrame, dataset_id: str, k: int, most_rounds: int = 70) -> DataFrame:
    """Leaves of the query start at the root of the dataset's tree; each round bounds their open nodes, drops those beyond
    reach and replaces the others by their children, which are joined on their parent's path."""
    d = index.d
    d_tree = index.tree.filter(F.col("dataset_id") == dataset_id)
    nodes = checkpointed(d_tree.filter("kind = 0").select(F.col("path").alias("b_path"), F.expr("CASE WHEN path = '' THEN NULL ELSE substring(path, 1, length(path) - 1) END").alias("parent"), F.col("n").alias("b_n"), F.col("radius").alias("b_r"), F.col("is_leaf").alias("b_leaf"), *(F.col(f"o{i}").alias(f"bo{i}") for i in range(d))))
    leaves = q_tree.filter("kind = 0 AND is_leaf").select(F.col("path").alias("a_path"), F.col("radius").alias("a_r"), *(F.col(f"o{i}").alias(f"ao{i}") for i in range(d)))
    a, b = vec("ao", d), vec("bo", d)
    own, other = ["a_path", "a_r", *(f"ao{i}" for i in range(d))], ["b_path", "b_n", "b_r", "b_leaf", *(f"bo{i}" for i in range(d))]
    # The root is one row.
    pairs = leaves.join(F.broadcast(nodes.filter("parent IS NULL").drop("parent").limit(1)))
    for _ in range(most_rounds):
        # A node is within reach of a leaf unless others are sure to hold k nearer points.
        if k == 1:
            upper = F.min(ball_upper(a, F.col("a_r"), b, F.col("b_r"))).over(Window.partitionBy("a_path"))
        else:
            pairs = pairs.withColumn("far", euclid(a, b) + F.col("a_r") + F.col("b_r"))
            pairs = pairs.withColumn("seen", F.sum("b_n").over(Window.partitionBy("a_path").orderBy("far", "b_path").rowsBetween(Window.unboundedPreceding, 0)))
            upper = F.coalesce(F.min(F.when(F.col("seen") >= k, F.col("far"))).over(Window.partitionBy("a_path")), F.lit(float("inf")))
        pairs = checkpointed(pairs.withColumn("u", upper).filter(ball_gap(a, F.col("a_r"), b, F.col("b_r")) <= F.col("u") * (1 + 1e-12)).select(*own, *other))
        inner = pairs.filter("NOT b_leaf")
        if not inner.limit(1).count():
            break
        pairs = pairs.filter("b_leaf").unionByName(inner.select(*own, F.col("b_path").alias("parent")).join(nodes, "parent").select(*own, *other))
    near = pairs.select("a_path", "b_path")
    qs = q_tree.filter("kind = 1").select(F.col("path").alias("a_path"), F.col("point_id").alias("q_point_id"), *(F.col(f"o{i}").alias(f"q{i}") for i in range(d)))
    ds = d_tree.filter("kind = 1").select(F.col("path").alias("b_path"), F.col("point_id").alias("d_point_id"), *(F.col(f"o{i}").alias(f"c{i}") for i in range(d)))
    joined = qs.join(near, "a_path").join(ds, "b_path").withColumn("distance", euclid(vec("q", d), vec("c", d)))
    order = Window.partitionBy("a_path", "q_point_id").orderBy("distance", *vec("c", d), "d_point_id")
    return joined.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("q_point_id", "rank", "d_point_id", "distance")


def _kernel_join(index: SearchIndex, query: str | DataFrame, data: bytes, k: int, strategy: str) -> DataFrame:
    """The dataset's packed tree, of bounded size, goes to every task with query points; these are read where they lie."""
    d = index.d
    if isinstance(query, str):
        rows = index.tree.filter((F.col("dataset_id") == query) & (F.col("kind") == 1)).select("point_id", *vec("o", d))
    else:
        rows = query.select("point_id", *(F.col(f"c{i}").alias(f"o{i}") for i in range(d)))

    def nearest(tree, p: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Down the tree for one point: nodes by gap, leaves in blocks."""
        dn = len(tree.path)
        best, best_far = np.zeros(0, np.int64), np.zeros(0)
        todo = [(0.0, 0)]
        while todo:
            gap, node = heapq.heappop(todo)
            if len(best) >= k and gap > best_far[k - 1]:
                break
            down = tree.below(node)
            if tree.leaf[node]:
                c = np.concatenate((best, down - dn))
                far = np.sqrt(((tree.points[c] - p) ** 2).sum(axis=1))
                o = np.lexsort((rank[c], far))[:k]
                best, best_far = c[o], far[o]
            else:
                g = np.maximum(np.sqrt(((tree.centre[down] - p) ** 2).sum(axis=1)) - tree.radius[down], 0)
                for x in zip(g.tolist(), down.tolist()):
                    heapq.heappush(todo, x)
        return best, best_far

    def run(batches):
        tree = unpack(data)
        order = np.lexsort((tree.ids, *tree.points.T[::-1]))
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        for b in batches:
            if not b.num_rows:
                continue
            q, q_ids = np.column_stack([b.column(b.schema.get_field_index(f"o{i}")).to_numpy() for i in range(d)]), b.column(0).to_numpy()
            if strategy == "packed":
                places, far, _ = nearest_in_tree(q, tree, k)
            elif strategy == "from_hausdorff":
                t = build_tree(q, 10)
                places = np.zeros((len(q), 1), np.int64)
                places[t.ids, 0] = drain(t, tree, best_first(t, tree).frontier)
                far = np.sqrt(((tree.points[places[:, 0]] - q) ** 2).sum(axis=1))[:, None]
            elif strategy == "early_break":
                index_, far, _ = early_break(q, tree.points[order], k)
                index_, far = index_[:, : len(order)], far[:, : len(order)]
                places = order[index_]
            else:
                got = [nearest(tree, p, rank) for p in q]
                places, far = np.array([x for x, _ in got]), np.array([x for _, x in got])
            n, m = places.shape
            columns = (np.repeat(q_ids, m), np.tile(np.arange(1, m + 1), n).astype(np.int32), tree.ids[places.ravel()], far.ravel())
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["q_point_id", "rank", "d_point_id", "distance"])

    return rows.mapInArrow(run, "q_point_id long, rank int, d_point_id long, distance double")


def enrich(nearest: DataFrame, attributes: DataFrame, columns: list[str], key: str = "point_id") -> DataFrame:
    """Query points with attributes of their nearest points."""
    return nearest.join(attributes.select(F.col(key).alias("d_point_id"), *columns), "d_point_id", "left")
