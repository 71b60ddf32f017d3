"""The bottom level of the index: one midpoint-split tree per dataset, stored as rows."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import dims, vec
from .kernels import MAX_DEPTH, Forest, build_forest, build_tree, pack, refresh_forest, tree_from_rows

#: Points of a dataset that is built together with others, and about as many as go together.
MOST_BLOCK_POINTS = 300_000
BLOCK_POINTS = 100_000


def tree_schema(d: int) -> str:
    vectors = ", ".join(f"{n}{i} double" for n in ("o", "lo", "hi") for i in range(d))
    return f"dataset_id string, kind int, path string, point_id long, n long, radius double, is_leaf boolean, split_dim int, split_at double, {vectors}"


def build_bottom(points: DataFrame, f: int = 10, strategy: str = "auto", max_group_rows: int = 2_000_000, splitter: str = "midpoint", sizes: tuple[int, int] | None = None) -> DataFrame:
    """The tree rows of every dataset. Datasets up to max_group_rows are built in one task each; larger ones level by
    level with aggregates, never in one task. `sizes`, if known: all points, and those of the largest dataset."""
    if f < 1:
        raise ValueError("a leaf needs room for one point")
    if strategy == "groups":
        return build_groups(points, f, splitter)
    if strategy == "levels":
        return build_levels(points, f)
    counts = points.groupBy("dataset_id").count()
    total, largest = sizes or counts.agg(F.sum("count"), F.max("count")).first()
    limit = min(MOST_BLOCK_POINTS, max_group_rows)
    if splitter != "midpoint" or (largest or 0) > limit:
        wide = counts.filter(F.col("count") > (limit if splitter == "midpoint" else 0)).withColumn("giant", F.col("count") > max_group_rows).drop("count")
        wide = checkpointed(wide)
        of = lambda x: points.join(wide.filter(x), "dataset_id", "left_semi")
        out = build_groups(of("NOT giant"), f, splitter)
        if (largest or 0) > max_group_rows:
            out = out.unionByName(build_levels(of("giant"), f))
        return out if splitter != "midpoint" else out.unionByName(build_blocks(points.join(wide, "dataset_id", "left_anti"), f, total))
    return build_blocks(points, f, total or 0)


def in_blocks(df: DataFrame, total: int) -> DataFrame:
    """The rows of a dataset in one partition, with those of others; `total` points in all."""
    return df.repartition(max(2 * df.sparkSession.sparkContext.defaultParallelism, -(-total // BLOCK_POINTS)), "dataset_id")


def _table(batches) -> pa.Table | None:
    held = [b for b in batches if b.num_rows]
    return pa.Table.from_batches(held).combine_chunks() if held else None


def _numbered(table: pa.Table) -> tuple[np.ndarray, pa.Array]:
    """The number of each row's dataset, and the datasets."""
    coded = table.column("dataset_id").combine_chunks()
    coded = (coded.chunk(0) if isinstance(coded, pa.ChunkedArray) else coded).dictionary_encode()
    return coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), coded.dictionary


def forest_table(t: Forest, names: pa.Array, owner: np.ndarray, ids: np.ndarray, points: np.ndarray) -> pa.Table:
    """Tree rows of a forest; owner, ids and points in the order of its leaf_of."""
    m, k, d = len(t.path), len(points), points.shape[1]
    paths, none = pa.array(t.path, pa.string()), np.full(k, np.nan)
    columns = {
        "dataset_id": names.take(pa.array(np.concatenate((t.owner, owner)))),
        "kind": pa.array(np.repeat(np.array([0, 1], np.int32), [m, k])),
        "path": pa.concat_arrays([paths, paths.take(pa.array(t.leaf_of))]),
        "point_id": pa.concat_arrays([pa.nulls(m, pa.int64()), pa.array(ids, pa.int64())]),
        "n": pa.array(np.concatenate((t.n, np.ones(k, np.int64))), pa.int64()),
        "radius": pa.array(np.concatenate((t.radius, t.point_distance))),
        "is_leaf": pa.concat_arrays([pa.array(t.leaf, pa.bool_()), pa.nulls(k, pa.bool_())]),
        "split_dim": pa.array(np.concatenate((t.split_dim, np.full(k, -1))), pa.int32()),
        "split_at": pa.array(np.concatenate((t.split_at, none)), from_pandas=True),
    }
    for name, nodes, own in (("o", t.centre, points), ("lo", t.lo, None), ("hi", t.hi, None)):
        for i in range(d):
            columns[f"{name}{i}"] = pa.array(np.concatenate((nodes[:, i], own[:, i] if own is not None else none)), from_pandas=own is None)
    return pa.table(columns)


def build_blocks(points: DataFrame, f: int, total: int) -> DataFrame:
    """Tree rows of datasets up to MOST_BLOCK_POINTS: those of a partition are built together."""
    d = dims(points)

    def run(batches):
        table = _table(batches)
        if table is None:
            return
        number, names = _numbered(table)
        order = np.argsort(number, kind="stable")
        p = np.column_stack([table.column(f"c{i}").to_numpy() for i in range(d)])[order]
        t = build_forest(p, np.bincount(number), f)
        yield from forest_table(t, names, number[order], table.column("point_id").to_numpy()[order], p).to_batches(50_000)

    return in_blocks(points.select("dataset_id", "point_id", *vec("c", d)), total).mapInArrow(run, tree_schema(d))


def clean_blocks(tree: DataFrame, limit: float, on_empty: str, total: int) -> DataFrame:
    """The tree rows of what a cleaning keeps: of leaves wider than the limit, points within it. Datasets of a partition go together."""
    d = dims(tree, "o")

    def run(batches):
        table = _table(batches)
        if table is None:
            return
        number, names = _numbered(table)
        kind, radius = table.column("kind").to_numpy(), table.column("radius").to_numpy()
        path = np.array(table.column("path").to_pylist(), f"S{MAX_DEPTH}")
        leaves, at = np.flatnonzero(table.column("is_leaf").fill_null(False).to_numpy(zero_copy_only=False)), np.flatnonzero(kind == 1)
        # Leaves and their points, both by dataset and path.
        leaves, at = (x[np.lexsort((path[x], number[x]))] for x in (leaves, at))
        same = (number[at][1:] == number[at][:-1]) & (path[at][1:] == path[at][:-1])
        wide = radius[leaves][np.concatenate(([0], np.cumsum(~same)))] > limit
        kept = ~wide | (radius[at] <= limit)
        if on_empty == "keep":
            kept |= ~(np.bincount(number[at], kept, len(names)) > 0)[number[at]]
        at = at[kept]
        if not len(at):
            return
        p = np.column_stack([table.column(f"o{i}").to_numpy() for i in range(d)])[at]
        t, order = refresh_forest(number[at], path[at], p)
        at, p = at[order], p[order]
        yield from forest_table(t, names, number[at], pa.compute.fill_null(table.column("point_id"), -1).to_numpy()[at], p).to_batches(50_000)

    columns = ["dataset_id", "kind", "path", "point_id", "radius", "is_leaf", *(f"o{i}" for i in range(d))]
    return in_blocks(tree.select(*columns), total).mapInArrow(run, tree_schema(d))


def build_groups(points: DataFrame, f: int, splitter: str = "midpoint") -> DataFrame:
    d = dims(points)
    schema = tree_schema(d)

    def run(table: pa.Table) -> pa.Table:
        p = np.column_stack([table.column(f"c{i}").to_numpy() for i in range(d)])
        t = build_tree(p, f, splitter, table.column("point_id").to_numpy(zero_copy_only=False).astype(np.int64))
        m, k, p = len(t.path), len(p), t.points
        leaf_path = np.array(t.path, dtype=object)[t.point_leaf]
        none = np.full(k, np.nan)
        columns = {
            "dataset_id": pa.array([table.column("dataset_id")[0].as_py()] * (m + k)),
            "kind": pa.array([0] * m + [1] * k, pa.int32()),
            "path": pa.array(t.path + leaf_path.tolist()),
            "point_id": pa.array([None] * m + t.ids.tolist(), pa.int64()),
            "n": pa.array(np.concatenate((t.n, np.ones(k, np.int64))), pa.int64()),
            "radius": pa.array(np.concatenate((t.radius, t.point_distance))),
            "is_leaf": pa.array(t.leaf.tolist() + [None] * k, pa.bool_()),
            "split_dim": pa.array(np.concatenate((t.split_dim, np.full(k, -1))), pa.int32()),
            "split_at": pa.array(np.concatenate((t.split_at, none)), from_pandas=True),
        }
        for name, nodes, own in (("o", t.centre, p), ("lo", t.lo, None), ("hi", t.hi, None)):
            for i in range(d):
                columns[f"{name}{i}"] = pa.array(np.concatenate((nodes[:, i], own[:, i] if own is not None else none)), from_pandas=own is None)
        return pa.table(columns)

    return points.select("dataset_id", "point_id", *vec("c", d)).groupBy("dataset_id").applyInArrow(run, schema)


def build_levels(points: DataFrame, f: int, every: int = 4) -> DataFrame:
    """The same trees by one aggregate and join per level; lineage is cut every few levels."""
    d = dims(points)
    state = points.select("dataset_id", "point_id", *vec("c", d), F.lit("").alias("path"), F.lit(False).alias("done"))
    for level in range(MAX_DEPTH + 1):
        stats = state.filter(~F.col("done")).groupBy("dataset_id", "path").agg(F.count(F.lit(1)).alias("n"), *(F.min(f"c{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"c{i}").alias(f"hi{i}") for i in range(d)))
        wide = F.greatest(*(F.col(f"hi{i}") - F.col(f"lo{i}") for i in range(d)))
        dim = F.coalesce(*(F.when(F.col(f"hi{i}") - F.col(f"lo{i}") == F.col("wide"), i) for i in range(d)))
        middle = F.coalesce(*(F.when(F.col("dim") == i, (F.col(f"lo{i}") + F.col(f"hi{i}")) / 2) for i in range(d)))
        top = F.coalesce(*(F.when(F.col("dim") == i, F.col(f"hi{i}")) for i in range(d)))
        cut = stats.withColumn("wide", wide).withColumn("dim", dim).withColumn("at", middle).filter((F.col("n") > f) & (F.col("wide") > 0) & (F.col("at") < top)).select("dataset_id", "path", "dim", "at")
        if level == MAX_DEPTH or not cut.limit(1).count():
            break
        x = F.coalesce(*(F.when(F.col("dim") == i, F.col(f"c{i}")) for i in range(d)))
        step = F.when(F.col("dim").isNull(), F.lit("")).when(x > F.col("at"), F.lit("1")).otherwise(F.lit("0"))
        state = state.join(cut, ["dataset_id", "path"], "left").withColumn("path", F.concat("path", step)).withColumn("done", F.col("dim").isNull()).drop("dim", "at")
        if level % every == every - 1:
            state = checkpointed(state)
    return tree_rows(state.drop("done"))


def tree_rows(placed: DataFrame) -> DataFrame:
    """Tree rows of points whose leaf path is known. Leaves are aggregates of their points, nodes above are aggregates of
    leaves over the prefixes of their paths; only a node's radius asks for points again, and those meet each of their
    nodes on (dataset, path) in partial aggregates. Of a node whose points all went one way, the split is unknown and
    left null; is_leaf says that no path goes on."""
    d = dims(placed)
    leaves = placed.groupBy("dataset_id", F.col("path").alias("leaf")).agg(F.count(F.lit(1)).alias("n"), *(F.sum(f"c{i}").alias(f"s{i}") for i in range(d)), *(F.min(f"c{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"c{i}").alias(f"hi{i}") for i in range(d)))
    prefixes = F.transform(F.sequence(F.lit(0), F.length("leaf")), lambda i: F.substring("leaf", F.lit(1), i))
    above = leaves.withColumn("path", F.explode(prefixes))
    nodes = above.groupBy("dataset_id", "path").agg(F.sum("n").alias("n"), F.max(F.length("leaf")).alias("deepest"), *((F.sum(f"s{i}") / F.sum("n")).alias(f"o{i}") for i in range(d)), *(F.min(f"lo{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"hi{i}").alias(f"hi{i}") for i in range(d)))
    # The centres above a leaf travel with it, once per leaf; its points then know their distance from each.
    centres = above.select("dataset_id", "leaf", "path").join(nodes.select("dataset_id", "path", *vec("o", d)), ["dataset_id", "path"])
    chains = centres.groupBy("dataset_id", "leaf").agg(F.collect_list(F.struct("path", *vec("o", d))).alias("chain"))
    met = placed.withColumnRenamed("path", "leaf").join(chains, ["dataset_id", "leaf"])

    def away(x) -> Column:
        return F.sqrt(reduce(lambda a, b: a + b, [(F.col(f"c{i}") - x[f"o{i}"]) * (F.col(f"c{i}") - x[f"o{i}"]) for i in range(d)]))

    # Farthest distances within a leaf first, per place in its chain; then over the leaves below each node.
    far = met.select("dataset_id", "leaf", F.posexplode(F.transform("chain", lambda x: F.struct(x["path"].alias("path"), away(x).alias("away")))).alias("k", "x")).groupBy("dataset_id", "leaf", "x.path").agg(F.max("x.away").alias("away"))
    radii = far.groupBy("dataset_id", "path").agg(F.max("away").alias("radius"))
    whole = nodes.join(radii, ["dataset_id", "path"]).withColumn("is_leaf", F.col("deepest") == F.length("path"))
    out_nodes = whole.select("dataset_id", F.lit(0).alias("kind"), "path", F.lit(None).cast("long").alias("point_id"), "n", "radius", "is_leaf", F.lit(-1).alias("split_dim"), F.lit(None).cast("double").alias("split_at"), *vec("o", d), *vec("lo", d), *vec("hi", d))
    none = [F.lit(None).cast("double").alias(f"{n}{i}") for n in ("lo", "hi") for i in range(d)]
    own = F.element_at(F.filter("chain", lambda x: x["path"] == F.col("leaf")), 1)
    out_points = met.withColumn("own", own).select("dataset_id", F.lit(1).alias("kind"), F.col("leaf").alias("path"), "point_id", F.lit(1).cast("long").alias("n"), away(F.col("own")).alias("radius"), F.lit(None).cast("boolean").alias("is_leaf"), F.lit(-1).alias("split_dim"), F.lit(None).cast("double").alias("split_at"), *(F.col(f"c{i}").alias(f"o{i}") for i in range(d)), *none)
    return out_nodes.unionByName(out_points)


def tree_points(tree: DataFrame) -> DataFrame:
    """The points of tree rows, with their leaf and their distance from its centre."""
    d = dims(tree, "o")
    return tree.filter("kind = 1").select("dataset_id", "point_id", F.col("path").alias("leaf_path"), F.col("radius").alias("leaf_distance"), *(F.col(f"o{i}").alias(f"c{i}") for i in range(d)))


def packed_trees(tree: DataFrame) -> DataFrame:
    """dataset_id and its tree as one value, see kernels.pack."""
    d = dims(tree, "o")

    def run(batches):
        table = _table(batches)
        if table is None:
            return
        number, names = _numbered(table)
        order = np.argsort(number, kind="stable")
        get = lambda n: np.column_stack([table.column(f"{n}{i}").to_numpy(zero_copy_only=False) for i in range(d)])[order]
        ids, path, leaf = (table.column(c).take(pa.array(order)) for c in ("point_id", "path", "is_leaf"))
        ids, path, leaf = pa.compute.fill_null(ids, -1).to_numpy(), path.to_pylist(), leaf.to_pylist()
        kind, n, radius = (table.column(c).to_numpy()[order] for c in ("kind", "n", "radius"))
        o, lo, hi = get("o"), get("lo"), get("hi")
        ends = np.cumsum(np.bincount(number)).tolist()
        for first in range(0, len(ends), 256):
            packed = []
            for a, b in zip([0, *ends][first : first + 256], ends[first : first + 256]):
                packed.append(pack(tree_from_rows(path[a:b], kind[a:b], n[a:b], radius[a:b], leaf[a:b], o[a:b], lo[a:b], hi[a:b], ids[a:b])))
            yield pa.RecordBatch.from_arrays([names.slice(first, len(packed)), pa.array(packed, pa.binary())], names=["dataset_id", "tree"])

    columns = ["dataset_id", "kind", "path", "point_id", "n", "radius", "is_leaf", *(f"{n}{i}" for n in ("o", "lo", "hi") for i in range(d))]
    total = tree.filter("kind = 1").count()
    return in_blocks(tree.select(*columns), total).mapInArrow(run, "dataset_id string, tree binary")


def dataset_roots(tree: DataFrame) -> DataFrame:
    d = dims(tree, "o")
    return tree.filter("kind = 0 AND path = ''").select("dataset_id", "n", "radius", *vec("o", d), *vec("lo", d), *vec("hi", d))
