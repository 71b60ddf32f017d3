"""The upper level: a tree over dataset roots, with the union of the cells below each node."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import dims, euclid, vec
from ..functions.zorder import z_id
from ..model import GridSpec
from .kernels import MAX_DEPTH


def split_roots(o: np.ndarray, lo: np.ndarray, hi: np.ndarray, f: int) -> list[str]:
    """The leaf path of each root. A node's widest side of the union of its boxes is halved and centres decide the side;
    where that leaves a side empty, the centres' own range is halved instead."""
    path = [""] * len(o)
    todo = [(np.arange(len(o)), "")]
    while todo:
        index, at = todo.pop()
        up = None
        if len(index) > f and len(at) < MAX_DEPTH:
            low, high = lo[index].min(axis=0), hi[index].max(axis=0)
            dim = int((high - low).argmax())
            up = o[index, dim] > (low[dim] + high[dim]) / 2
            if up.all() or not up.any():
                low, high = o[index].min(axis=0), o[index].max(axis=0)
                dim = int((high - low).argmax())
                up = o[index, dim] > (low[dim] + high[dim]) / 2
        if up is None or up.all() or not up.any():
            for i in index:
                path[i] = at
        else:
            todo += [(index[up], at + "1"), (index[~up], at + "0")]
    return path


def node_table(paths: list[str], n: np.ndarray, radius: np.ndarray, o: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> dict[str, list]:
    """The columns of `upper_nodes` from the leaf path of each root; in the order of the paths, nodes below one another are side by side."""
    names, leaf = np.unique(np.array(paths, f"S{MAX_DEPTH * 2}"), return_inverse=True)
    by = np.argsort(leaf, kind="stable")
    first = np.searchsorted(leaf[by], np.arange(len(names)))
    count = np.diff(np.append(first, len(by)))
    total, weighted = np.add.reduceat(n[by], first), np.add.reduceat((o * n[:, None])[by], first)
    low, high = np.minimum.reduceat(lo[by], first), np.maximum.reduceat(hi[by], first)
    centre = weighted / total[:, None]
    reach = np.maximum.reduceat(np.sqrt(((centre[leaf] - o) ** 2).sum(axis=1))[by] + radius[by], first)
    length = np.char.str_len(names)
    out: dict[str, list] = {c: [] for c in ("path", "depth", "is_leaf", "n_datasets", "n", "radius", "o", "lo", "hi")}
    for depth in range(int(length.max()) + 1):
        at = np.flatnonzero(length >= depth)
        head = names[at].astype(f"S{depth}") if depth else np.full(len(at), b"")
        start = np.flatnonzero(np.concatenate(([True], head[1:] != head[:-1])))
        sums = np.add.reduceat(total[at], start)
        mid = np.add.reduceat(weighted[at], start) / sums[:, None]
        owner = np.repeat(np.arange(len(start)), np.diff(np.append(start, len(at))))
        out["path"] += [x.decode() for x in head[start].tolist()]
        out["depth"] += [depth] * len(start)
        out["is_leaf"] += (np.maximum.reduceat(length[at], start) == depth).tolist()
        for name, values in (("n_datasets", np.add.reduceat(count[at], start)), ("n", sums), ("radius", np.maximum.reduceat(np.sqrt(((mid[owner] - centre[at]) ** 2).sum(axis=1)) + reach[at], start))):
            out[name] += values.tolist()
        out["o"].append(mid)
        out["lo"].append(np.minimum.reduceat(low[at], start))
        out["hi"].append(np.maximum.reduceat(high[at], start))
    return out


def upper_in_task(roots: DataFrame, f: int = 10) -> DataFrame:
    """Upper nodes and, with a dataset_id, members as rows of one frame: the same tree from one task, for roots that it holds."""
    d = dims(roots, "o")
    vectors = [f"{x}{i}" for x in ("o", "lo", "hi") for i in range(d)]

    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        get = lambda x: np.column_stack([table.column(f"{x}{i}").to_numpy() for i in range(d)])
        paths = split_roots(get("o"), get("lo"), get("hi"), f)
        nodes, m = node_table(paths, table.column("n").to_numpy(), table.column("radius").to_numpy(), get("o"), get("lo"), get("hi")), len(paths)
        columns = {"path": pa.array(nodes["path"] + paths), "dataset_id": pa.array([None] * len(nodes["path"]) + table.column("dataset_id").to_pylist(), pa.string())}
        for name, kind in (("depth", pa.int32()), ("is_leaf", pa.bool_()), ("n_datasets", pa.int64()), ("n", pa.int64()), ("radius", pa.float64())):
            columns[name] = pa.array(nodes[name] + [None] * m, kind)
        for x in ("o", "lo", "hi"):
            values = np.concatenate(nodes[x])
            for i in range(d):
                columns[f"{x}{i}"] = pa.array(values[:, i].tolist() + [None] * m, pa.float64())
        yield from pa.table(columns).to_batches(50_000)

    schema = "path string, dataset_id string, depth int, is_leaf boolean, n_datasets long, n long, radius double, " + ", ".join(f"{c} double" for c in vectors)
    return roots.select("dataset_id", "n", "radius", *vectors).coalesce(1).mapInArrow(run, schema)


def build_upper(roots: DataFrame, f: int = 10, max_rows: int = 2_000_000) -> tuple[DataFrame, DataFrame]:
    """(upper nodes, members)."""
    members = build_members(roots, f, max_rows)
    return upper_nodes(roots, members), members


def build_members(roots: DataFrame, f: int = 10, max_rows: int = 2_000_000) -> DataFrame:
    """The leaf of each root. Up to max_rows roots are split in one task; more are first dealt to coarse cells of
    their centres, whose bits are the upper part of the paths."""
    d = dims(roots, "o")
    stats = roots.agg(F.count(F.lit(1)).alias("n"), *(g(f"o{i}").alias(f"{x}{i}") for i in range(d) for g, x in ((F.min, "lo"), (F.max, "hi")))).first()
    levels = 0 if stats["n"] <= max_rows else math.ceil(math.log2(stats["n"] / max_rows) / d) + 1
    prefix = F.lit("")
    if levels:
        spec = GridSpec(tuple(stats[f"lo{i}"] for i in range(d)), tuple(stats[f"hi{i}"] for i in range(d)), levels)
        prefix = F.lpad(F.bin(z_id(vec("o", d), spec)), levels * d, "0")

    def run(table: pa.Table) -> pa.Table:
        get = lambda n: np.column_stack([table.column(f"{n}{i}").to_numpy() for i in range(d)])
        head = table.column("prefix")[0].as_py()
        paths = split_roots(get("o"), get("lo"), get("hi"), f)
        return pa.table({"path": pa.array([head + p for p in paths]), "dataset_id": table.column("dataset_id")})

    return roots.withColumn("prefix", prefix).select("prefix", "dataset_id", *vec("o", d), *vec("lo", d), *vec("hi", d)).groupBy("prefix").applyInArrow(run, "path string, dataset_id string")


def ancestors(members: DataFrame) -> DataFrame:
    """path and dataset_id for every node above a dataset."""
    return members.select(F.explode(F.transform(F.sequence(F.lit(0), F.length("path")), lambda i: F.substring("path", F.lit(1), i))).alias("path"), "dataset_id", F.length("path").alias("leaf_depth"))


def upper_nodes(roots: DataFrame, members: DataFrame) -> DataFrame:
    """Nodes from their members: boxes united, centres weighted by points, and a radius that reaches every point below.

    Leaves are aggregated first, nodes above from leaves, so that no node's key carries all of its datasets. A node's
    radius comes from the balls around its leaves: far enough for each of their datasets.
    """
    d = dims(roots, "o")
    met = members.join(roots, "dataset_id")
    leaves = met.groupBy(F.col("path").alias("leaf")).agg(
        F.count(F.lit(1)).alias("n_datasets"), F.sum("n").alias("n"),
        *(F.sum(F.col(f"o{i}") * F.col("n")).alias(f"s{i}") for i in range(d)),
        *(F.min(f"lo{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"hi{i}").alias(f"hi{i}") for i in range(d)),
    )
    prefixes = F.transform(F.sequence(F.lit(0), F.length("leaf")), lambda i: F.substring("leaf", F.lit(1), i))
    above = leaves.withColumn("path", F.explode(prefixes))
    nodes = above.groupBy("path").agg(
        F.sum("n_datasets").alias("n_datasets"), F.sum("n").alias("n"), F.max(F.length("leaf")).alias("deepest"),
        *((F.sum(f"s{i}") / F.sum("n")).alias(f"o{i}") for i in range(d)),
        *(F.min(f"lo{i}").alias(f"lo{i}") for i in range(d)), *(F.max(f"hi{i}").alias(f"hi{i}") for i in range(d)),
    )
    # The ball of a leaf around its own centre, then of each node around the balls of its leaves.
    own = nodes.select(F.col("path").alias("leaf"), *(F.col(f"o{i}").alias(f"m{i}") for i in range(d)))
    near = met.withColumnRenamed("path", "leaf").join(own, "leaf").groupBy("leaf", *vec("m", d)).agg(F.max(euclid(vec("m", d), vec("o", d)) + F.col("radius")).alias("reach"))
    far = above.select("leaf", "path").join(near, "leaf").join(nodes.select("path", *vec("o", d)), "path").groupBy("path").agg(F.max(euclid(vec("m", d), vec("o", d)) + F.col("reach")).alias("radius"))
    return nodes.join(far, "path").select("path", F.length("path").alias("depth"), (F.col("deepest") == F.length("path")).alias("is_leaf"), "n_datasets", "n", "radius", *vec("o", d), *vec("lo", d), *vec("hi", d))


def upper_signatures(members: DataFrame, cells: DataFrame) -> DataFrame:
    return ancestors(members).join(cells, "dataset_id").select("path", "cell").distinct()
