"""Building, storing, extending and describing the two-level index."""

from __future__ import annotations

import functools
import json
from dataclasses import asdict, dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import dims, vec
from ..functions.zorder import signatures
from ..model import GridSpec
from ..sources.repositories import sized_extent
from .bottom_index import build_bottom, dataset_roots, packed_trees, tree_points
from .outliers import knee_threshold, leaf_radii, remove_outliers
from .upper_index import build_members, upper_in_task, upper_nodes, upper_signatures

#: Nodes of the upper tree that a search orders on the driver.
MOST_NODES = 100_000
#: Points of a dataset that one task takes; larger ones are compared through the frontier.
MOST_TASK_POINTS = 100_000
FRAMES = ("tree", "roots", "cells", "upper", "members", "upper_cells")


@dataclass(frozen=True)
class SearchIndex:
    tree: DataFrame
    roots: DataFrame
    cells: DataFrame
    upper: DataFrame
    members: DataFrame
    upper_cells: DataFrame
    spec: GridSpec
    f: int
    threshold: float | None
    #: Depth at which searches stop on the way down the upper tree, if it has too many leaves for the driver; None: at the leaves.
    cut: int | None = None

    @property
    def variant(self) -> str:
        return "raw" if self.threshold is None else "clean"

    @property
    def d(self) -> int:
        return self.spec.d

    @property
    def spark(self) -> SparkSession:
        return self.tree.sparkSession

    @functools.cached_property
    def packed(self) -> DataFrame:
        """dataset_id, path (its upper leaf), n, radius, o.., lo.., hi.. and its tree as one value; datasets of more points than
        one task takes have none. Searches read it in place of tree rows: a dataset is one row and is never moved."""
        most = MOST_TASK_POINTS
        small = self.roots.filter(F.col("n") <= most).select("dataset_id")
        some_large = self.roots.filter(F.col("n") > most).limit(1).count()
        trees = packed_trees(self.tree.join(small, "dataset_id", "left_semi") if some_large else self.tree)
        whole = self.roots.join(self.members, "dataset_id").join(trees, "dataset_id", "left")
        # Trees are few bytes but much work, so they are spread over all tasks that the session has for a shuffle.
        return checkpointed(whole.repartition(int(self.spark.conf.get("spark.sql.shuffle.partitions")), "dataset_id"))

    @functools.cached_property
    def packed_by_place(self) -> DataFrame:
        """The same in blocks of neighbours in the upper tree, for very many queries."""
        tasks = max(8 * self.spark.sparkContext.defaultParallelism, self.roots.count() // 1_000)
        return checkpointed(self.packed.repartitionByRange(tasks, "path", "dataset_id"))

    @functools.cached_property
    def top(self) -> dict[str, np.ndarray]:
        """The nodes at which searches stop on the way down, at most MOST_NODES of them, as arrays for the driver."""
        leaf = F.col("is_leaf")
        frontier = leaf if self.cut is None else (F.col("depth") == self.cut) | (leaf & (F.col("depth") < self.cut))
        got = self.upper.filter(frontier).select("path", "n_datasets", "radius", *vec("o", self.d), *vec("lo", self.d), *vec("hi", self.d)).toPandas()
        stack = lambda n: got[[f"{n}{i}" for i in range(self.d)]].to_numpy()
        return {"path": got["path"].to_numpy(), "n": got["n_datasets"].to_numpy(), "radius": got["radius"].to_numpy(), "o": stack("o"), "lo": stack("lo"), "hi": stack("hi")}

    @property
    def points(self) -> DataFrame:
        return tree_points(self.tree)

    def where(self, datasets: DataFrame) -> SearchIndex:
        """The index of the datasets named in a frame with dataset_id: metadata filters before a search. Trees, cells and places
        in the upper tree stay as they are; only the upper nodes are aggregated again, over the roots that are left."""
        named = checkpointed(datasets.select("dataset_id").distinct())
        keep = lambda df: df.join(named, "dataset_id", "left_semi")
        roots, cells, members = keep(self.roots), keep(self.cells), keep(self.members)
        nodes = checkpointed(upper_nodes(roots, members))
        return SearchIndex(keep(self.tree), roots, cells, nodes, members, upper_signatures(members, cells), self.spec, self.f, self.threshold, cut_depth(nodes))


def build_index(points: DataFrame, f: int = 10, theta: int = 5, clean: bool = True, spec: GridSpec | None = None, strategy: str = "auto", splitter: str = "midpoint", scope: str = "repository", threshold: float | None = None, order: str = "desc", chord_span: str = "count", on_empty: str = "keep") -> SearchIndex:
    """Bottom trees, outlier removal with refreshed nodes, then the upper tree. The grid spans the raw points."""
    box, total, largest = sized_extent(points)
    spec = spec or GridSpec.from_extent(box, theta)
    tree = checkpointed(build_bottom(points, f, strategy, splitter=splitter, sizes=(total, largest)))
    limit = None
    if clean:
        limit = knee_threshold(leaf_radii(tree), order, chord_span) if threshold is None else threshold
        given = None if scope == "dataset" else limit
        tree = checkpointed(remove_outliers(tree, given, scope, on_empty, **({} if given is not None else {"order": order, "chord_span": chord_span})))
    return finish(tree, spec, f, limit)


def cut_depth(upper: DataFrame, most: int = MOST_NODES) -> int | None:
    """The greatest depth at which the nodes, with the leaves above it, are at most `most`; None if all leaves are."""
    rows = upper.groupBy("depth", "is_leaf").agg(F.count(F.lit(1)).alias("n")).collect()
    if sum(r["n"] for r in rows if r["is_leaf"]) <= most:
        return None
    at = 0
    for depth in sorted({r["depth"] for r in rows}):
        if sum(r["n"] for r in rows if r["depth"] == depth or (r["is_leaf"] and r["depth"] < depth)) > most:
            break
        at = depth
    return at


def finish(tree: DataFrame, spec: GridSpec, f: int, threshold: float | None) -> SearchIndex:
    roots = checkpointed(dataset_roots(tree))
    cells = checkpointed(signatures(tree_points(tree), spec))
    if 0 < roots.count() <= MOST_NODES:
        # Few roots: their tree is made in one task, and its leaves are no more than they are.
        upper = checkpointed(upper_in_task(roots, f))
        nodes, members, cut = upper.filter("dataset_id IS NULL").drop("dataset_id"), upper.filter("dataset_id IS NOT NULL").select("path", "dataset_id"), None
    else:
        members = checkpointed(build_members(roots, f))
        nodes = checkpointed(upper_nodes(roots, members))
        cut = cut_depth(nodes)
    return SearchIndex(tree, roots, cells, nodes, members, checkpointed(upper_signatures(members, cells)), spec, f, threshold, cut)


def save(index: SearchIndex, path: str, buckets: int = 64) -> None:
    """Parquet, tree and cells by bucket of dataset_id so that a search of few datasets reads few files."""
    bucket = F.pmod(F.xxhash64("dataset_id"), F.lit(buckets)).cast("int")
    for name in FRAMES:
        df = getattr(index, name)
        if name in ("tree", "cells"):
            df.withColumn("bucket", bucket).repartition("bucket").sortWithinPartitions("bucket", "dataset_id").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/{name}")
        else:
            df.write.mode("overwrite").parquet(f"{path}/{name}")
    meta = {"spec": asdict(index.spec), "f": index.f, "threshold": index.threshold, "buckets": buckets}
    index.spark.createDataFrame([(json.dumps(meta),)], "meta string").write.mode("overwrite").parquet(f"{path}/meta")


def load(spark: SparkSession, path: str) -> SearchIndex:
    meta = json.loads(spark.read.parquet(f"{path}/meta").first()[0])
    frames = {n: spark.read.parquet(f"{path}/{n}") for n in FRAMES}
    frames = {n: df.drop("bucket") for n, df in frames.items()}
    return SearchIndex(**frames, spec=GridSpec(tuple(meta["spec"]["lo"]), tuple(meta["spec"]["hi"]), meta["spec"]["theta"]), f=meta["f"], threshold=meta["threshold"], cut=cut_depth(frames["upper"]))


def append_datasets(index: SearchIndex, points: DataFrame) -> SearchIndex:
    """The index with new datasets: their trees are built and cleaned with the known threshold, the upper level anew."""
    known = points.join(index.roots, "dataset_id", "left_semi").limit(1).count()
    if known:
        raise ValueError("a dataset of that id is in the index")
    tree = build_bottom(points, index.f)
    if index.threshold is not None:
        tree = remove_outliers(tree, index.threshold)
    return finish(checkpointed(index.tree.unionByName(tree)), index.spec, index.f, index.threshold)


def grow_datasets(index: SearchIndex, points: DataFrame) -> SearchIndex:
    """The index with new points of known or new datasets; points whose (dataset_id, point_id) is there are left out.
    Trees of datasets that grew are built anew and cleaned with the known threshold. Points that an earlier cleaning took
    out are not in the index; if they come again they are judged again by that threshold."""
    columns = ["dataset_id", "point_id", *(f"c{i}" for i in range(index.d))]
    new = checkpointed(points.select(*columns).join(index.points.select("dataset_id", "point_id"), ["dataset_id", "point_id"], "left_anti"))
    if not new.limit(1).count():
        return index
    grown = new.select("dataset_id").distinct()
    tree = build_bottom(new.unionByName(index.points.select(*columns).join(grown, "dataset_id", "left_semi")), index.f)
    if index.threshold is not None:
        tree = remove_outliers(tree, index.threshold)
    return finish(checkpointed(index.tree.join(grown, "dataset_id", "left_anti").unionByName(tree)), index.spec, index.f, index.threshold)


def frame_space(df: DataFrame) -> tuple[int, int]:
    """Rows and bytes (fixed widths plus text) of a frame."""
    fixed = sum({"bigint": 8, "double": 8, "int": 4, "boolean": 1}.get(t, 0) for _, t in df.dtypes)
    text = [F.coalesce(F.octet_length(c), F.lit(0)) for c, t in df.dtypes if t in ("string", "binary")]
    n, b = df.agg(F.count(F.lit(1)), F.coalesce(F.sum(sum(text, F.lit(fixed))), F.lit(0))).first()
    return n, int(b)


def index_space(index: SearchIndex) -> DataFrame:
    """Rows and bytes of each part."""
    return index.spark.createDataFrame([(name, *frame_space(getattr(index, name))) for name in FRAMES], "part string, n_rows long, n_bytes long")


def with_resolution(index: SearchIndex, theta: int) -> SearchIndex:
    """The same trees over a grid of another resolution."""
    spec = GridSpec(index.spec.lo, index.spec.hi, theta)
    cells = checkpointed(signatures(index.points, spec))
    return replace(index, spec=spec, cells=cells, upper_cells=checkpointed(upper_signatures(index.members, cells)))


def radius_distribution(index: SearchIndex, bins: int = 20, high: float | None = None) -> DataFrame:
    """Histogram of leaf radii and their largest depth."""
    leaves = index.tree.filter("kind = 0 AND is_leaf")
    high = high if high is not None else leaves.agg(F.max("radius")).first()[0] or 1.0
    b = F.least(F.floor(F.col("radius") / F.lit((high or 1.0) / bins)), F.lit(bins - 1)).alias("bin")
    return leaves.groupBy(b).agg(F.count(F.lit(1)).alias("leaves"), F.max(F.length("path")).alias("max_depth"), F.max("radius").alias("max_radius")).orderBy("bin")


def index_dims(index: SearchIndex) -> int:
    return dims(index.roots, "o")
