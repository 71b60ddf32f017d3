"""Dataset search: by rectangle, and the k best under overlap of boxes, shared cells or Hausdorff distance."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.geometry import ball_lower, ball_upper, box_overlap, boxes_meet, constants, dims, euclid, vec
from ..functions.zorder import signatures
from ..model import Box
from ..plans.waves import WavePlan
from . import frontier
from .index import SearchIndex
from .kernels import Outline as TreeOutline
from .kernels import Tree, best_first, build_tree, by_parts, outline, pack, parts_of, squares, tree_from_rows, unpack
from .outliers import remove_outliers
from .bottom_index import build_bottom, tree_points

#: Points of a query dataset that go to every task, and of all queries that go together; more are compared in another way.
MOST_QUERY_POINTS = 100_000
MOST_BATCH_POINTS = 1_000_000
#: Cells of datasets that a task of shared cells takes.
MOST_TASK_CELLS = 4_000_000


@dataclass(frozen=True)
class Query:
    """A query dataset: a member of the index or any points; few enough points to go to every task."""

    id: str
    n: int
    o: tuple[float, ...]
    radius: float
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    points: np.ndarray
    ids: list[int]
    cells: DataFrame
    member: bool
    tree: Tree | None = None
    #: The tree as index.packed holds it, in place of tree and points.
    packed: bytes | None = None


@dataclass
class Run:
    """The rows of a search and what it took."""

    rows: list[tuple]
    metrics: dict = field(default_factory=dict)


@dataclass(frozen=True)
class Outline:
    """A query dataset of any size: its box, and its points and cells as frames."""

    id: str
    n: int
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    points: DataFrame
    cells: DataFrame
    member: bool


def _frames(index: SearchIndex, query: str | DataFrame, clean: bool) -> tuple[DataFrame, DataFrame]:
    """Points and cells of a query."""
    if isinstance(query, str):
        return index.points.filter(F.col("dataset_id") == query), index.cells.filter(F.col("dataset_id") == query).select("cell")
    points = query
    if clean and index.threshold is not None:
        points = tree_points(remove_outliers(build_bottom(query, index.f), index.threshold))
    return points, signatures(points, index.spec).select("cell").distinct()


def as_outline(index: SearchIndex, query: str | DataFrame, clean: bool = True) -> Outline:
    points, cells = _frames(index, query, clean)
    d, member = index.d, isinstance(query, str)
    if member:
        got = index.roots.filter(F.col("dataset_id") == query).select("dataset_id", "n", *vec("lo", d), *vec("hi", d)).first()
    else:
        got = points.agg(F.min("dataset_id").alias("dataset_id"), F.count(F.lit(1)).alias("n"), *(g(f"c{i}").alias(f"{x}{i}") for i in range(d) for g, x in ((F.min, "lo"), (F.max, "hi")))).first()
    if got is None or not got["n"]:
        raise ValueError("the query dataset has no points")
    return Outline(got["dataset_id"], got["n"], tuple(got[f"lo{i}"] for i in range(d)), tuple(got[f"hi{i}"] for i in range(d)), points, cells, member)


def _ball(q: Outline, d: int) -> tuple[tuple[float, ...], float]:
    """Mean and exact radius of the points, by aggregates."""
    o = tuple(q.points.agg(*(F.avg(f"c{i}") for i in range(d))).first())
    return o, q.points.agg(F.max(euclid(vec("c", d), constants(o)))).first()[0]


def as_query(index: SearchIndex, query: str | DataFrame, clean: bool = True) -> Query:
    """Points of a query that is not in the index are cleaned like the index unless clean=False."""
    member = isinstance(query, str)
    points, cells = _frames(index, query, clean)
    d = index.d
    got = points.select("dataset_id", "point_id", *vec("c", d)).limit(MOST_QUERY_POINTS + 1).toPandas()
    if not len(got):
        raise ValueError("the query dataset has no points")
    if len(got) > MOST_QUERY_POINTS:
        raise ValueError(f"the query has more than {MOST_QUERY_POINTS} points; use frontier.hausdorff")
    got = got.sort_values([f"c{i}" for i in range(d)] + ["point_id"], kind="stable")
    p = got[[f"c{i}" for i in range(d)]].to_numpy()
    o = p.mean(axis=0)
    return Query(query if member else str(got["dataset_id"].iloc[0]), len(p), tuple(o.tolist()), float(np.sqrt(((p - o) ** 2).sum(axis=1)).max()), tuple(p.min(axis=0).tolist()), tuple(p.max(axis=0).tolist()), p, got["point_id"].tolist(), cells, member)


def _result(index: SearchIndex, q: str, rows: list[tuple[float, str]], measure: str, kind: str, method: str) -> DataFrame:
    made = [(q, i + 1, ds, kind(v), method, index.variant) for i, (v, ds) in enumerate(rows)]
    return index.spark.createDataFrame(made, f"query_id string, rank int, dataset_id string, {measure}, method string, data_variant string")


def _others(df: DataFrame, q: Query | Outline, exclude_self: bool) -> DataFrame:
    return df.filter(F.col("dataset_id") != q.id) if q.member and exclude_self else df


def _frontier(index: SearchIndex) -> Column:
    """The nodes at which a search of the upper tree stops: few enough for the driver, and above every dataset once."""
    leaf = F.col("is_leaf")
    return leaf if index.cut is None else (F.col("depth") == index.cut) | (leaf & (F.col("depth") < index.cut))


def _below(index: SearchIndex, paths: list[str]) -> DataFrame:
    """The datasets below frontier nodes."""
    at = F.col("path") if index.cut is None else F.substring("path", 1, index.cut)
    members = index.members.select(at.alias("path"), "dataset_id")
    if len(paths) <= 200:
        return members.filter(F.col("path").isin(paths)).select("dataset_id")
    return members.join(F.broadcast(index.spark.createDataFrame([(p,) for p in paths], "path string")), "path").select("dataset_id")


def _leaves(index: SearchIndex, bound: Column) -> list[tuple[str, int, float]]:
    return [tuple(r) for r in index.upper.filter(_frontier(index)).select("path", "n_datasets", bound.cast("double").alias("bound")).collect()]


def range_datasets(index: SearchIndex, box: Box) -> DataFrame:
    """Datasets whose box meets the rectangle: upper leaves first, then the roots below them."""
    d = index.d
    lo, hi = constants(box.lo), constants(box.hi)
    leaves = index.upper.filter(F.col("is_leaf") & boxes_meet(vec("lo", d), vec("hi", d), lo, hi)).select("path")
    near = index.members.join(leaves, "path", "left_semi").select("dataset_id")
    return index.roots.filter(boxes_meet(vec("lo", d), vec("hi", d), lo, hi)).join(near, "dataset_id", "left_semi").select("dataset_id", "n")


def range_datasets_batch(index: SearchIndex, queries: DataFrame, most: int = 10_000) -> DataFrame:
    """The same for many rectangles (query_id, qlo.., qhi..): upper leaves are met first, then members are joined. Up to
    `most` rectangles are broadcast; more, and the leaves, meet in cells of the grid's first dimension that they cover."""
    d = index.d
    leaves = index.upper.filter("is_leaf").select("path", *(F.col(f"{n}{i}").alias(f"u{n}{i}") for n in ("lo", "hi") for i in range(d)))
    meet = boxes_meet(vec("ulo", d), vec("uhi", d), vec("qlo", d), vec("qhi", d))
    if queries.limit(most + 1).count() <= most:
        hit = leaves.join(F.broadcast(queries), meet)
    else:
        lo, width = index.spec.lo[0], index.spec.widths[0] or 1.0
        cell = lambda c: F.greatest(F.least(F.floor((F.col(c) - lo) / width), F.lit((1 << index.spec.theta) - 1)), F.lit(0)).cast("long")
        cover = lambda df, a, b: df.withColumn("first", cell(a)).withColumn("cell", F.explode(F.sequence(F.col("first"), cell(b))))
        a, b = cover(leaves, "ulo0", "uhi0").withColumnRenamed("first", "a"), cover(queries, "qlo0", "qhi0").withColumnRenamed("first", "b")
        hit = a.join(b, "cell").filter(meet & (F.col("cell") == F.greatest("a", "b")))
    near = hit.select("path", "query_id", *vec("qlo", d), *vec("qhi", d)).join(index.members, "path").join(index.roots, "dataset_id")
    return near.filter(boxes_meet(vec("lo", d), vec("hi", d), vec("qlo", d), vec("qhi", d))).select("query_id", "dataset_id")


def topk_ia(index: SearchIndex, query: str | DataFrame, k: int = 10, include_zero: bool = False, exclude_self: bool = True) -> Run:
    q = as_outline(index, query)
    d, lo, hi = index.d, constants(q.lo), constants(q.hi)
    score = lambda: box_overlap(vec("lo", d), vec("hi", d), lo, hi)

    def best(paths: list[str]) -> list[tuple[float, str]]:
        rows = _others(index.roots.join(_below(index, paths), "dataset_id", "left_semi"), q, exclude_self).select("dataset_id", score().alias("s"))
        rows = rows if include_zero else rows.filter("s > 0")
        return [(r["s"], r["dataset_id"]) for r in rows.orderBy(F.desc("s"), "dataset_id").limit(k).collect()]

    leaves = [x for x in _leaves(index, score()) if include_zero or x[2] > 0]
    plan = WavePlan(leaves, k + 1 if q.member and exclude_self else k, True, best)
    found = plan.run()[:k]
    return Run(found, {"nodes_visited": plan.visited, "nodes_pruned": len(leaves) - plan.visited, "rounds": plan.rounds})


def topk_gbo(index: SearchIndex, query: str | DataFrame, k: int = 10, exclude_self: bool = True, plan: str = "tree") -> Run:
    """Datasets that share most cells with the query; none without a shared cell. plan="inverted" skips the tree."""
    member = isinstance(query, str)
    # A query has at most as many cells as the grid; its box and size play no part here.
    cells = F.broadcast(_frames(index, query, True)[1].distinct())

    # Cells that the query has meet its cells before they meet the datasets of a wave.
    met = (index.cells.filter(F.col("dataset_id") != query) if member and exclude_self else index.cells).join(cells, "cell")

    def best(part: DataFrame) -> list[tuple[float, str]]:
        rows = part.groupBy("dataset_id").agg(F.count(F.lit(1)).alias("s"))
        return [(r["s"], r["dataset_id"]) for r in rows.orderBy(F.desc("s"), "dataset_id").limit(k).collect()]

    if plan == "inverted":
        return Run(best(met), {"rounds": 1})
    shared = index.upper_cells if index.cut is None else index.upper_cells.filter(F.length("path") <= index.cut)
    frontier_size = dict(zip(index.top["path"].tolist(), index.top["n"].tolist()))
    bounds = shared.join(cells, "cell").groupBy("path").agg(F.count(F.lit(1)).alias("bound")).collect()
    leaves = [(r["path"], frontier_size[r["path"]], r["bound"]) for r in bounds if r["path"] in frontier_size]
    wave = WavePlan(leaves, k + 1 if member and exclude_self else k, True, lambda paths: best(met.join(_below(index, paths), "dataset_id", "left_semi")))
    found = wave.run()[:k]
    return Run(found, {"nodes_visited": wave.visited, "nodes_pruned": len(leaves) - wave.visited, "rounds": wave.rounds})


def kernel_frame(tree_rows: DataFrame, q: Tree, tau: float, mode: str, eps: float, returns: str, bounds: str = "ball", f: int | None = None) -> DataFrame:
    """dataset_id, distance (null beyond tau) and counters, one task per dataset. With f, trees are built from the
    points on the spot, as boxes of a bulk-loaded tree."""
    d = dims(tree_rows, "o")

    def run(table: pa.Table) -> pa.Table:
        get = lambda n: np.column_stack([table.column(f"{n}{i}").to_numpy(zero_copy_only=False) for i in range(d)])
        kind = table.column("kind").to_numpy()
        if f is None:
            t = tree_from_rows(table.column("path").to_pylist(), kind, table.column("n").to_numpy(), table.column("radius").to_numpy(), table.column("is_leaf").to_pylist(), get("o"), get("lo"), get("hi"))
        else:
            from .baselines import bulk_tree

            t = bulk_tree(get("o")[kind == 1], f)
        got = best_first(q, t, tau, mode, eps, returns, bounds)
        return pa.table({"dataset_id": table.column("dataset_id")[:1], "distance": pa.array([got.distance], pa.float64()), "evaluations": pa.array([got.evaluations], pa.int64()), "expansions": pa.array([got.expansions], pa.int64())})

    return tree_rows.groupBy("dataset_id").applyInArrow(run, "dataset_id string, distance double, evaluations long, expansions long")


def _of(trees: DataFrame, ids: list[str]) -> DataFrame:
    if len(ids) <= 500:
        return trees.filter(F.col("dataset_id").isin(ids))
    return trees.join(F.broadcast(trees.sparkSession.createDataFrame([(i,) for i in ids], "dataset_id string")), "dataset_id", "left_semi")


def _task_query(index: SearchIndex, query: str | DataFrame, clean: bool) -> Query | None:
    """The query with its points, or None if they are too many to go to every task."""
    if isinstance(query, str):
        d = index.d
        got = index.packed.filter(F.col("dataset_id") == query).select("n", "radius", "tree", *vec("o", d), *vec("lo", d), *vec("hi", d)).first()
        if got is None:
            raise ValueError(f"no dataset {query}")
        if got["n"] > MOST_QUERY_POINTS or got["tree"] is None:
            return None
        t = unpack(bytes(got["tree"]))
        vector = lambda n: tuple(got[f"{n}{i}"] for i in range(d))
        return Query(query, got["n"], vector("o"), got["radius"], vector("lo"), vector("hi"), t.points, t.ids.tolist(), _frames(index, query, clean)[1], True, t)
    if query.limit(MOST_QUERY_POINTS + 1).count() > MOST_QUERY_POINTS:
        return None
    return as_query(index, query, clean)


#: Pairs of points that are compared outright; pairs of larger datasets go down their trees after some probes.
MOST_PLAIN_PAIRS = 250_000
PROBES = 16


def _probed(q: tuple[Tree, TreeOutline], others: list[tuple[Tree, TreeOutline]], limit: float, known: list[float], k: int, slack: float, probes: int | None):
    """(distances, what they are at most, whether they are final, evaluations) from one tree to many, infinite beyond the limit.

    Outlines bound all pairs at once; the k least upper bounds, with the distances known, lower the limit. Then points of
    q meet the points of all that are left, those of the widest bounds and few at first. A tree is done when no further point
    of q can raise its distance by more than the slack."""
    tree, own = q
    n, starts = len(others), lambda sizes: np.cumsum(sizes) - sizes
    far, high, final = np.full(n, np.inf), np.full(n, np.inf), np.ones(n, bool)
    parts = np.array([len(x.radius) for _, x in others])
    r = np.concatenate([x.radius for _, x in others])
    square = squares(own.centre, np.concatenate([x.centre for _, x in others]))
    evaluations = square.size
    upper = (np.minimum.reduceat(np.sqrt(square + r * r), starts(parts), axis=1) + own.radius[:, None]) * (1 + 1e-12)
    gap = (np.sqrt(square) - r - own.radius[:, None]) * (1 - 1e-12)
    bounds = np.concatenate((known, upper.max(axis=0)))
    if len(bounds) >= k:
        limit = min(limit, float(np.partition(bounds, k - 1)[k - 1]) * (1 + 1e-12))
    open_ = np.flatnonzero(np.minimum.reduceat(gap, starts(parts), axis=1).max(axis=0) <= limit)
    if not len(open_):
        return far, high, final, evaluations
    near = gap <= np.repeat(upper, parts, axis=1)  # parts that may hold the nearest point of a point below a part of q
    order = np.argsort(-upper[:, open_].mean(axis=1)[own.owner], kind="stable")
    # Of each tree, the largest bound of the points of q from there on.
    rest = np.vstack((np.maximum.accumulate(upper[own.owner[order]][::-1], axis=0)[::-1], np.zeros(n)))
    end = len(order) if probes is None else min(probes, len(order))
    points = np.concatenate([others[i][0].points for i in open_.tolist()])
    part = np.concatenate([others[i][1].owner + at for i, at in zip(open_.tolist(), starts(parts)[open_].tolist())])
    sizes = np.array([len(others[i][0].points) for i in open_.tolist()])
    now, at, size = np.zeros(len(open_)), 0, 2
    while at < end and len(open_):
        some = order[at : min(end, at + max(1, min(size, 4_000_000 // len(points))))]
        met = near[np.unique(own.owner[some])].any(axis=0)[part]
        square = squares(tree.points[some], points[met])
        evaluations += square.size
        now = np.maximum(now, np.sqrt(np.minimum.reduceat(square, starts(np.add.reduceat(met, starts(sizes), dtype=np.int64)), axis=1).max(axis=0)))
        at, size = at + len(some), size + max(1, size // 2)
        done, keep = now + slack >= rest[at, open_], now <= limit
        got = open_[done & keep]
        far[got], high[got] = now[done & keep], np.maximum(now, rest[at, open_])[done & keep]
        keep &= ~done
        if not keep.all():
            held = np.repeat(keep, sizes)
            points, part, open_, now, sizes = points[held], part[held], open_[keep], now[keep], sizes[keep]
    far[open_], final[open_] = now, False
    return far, high, final, evaluations


def _lower_bounds(queries: list[dict], o: np.ndarray, radius: np.ndarray, lo: np.ndarray, hi: np.ndarray, paths: list[str] | None, met: tuple[bool, dict] | None, balls: bool, most: int = 2_000_000):
    """(number of the query, lower bounds of its distances) of queries that have a dataset within their limit. Queries are bounded
    in blocks; datasets that a query does not meet are infinitely far."""
    size = max(1, most // max(1, len(o)))
    rows: dict[str, list[int]] = {}
    for i, path in enumerate(paths if met is not None else []):
        rows.setdefault(path, []).append(i)
    for first in range(0, len(queries), size):
        some = queries[first : first + size]
        stack = lambda n: np.array([q[n] for q in some])  # noqa: B023, E731
        lower = np.maximum(np.sqrt(squares(stack("o"), o)) - radius, 0)
        if balls:
            a, b = stack("lo"), stack("hi")
            for j in range(o.shape[1]):
                np.maximum(lower, b[:, j][:, None] - hi[:, j], out=lower)
                np.maximum(lower, lo[:, j] - a[:, j][:, None], out=lower)
        if met is not None:
            only, by_path = met
            for path, at in rows.items():
                numbers = by_path.get(path, np.zeros(0, np.int64))
                numbers = numbers[(numbers >= first) & (numbers < first + len(some))] - first
                if only:
                    out = np.ones(len(some), bool)
                    out[numbers] = False
                    numbers = np.flatnonzero(out)
                lower[np.ix_(numbers, at)] = np.inf
        limits = stack("limit")
        for i in np.flatnonzero((lower.min(axis=1) <= limits) & np.isfinite(lower).any(axis=1)).tolist():
            yield first + i, lower[i]


def _kernels(queries: list[dict], mode: str, eps: float, returns: str, k: int, box_f: int | None = None, met: tuple[bool, dict] | None = None):
    """Rows of packed trees to (number of the query, dataset_id or null, distance, evaluations, expansions, kernels): of each batch the k
    nearest datasets of each query, datasets without a packed tree, and a row of counters.

    Datasets are taken by increasing lower bound: of balls, and of boxes, as each side of a query's box holds one of its points.
    Those left are bounded and compared together; where pairs of points are many, they go down the trees once some points have
    been tried. Approximate distances are those from below at which no point can add more than 2 eps, or (upper) from above.
    With `met`, (True, {path: queries}) has the only queries that meet the datasets below a node, (False, ..) those that do not."""
    slack = 2 * eps if mode == "approx" else 0.0
    # One query, or boxes: pair by pair, best first, with the fewest evaluations.
    alone = box_f is not None or len(queries) == 1

    if box_f is not None:
        from .baselines import bulk_tree

    def run(batches):
        own: dict[int, list] = {}
        for b in batches:
            if not b.num_rows:
                continue
            ids, trees, sizes = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("dataset_id", "tree", "n"))
            radius = b.column(b.schema.get_field_index("radius")).to_numpy()
            place, numbers, missing = {i: at for at, i in enumerate(ids)}, np.array(sizes), np.array([t is None for t in trees])
            d = len(queries[0]["o"])
            o, lo, hi = (np.column_stack([b.column(b.schema.get_field_index(f"{c}{i}")).to_numpy() for i in range(d)]) for c in ("o", "lo", "hi"))
            paths = b.column(b.schema.get_field_index("path")).to_pylist() if met is not None else None
            opened: dict[int, tuple[Tree, TreeOutline | None]] = {}
            out = []

            def opened_(i: int) -> tuple[Tree, TreeOutline | None]:
                if i not in opened:  # noqa: B023
                    t = unpack(trees[i])  # noqa: B023
                    opened[i] = (t, outline(t)) if box_f is None else (bulk_tree(t.points, box_f), None)  # noqa: B023
                return opened[i]  # noqa: B023

            for number, lower in _lower_bounds(queries, o, radius, lo, hi, paths, met, box_f is None):
                q = queries[number]
                limit, best, evaluations, expansions, kernels = q["limit"], [], 0, 0, 0
                near = np.flatnonzero((lower <= limit) & np.isfinite(lower))
                if q["skip"] in place:
                    near = near[near != place[q["skip"]]]
                if not len(near):
                    continue
                large = missing[near] | (numbers[near] > q["most"])
                out += [(number, ids[i], None, 0, 0, 0) for i in near[large].tolist()]
                near = near[~large]
                near = near[np.argsort(lower[near], kind="stable")]
                if number not in own:
                    t = unpack(q["tree"]) if isinstance(q["tree"], bytes) else q["tree"]
                    own[number] = [t, outline(t) if box_f is None else None, None]
                q_tree, q_outline, _ = own[number]

                def add(found: list[tuple[float, str]]) -> None:
                    nonlocal best, limit
                    best = sorted(best + found)[:k]  # noqa: B023
                    if len(best) == k:
                        limit = min(limit, best[-1][0])  # noqa: B023

                at, size = 0, 1 if alone else 2 * k if np.isinf(limit) else max(32, 2 * k)
                while at < len(near) and lower[near[at]] <= limit:
                    now = near[at : at + size]
                    now = now[lower[now] <= limit]
                    total = np.cumsum(numbers[now])
                    now = now[: max(1, int(np.searchsorted(total, 1_000_000, "right")))]
                    at, kernels = at + len(now), kernels + len(now)
                    if alone:
                        i = int(now[0])
                        x = best_first(q_tree, opened_(i)[0], limit, mode, eps, returns, "ball" if box_f is None else "box")
                        evaluations, expansions = evaluations + x.evaluations, expansions + x.expansions
                        add([(x.distance, ids[i])] if x.distance is not None else [])
                        continue
                    size *= 2
                    plain = len(q_tree.points) * int(total[len(now) - 1]) <= MOST_PLAIN_PAIRS * len(now)
                    far, high, final, n = _probed((q_tree, q_outline), [opened_(i) for i in now.tolist()], limit, [v for v, _ in best], k, slack, None if plain else PROBES)
                    evaluations += n
                    value = high if returns == "upper" and mode == "approx" else far
                    add([(v, ids[i]) for v, i, done in zip(value.tolist(), now.tolist(), final & np.isfinite(far)) if done])
                    if not final.all() and own[number][2] is None:
                        own[number][2] = parts_of(q_tree, 64)
                    for v, i in sorted(zip(far[~final].tolist(), now[~final].tolist())):
                        if v > limit:
                            break
                        v, w, n, m = by_parts(q_tree, opened_(i)[0], limit, own[number][2], v, slack)
                        evaluations, expansions = evaluations + n, expansions + m
                        if v is not None:
                            add([(w if returns == "upper" and mode == "approx" else v, ids[i])])
                out += [(number, i, v, 0, 0, 0) for v, i in best]
                out.append((number, None, None, evaluations, expansions, kernels))
            kinds = (pa.int32(), pa.string(), pa.float64(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*out)) or [()] * 6, kinds)], names=["q", "dataset_id", "distance", "evaluations", "expansions", "kernels"])

    return run


def topk_hausdorff_many(index: SearchIndex, queries: list[Query], k: int = 10, mode: str = "exact", eps: float | None = None, exclude_self: bool = True, returns: str = "center", wave: int | None = None, box_f: int | None = None) -> list[Run]:
    """The k datasets of smallest directed Hausdorff distance from each query, all queries in the same waves.

    The upper tree's nodes are bounded on the driver: a node of enough datasets gives a first limit, and nodes beyond the
    limit are never read (box_f: in place of the packed trees, box trees of that fanout are made on the spot). A wave reads the packed trees below the nearest open nodes of each query; a task takes its
    datasets by increasing lower bound and tightens the limit as it goes. Waves grow until no open node is within the k-th distance.
    Approximate distances are off by 2 eps at most, and so is the k-th of them: a dataset left out is truly farther than it,
    and each of the k found is truly no farther than it and 2 eps.
    """
    d, top = index.d, index.top
    eps = index.spec.epsilon() if eps is None else eps
    size = wave or max(4 * k, 4 * index.spark.sparkContext.defaultParallelism)
    most = MOST_QUERY_POINTS
    if len(queries) > 1:
        return _in_two_waves(index, queries, k, mode, eps, exclude_self, returns, size, most, box_f)
    done = np.zeros(len(top["path"]), bool)  # nodes of earlier waves: their datasets met every query that was still open
    state = []
    for q in queries:
        far = np.sqrt(((top["o"] - np.array(q.o)) ** 2).sum(axis=1))
        lower, upper = np.maximum(far - top["radius"], 0), far + top["radius"] + q.radius
        need = k + (1 if q.member and exclude_self else 0)
        by = np.argsort(upper, kind="stable")
        enough = int(np.searchsorted(np.cumsum(top["n"][by]), need))
        limit = float(upper[by[enough]]) * (1 + 1e-12) if enough < len(by) else float("inf")
        state.append({"limit": limit, "lower": lower, "order": np.argsort(lower, kind="stable"), "at": 0, "found": [], "metrics": {"evaluations": 0, "expansions": 0, "kernels": 0, "rounds": 0, "nodes_visited": 0}})
    while True:
        wanted: dict[int, None] = {}
        active = []
        for number, x in enumerate(state):
            # The nodes that were not read, as far as the limit goes, until enough datasets are seen.
            rest = x["order"][x["at"] :]
            rest = rest[: int(np.searchsorted(x["lower"][rest], x["limit"], "right"))]
            fresh = np.flatnonzero(~done[rest])
            fresh = fresh[: int(np.searchsorted(np.cumsum(top["n"][rest[fresh]]), size)) + 1]
            if len(fresh):
                x["at"] += int(fresh[-1]) + 1
                wanted |= dict.fromkeys(rest[fresh].tolist())
                active.append(number)
                x["metrics"]["rounds"] += 1
                x["metrics"]["nodes_visited"] += len(fresh)
        if not active:
            break
        for number, rows in _wave(index, [(n, queries[n], state[n]["limit"]) for n in active], top["path"][list(wanted)].tolist(), mode, eps, returns, k, exclude_self, most, box_f).items():
            x = state[number]
            for key in ("evaluations", "expansions", "kernels"):
                x["metrics"][key] += rows[key]
            found = x["found"] + rows["best"]
            if rows["large"]:
                found += _beyond(index, queries[number], rows["large"], x["limit"])
            x["found"] = sorted(set(found))[:k]  # a dataset may come again with another query's nodes
            if len(x["found"]) == k:
                x["limit"] = min(x["limit"], x["found"][-1][0])
        done[list(wanted)] = True
        size *= 4
    return [Run(x["found"], x["metrics"]) for x in state]


def _in_two_waves(index: SearchIndex, queries: list[Query], k: int, mode: str, eps: float, exclude_self: bool, returns: str, size: int, most: int, box_f: int | None) -> list[Run]:
    """The same for many queries. A wave reads all packed trees, whatever it takes of them, so there are two: each query meets the
    datasets below its nearest nodes, which give it a limit, and then all others within that limit. The driver keeps a few nodes
    of each query and its k best, and no row of a pair."""
    top, near, state = index.top, {}, []
    for number, q in enumerate(queries):
        far = np.sqrt(((top["o"] - np.array(q.o)) ** 2).sum(axis=1))
        lower, upper = np.maximum(far - top["radius"], 0), far + top["radius"] + q.radius

        def least(values: np.ndarray, datasets: int) -> np.ndarray:
            """The nodes of the least values that have so many datasets; every node has one."""
            some = np.argpartition(values, datasets)[: datasets + 1] if datasets + 1 < len(values) else np.arange(len(values))
            some = some[np.argsort(values[some], kind="stable")]
            return some[: int(np.searchsorted(np.cumsum(top["n"][some]), datasets)) + 1]

        need = k + (1 if q.member and exclude_self else 0)
        enough = least(upper, need)
        limit = float(upper[enough[-1]]) * (1 + 1e-12) if top["n"][enough].sum() >= need else float("inf")
        nodes = least(upper, size)  # balls that overlap have a lower bound of 0 alike
        for node in nodes[lower[nodes] <= limit].tolist():
            near.setdefault(node, []).append(number)
        state.append({"limit": limit, "found": [], "metrics": {"evaluations": 0, "expansions": 0, "kernels": 0, "rounds": 0, "nodes_visited": 0}})
    met = {top["path"][node]: np.array(numbers, np.int64) for node, numbers in near.items()}
    for only in (True, False):
        if not only and len(met) == len(top["path"]) and all(len(x) == len(queries) for x in met.values()):
            break
        active = [(n, q, x["limit"]) for n, (q, x) in enumerate(zip(queries, state))]
        got = _wave(index, active, list(met) if only else top["path"].tolist(), mode, eps, returns, k, exclude_self, most, box_f, (only, met))
        for number, rows in got.items():
            x = state[number]
            for key in ("evaluations", "expansions", "kernels"):
                x["metrics"][key] += rows[key]
            found = x["found"] + rows["best"]
            if rows["large"]:
                found += _beyond(index, queries[number], rows["large"], x["limit"])
            x["found"] = sorted(set(found))[:k]
            x["metrics"]["rounds"] += 1
            if len(x["found"]) == k:
                x["limit"] = min(x["limit"], x["found"][-1][0])
        if only:
            for numbers in met.values():
                for number in numbers.tolist():
                    state[number]["metrics"]["nodes_visited"] += 1
    return [Run(x["found"], x["metrics"]) for x in state]


def _tree_of(q: Query, f: int, box_f: int | None) -> Tree:
    if box_f is not None:
        from .baselines import bulk_tree

        return bulk_tree(q.points if q.packed is None else unpack(q.packed).points, box_f)
    return q.tree or build_tree(q.points, f)


#: Queries from which trees are read in blocks of neighbours.
MANY_QUERIES = 1_000


def _wave(index: SearchIndex, active: list, paths: list[str], mode: str, eps: float, returns: str, k: int, exclude_self: bool, most: int, box_f: int | None, met: tuple[bool, dict] | None = None) -> dict:
    """{query: its k best, its large datasets and counters} over the datasets below the nodes; the best of all tasks are picked
    before they come to the driver."""
    d = index.d
    at = F.col("path") if index.cut is None else F.substring("path", 1, index.cut)
    # Many queries meet neighbours side by side: a task has few queries then, and each of them few tasks.
    rows = index.packed_by_place if len(active) >= MANY_QUERIES else index.packed
    rows = rows.select(at.alias("path"), "dataset_id", "n", "radius", "tree", *vec("o", d), *vec("lo", d), *vec("hi", d))
    if len(paths) <= 200:
        rows = rows.filter(F.col("path").isin(paths))
    elif len(paths) < len(index.top["path"]):
        rows = rows.join(F.broadcast(index.spark.createDataFrame([(p,) for p in paths], "path string")), "path", "left_semi")
    tree = lambda q: _tree_of(q, index.f, box_f) if box_f is not None else q.packed or pack(_tree_of(q, index.f, None))
    shared = [{"o": np.array(q.o), "lo": q.lo, "hi": q.hi, "limit": limit, "skip": q.id if q.member and exclude_self else None, "most": most, "tree": tree(q)} for _, q, limit in active]
    if len(active) <= 20:
        rows = rows.filter(reduce(lambda a, b: a | b, [ball_lower(constants(q.o), vec("o", d), F.col("radius")) <= F.lit(limit) for _, q, limit in active]))
    pairs = rows.mapInArrow(_kernels(shared, mode, eps, returns, k, box_f, met), "q int, dataset_id string, distance double, evaluations long, expansions long, kernels long")
    is_pair = F.col("dataset_id").isNotNull()
    best = F.collect_list(F.when(F.col("distance").isNotNull(), F.struct("distance", "dataset_id")))
    # A dataset below a node of another query's wave may come twice.
    best = F.slice(F.array_sort(F.array_distinct(best)), 1, k)
    got = pairs.groupBy("q").agg(best.alias("best"), F.collect_set(F.when(is_pair & F.col("distance").isNull(), F.col("dataset_id"))).alias("large"), *(F.sum(c).alias(c) for c in ("evaluations", "expansions", "kernels")))
    got = got.select("q", F.col("best.distance").alias("distances"), F.col("best.dataset_id").alias("ids"), "large", "evaluations", "expansions", "kernels").collect()
    out = {n: {"best": [], "large": [], "evaluations": 0, "expansions": 0, "kernels": 0} for n, _, _ in active}
    for r in got:
        x = out[active[r["q"]][0]]
        x["best"], x["large"] = list(zip(r["distances"], r["ids"])), sorted(r["large"])
        for key in ("evaluations", "expansions", "kernels"):
            x[key] = r[key]
    return out


def _beyond(index: SearchIndex, q: Query, large: list[str], limit: float) -> list[tuple[float, str]]:
    """Distances to datasets of more points than a task takes."""
    q_tree = checkpointed(index.tree.filter(F.col("dataset_id") == q.id) if q.member else build_bottom(_points_frame(index, q), index.f))
    got = frontier.hausdorff(q_tree, _of(index.tree, large), None if limit == float("inf") else limit).collect()
    return [(x["distance"], x["dataset_id"]) for x in got]


def _points_frame(index: SearchIndex, q: Query) -> DataFrame:
    return index.spark.createDataFrame([(q.id, int(i), *map(float, p)) for i, p in zip(q.ids, q.points)], "dataset_id string, point_id long, " + ", ".join(f"c{i} double" for i in range(index.d)))


def topk_hausdorff(index: SearchIndex, query: str | DataFrame, k: int = 10, mode: str = "exact", eps: float | None = None, exclude_self: bool = True, returns: str = "center", wave: int | None = None, clean_query: bool = True) -> Run:
    """The k datasets of smallest directed Hausdorff distance from the query, exactly or to 2 eps.

    A query or a candidate of more than MOST_QUERY_POINTS points is compared through the frontier, exactly in either
    mode and without counters.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    if mode not in ("exact", "approx"):
        raise ValueError("mode is exact or approx")
    q = _task_query(index, query, clean_query)
    if q is not None:
        return topk_hausdorff_many(index, [q], k, mode, eps, exclude_self, returns, wave)[0]
    return _large_query(index, as_outline(index, query, clean_query), query, k, exclude_self, wave)


def _large_query(index: SearchIndex, whole: Outline, query: str | DataFrame, k: int, exclude_self: bool, wave: int | None) -> Run:
    """The search for a query that no task takes: candidates by increasing lower bound, each wave through the frontier."""
    d = index.d
    centre, radius = _ball(whole, d)
    o, r = constants(centre), F.lit(radius)
    bounds = _others(index.roots, whole, exclude_self).select("dataset_id", ball_lower(o, vec("o", d), F.col("radius")).alias("lower"), ball_upper(o, r, vec("o", d), F.col("radius")).alias("upper"))
    first = [x["upper"] for x in bounds.orderBy("upper").limit(k).collect()]
    tau = first[-1] * (1 + 1e-12) if len(first) == k else float("inf")
    q_tree = checkpointed(index.tree.filter(F.col("dataset_id") == query) if whole.member else build_bottom(whole.points, index.f))
    size, found, last, rounds = wave or max(4 * k, 4 * index.spark.sparkContext.defaultParallelism), [], None, 0
    while True:
        limit = found[k - 1][0] if len(found) >= k else tau
        rest = bounds.filter(F.col("lower") <= limit)
        if last is not None:
            rest = rest.filter((F.col("lower") > last[0]) | ((F.col("lower") == last[0]) & (F.col("dataset_id") > last[1])))
        now = rest.orderBy("lower", "dataset_id").limit(size).select("dataset_id", "lower").collect()
        if not now:
            return Run(found, {"rounds": rounds, "evaluations": 0, "expansions": 0, "kernels": 0})
        rounds, last = rounds + 1, (now[-1]["lower"], now[-1]["dataset_id"])
        far = frontier.hausdorff(q_tree, _of(index.tree, [x["dataset_id"] for x in now]), None if limit == float("inf") else limit).collect()
        found = sorted(found + [(x["distance"], x["dataset_id"]) for x in far])[:k]
        size *= 2


def hausdorff_pair(index: SearchIndex, q_id: str, d_id: str, mode: str = "exact", eps: float | None = None, returns: str = "center", bounds: str = "ball") -> Run:
    """The distance from one member to another, with the kernel's counters; beyond the points of a task through the frontier."""
    eps = index.spec.epsilon() if eps is None else eps
    got = {r["dataset_id"]: r for r in index.packed.filter(F.col("dataset_id").isin([q_id, d_id])).select("dataset_id", "n", "tree").collect()}
    if set(got) != {q_id, d_id}:
        raise ValueError(f"no dataset {({q_id, d_id} - set(got)).pop()}")
    if any(r["tree"] is None or r["n"] > MOST_QUERY_POINTS for r in got.values()):
        far = frontier.hausdorff(*(index.tree.filter(F.col("dataset_id") == i) for i in (q_id, d_id))).first()
        return Run([(far["distance"], d_id)], {"evaluations": 0, "expansions": 0})
    x = best_first(unpack(bytes(got[q_id]["tree"])), unpack(bytes(got[d_id]["tree"])), float("inf"), mode, eps, returns, bounds)
    return Run([(x.distance, d_id)], {"evaluations": x.evaluations, "expansions": x.expansions})


def symmetric_topk(index: SearchIndex, query: str, k: int = 10) -> Run:
    """By the larger of both directions: the query's direction bounds from below, so its order drives the search."""
    q = _task_query(index, query, True)
    n, want = index.roots.count(), k

    while True:
        there = topk_hausdorff(index, query, min(want, n))
        ids = [i for _, i in there.rows]
        rows: dict[str, float] = {}
        if q is not None:
            shared = q.tree

            def back(batches):
                for b in batches:
                    out = [(i, best_first(unpack(t), shared).distance) for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist())]
                    yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in out], pa.string()), pa.array([v for _, v in out], pa.float64())], names=["dataset_id", "distance"])

            small = _of(index.packed, ids).filter((F.col("n") <= MOST_QUERY_POINTS) & F.col("tree").isNotNull())
            rows = {r["dataset_id"]: r["distance"] for r in small.select("dataset_id", "tree").mapInArrow(back, "dataset_id string, distance double").collect()}
        for i in ids:
            if i not in rows:
                rows[i] = frontier.hausdorff(index.tree.filter(F.col("dataset_id") == i), index.tree.filter(F.col("dataset_id") == query)).first()["distance"]
        both = sorted((max(v, rows[i]), i) for v, i in there.rows)[:k]
        if len(there.rows) < want or both[-1][0] < there.rows[-1][0]:
            return Run(both, there.metrics | {"candidates": len(ids)})
        want *= 2


@dataclass(frozen=True)
class Measure:
    """A measure of the user's: bounds over roots as expressions of a Query, and the exact value of candidates."""

    lower: Callable[[Query, int], Column]
    exact: Callable[[SearchIndex, Query, DataFrame], DataFrame]


def custom_topk(index: SearchIndex, query: str | DataFrame, measure: Measure, k: int = 10) -> Run:
    """The k smallest values of a user's measure; candidates by increasing lower bound."""
    q = as_query(index, query)
    bounds = _others(index.roots, q, True).withColumn("lower", measure.lower(q, index.d))
    found, last, size, rounds = [], None, 4 * k, 0
    while True:
        rest = bounds if len(found) < k else bounds.filter(F.col("lower") <= found[k - 1][0])
        if last is not None:
            rest = rest.filter((F.col("lower") > last[0]) | ((F.col("lower") == last[0]) & (F.col("dataset_id") > last[1])))
        now = rest.orderBy("lower", "dataset_id").limit(size).select("dataset_id", "lower").collect()
        if not now:
            return Run(found, {"rounds": rounds})
        rounds, last = rounds + 1, (now[-1]["lower"], now[-1]["dataset_id"])
        ids = index.spark.createDataFrame([(x["dataset_id"],) for x in now], "dataset_id string")
        found = sorted(found + [(r["distance"], r["dataset_id"]) for r in measure.exact(index, q, ids).collect()])[:k]
        size *= 2


def exemplar_search(index: SearchIndex, query: str | DataFrame, k: int = 10, measure: str | Measure = "ia", **options) -> DataFrame:
    """The k best datasets as a frame, under a named measure or one of the user's."""
    name = query if isinstance(query, str) else "query"
    if isinstance(measure, Measure):
        return _result(index, name, custom_topk(index, query, measure, k).rows, "distance double", float, "custom")
    if measure == "ia":
        return _result(index, name, topk_ia(index, query, k, **options).rows, "score double", float, "ia")
    if measure == "gbo":
        return _result(index, name, topk_gbo(index, query, k, **options).rows, "score long", int, "gbo")
    if measure in ("hausdorff", "approx"):
        run = topk_hausdorff(index, query, k, mode="approx" if measure == "approx" else "exact", **options)
        return _result(index, name, run.rows, "distance double", float, measure)
    if measure == "symmetric":
        return _result(index, name, symmetric_topk(index, query, k).rows, "distance double", float, measure)
    raise ValueError(f"no measure {measure}")


def ia_batch(index: SearchIndex, query_ids: list[str], k: int = 10) -> DataFrame:
    """Top-k by shared area of many members at once: upper leaves that meet a query's box, then the datasets below them."""
    d = index.d
    q = index.roots.join(_ids(index, query_ids), "dataset_id", "left_semi").select(F.col("dataset_id").alias("query_id"), *(F.col(f"{n}{i}").alias(f"q{n}{i}") for n in ("lo", "hi") for i in range(d)))
    leaves = index.upper.filter("is_leaf").select("path", *(F.col(f"{n}{i}").alias(f"u{n}{i}") for n in ("lo", "hi") for i in range(d)))
    hit = leaves.join(F.broadcast(q) if len(query_ids) <= 10_000 else q, boxes_meet(vec("ulo", d), vec("uhi", d), vec("qlo", d), vec("qhi", d))).select("path", "query_id", *vec("qlo", d), *vec("qhi", d))
    scored = hit.join(index.members, "path").join(index.roots, "dataset_id").filter("dataset_id != query_id")
    return _best_per_query(scored.select("query_id", "dataset_id", box_overlap(vec("lo", d), vec("hi", d), vec("qlo", d), vec("qhi", d)).alias("score")).filter("score > 0"), k)


def _ids(index: SearchIndex, ids: list[str]) -> DataFrame:
    return F.broadcast(index.spark.createDataFrame([(i,) for i in ids], "dataset_id string"))


def _shared_cells(k: int):
    """Queries (query_id, q_cells) and datasets (dataset_id, cells) of a task to the k datasets that share most cells with each query."""

    def flat(table: pa.Table, name: str, cells: str) -> tuple[list[str], np.ndarray, np.ndarray]:
        ids, lists = table.column(name).to_pylist(), table.column(cells).combine_chunks()
        return ids, lists.flatten().to_numpy(zero_copy_only=False), np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))))

    def run(q: pa.Table, others: pa.Table) -> pa.Table:
        q_ids, q_cells, q_at = flat(q, "query_id", "q_cells")
        others = others.take(pa.array(sorted(range(others.num_rows), key=others.column("dataset_id").to_pylist().__getitem__), pa.int64()))
        ids, cells, at = flat(others, "dataset_id", "cells")
        n, place = len(ids), {i: a for a, i in enumerate(ids)}
        by = np.argsort(cells, kind="stable")
        owner = np.repeat(np.arange(n, dtype=np.int64), np.diff(at))[by]
        begin, end = (np.searchsorted(cells[by], q_cells, side) for side in ("left", "right"))
        out: list[tuple[str, str, int]] = []
        for a, i in enumerate(q_ids):
            parts = [owner[x:y] for x, y in zip(begin[q_at[a] : q_at[a + 1]].tolist(), end[q_at[a] : q_at[a + 1]].tolist()) if x < y]
            if not parts:
                continue
            shared = np.bincount(np.concatenate(parts), minlength=n)
            if i in place:
                shared[place[i]] = 0
            found = np.flatnonzero(shared)
            # Equal scores by dataset_id, whose order the numbers have.
            order = shared[found] * n - found
            if len(found) > k:
                best = np.argpartition(-order, k - 1)[:k]
                found, order = found[best], order[best]
            out += [(i, ids[j], int(shared[j])) for j in found.tolist()]
        columns = list(zip(*out)) or [(), (), ()]
        return pa.table({c: pa.array(x, t) for c, x, t in zip(("query_id", "dataset_id", "score"), columns, (pa.string(), pa.string(), pa.int64()))})

    return run


def gbo_batch(index: SearchIndex, query_ids: list[str], k: int = 10, most: int = MOST_TASK_CELLS, most_queries: int = 5_000) -> DataFrame:
    """Top-k by shared cells of many members at once. Datasets are dealt into blocks of about `most` cells and queries into
    parts; a task counts the shared cells of a part and a block from the block's postings, so pairs are never rows."""
    arrays = index.cells.groupBy("dataset_id").agg(F.collect_list("cell").alias("cells"))
    tasks = index.spark.sparkContext.defaultParallelism
    blocks = max(1, -(-index.cells.count() // most))
    parts = max(1, -(-len(query_ids) // most_queries), min(tasks, -(-len(query_ids) // 25)))
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    own = lambda n: F.pmod(F.xxhash64("dataset_id"), F.lit(n)).cast("int")
    q = arrays.join(_ids(index, query_ids), "dataset_id", "left_semi").select(F.col("dataset_id").alias("query_id"), F.col("cells").alias("q_cells"), own(parts).alias("q_part")).withColumn("q_block", each(blocks))
    others = arrays.withColumn("block", own(blocks)).withColumn("part", each(parts))
    scored = q.groupBy("q_part", "q_block").cogroup(others.groupBy("part", "block")).applyInArrow(_shared_cells(k), "query_id string, dataset_id string, score long")
    return _best_per_query(scored, k)


def gbo_tree_batch(index: SearchIndex, query_ids: list[str], k: int = 10) -> DataFrame:
    """Top-k by shared cells of many members at once through the upper tree. Nodes of the most shared cells, of enough datasets, are
    scored first; the k-th score of a query drops its nodes that share fewer cells, and the rest are scored in a second wave."""
    at = F.col("path") if index.cut is None else F.substring("path", 1, index.cut)
    members = index.members.select(at.alias("path"), "dataset_id")
    own = index.cells.join(_ids(index, query_ids), "dataset_id", "left_semi").select(F.col("dataset_id").alias("query_id"), "cell")
    own = F.broadcast(own) if len(query_ids) <= 1_000 else own
    nodes = index.upper.filter(_frontier(index)).select("path", "n_datasets")
    bounds = index.upper_cells.join(own, "cell").groupBy("query_id", "path").agg(F.count(F.lit(1)).alias("bound")).join(nodes, "path")
    along = Window.partitionBy("query_id").orderBy(F.desc("bound"), "path").rowsBetween(Window.unboundedPreceding, -1)
    bounds = checkpointed(bounds.withColumn("first", F.coalesce(F.sum("n_datasets").over(along), F.lit(0)) <= k))  # one more than k, as a query is among them
    # Cells that the queries have, with the node of their dataset: both waves read them.
    met = checkpointed(index.cells.join(own, "cell").filter("dataset_id != query_id").select("query_id", "dataset_id").join(members, "dataset_id"))

    def scored(wave: DataFrame) -> DataFrame:
        return met.join(wave.select("query_id", "path"), ["query_id", "path"], "left_semi").groupBy("query_id", "dataset_id").agg(F.count(F.lit(1)).alias("score"))

    found = checkpointed(_best_per_query(scored(bounds.filter("first")), k).drop("rank"))
    limit = found.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.min("score").alias("least")).filter(F.col("n") == k).select("query_id", "least")
    rest = bounds.filter("NOT first").join(limit, "query_id", "left").filter(F.col("least").isNull() | (F.col("bound") >= F.col("least")))
    return _best_per_query(found.unionByName(scored(rest)), k)


def hausdorff_batch(index: SearchIndex, query_ids: list[str], k: int = 10, mode: str = "exact", eps: float | None = None, box_f: int | None = None) -> dict[str, Run]:
    """Runs of many members, in waves that all queries share; as many go together as have MOST_BATCH_POINTS points."""
    d, out = index.d, {}
    rows = _of(index.packed, query_ids).select("dataset_id", "n", "radius", "tree", *vec("o", d), *vec("lo", d), *vec("hi", d))
    sizes = {r["dataset_id"]: r["n"] for r in rows.select("dataset_id", "n").collect()}
    parts: list[list[str]] = [[]]
    for i in query_ids:
        if i not in sizes:
            raise ValueError(f"no dataset {i}")
        if sizes[i] > MOST_QUERY_POINTS:
            out[i] = topk_hausdorff(index, i, k, mode, eps)
            continue
        if parts[-1] and sum(sizes[x] for x in parts[-1]) + sizes[i] > MOST_BATCH_POINTS:
            parts.append([])
        parts[-1].append(i)
    for part in filter(None, parts):
        queries = []
        for r in _of(rows, part).collect():
            vector = lambda n: tuple(r[f"{n}{i}"] for i in range(d))  # noqa: B023, E731
            # Trees stay as they are packed: unpacked ones and lists of ids are many times as much memory.
            queries.append(Query(r["dataset_id"], r["n"], vector("o"), r["radius"], vector("lo"), vector("hi"), np.zeros((0, d)), [], index.cells, True, None, bytes(r["tree"])))
        out |= {q.id: run for q, run in zip(queries, topk_hausdorff_many(index, queries, k, mode, eps, box_f=box_f))}
    return out


def exemplar_batch(index: SearchIndex, query_ids: list[str], k: int = 10, measure: str = "hausdorff", **options) -> DataFrame:
    """query_id, rank, dataset_id and score of many members, each measure in one plan or in waves shared by all."""
    if measure == "ia":
        return ia_batch(index, query_ids, k)
    if measure == "gbo":
        return gbo_batch(index, query_ids, k)
    runs = hausdorff_batch(index, query_ids, k, "approx" if measure == "approx" else "exact", **options)
    rows = [(q, i + 1, ds, float(v)) for q in query_ids for i, (v, ds) in enumerate(runs[q].rows)]
    return index.spark.createDataFrame(rows, "query_id string, rank int, dataset_id string, score double")


def _best_per_query(scored: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "dataset_id")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def compare_measures(index: SearchIndex, query: str, k: int = 5) -> DataFrame:
    """The same query under the three measures, and how many of the others' results each shares."""
    runs = {"ia": topk_ia(index, query, k), "gbo": topk_gbo(index, query, k), "hausdorff": topk_hausdorff(index, query, k)}
    rows = []
    for m, run in runs.items():
        for i, (v, ds) in enumerate(run.rows):
            rows.append((query, m, i + 1, ds, float(v), sum(ds in {x for _, x in other.rows} for n, other in runs.items() if n != m)))
    return index.spark.createDataFrame(rows, "query_id string, method string, rank int, dataset_id string, value double, shared_with long")


def similar_pairs(index: SearchIndex, t: float, width: float | None = None) -> DataFrame:
    """Ordered pairs (q, d) of directed Hausdorff distance up to t.

    Every point of Q needs a point of D within t, so Q's centre lies within t of D's ball. Roots are dealt by the power of
    two of their radius: a D meets the Q of any size whose centre lies in a cell of width t + its own radius beside its own,
    so one wide dataset widens no other's cells. Balls prune, and what is left is one kernel per pair, or the frontier for large ones.
    """
    d = index.d
    # The least power of two that holds t + radius, or the given width where that is wider.
    level = F.greatest(F.ceil(F.log2(F.greatest(F.lit(t) + F.col("radius"), F.lit(max(width or 0.0, 1e-9))))), F.lit(-60)).cast("int")
    at = index.roots.withColumn("level", level)
    levels = [r[0] for r in at.select("level").distinct().collect()]
    cells = lambda df, o: df.withColumns({f"g{i}": F.floor(F.col(f"{o}{i}") / F.pow(F.lit(2.0), F.col("level"))) for i in range(d)})
    near = cells(at, "o")
    for i in range(d):
        near = near.withColumn(f"g{i}", F.explode(F.array(F.col(f"g{i}") - 1, F.col(f"g{i}"), F.col(f"g{i}") + 1)))
    left = index.roots.select(F.col("dataset_id").alias("q_id"), F.explode(F.array(*map(F.lit, levels or [0]))).alias("level"), *(F.col(f"o{i}").alias(f"q{i}") for i in range(d)))
    keys = ["level", *(f"g{i}" for i in range(d))]
    pairs = cells(left, "q").join(near.select("dataset_id", "radius", *keys, *vec("o", d)), keys).filter("q_id != dataset_id").filter(ball_lower(vec("q", d), vec("o", d), F.col("radius")) <= t).select("q_id", "dataset_id")
    packed = index.packed.select("dataset_id", "n", "tree", *vec("lo", d), *vec("hi", d))
    small = packed.filter((F.col("n") <= MOST_QUERY_POINTS) & F.col("tree").isNotNull())
    q_side = small.select(F.col("dataset_id").alias("q_id"), F.col("tree").alias("q_tree"))
    met = pairs.join(q_side, "q_id").join(small.select("dataset_id", "tree"), "dataset_id").select("q_id", "dataset_id", "q_tree", "tree")

    def run(batches):
        for b in batches:
            out, opened = [], {}
            for q_id, d_id, q, x in zip(*(b.column(i).to_pylist() for i in range(4))):
                if q_id not in opened:
                    opened = {q_id: unpack(q)}
                got = best_first(opened[q_id], unpack(x), t)
                if got.distance is not None and got.distance <= t:
                    out.append((q_id, d_id, got.distance))
            cols = list(zip(*out)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.string(), pa.string(), pa.float64()))], names=["q_id", "dataset_id", "distance"])

    out = met.mapInArrow(run, "q_id string, dataset_id string, distance double")
    giants = [r[0] for r in packed.filter((F.col("n") > MOST_QUERY_POINTS) | F.col("tree").isNull()).select("dataset_id").collect()]
    if giants:
        large = pairs.filter(F.col("q_id").isin(giants) | F.col("dataset_id").isin(giants)).groupBy("q_id").agg(F.collect_list("dataset_id").alias("ids")).collect()
        for r in large:
            far = frontier.hausdorff(index.tree.filter(F.col("dataset_id") == r["q_id"]), _of(index.tree, r["ids"]), t).filter(F.col("distance") <= t)
            out = out.unionByName(far.select(F.lit(r["q_id"]).alias("q_id"), "dataset_id", "distance"))
    return out
