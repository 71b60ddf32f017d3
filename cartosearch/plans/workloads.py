"""The experiments: each sweeps one parameter over repositories and methods and returns measured rows.

Every workload takes (spark, sf_dir), the repositories, the points of its sweep and how many query datasets to use; the
defaults are the whole grid and 100 queries, 40 where Hausdorff distances are swept, or as many as there are: those of the smallest hashes. Times and counters
are means per query. All queries of a point of the grid run in one plan or in shared waves. w_haus_k has 100 queries, and in it
and in w_overlap_f every method has all of them; elsewhere two baselines, which compare all pairs of points or of boxes, and
the tree form of shared cells take the first `few`.
"""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from ..functions.zorder import signatures
from ..model import GridSpec
from ..operators import baselines as base
from ..operators import index as ix
from ..operators import search_datasets as sd
from ..operators import search_points as sp
from ..operators.outliers import knee_threshold, leaf_radii, mark_outliers, remove_outliers
from ..sources.repositories import REPOSITORIES, pick_queries, range_around, repository, repository_extent, sample_datasets
from .metrics import overlap_accuracy, run_rows, scale_distribution, timed

KS, FS, THETAS, RS, DS, MS = (10, 20, 30, 40, 50), (10, 20, 30, 40, 50), (3, 4, 5, 6, 7), (1, 2, 3, 4, 5), (2, 4, 6, 8), (0.001, 0.01, 0.1, 1.0)

#: Indexes that a session keeps; the oldest one goes first.
KEPT_INDEXES = 24
_built: dict[tuple, tuple[str, ix.SearchIndex]] = {}


def built(spark: SparkSession, sf_dir: str, handle: str, f: int = 10, theta: int = 5, clean: bool = False, d: int | None = None) -> ix.SearchIndex:
    """The index of a repository; kept for this session, as searches share one."""
    key, app = (sf_dir, handle, f, theta, clean, d), spark.sparkContext.applicationId
    if key not in _built or _built[key][0] != app:
        while len(_built) >= KEPT_INDEXES:
            _built.pop(next(iter(_built)))
        _built[key] = app, ix.build_index(repository(spark, sf_dir, handle, d), f, theta, clean)
    return _built[key][1]


def forget() -> None:
    """The next searches build their indexes from the tables as they are then."""
    _built.clear()


class Sheet:
    def __init__(self, spark: SparkSession, workload: str):
        self.spark, self.workload, self.rows = spark, workload, []

    def add(self, repo: str, method: str, parameter: str, value: float, fn, truth: list | None = None, k: int = 10):
        """One run: fn gives a Run, a frame or an index."""
        got, ms = timed(fn)
        run = got if isinstance(got, sd.Run) else None
        n = len(run.rows) if run else got.count() if isinstance(got, DataFrame) else 0
        accuracy = overlap_accuracy(run.rows, truth, k) if run and truth else None
        self.rows.append((self.workload, repo, method, parameter, float(value), ms, int(run.metrics.get("evaluations", 0)) if run else 0, n, accuracy))
        return got

    def add_many(self, repo: str, method: str, parameter: str, value: float, ids: list[str], fn, truth: dict | None = None, k: int = 10) -> dict[str, sd.Run]:
        """Runs of many queries, as a dict or as a frame (query_id, rank, dataset_id, score[, evaluations]); means per query."""

        def collected():
            got = fn(ids)
            if isinstance(got, dict):
                return got
            runs = {i: sd.Run([], {}) for i in ids}
            for r in got.orderBy("query_id", "rank").collect():
                runs[r["query_id"]].rows.append((r["score"], r["dataset_id"]))
                if "evaluations" in got.columns:
                    runs[r["query_id"]].metrics["evaluations"] = r["evaluations"]
            return runs

        runs, ms = timed(collected)
        mean = lambda x: sum(x) / max(1, len(x))
        accuracy = mean([overlap_accuracy(runs[i].rows, truth[i].rows, k) for i in ids if truth[i].rows]) if truth else None
        self.rows.append((self.workload, repo, method, parameter, float(value), ms / max(1, len(ids)), int(mean([r.metrics.get("evaluations", 0) for r in runs.values()])), round(mean([len(r.rows) for r in runs.values()])), accuracy))
        return runs

    def add_frame(self, repo: str, method: str, parameter: str, value: float, n: int, fn) -> DataFrame:
        """One plan that answers n queries; results and time are means per query."""
        got, ms = timed(lambda: checkpointed(fn()))
        self.rows.append((self.workload, repo, method, parameter, float(value), ms / max(1, n), 0, round(got.count() / max(1, n)), None))
        return got

    def frame(self) -> DataFrame:
        return run_rows(self.spark, self.rows)


def queries_of(index: ix.SearchIndex, n: int) -> list[str]:
    return pick_queries(index.roots, n)


def _arrays(index: ix.SearchIndex) -> DataFrame:
    """The cell arrays of a scan, which all points of a sweep share as searches share an index."""
    return checkpointed(signatures(index.points, index.spec, "array"))


def _scan(arrays: DataFrame, k: int):
    """Shared cells without a tree or postings for many queries: every pair of cell arrays is intersected."""

    def run(ids: list[str]) -> DataFrame:
        q = arrays.filter(F.col("dataset_id").isin(ids)).select(F.col("dataset_id").alias("query_id"), F.col("cells").alias("qcells"))
        scored = arrays.join(F.broadcast(q), F.col("dataset_id") != F.col("query_id")).select("query_id", "dataset_id", F.size(F.array_intersect("cells", "qcells")).cast("long").alias("score")).filter("score > 0")
        w = Window.partitionBy("query_id").orderBy(F.desc("score"), "dataset_id")
        return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)

    return run


def _overlaps(s: Sheet, index: ix.SearchIndex, arrays: DataFrame, repo: str, parameter: str, value: float, ids: list[str], k: int, few: int | None) -> None:
    s.add_many(repo, "ia", parameter, value, ids, lambda i: sd.ia_batch(index, i, k))
    s.add_many(repo, "gbo", parameter, value, ids, lambda i: sd.gbo_batch(index, i, k))
    s.add_many(repo, "gbo_tree", parameter, value, ids[:few], lambda i: sd.gbo_tree_batch(index, i, k))
    s.add_many(repo, "scan", parameter, value, ids, _scan(arrays, k))


def _baselines(s: Sheet, index: ix.SearchIndex, repo: str, parameter: str, value: float, ids: list[str], k: int, few: int | None, truth: dict) -> None:
    s.add_many(repo, "box_bound", parameter, value, ids[:few], lambda i: base.box_bound_batch(index, i, k), truth, k)
    s.add_many(repo, "box_incremental", parameter, value, ids[:few], lambda i: sd.hausdorff_batch(index, i, k, box_f=index.f), truth, k)


def _rectangles(index: ix.SearchIndex, ids: list[str], r: float) -> DataFrame:
    """query_id, qlo.., qhi..: r cells to each side around the centres of the queries."""
    d = index.d
    q = index.roots.filter(F.col("dataset_id").isin(ids))
    return q.select(F.col("dataset_id").alias("query_id"), *((F.col(f"o{i}") + sign * r * w).alias(f"q{n}{i}") for n, sign in (("lo", -1), ("hi", 1)) for i, w in enumerate(index.spec.widths[:d])))


def w_overview(spark, sf_dir, repos=("ev_home", "ev_trip", "li_fort", "or_cust", "li_wide", "em_label"), n=100):
    """Seven steps: index, range, shared area, shared cells, Hausdorff, range points, nearest points."""
    s = Sheet(spark, "overview")
    for repo in repos:
        points = repository(spark, sf_dir, repo, 3 if repo in ("li_wide", "em_label") else None)
        index = s.add(repo, "index", "n", n, lambda: ix.build_index(points))
        ids = queries_of(index, n)
        boxes = checkpointed(_rectangles(index, ids, 3))
        s.add_frame(repo, "range_datasets", "n", n, len(ids), lambda: sd.range_datasets_batch(index, boxes))
        s.add_many(repo, "ia", "n", n, ids, lambda i: sd.ia_batch(index, i))
        s.add_many(repo, "gbo", "n", n, ids, lambda i: sd.gbo_batch(index, i))
        best = s.add_many(repo, "hausdorff", "n", n, ids, lambda i: sd.hausdorff_batch(index, i))
        s.add_frame(repo, "range_points", "n", n, len(ids), lambda: sp.range_points_batch(index, boxes.withColumn("dataset_id", F.col("query_id"))))
        pairs = [(q, best[q].rows[0][1]) for q in ids if best[q].rows]
        s.add_frame(repo, "nearest_points", "n", n, len(pairs), lambda: sp.nearest_points_batch(index, pairs))
    return s.frame()


def w_index_scale(spark, sf_dir, repos=("li_part", "or_cust", "ev_trip"), ms=MS):
    """Building time, rows and bytes of the one index against those of separate ones, by share of datasets. `evaluations` has bytes."""
    s = Sheet(spark, "index_scale")
    for repo in repos:
        whole = repository(spark, sf_dir, repo)
        for m in ms:
            points = sample_datasets(whole, m)
            if not points.limit(1).count():
                continue
            index, ms_own = timed(lambda: ix.build_index(points, clean=False))
            own = ix.index_space(index).agg(F.sum("n_rows"), F.sum("n_bytes")).first()
            s.rows.append((s.workload, repo, "unified", "m", float(m), ms_own, int(own[1]), int(own[0]), None))
            parts, ms_apart = timed(lambda: {n: checkpointed(df) for n, df in base.separate_indexes(points, index.spec).items()})
            rows, size = 0, 0
            for df in parts.values():
                a, b = ix.frame_space(df)
                rows, size = rows + a, size + b
            s.rows.append((s.workload, repo, "separate", "m", float(m), ms_apart, size, rows, None))
    return s.frame()


def w_overlap_k(spark, sf_dir, repos=("ev_home", "ev_trip", "li_part", "or_cust"), ks=KS, n=100, few=1):
    s = Sheet(spark, "overlap_k")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids, arrays = queries_of(index, n), _arrays(index)
        for k in ks:
            _overlaps(s, index, arrays, repo, "k", k, ids, k, few)
    return s.frame()


def w_overlap_f(spark, sf_dir, repos=("ev_home", "ev_trip", "li_part", "or_cust"), fs=FS, n=100, few=None):
    s = Sheet(spark, "overlap_f")
    for repo in repos:
        ids, arrays = [], None
        for f in fs:
            index = built(spark, sf_dir, repo, f)
            # Raw indexes of every f have the same datasets and cells.
            ids, arrays = (ids, arrays) if f != fs[0] else (queries_of(index, n), _arrays(index))
            _overlaps(s, index, arrays, repo, "f", f, ids, 10, few)
    return s.frame()


def w_gbo_theta(spark, sf_dir, repos=("li_fort", "li_supp", "ev_home"), thetas=THETAS, n=100, few=1):
    """Shared cells by resolution, by postings for all queries and through the tree for some; `evaluations` of "postings" is their number."""
    s = Sheet(spark, "gbo_theta")
    for repo in repos:
        whole = built(spark, sf_dir, repo)
        ids = queries_of(whole, n)
        for theta in thetas:
            index = ix.with_resolution(whole, theta)
            s.rows.append((s.workload, repo, "postings", "theta", float(theta), 0.0, index.cells.count(), 0, None))
            s.add_many(repo, "gbo", "theta", theta, ids, lambda i: sd.gbo_batch(index, i))
            s.add_many(repo, "gbo_tree", "theta", theta, ids[:few], lambda i: {q: sd.topk_gbo(index, q) for q in i})
    return s.frame()


def w_haus_k(spark, sf_dir, repos=("ev_home", "li_fort", "ev_slice", "ev_user"), ks=KS, n=100, few=None):
    s = Sheet(spark, "haus_k")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, n)
        for k in ks:
            truth = s.add_many(repo, "exact", "k", k, ids, lambda i: sd.hausdorff_batch(index, i, k))
            _baselines(s, index, repo, "k", k, ids, k, few, truth)
    return s.frame()


def w_appro_eps(spark, sf_dir, repos=("ev_home", "li_fort", "ev_user"), thetas=THETAS, n=40):
    s = Sheet(spark, "appro_eps")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, n)
        truth = sd.hausdorff_batch(index, ids)
        for theta in thetas:
            eps = GridSpec(index.spec.lo, index.spec.hi, theta).epsilon()
            s.add_many(repo, "approx", "theta", theta, ids, lambda i: sd.hausdorff_batch(index, i, mode="approx", eps=eps), truth)
            s.add(repo, "approx_pair", "theta", theta, lambda: sd.hausdorff_pair(index, ids[0], truth[ids[0]].rows[0][1], "approx", eps))
    return s.frame()


def w_accuracy(spark, sf_dir, repos=("ev_home", "ev_slice", "li_fort", "ev_trip"), n=40):
    s = Sheet(spark, "accuracy")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, n)
        truth = s.add_many(repo, "exact", "k", 10, ids, lambda i: sd.hausdorff_batch(index, i))
        s.add_many(repo, "approx", "k", 10, ids, lambda i: sd.hausdorff_batch(index, i, mode="approx"), truth)
        s.add_many(repo, "gbo", "k", 10, ids, lambda i: sd.gbo_batch(index, i), truth)
    return s.frame()


def injected(points: DataFrame, share: float = 0.01, seed: int = 7) -> DataFrame:
    """Points of which a share, by hash, is moved far out, marked in `injected`."""
    box = repository_extent(points)
    hit = F.pmod(F.xxhash64("dataset_id", "point_id", F.lit(seed)), F.lit(10_000)) < int(share * 10_000)
    moved = {f"c{i}": F.when(hit, F.col(f"c{i}") + (b - a) * (2 + F.pmod(F.xxhash64("point_id", F.lit(i)), F.lit(100)) / 50)).otherwise(F.col(f"c{i}")) for i, (a, b) in enumerate(zip(box.lo, box.hi))}
    return points.withColumn("injected", hit).withColumns(moved)


def w_outliers(spark, sf_dir, repos=("ev_home", "ev_user", "li_fort"), n=40):
    """Raw, our cleaning and isolation cleaning (the truth): time of cleaning and accuracy of the top-k."""
    s = Sheet(spark, "outliers")
    for repo in repos:
        whole = repository(spark, sf_dir, repo)
        points = checkpointed(whole if repo == "ev_user" else injected(whole).drop("injected"))  # ev_user has a tail of its own
        raw = ix.build_index(points, clean=False)
        threshold = knee_threshold(leaf_radii(raw.tree))
        s.add(repo, "clean_own", "n", n, lambda: mark_outliers(raw.tree, threshold))
        total, kept = points.count(), mark_outliers(raw.tree, threshold).filter("kept").count()
        s.add(repo, "clean_isolation", "n", n, lambda: base.isolation_nn_scores(points))
        own = ix.finish(checkpointed(remove_outliers(raw.tree, threshold)), raw.spec, raw.f, threshold)
        isolated = ix.build_index(base.isolation_nn_clean(points, max(1e-4, 1 - kept / total)), clean=False, spec=raw.spec)
        there = {r[0] for r in isolated.roots.select("dataset_id").collect()}
        ids = [q for q in queries_of(raw, n) if q in there]
        truth = s.add_many(repo, "isolation", "n", n, ids, lambda i: sd.hausdorff_batch(isolated, i))
        s.add_many(repo, "own", "n", n, ids, lambda i: sd.hausdorff_batch(own, i), truth)
        s.add_many(repo, "raw", "n", n, ids, lambda i: sd.hausdorff_batch(raw, i), truth)
    return s.frame()


def w_pair_f(spark, sf_dir, repos=("li_supp", "li_fort"), fs=FS):
    s = Sheet(spark, "pair_f")
    for repo in repos:
        for f in fs:
            index = built(spark, sf_dir, repo, f)
            a, b = queries_of(index, 2)
            s.add(repo, "ball_exact", "f", f, lambda: sd.hausdorff_pair(index, a, b))
            s.add(repo, "ball_approx", "f", f, lambda: sd.hausdorff_pair(index, a, b, "approx"))
            s.add(repo, "box_exact", "f", f, lambda: sd.hausdorff_pair(index, a, b, bounds="box"))
    return s.frame()


def w_topk_f(spark, sf_dir, repo="ev_home", fs=FS, n=40):
    s = Sheet(spark, "topk_f")
    for f in fs:
        index = built(spark, sf_dir, repo, f)
        s.add_many(repo, "exact", "f", f, queries_of(index, n), lambda i: sd.hausdorff_batch(index, i))
    return s.frame()


def w_dimension(spark, sf_dir, repos=("li_wide", "em_label"), ds=DS, n=40, few=1, k=10):
    s = Sheet(spark, "dimension")
    for repo in repos:
        for d in ds:
            index = built(spark, sf_dir, repo, d=d)
            ids = queries_of(index, n)
            s.add_many(repo, "ia", "d", d, ids, lambda i: sd.ia_batch(index, i, k))
            s.add_many(repo, "gbo", "d", d, ids, lambda i: sd.gbo_batch(index, i, k))
            truth = s.add_many(repo, "exact", "d", d, ids[:10], lambda i: sd.hausdorff_batch(index, i, k))
            _baselines(s, index, repo, "d", d, ids, k, few, truth)
    return s.frame()


def w_rangep(spark, sf_dir, repos=("ev_home", "li_fort"), rs=RS, n=100):
    s = Sheet(spark, "rangep")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, n)
        for r in rs:
            boxes = _rectangles(index, ids, r).withColumn("dataset_id", F.col("query_id"))
            s.add_frame(repo, "range_points", "R", r, len(ids), lambda: sp.range_points_batch(index, boxes))
    return s.frame()


def w_ranges(spark, sf_dir, repos=("ev_home", "ev_slice", "ev_trip"), rs=RS, n=100):
    s = Sheet(spark, "ranges")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, n)
        for r in rs:
            s.add_frame(repo, "range_datasets", "R", r, len(ids), lambda: sd.range_datasets_batch(index, _rectangles(index, ids, r)))
    return s.frame()


def w_nnp(spark, sf_dir, repos=("li_part", "ev_trip"), ss=(1, 10, 100, 1000, 10_000)):
    """Nearest points of one dataset for the points of s others together, s up to as many as there are; `evaluations` has the query's points."""
    s = Sheet(spark, "nnp")
    for repo in repos:
        index = built(spark, sf_dir, repo)
        ids = queries_of(index, max(ss) + 1)
        target = ids.pop()
        for size in sorted({min(x, len(ids)) for x in ss}):
            key = F.xxhash64("dataset_id", "point_id", *(F.col(f"c{i}") for i in range(index.d)))
            some = index.points if size > 1000 else index.points.filter(F.col("dataset_id").isin(ids[:size]))
            some = some if size <= 1000 else some.join(F.broadcast(spark.createDataFrame([(i,) for i in ids[:size]], "dataset_id string")), "dataset_id", "left_semi")
            q = checkpointed(some.withColumn("point_id", key).withColumn("dataset_id", F.lit("query")))
            own = s.add(repo, "packed", "s", size, lambda: sp.nearest_points(index, q, target))
            s.add(repo, "from_hausdorff", "s", size, lambda: sp.nearest_points(index, q, target, strategy="from_hausdorff"))
            both = q.unionByName(index.points.filter(F.col("dataset_id") == target), allowMissingColumns=True)
            s.add(repo, "early_break", "s", size, lambda: base.knn_early_break(both, "query", target))
            del own
    return s.frame()


def w_case(spark, sf_dir, repo="ev_home"):
    index = built(spark, sf_dir, repo)
    return sd.compare_measures(index, queries_of(index, 1)[0], 5)


def w_scale_dist(spark, sf_dir, repos=tuple(REPOSITORIES)):
    out = None
    for repo in repos:
        one = scale_distribution(repository(spark, sf_dir, repo)).withColumn("repository", F.lit(repo))
        out = one if out is None else out.unionByName(one)
    return out


def w_radii(spark, sf_dir, repos=("ev_user", "li_supp")):
    """Leaf radii before and after cleaning."""
    out = None
    for repo in repos:
        before, after = built(spark, sf_dir, repo), built(spark, sf_dir, repo, clean=True)
        high = before.tree.filter("kind = 0 AND is_leaf").agg(F.max("radius")).first()[0]
        for name, index in (("before", before), ("after", after)):
            one = ix.radius_distribution(index, 20, high).withColumn("repository", F.lit(repo)).withColumn("stage", F.lit(name))
            out = one if out is None else out.unionByName(one)
    return out


def w_scale(spark, sf_dir, repos=("ev_trip", "li_part"), ms=MS, n=100):
    """All searches by share of datasets."""
    s = Sheet(spark, "scale")
    for repo in repos:
        whole = repository(spark, sf_dir, repo)
        for m in ms:
            points = sample_datasets(whole, m)
            if points.select("dataset_id").distinct().limit(2).count() < 2:
                continue
            index = s.add(repo, "index", "m", m, lambda: ix.build_index(points, clean=False))
            ids = queries_of(index, n)
            s.add_many(repo, "ia", "m", m, ids, lambda i: sd.ia_batch(index, i))
            s.add_many(repo, "gbo", "m", m, ids, lambda i: sd.gbo_batch(index, i))
            s.add_many(repo, "hausdorff", "m", m, ids, lambda i: sd.hausdorff_batch(index, i))
    return s.frame()


def w_chain(spark: SparkSession, sf_dir: str, repo: str = "ev_home") -> DataFrame:
    """A rectangle finds datasets, one of them the most similar ones, the best of those its points in the rectangle, and
    these their nearest points in the example."""
    index = built(spark, sf_dir, repo)
    q = queries_of(index, 1)[0]
    root = index.roots.filter(F.col("dataset_id") == q).first()
    box = range_around(root, 5, index.spec)
    found = sd.range_datasets(index, box)
    near = sd.exemplar_search(index.where(found), q, 3, "hausdorff")
    best = near.orderBy("rank").first()["dataset_id"]
    inside = sp.range_points(index, box, best)
    return sp.nearest_points(index, inside.select("dataset_id", "point_id", "c0", "c1"), q).withColumn("example", F.lit(q)).withColumn("dataset_id", F.lit(best)) if inside.limit(1).count() else sp.nearest_points(index, best, q).withColumn("example", F.lit(q)).withColumn("dataset_id", F.lit(best))


WORKLOADS = {f.__name__: f for f in (w_overview, w_index_scale, w_overlap_k, w_overlap_f, w_gbo_theta, w_haus_k, w_appro_eps, w_accuracy, w_outliers, w_pair_f, w_topk_f, w_dimension, w_rangep, w_ranges, w_nnp, w_case, w_scale_dist, w_radii, w_scale, w_chain)}
