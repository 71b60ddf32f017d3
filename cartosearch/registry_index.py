"""Queries on the index itself, on cleaned repositories, on bounds, on chains of searches and on streams, with their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle as sql
from . import oracle_index as osql
from .checkpoints import checkpoint_dir, checkpointed
from .functions.geometry import ball_gap, ball_lower, ball_upper, box_lower, box_overlap, box_upper, constants, vec
from .functions.zorder import signatures, z_decode
from .model import Box, GridSpec
from .operators import baselines as base
from .operators import index as ix
from .operators import search_datasets as sd
from .operators import search_points as sp
from .operators.bottom_index import build_bottom
from .operators.measures import summarise_nodes
from .operators.outliers import gap_profile, knee_per_dataset, knee_threshold, leaf_radii, mark_outliers
from .plans.workloads import built
from .session import SpatialSearch
from .sources import repositories as rp
from .sources.sinks import write_result

SIX = 6


def first_id(points: DataFrame) -> str:
    return points.agg(F.min("dataset_id")).first()[0]


def last_id(points: DataFrame) -> str:
    return points.agg(F.max("dataset_id")).first()[0]


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, SIX) for c in columns})


def run_frame(spark: SparkSession, run: sd.Run, score: str = "distance", kind: type = float) -> DataFrame:
    rows = [(i, round(v, SIX) if kind is float else int(v), r + 1) for r, (v, i) in enumerate(run.rows)]
    return spark.createDataFrame(rows, f"dataset_id string, {score} {'double' if kind is float else 'long'}, rank int")


def means(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c) + osql.OFF_HALF, SIX) for c in sides("o")})


def sides(*names: str) -> list[str]:
    return [f"{n}{i}" for n in names for i in (0, 1)]


def clean_run(handle: str, search: Callable, score: str = "distance", kind: type = float):
    """A search on the index as it is by default, cleaned."""

    def run(s, d):
        i = built(s, d, handle, clean=True)
        return run_frame(s, search(i, first_id(i.roots)), score, kind)

    return run


def middle_box(index: ix.SearchIndex, q: str) -> Box:
    r = index.roots.filter(F.col("dataset_id") == q).first()
    side = [r[f"hi{j}"] - r[f"lo{j}"] for j in (0, 1)]
    return Box(tuple(r[f"lo{j}"] + side[j] * 0.25 for j in (0, 1)), tuple(r[f"hi{j}"] - side[j] * 0.25 for j in (0, 1)))


def clean_range_points(s, d):
    i = built(s, d, "ev_user", clean=True)
    q = first_id(i.roots)
    return rounded(sp.range_points(i, middle_box(i, q), q), *sides("c"))


def clean_nearest(s, d):
    i = built(s, d, "ev_user", clean=True)
    return rounded(sp.nearest_points(i, first_id(i.roots), last_id(i.roots)), "distance")


def clean_range_datasets(s, d):
    i = built(s, d, "ev_home", clean=True)
    r, e = i.roots.filter(F.col("dataset_id") == first_id(i.roots)).first(), [0.02 * (b - a) for a, b in zip(i.spec.lo, i.spec.hi)]
    return sd.range_datasets(i, Box(tuple(r[f"lo{j}"] - e[j] for j in (0, 1)), tuple(r[f"hi{j}"] + e[j] for j in (0, 1)))).select("dataset_id", "n")


def raw_and_clean(s, d):
    """The search that cleaning is there for, on both indexes, with the points that cleaning leaves of each result."""
    raw, own = built(s, d, "ev_home"), built(s, d, "ev_home", clean=True)
    q = first_id(raw.roots)
    both = run_frame(s, base.raw_hausdorff_topk(raw, q)).withColumn("variant", F.lit("raw")).unionByName(run_frame(s, sd.topk_hausdorff(own, q)).withColumn("variant", F.lit("clean")))
    return both.join(own.roots.select("dataset_id", F.col("n").alias("n_kept")), "dataset_id")


def tree_nodes(strategy: str, handle: str = "ev_user"):
    def run(s, d):
        nodes = build_bottom(rp.repository(s, d, handle), strategy=strategy).filter("kind = 0")
        return means(rounded(nodes, "radius", *sides("lo", "hi"))).select("dataset_id", "path", "n", "radius", "is_leaf", *sides("o", "lo", "hi"))

    return run


def tree_leaf_points(s, d):
    points = build_bottom(rp.repository(s, d, "ev_user")).filter("kind = 1")
    return points.select("dataset_id", "point_id", F.col("path").alias("leaf_path"), F.round("radius", SIX).alias("leaf_distance"))


def of_tree(handle: str, make: Callable[[SparkSession, DataFrame], DataFrame]):
    return lambda s, d: make(s, checkpointed(build_bottom(rp.repository(s, d, handle))))


def gaps(order: str):
    return lambda s, tree: rounded(gap_profile(leaf_radii(tree), order).select("rank", "radius", "gap"), "radius", "gap").withColumn("rank", F.col("rank").cast("long"))


def knee(order: str):
    return lambda s, tree: s.createDataFrame([(round(knee_threshold(leaf_radii(tree), order), SIX),)], "threshold double")


def removed_points(s, tree):
    return _gone(mark_outliers(tree, knee_threshold(leaf_radii(tree))))


def _gone(marked: DataFrame) -> DataFrame:
    some = marked.groupBy("dataset_id").agg(F.max("kept").alias("some"))
    return marked.join(some, "dataset_id").filter("some AND NOT kept").select("dataset_id", "point_id")


def refreshed_roots(s, d):
    roots = built(s, d, "ev_user", clean=True).roots
    return means(rounded(roots, "radius", *sides("lo", "hi"))).select("dataset_id", "n", "radius", *sides("o", "lo", "hi"))


def refreshed_nodes(s, d):
    return rounded(built(s, d, "ev_user", clean=True).tree.filter("kind = 0").select("dataset_id", "path", "n", *sides("lo", "hi")), *sides("lo", "hi"))


def summary(s, d):
    return rounded(summarise_nodes(rp.repository(s, d, "ev_user"), ["dataset_id"]).select("dataset_id", "n", "radius"), "radius")


def radius_bins(s, d):
    return ix.radius_distribution(built(s, d, "ev_user")).select(F.col("bin").cast("long").alias("bin"), "leaves", "max_depth")


def space(s, d):
    return ix.index_space(built(s, d, "ev_user")).filter(F.col("part").isin("tree", "roots", "members", "cells")).select("part", "n_rows")


def _pair(index: ix.SearchIndex, prefix: str) -> DataFrame:
    """All other roots beside the query's, as columns of that prefix."""
    q = first_id(index.roots)
    one = index.roots.filter(F.col("dataset_id") == q).select(F.col("radius").alias(f"{prefix}_r"), *(F.col(c).alias(f"{prefix}_{c}") for c in sides("o", "lo", "hi")))
    return index.roots.filter(F.col("dataset_id") != q).join(F.broadcast(one))


def ball_bounds(s, d):
    a, b, r = vec("q_o", 2), vec("o", 2), F.col("radius")
    got = _pair(built(s, d, "ev_home"), "q").select("dataset_id", ball_lower(a, b, r).alias("lower"), ball_upper(a, F.col("q_r"), b, r).alias("upper"), ball_gap(a, F.col("q_r"), b, r).alias("gap"))
    return rounded(got, "lower", "upper", "gap")


def box_bounds(s, d):
    a = vec("q_lo", 2), vec("q_hi", 2), vec("lo", 2), vec("hi", 2)
    return rounded(_pair(built(s, d, "ev_home"), "q").select("dataset_id", box_lower(*a).alias("lower"), box_upper(*a).alias("upper")), "lower", "upper")


def upper_nodes(s, d):
    return means(rounded(built(s, d, "ev_home").upper.select("path", "n_datasets", "n", *sides("lo", "hi", "o")), *sides("lo", "hi")))


def upper_cells(s, d):
    return built(s, d, "ev_home").upper_cells.groupBy("path").agg(F.count(F.lit(1)).alias("n_cells"))


def upper_bounds(s, d):
    """Bounds of the upper nodes for the query: area shared by the boxes, and the query's cells that occur below."""
    i = built(s, d, "ev_home")
    q = sd.as_outline(i, first_id(i.roots))
    shared = i.upper_cells.join(F.broadcast(q.cells.distinct()), "cell").groupBy("path").agg(F.count(F.lit(1)).alias("gbo_bound"))
    ia = i.upper.select("path", F.round(box_overlap(vec("lo", 2), vec("hi", 2), constants(q.lo), constants(q.hi)), SIX).alias("ia_bound"))
    return ia.join(shared, "path", "left").select("path", "ia_bound", F.coalesce("gbo_bound", F.lit(0)).alias("gbo_bound"))


def z_corners(s, d):
    p = rp.repository(s, d, "ev_user")
    spec = GridSpec.from_extent(rp.repository_extent(p), 5)
    lo, hi = z_decode(F.col("cell"), spec)
    return signatures(p, spec).select("cell").distinct().select("cell", *(F.round(x, SIX).alias(f"{n}{i}") for n, c in (("lo", lo), ("hi", hi)) for i, x in enumerate(c)))


def saved(s, d):
    """Stored in the shared folder, loaded again and searched."""
    path = f"{checkpoint_dir(s)}/index-{uuid.uuid4().hex}"
    ix.save(built(s, d, "ev_home"), path, buckets=4)
    i = ix.load(s, path)
    return run_frame(s, sd.topk_hausdorff(i, first_id(i.roots)))


def appended(s, d):
    """Built from half of the datasets, the others appended."""
    p = rp.repository(s, d, "ev_home")
    half = F.col("dataset_id").cast("long") % 2 == 0
    i = ix.append_datasets(ix.build_index(p.filter(half), clean=False, spec=GridSpec.from_extent(rp.repository_extent(p))), p.filter(~half))
    return run_frame(s, sd.topk_hausdorff(i, first_id(i.roots)))


def grown(s, d):
    """Built from half of the points of every dataset, then given all points."""
    p = rp.repository(s, d, "ev_home")
    i = ix.grow_datasets(ix.build_index(p.filter("point_id % 2 = 0"), clean=False, spec=GridSpec.from_extent(rp.repository_extent(p))), p)
    return run_frame(s, sd.topk_gbo(i, first_id(i.roots)), "score", int)


def filtered(s, d):
    i = built(s, d, "ev_home")
    q = first_id(i.roots)
    keep = i.roots.filter((F.col("dataset_id").cast("long") % 3 == 0) | (F.col("dataset_id") == q)).select("dataset_id")
    return run_frame(s, sd.topk_hausdorff(i.where(keep), q))


def approximate(s, d):
    """Every dataset: its true distance and whether the approximate one is within twice the error bound."""
    i = built(s, d, "ev_home")
    q, n = first_id(i.roots), i.roots.count()
    near, eps = {x: v for v, x in sd.topk_hausdorff(i, q, n, mode="approx").rows}, i.spec.epsilon()
    rows = [(x, round(v, SIX), x in near and abs(near[x] - v) <= 2 * eps) for v, x in sd.topk_hausdorff(i, q, n).rows]
    return s.createDataFrame(rows, "dataset_id string, exact double, within boolean")


def exemplars(s, d):
    i = built(s, d, "ev_home")
    got = sd.compare_measures(i, first_id(i.roots), 5)
    return rounded(got.select("query_id", "method", "rank", "dataset_id", "value", "shared_with"), "value")


def dispatched(s, d):
    """The dispatcher under each named measure."""
    i = built(s, d, "ev_home")
    out = None
    for m in ("ia", "gbo", "hausdorff"):
        one = sd.exemplar_search(i, first_id(i.roots), 5, m)
        value = F.col("distance" if m == "hausdorff" else "score").cast("double")
        one = one.select("query_id", "method", "rank", "dataset_id", F.round(value, SIX).alias("value"))
        out = one if out is None else out.unionByName(one)
    return out


def batch(measure: str, k: int):
    def run(s, d):
        i = built(s, d, "ev_home")
        ids = [r[0] for r in i.roots.select("dataset_id").collect()]
        return sd.exemplar_batch(i, ids, k, measure).select("query_id", F.col("rank").cast("int").alias("rank"), "dataset_id", F.round(F.col("score").cast("double"), SIX).alias("score"))

    return run


def centre_measure(s, d):
    """A measure of a user's: the distance of the centres, bounded by itself."""
    i = built(s, d, "ev_home")

    def exact(index, q, ids):
        near = index.roots.join(ids, "dataset_id", "left_semi")
        return near.select("dataset_id", ball_upper(constants(q.o), F.lit(0.0), vec("o", 2), F.lit(0.0)).alias("distance"))

    own = sd.Measure(lambda q, d_: ball_lower(constants(q.o), vec("o", d_), F.lit(0.0)), exact)
    return run_frame(s, sd.custom_topk(i, first_id(i.roots), own, 10))


def range_points_all(s, d):
    i = built(s, d, "ev_user")
    return rounded(sp.range_points(i, middle_box(i, first_id(i.roots)), i.roots.select("dataset_id")), *sides("c"))


def drill_down(s, d):
    """Example, the datasets most like it, their points in a rectangle."""
    i = built(s, d, "ev_home")
    q = first_id(i.roots)
    return rounded(SpatialSearch(i).similar(q, 3, "ia").points(middle_box(i, q)), *sides("c"))


def enriched(s, d):
    i = built(s, d, "ev_user")
    got = sp.enrich(sp.nearest_points(i, first_id(i.roots), last_id(i.roots)), rp.load_table(s, d, "events"), ["event_type"], "event_id")
    return got.select("q_point_id", "d_point_id", "event_type")


def rtree_boxes(s, d):
    tree = base.build_rtree(rp.repository(s, d, "li_supp"), 10).filter("level = 0")
    return rounded(tree.select("dataset_id", F.col("node").cast("long").alias("node"), "n", *sides("lo", "hi")), *sides("lo", "hi"))


def separate_sizes(s, d):
    """Points per dataset, from the roots of the separate ball tree."""
    p = rp.repository(s, d, "ev_user")
    return base.separate_indexes(p, GridSpec.from_extent(rp.repository_extent(p)))["roots"].select("dataset_id", "n")


def neighbours(s, d):
    return base.neighbour_count_clean(rp.repository(s, d, "ev_user"), 20.0, 2).select("dataset_id", "point_id")


def emd(s, d):
    from .operators.emd import topk_emd

    i = built(s, d, "ev_home")
    return rounded(topk_emd(i, first_id(i.roots), 5), "distance")


def sql_functions(s, d):
    from .functions.sql_surface import register

    register(s)
    rp.repository(s, d, "ev_user").createOrReplaceTempView("carto_ev_user")
    return s.sql("SELECT dataset_id, round(max(distance_2d(c0, c1, 0.0, 0.0)), 6) AS length, min(z_cell_2d(c0, c1, 0.0, 0.0, 64.0, 64.0, 5)) AS cell FROM carto_ev_user GROUP BY dataset_id")


def table_function(s, d):
    """A search as a table function of a statement."""
    from .functions.sql_surface import register_search

    i = built(s, d, "ev_home")
    q = first_id(i.roots)
    register_search(s, i, [q], "carto_search")
    return rounded(s.sql(f"SELECT * FROM carto_search('hausdorff', 15, '{q}')"), "value")


def streamed(make: Callable):
    """What a stream over the event files has given after its last batch."""

    def run(s, d):
        from .streaming import points as st

        events = st.stream_events(s, d, "events.parquet")
        return make(s, d, st, st.stream_points(events, "ev_user"))

    return run


def latest(df: DataFrame, by: str, order: str) -> DataFrame:
    w = Window.partitionBy(by).orderBy(F.desc(order))
    return df.withColumn("_r", F.row_number().over(w)).filter("_r = 1").drop("_r")


def _spec(s, d) -> GridSpec:
    return GridSpec.from_extent(rp.repository_extent(rp.repository(s, d, "ev_user")), 5)


def s_roots(s, d, st, points):
    got = latest(st.to_files(st.stream_roots(points), "update"), "dataset_id", "n")
    return rounded(got.select("dataset_id", "n", "lo1", "hi1", F.col("radius").alias("radius_bound") if "radius" in got.columns else F.col("radius_bound")), "lo1", "hi1", "radius_bound")


def s_cells(s, d, st, points):
    return st.to_files(st.stream_cells(points, _spec(s, d), "4000 days"), "append").select("dataset_id", "cell")


def s_slices(s, d, st, points):
    got = st.to_files(st.stream_slices(points, "1 day", lateness="4000 days"), "update")
    got = got.withColumn("start", F.date_format("start", "yyyy-MM-dd")).withColumn("key", F.concat("dataset_id", F.lit("|"), "start"))
    return rounded(latest(got, "key", "n").select("dataset_id", "start", "n", "lo1", "hi1"), "lo1", "hi1")


def s_box(s, d, st, points):
    return st.to_files(st.stream_range_points(points, Box((10.0, 5.0), (300.0, 40.0))), "append").select("dataset_id", "point_id")


def s_fences(s, d, st, points):
    fences = s.createDataFrame([("a", 0.0, 0.0, 100.0, 20.0), ("b", 50.0, 10.0, 400.0, 60.0)], "fence string, qlo0 double, qlo1 double, qhi0 double, qhi1 double")
    return st.to_files(st.stream_fences(points, fences), "append").select("dataset_id", "point_id", "fence")


def s_gbo(s, d, st, points):
    cells = built(s, d, "ev_user").cells
    q = cells.filter(F.col("dataset_id") == first_id(cells)).select("cell")
    return latest(st.to_files(st.stream_gbo(points, _spec(s, d), q), "update"), "dataset_id", "score").select("dataset_id", "score")


def s_index(s, d, st, points):
    """An index that a stream has filled from nothing but one dataset's first point, searched."""
    p = rp.repository(s, d, "ev_user")
    start = p.filter(F.col("dataset_id") == first_id(p)).orderBy("point_id").limit(1)
    held = [ix.build_index(start, clean=False, spec=GridSpec.from_extent(rp.repository_extent(p)))]
    st.stream_index_append(points, held, f"{checkpoint_dir(s)}/stream-{uuid.uuid4().hex}").awaitTermination()
    return run_frame(s, sd.topk_hausdorff(held[0], first_id(held[0].roots)))


def trips(s, d):
    events = rp.load_table(s, d, "events").withColumn("dataset_id", F.col("user_id").cast("string")).withColumn("ts", F.col("ts").cast("timestamp"))
    got = rp.split_trips(events, "dataset_id", "ts", "12 HOURS").withColumn("ms", F.unix_millis("ts"))
    return got.groupBy("dataset_id", F.col("trip").cast("long").alias("trip")).agg(F.count(F.lit(1)).alias("n"), F.min("ms").alias("first_ms"), F.max("ms").alias("last_ms"))


def slices(s, d):
    events = rp.load_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return rp.slice_by_time(events, "ts", "6 hours").groupBy(F.date_format("slice", "yyyy-MM-dd HH:mm").alias("slice")).agg(F.count(F.lit(1)).alias("n"))


def around(s, d):
    i = built(s, d, "ev_user")
    root = i.roots.filter(F.col("dataset_id") == first_id(i.roots)).first()
    return sp.range_points(i, rp.range_around(root, 3, i.spec), i.roots.select("dataset_id")).select("dataset_id", "point_id")


def rescaled(s, d):
    return rounded(rp.repository(s, d, "ev_user", scale="unit").select("dataset_id", "point_id", *sides("c")), *sides("c"))


def files(s, d):
    """Three datasets through CSV, JSON and text files and back; a file is a dataset."""
    part = rp.load_table(s, d, "part").select(F.col("p_brand").alias("brand"), F.col("p_size").cast("double").alias("x"), F.col("p_retailprice").alias("y"))
    brands = [r[0] for r in part.select("brand").distinct().orderBy("brand").limit(3).collect()]
    out = None
    for brand, fmt in zip(brands, ("csv", "json", "parquet")):
        path = f"{checkpoint_dir(s)}/files-{uuid.uuid4().hex}"
        write_result(part.filter(F.col("brand") == brand).select("x", "y").coalesce(1), path, fmt)
        one = rp.read_point_files(s, path, fmt, ["x", "y"], "x double, y double").select(F.lit(brand).alias("brand"), *(F.round(c, SIX).alias(c) for c in sides("c")))
        out = one if out is None else out.unionByName(one)
    return out


#: name: (query, SQL)
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "hausdorff_topk_clean_ev_home": (clean_run("ev_home", sd.topk_hausdorff), osql.cleaned("ev_home", sql.haus_topk("ev_home"))),
    "hausdorff_topk_clean_ev_user": (clean_run("ev_user", sd.topk_hausdorff), osql.cleaned("ev_user", sql.haus_topk("ev_user"))),
    "hausdorff_symmetric_topk_clean": (clean_run("ev_home", lambda i, q: sd.symmetric_topk(i, q, 5)), osql.cleaned("ev_home", sql.symmetric("ev_home", 5))),
    "ia_topk_clean_ev_home": (clean_run("ev_home", sd.topk_ia, "score"), osql.cleaned("ev_home", sql.ia_topk("ev_home"))),
    "gbo_topk_clean_ev_home": (clean_run("ev_home", sd.topk_gbo, "score", int), osql.cleaned_cells("ev_home", sql.gbo_topk("ev_home"))),
    "range_datasets_clean": (clean_range_datasets, osql.cleaned("ev_home", sql.range_datasets("ev_home", 0.02)).replace("ext AS (SELECT max(c0) - min(c0) AS e0, max(c1) - min(c1) AS e1 FROM p)", "ext AS (SELECT max(c0) - min(c0) AS e0, max(c1) - min(c1) AS e1 FROM raw)")),
    "range_points_clean": (clean_range_points, osql.cleaned("ev_user", sql.range_points("ev_user"))),
    "nearest_points_clean": (clean_nearest, osql.cleaned("ev_user", sql.nearest("ev_user"))),
    "gap_profile_leaf_radii": (of_tree("ev_user", gaps("desc")), osql.gap_profile("ev_user")),
    "gap_profile_ascending": (of_tree("ev_user", gaps("asc")), osql.gap_profile("ev_user", "ASC")),
    "knee_leaf_radii": (of_tree("ev_user", knee("desc")), osql.threshold("ev_user")),
    "knee_leaf_radii_ev_home": (of_tree("ev_home", knee("desc")), osql.threshold("ev_home")),
    "knee_leaf_radii_ascending": (of_tree("ev_user", knee("asc")), osql.threshold("ev_user", "ASC")),
    "knee_per_dataset": (of_tree("ev_user", lambda s, t: rounded(knee_per_dataset(leaf_radii(t)), "threshold")), osql.per_dataset_threshold("ev_user")),
    "outlier_filter_repository": (of_tree("ev_user", removed_points), osql.outliers("ev_user")),
    "outlier_filter_ev_home": (of_tree("ev_home", removed_points), osql.outliers("ev_home")),
    "refreshed_roots": (refreshed_roots, osql.refreshed_roots("ev_user")),
    "refreshed_nodes": (refreshed_nodes, osql.refreshed_nodes("ev_user")),
    "build_index_groups": (tree_nodes("groups"), osql.tree_nodes("ev_user")),
    "build_index_levels": (tree_nodes("levels"), osql.tree_nodes("ev_user")),
    "tree_leaf_points": (tree_leaf_points, osql.tree_points("ev_user")),
    "node_summary": (summary, osql.summary("ev_user")),
    "radius_histogram": (radius_bins, osql.radius_bins("ev_user")),
    "index_space": (space, osql.space("ev_user")),
    "ball_bounds": (ball_bounds, osql.ball_bounds("ev_home")),
    "box_bounds": (box_bounds, osql.box_bounds("ev_home")),
    "upper_nodes": (upper_nodes, osql.upper_nodes("ev_home")),
    "upper_signatures": (upper_cells, osql.upper_cells("ev_home")),
    "upper_bounds": (upper_bounds, osql.upper_bounds("ev_home")),
    "z_corners": (z_corners, osql.z_corners("ev_user")),
    "saved_index_topk": (saved, sql.haus_topk("ev_home")),
    "appended_index_topk": (appended, sql.haus_topk("ev_home")),
    "grown_index_topk": (grown, sql.gbo_topk("ev_home")),
    "filtered_topk": (filtered, osql.filtered("ev_home", "CAST(dataset_id AS BIGINT) % 3 = 0")),
    "approx_hausdorff_all": (approximate, osql.approximate("ev_home", 10)),
    "compare_measures": (exemplars, osql.exemplars("ev_home", 5)),
    "exemplar_search": (dispatched, f"SELECT query_id, method, rank, dataset_id, value FROM ({osql.exemplars('ev_home', 5)}) x"),
    "hausdorff_batch": (batch("hausdorff", 5), osql.hausdorff_batch("ev_home", 5)),
    "ia_batch": (batch("ia", 5), osql.ia_batch("ev_home", 5)),
    "gbo_batch": (batch("gbo", 5), osql.gbo_batch("ev_home", 5)),
    "custom_measure_topk": (centre_measure, osql.centre_topk("ev_home", 10)),
    "range_points_all": (range_points_all, osql.range_points_all("ev_user")),
    "drill_down": (drill_down, osql.drill_down("ev_home", 3)),
    "enriched_neighbours": (enriched, osql.enriched("ev_user")),
    "rtree_boxes": (rtree_boxes, osql.rtree("li_supp", 10)),
    "separate_indexes": (separate_sizes, osql.isolated_sizes("ev_user")),
    "neighbour_count_clean": (neighbours, osql.neighbours("ev_user", 20.0, 2)),
    "emd_topk": (emd, osql.emd("ev_home", 5)),
    "sql_functions": (sql_functions, osql.sql_functions("ev_user")),
    "sql_table_function": (table_function, osql.table_function("ev_home", 15)),
    "stream_roots": (streamed(s_roots), osql.stream_roots("ev_user")),
    "stream_cells": (streamed(s_cells), sql.z_signatures("ev_user")),
    "stream_slices": (streamed(s_slices), osql.stream_slices()),
    "stream_range_points": (streamed(s_box), osql.stream_box("ev_user")),
    "stream_fences": (streamed(s_fences), osql.stream_fences("ev_user")),
    "stream_gbo": (streamed(s_gbo), osql.stream_gbo("ev_user")),
    "stream_index_topk": (streamed(s_index), sql.haus_topk("ev_user")),
    "split_trips": (trips, osql.trips(12 * 3_600_000)),
    "time_slices": (slices, osql.slices()),
    "range_around_points": (around, osql.around("ev_user", 3)),
    "rescaled_points": (rescaled, osql.rescaled("ev_user")),
    "point_files": (files, osql.files()),
    "raw_and_clean_topk": (raw_and_clean, ""),
}
