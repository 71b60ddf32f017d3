"""The index and its searches against scans, and invariants of each."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cartosearch.model import Box, GridSpec
from cartosearch.operators import baselines as base
from cartosearch.operators import frontier
from cartosearch.operators import index as ix
from cartosearch.operators import search_datasets as sd
from cartosearch.operators import search_points as sp
from cartosearch.operators.bottom_index import build_bottom, tree_points
from cartosearch.operators.measures import hausdorff_scan
from cartosearch.operators.outliers import gap_profile, knee_per_dataset, knee_threshold, leaf_radii, mark_outliers, remove_outliers
from cartosearch.operators.upper_index import build_upper
from cartosearch.plans import metrics
from cartosearch.plans.workloads import injected
from cartosearch.session import SpatialSearch
from cartosearch.sources.repositories import combine_queries, pick_queries, repository

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def points(spark):
    return repository(spark, SF, "ev_home").cache()


@pytest.fixture(scope="module")
def index(points):
    return ix.build_index(points, f=5, clean=False)


@pytest.fixture(scope="module")
def truth(points):
    rows = hausdorff_scan(points, "1").collect()
    return sorted((r["distance"], r["dataset_id"]) for r in rows)


def test_exact_topk_equals_scan(index, truth):
    q = "1"
    for run in (sd.topk_hausdorff(index, q, 5), sd.topk_hausdorff(index, q, 5, wave=1), base.box_bound_topk(index, q, 5), base.box_incremental_topk(index, q, 5)):
        assert [i for _, i in run.rows] == [i for _, i in truth[:5]]
        assert np.allclose([v for v, _ in run.rows], [v for v, _ in truth[:5]])
    everything = sd.topk_hausdorff(index, q, 1000).rows
    assert [i for _, i in everything] == [i for _, i in truth]
    eps = index.spec.epsilon()
    near = {i: v for v, i in sd.topk_hausdorff(index, q, 1000, mode="approx").rows}
    assert len(near) == len(truth) and all(abs(near[i] - v) <= 2 * eps for v, i in truth)


def test_search_is_cheaper_than_baselines(spark):
    index = ix.build_index(repository(spark, SF, "li_fort"), clean=False)
    q = pick_queries(index.roots, 1)[0]
    own, approx = sd.topk_hausdorff(index, q), sd.topk_hausdorff(index, q, mode="approx")
    bound = base.box_bound_topk(index, q)
    n = index.roots.filter(F.col("dataset_id") == q).first()["n"]
    assert own.metrics["evaluations"] < bound.metrics["evaluations"] < n * index.points.count()
    assert approx.metrics["evaluations"] <= own.metrics["evaluations"]
    assert metrics.overlap_accuracy(approx.rows, own.rows, 10) >= metrics.overlap_accuracy(sd.topk_gbo(index, q).rows, own.rows, 10)


def test_frontier_equals_scan(index, truth):
    q = index.tree.filter(F.col("dataset_id") == "1")
    got = {r["dataset_id"]: r["distance"] for r in frontier.hausdorff(q, index.tree.filter(F.col("dataset_id") != "1")).collect()}
    assert got.keys() == {i for _, i in truth} and all(got[i] == pytest.approx(v) for v, i in truth)
    some = frontier.hausdorff(q, index.tree.filter(F.col("dataset_id") != "1"), tau=truth[3][0]).collect()
    assert {i for _, i in truth[:4]} <= {r["dataset_id"] for r in some}


def test_group_and_level_trees_agree(points):
    rows = lambda t: sorted((r["dataset_id"], r["path"], r["n"], r["is_leaf"], round(r["radius"], 9), round(r["o0"], 9)) for r in t.filter("kind = 0").collect())
    assert rows(build_bottom(points, 5, "groups")) == rows(build_bottom(points, 5, "levels"))
    mixed = build_bottom(points, 5, max_group_rows=70)
    assert rows(mixed) == rows(build_bottom(points, 5, "groups"))


def test_upper_tree(index):
    nodes = {r["path"]: r for r in index.upper.collect()}
    assert nodes[""]["n_datasets"] == index.roots.count()
    for r in index.members.join(index.roots, "dataset_id").collect():
        for k in range(len(r["path"]) + 1):
            n = nodes[r["path"][:k]]
            away = np.hypot(r["o0"] - n["o0"], r["o1"] - n["o1"])
            assert away + r["radius"] <= n["radius"] + 1e-9 and n["lo0"] <= r["lo0"] and n["hi1"] >= r["hi1"]
    cells = {(r["path"], r["cell"]) for r in index.upper_cells.collect()}
    own = {("", r["cell"]) for r in index.cells.select("cell").distinct().collect()}
    assert own == {x for x in cells if x[0] == ""}
    split, members = build_upper(index.roots, 2, max_rows=4)
    assert members.count() == index.roots.count() and split.filter("path = ''").first()["n_datasets"] == index.roots.count()


def test_upper_split_with_an_empty_side(spark):
    roots = spark.createDataFrame([(str(i), 1, 0.0, x, 0.0, x, 0.0, h, 0.0) for i, (x, h) in enumerate([(0.0, 0.0), (0.1, 0.1), (0.2, 0.2), (0.3, 100.0)])], "dataset_id string, n long, radius double, o0 double, o1 double, lo0 double, lo1 double, hi0 double, hi1 double")
    nodes, _ = build_upper(roots, 1)
    assert nodes.filter("is_leaf").count() == 4


def test_knee_fixture(spark):
    radii = spark.createDataFrame([("d", x) for x in (1.5, 10.0, 2.0, 1.0, 6.0, 1.2)], "dataset_id string, radius double")
    gaps = lambda *a: [round(r["gap"], 6) for r in gap_profile(radii, *a).orderBy("rank").collect()]
    assert gaps() == [0, 2.5, 5, 4, 2.8, 1.5] and gaps("desc", "steps") == [0, 2.2, 4.4, 3.1, 1.6, 0]
    assert gaps("asc") == [0, 1.3, 2.5, 3.5, 1, -1.5]
    assert {knee_threshold(radii, o, c) for o in ("desc", "asc") for c in ("count", "steps")} == {2.0}
    assert knee_per_dataset(radii).first()["threshold"] == 2.0
    flat = spark.createDataFrame([("d", 3.0)] * 4, "dataset_id string, radius double")
    assert knee_threshold(flat) == 3.0
    assert abs(knee_threshold(radii, approx=True) - 2.0) < 1e-9


def test_cleaning_fixtures(spark):
    rows = [("a", i, float(x), float(y)) for i, (x, y) in enumerate([(0, 0), (1, 0), (0, 1), (1, 1), (20, 20)])] + [("b", i, float(x), 0.0) for i, x in enumerate((0, 10))]
    points = spark.createDataFrame(rows, "dataset_id string, point_id long, c0 double, c1 double")
    tree = build_bottom(points, 10)
    got = {r["dataset_id"]: r for r in remove_outliers(tree, 10.0).filter("kind = 0 AND path = ''").collect()}
    assert got["a"]["n"] == 4 and (got["a"]["o0"], round(got["a"]["radius"], 4)) == (0.5, 0.7071)
    assert remove_outliers(tree, 4.0, on_empty="drop").filter("dataset_id = 'b'").count() == 0
    assert tree_points(remove_outliers(tree, 4.0)).filter("dataset_id = 'b'").count() == 2


def test_cleaning_finds_injected_points(points):
    moved = injected(points)
    raw = ix.build_index(moved.drop("injected"), clean=False)
    marked = mark_outliers(raw.tree, knee_threshold(leaf_radii(raw.tree))).join(moved.select("dataset_id", "point_id", "injected"), ["dataset_id", "point_id"])
    hit = marked.filter("injected AND NOT kept").count()
    assert hit >= 0 and marked.filter("NOT kept").count() < marked.count() / 2
    clean = ix.build_index(moved.drop("injected"))
    assert clean.variant == "clean" and clean.points.count() <= raw.points.count()


@pytest.mark.parametrize("f", [3, 20])
def test_overlap_does_not_depend_on_fanout(points, index, f):
    other = ix.build_index(points, f=f, clean=False)
    assert sd.topk_ia(other, "3").rows == sd.topk_ia(index, "3").rows
    assert sd.topk_gbo(other, "3").rows == sd.topk_gbo(index, "3").rows == sd.topk_gbo(index, "3", plan="inverted").rows


def test_range_searches(index, points):
    r = index.roots.filter("dataset_id = '2'").first()
    box = Box((r["lo0"] - 30, r["lo1"] - 30), (r["hi0"] + 30, r["hi1"] + 30))
    ids = lambda df: sorted(x["dataset_id"] for x in df.collect())
    assert ids(sd.range_datasets(index, box)) == ids(base.scan_range_datasets(points, box))
    small = Box((r["o0"] - 5, r["o1"] - 20), (r["o0"] + 60, r["o1"] + 20))
    keys = lambda df: sorted((x["dataset_id"], x["point_id"]) for x in df.collect())
    assert keys(sp.range_points(index, small, "2")) == keys(base.scan_range_points(points, small, "2"))
    assert sp.range_points(index, Box((-1e6, -1e6), (1e6, 1e6)), "2").count() == r["n"]
    touching = Box((r["hi0"], r["hi1"]), (r["hi0"] + 1, r["hi1"] + 1))
    assert "2" in ids(sd.range_datasets(index, touching))


def test_nearest_points_strategies(index):
    rows = lambda df: sorted((x["q_point_id"], x["rank"], x["d_point_id"], round(x["distance"], 9)) for x in df.collect())
    want = rows(sp.nearest_points(index, "1", "4", 1, "early_break"))
    for s in ("leaf_join", "per_point", "from_hausdorff"):
        assert rows(sp.nearest_points(index, "1", "4", 1, s)) == want
    assert rows(sp.nearest_points(index, "1", "4", 4)) == rows(sp.nearest_points(index, "1", "4", 4, "early_break"))
    many = sp.nearest_points(index, "1", "4", 10_000).groupBy("q_point_id").count().agg(F.min("count")).first()[0]
    assert many == index.roots.filter("dataset_id = '4'").first()["n"]
    assert sp.nearest_points(index, combine_queries(index.points, ["1", "2"], "u"), "4").count() > 0


def test_symmetric_custom_and_pairs(index, points, truth):
    both = sorted((r["distance"], r["dataset_id"]) for r in hausdorff_scan(points, "1", symmetric=True).collect())
    assert [i for _, i in sd.symmetric_topk(index, "1", 3).rows] == [i for _, i in both[:3]]
    from cartosearch.functions.geometry import ball_lower, constants, vec

    measure = sd.Measure(lambda q, d: ball_lower(constants(q.o), vec("o", d), F.col("radius")), lambda i, q, ids: hausdorff_scan(i.points, q.id).join(ids, "dataset_id"))
    assert [i for _, i in sd.custom_topk(index, "1", measure, 4).rows] == [i for _, i in truth[:4]]
    t = truth[2][0]
    near = {(r["q_id"], r["dataset_id"]) for r in sd.similar_pairs(index, t).collect()}
    assert {("1", i) for v, i in truth if v <= t} == {p for p in near if p[0] == "1"}


def test_store_and_append(index, points, tmp_path):
    ix.save(index, str(tmp_path / "i"), 4)
    back = ix.load(points.sparkSession, str(tmp_path / "i"))
    assert back.spec == index.spec and sd.topk_hausdorff(back, "1", 5).rows == sd.topk_hausdorff(index, "1", 5).rows
    part = ix.build_index(points.filter("dataset_id < '5'"), f=5, clean=False, spec=index.spec)
    whole = ix.append_datasets(part, points.filter("dataset_id >= '5'"))
    assert sd.topk_gbo(whole, "1").rows == sd.topk_gbo(index, "1").rows
    with pytest.raises(ValueError):
        ix.append_datasets(whole, points.filter("dataset_id = '1'"))
    assert {r["part"] for r in ix.index_space(index).collect()} == set(ix.FRAMES)


def test_external_query_and_facade(index, points, truth):
    q = points.filter("dataset_id = '1'").withColumn("dataset_id", F.lit("new"))
    rows = sd.topk_hausdorff(index, q, 3).rows
    assert rows[0] == (0.0, "1") and [i for _, i in rows[1:]] == [i for _, i in truth[:2]]
    s = SpatialSearch(index)
    wide = Box((-1e6, -1e6), (1e6, 1e6))
    near = s.range(wide).similar("1", 3, "hausdorff")
    assert {r["dataset_id"] for r in near.datasets.collect()} == {i for _, i in truth[:3]}
    assert near.points(wide).select("dataset_id").distinct().count() == 3
    with pytest.raises(ValueError):
        sd.topk_hausdorff(index, "1", 0)
    with pytest.raises(ValueError):
        sd.topk_ia(index, "nobody")


def test_metamorphic(points, index):
    moved = ix.build_index(points.withColumn("c0", F.col("c0") + 1000).withColumn("c1", F.col("c1") - 500), f=5, clean=False)
    assert np.allclose([v for v, _ in sd.topk_hausdorff(moved, "1", 5).rows], [v for v, _ in sd.topk_hausdorff(index, "1", 5).rows])
    assert np.allclose([v for v, _ in sd.topk_ia(moved, "3").rows], [v for v, _ in sd.topk_ia(index, "3").rows])
    own = sd.topk_gbo(index, "1", 1, exclude_self=False).rows[0]
    assert own == (index.cells.filter("dataset_id = '1'").count(), "1")
    assert GridSpec((0.0, 0.0), (32.0, 64.0), 5).epsilon() == 2.0


def test_search_stops_above_the_leaves(points, index):
    from dataclasses import replace

    assert ix.cut_depth(index.upper) is None
    cut = ix.cut_depth(index.upper, 3)
    short = replace(index, cut=cut)
    assert 0 <= cut < max(r["depth"] for r in index.upper.collect())
    assert sd.topk_ia(short, "3").rows == sd.topk_ia(index, "3").rows
    assert sd.topk_gbo(short, "3").rows == sd.topk_gbo(index, "3").rows


def test_batches_equal_single_queries(index):
    for measure, single in (("ia", sd.topk_ia), ("gbo", sd.topk_gbo), ("hausdorff", sd.topk_hausdorff)):
        got = sd.exemplar_batch(index, ["1", "3"], 3, measure).orderBy("query_id", "rank").collect()
        for q in ("1", "3"):
            assert [(r["score"], r["dataset_id"]) for r in got if r["query_id"] == q] == single(index, q, 3).rows
    boxes = index.roots.filter(F.col("dataset_id").isin("1", "3")).select(F.col("dataset_id").alias("query_id"), *(F.col(f"{n}{i}").alias(f"q{n}{i}") for n in ("lo", "hi") for i in (0, 1)))
    pairs = {(r["query_id"], r["dataset_id"]) for r in sd.range_datasets_batch(index, boxes).collect()}
    for r in index.roots.filter(F.col("dataset_id").isin("1", "3")).collect():
        one = sd.range_datasets(index, Box((r["lo0"], r["lo1"]), (r["hi0"], r["hi1"])))
        assert {x["dataset_id"] for x in one.collect()} == {d for q, d in pairs if q == r["dataset_id"]}


def test_aggregates(spark, points, index):
    from cartosearch.functions import aggregates as agg
    from cartosearch.functions.geometry import vec

    c = vec("c", 2)
    got = {r["dataset_id"]: r for r in points.groupBy("dataset_id").agg(agg.dataset_box(c).alias("b"), agg.signature(c, index.spec).alias("z")).collect()}
    far = {r["dataset_id"]: r["r"] for r in points.groupBy("dataset_id").agg(agg.dataset_radius("c0", "c1").alias("r")).collect()}
    for r in index.roots.collect():
        own = got[r["dataset_id"]]
        assert (own["b"]["lo0"], own["b"]["hi1"]) == (r["lo0"], r["hi1"]) and own["z"] == sorted(own["z"]) and far[r["dataset_id"]] == pytest.approx(r["radius"])


def test_queries_read_the_tables_as_they_are(spark, tmp_path):
    from cartosearch import registry

    events = spark.read.parquet(f"{SF}/events.parquet")
    for users, more in ((3, 0.0), (5, 0.0), (5, 50.0)):
        events.filter(F.col("user_id") < users).withColumn("value", F.col("value") + F.when(F.col("user_id") == 1, more).otherwise(0.0)).write.mode("overwrite").parquet(f"{tmp_path}/events.parquet")
        got = {r["dataset_id"]: r["upper"] for r in registry.queries()["box_bounds"](spark, str(tmp_path)).collect()}
        assert len(got) == users - 1
        assert more == 0 or got["1"] > last["1"]
        last = got


def test_blocks_make_the_trees_of_single_datasets(spark, points, monkeypatch):
    """All datasets of a partition at once, with or without large ones beside them: built, cleaned and packed."""
    from cartosearch.checkpoints import checkpointed
    from cartosearch.operators import bottom_index as bi
    from cartosearch.operators import outliers
    from cartosearch.operators.kernels import unpack

    def agree(a, b):
        a, b = (sorted(tuple((r["dataset_id"], r["kind"], r["path"], r["point_id"] or 0, r["n"], bool(r["is_leaf"]), r["radius"], r["o0"], r["o1"], r["lo0"] or 0, r["hi1"] or 0)) for r in t.collect()) for t in (a, b))
        return [x[:6] for x in a] == [x[:6] for x in b] and np.allclose([x[6:] for x in a], [x[6:] for x in b], rtol=1e-12)

    tree = checkpointed(bi.build_bottom(points, 5))
    assert agree(bi.build_groups(points, 5), tree)
    limit = knee_threshold(leaf_radii(tree))
    assert agree(remove_outliers(tree, limit), outliers._remove(tree, limit, "keep"))
    assert agree(remove_outliers(tree, 0.0, on_empty="drop"), outliers._remove(tree, 0.0, "drop"))
    packed = {r["dataset_id"]: unpack(bytes(r["tree"])) for r in bi.packed_trees(tree).collect()}
    roots = {r["dataset_id"]: r for r in bi.dataset_roots(tree).collect()}
    assert packed.keys() == roots.keys() and all(len(packed[i].points) == r["n"] and packed[i].radius[0] == r["radius"] for i, r in roots.items())
    monkeypatch.setattr(bi, "MOST_BLOCK_POINTS", 65)
    assert agree(bi.build_bottom(points, 5), tree)
    assert agree(remove_outliers(tree, limit), outliers._remove(tree, limit, "keep"))
