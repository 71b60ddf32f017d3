"""Bounds, measures and grids against hand fixtures and brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cartosearch.functions.geometry import ball_gap, ball_lower, ball_upper, box_lower, box_upper, constants, point_inside, vec
from cartosearch.functions.zorder import signatures, z_decode, z_id
from cartosearch.model import Box, GridSpec
from cartosearch.operators import kernels
from cartosearch.operators.baselines import bulk_tree
from cartosearch.operators.measures import dataset_boxes, hausdorff_scan, inverted_gbo, scan_gbo, scan_ia, summarise_nodes
from cartosearch.sources.repositories import repository_from

SETS = {"Q": [(1, 1), (2, 3), (3, 2)], "D1": [(2, 2), (3, 3), (4, 1)], "D2": [(6, 6), (7, 7), (6, 7)], "D3": [(1, 1), (2, 3), (3, 2), (8, 8)], "D4": [(5, 1)] * 3}
SPEC = GridSpec((0.0, 0.0), (8.0, 8.0), 2)


def brute(q, d):
    return np.sqrt(((np.asarray(q, float)[:, None] - np.asarray(d, float)[None]) ** 2).sum(axis=2)).min(axis=1).max()


@pytest.fixture(scope="module")
def points(spark):
    df = spark.createDataFrame([(n, float(x), float(y)) for n, s in SETS.items() for x, y in s], "name string, a double, b double")
    return repository_from(df, F.col("name"), [F.col("a"), F.col("b")])


def test_hand_measures(points):
    ia = {r["dataset_id"]: r["score"] for r in scan_ia(dataset_boxes(points), "Q", include_zero=True).collect()}
    assert ia == {"D1": 2.0, "D2": 0.0, "D3": 4.0, "D4": 0.0}
    expected = {"D1": 1, "D3": 2}
    assert {r["dataset_id"]: r["score"] for r in scan_gbo(points, SPEC, "Q").collect()} == expected
    assert {r["dataset_id"]: r["score"] for r in inverted_gbo(signatures(points, SPEC), "Q").collect()} == expected
    h = {r["dataset_id"]: round(r["distance"], 4) for r in hausdorff_scan(points, "Q").collect()}
    assert h == {"D1": 1.4142, "D2": 7.0711, "D3": 0.0, "D4": 4.0}
    both = {r["dataset_id"]: round(r["distance"], 4) for r in hausdorff_scan(points, "Q", symmetric=True).collect()}
    assert both["D3"] == 7.8102 and both["D2"] == 7.0711


def test_hand_signatures_and_summaries(points):
    cells = {r["dataset_id"]: r["cells"] for r in signatures(points, SPEC, "array").collect()}
    assert cells == {"Q": [0, 3], "D1": [3, 4], "D2": [15], "D3": [0, 3, 15], "D4": [4]}
    got = {r["dataset_id"]: r for r in summarise_nodes(points, ["dataset_id"]).collect()}
    assert round(got["D2"]["radius"], 4) == 0.7454 and got["D3"]["o0"] == 3.5 and got["D4"]["radius"] == 0


def test_cells_decode(points):
    lo, hi = z_decode(F.col("z"), SPEC)
    inside = points.withColumn("z", z_id(vec("c", 2), SPEC)).filter(~point_inside(vec("c", 2), lo, hi))
    assert inside.count() == 0
    with pytest.raises(ValueError):
        GridSpec((0.0,) * 9, (1.0,) * 9, 7)


def random_sets(n, d, seed):
    rng = np.random.default_rng(seed)
    for i in range(n):
        kind = i % 5
        a, b = (rng.normal(rng.uniform(0, 5, d), rng.uniform(0.1, 2), (rng.integers(1, 60), d)) for _ in range(2))
        if kind == 1:
            b[:, 0] = b[0, 0]
        if kind == 2:
            a[:] = a[0]
        if kind == 3:
            b = a[: max(1, len(a) // 2)] + 0.01
        yield a, b


@pytest.mark.parametrize("d", [2, 3, 8])
def test_bounds_hold(spark, d):
    rows = []
    for a, b in random_sets(60, d, d):
        o = [x.mean(axis=0) for x in (a, b)]
        r = [np.sqrt(((x - c) ** 2).sum(axis=1)).max() for x, c in zip((a, b), o)]
        rows.append([float(brute(a, b)), float(r[0]), float(r[1]), *map(float, np.concatenate((*o, a.min(0), a.max(0), b.min(0), b.max(0))))])
    names = ["h", "rq", "rd"] + [f"{n}{i}" for n in ("q", "d", "al", "ah", "bl", "bh") for i in range(d)]
    df = spark.createDataFrame(rows, names)
    q, e = vec("q", d), vec("d", d)
    got = df.select("h", ball_lower(q, e, F.col("rd")).alias("lb"), ball_upper(q, F.col("rq"), e, F.col("rd")).alias("ub"), ball_gap(q, F.col("rq"), e, F.col("rd")).alias("gap"), box_lower(vec("al", d), vec("ah", d), vec("bl", d), vec("bh", d)).alias("blb"), box_upper(vec("al", d), vec("ah", d), vec("bl", d), vec("bh", d)).alias("bub")).collect()
    for r in got:
        assert max(r["lb"], r["gap"], r["blb"]) <= r["h"] + 1e-9 <= min(r["ub"], r["bub"]) + 2e-9


@pytest.mark.parametrize("f", [1, 4, 10])
@pytest.mark.parametrize("d", [2, 3])
def test_best_first_is_exact_and_approx_within_bound(d, f):
    for a, b in random_sets(60, d, 10 * d + f):
        truth = brute(a, b)
        q, t = kernels.build_tree(a, f), kernels.build_tree(b, f)
        got = kernels.best_first(q, t)
        assert got.distance == pytest.approx(truth, abs=1e-9)
        assert kernels.best_first(bulk_tree(a, max(2, f)), bulk_tree(b, max(2, f)), bounds="box").distance == pytest.approx(truth, abs=1e-9)
        beyond = kernels.best_first(q, t, tau=truth * 0.9 - 1e-9) if truth > 0 else None
        assert beyond is None or beyond.distance is None or beyond.distance >= truth * 0.9 - 1e-9
        for eps in (0.05, 0.5, 2.0):
            near = kernels.best_first(q, t, mode="approx", eps=eps).distance
            upper = kernels.best_first(q, t, mode="approx", eps=eps, returns="upper").distance
            assert abs(near - truth) <= 2 * eps and truth - 1e-9 <= upper < truth + 3 * eps
        nearest = kernels.drain(q, t, got.frontier)
        assert np.allclose(((q.points - t.points[nearest]) ** 2).sum(axis=1), ((q.points[:, None] - t.points[None]) ** 2).sum(axis=2).min(axis=1))
        places, far, looked = kernels.nearest_in_tree(a, t, 3)
        d2 = ((a[:, None] - b[None]) ** 2).sum(axis=2)
        assert np.allclose(far, np.sqrt(np.sort(d2, axis=1)[:, :3])) and np.allclose(np.sqrt(((a[:, None] - t.points[places]) ** 2).sum(axis=2)), far)
        packed = kernels.unpack(kernels.pack(t))
        assert kernels.best_first(q, packed).distance == got.distance and (packed.ids == t.ids).all()
        i, dist, looked = kernels.early_break(a, b, 2)
        assert np.allclose(dist[:, 0], np.sqrt(d2.min(axis=1))) and looked <= d * len(a) * len(b)


def test_discard_needs_the_gap():
    """Ordering by the whole-dataset bound must not drop parts: the distance here is 0."""
    a, b = np.array([[-1.0, 0], [1, 0]]), np.array([[-1.0, 0], [1, 0]])
    assert kernels.best_first(kernels.build_tree(a, 2), kernels.build_tree(b, 1)).distance == 0


@pytest.mark.parametrize("splitter", ["midpoint", "median", "farthest_pair"])
def test_tree_structure(splitter):
    rng = np.random.default_rng(1)
    for p in (rng.normal(0, 1, (300, 2)), np.repeat(rng.normal(0, 1, (5, 2)), 30, axis=0), np.ones((40, 2)), rng.normal(0, 1, (1, 2))):
        t = kernels.build_tree(p, 7, splitter)
        assert sorted(np.concatenate([t.below(i) - len(t.path) for i in np.flatnonzero(t.leaf)]).tolist()) == list(range(len(p)))
        for i in range(len(t.path)):
            if t.leaf[i]:
                assert t.n[i] <= 7 or (t.hi[i] == t.lo[i]).all() or splitter != "midpoint"
            else:
                c = t.below(i)
                assert t.n[c].sum() == t.n[i] and (t.lo[c] >= t.lo[i]).all() and (t.hi[c] <= t.hi[i]).all()


def test_inputs_are_checked(spark):
    df = spark.createDataFrame([("a", 1.0, float("nan"))], "k string, x double, y double")
    with pytest.raises(Exception, match="NaN"):
        repository_from(df, F.col("k"), [F.col("x"), F.col("y")]).collect()
    assert repository_from(df, F.col("k"), [F.col("x"), F.col("y")], on_bad="drop").count() == 0
    with pytest.raises(ValueError):
        repository_from(df, F.col("k"), [F.col("x")])
    with pytest.raises(ValueError):
        Box((1.0, 0.0), (0.0, 1.0))
    assert constants((1, 2))
