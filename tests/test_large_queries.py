"""Searches with queries and candidates beyond the points that one task takes."""

import pytest

from cartosearch.operators import index as ix
from cartosearch.operators import search_datasets as sd


@pytest.fixture(scope="module")
def points(spark):
    made = [(str(ds), i, ds * 3.0 + (i * 7 % 11) / 4, (i * 5 % 13) / 3 + ds % 2) for ds in range(3) for i in range(10 if ds < 2 else 3)]
    return spark.createDataFrame(made, "dataset_id string, point_id long, c0 double, c1 double").cache()


def test_large_queries_and_candidates(spark, points, monkeypatch):
    index = ix.build_index(points, f=3, clean=False)

    def rounded(run):
        return [(i, round(v, 9)) for v, i in run.rows]

    def boxes_and_cells(q):
        return [rounded(sd.topk_ia(index, q, 3)), rounded(sd.topk_gbo(index, q, 3))]

    expected, near = boxes_and_cells("0"), rounded(sd.topk_hausdorff(index, "0", 1))
    monkeypatch.setattr(sd, "MOST_QUERY_POINTS", 8)
    assert boxes_and_cells("0") == expected
    assert rounded(sd.topk_hausdorff(index, "0", 1)) == near


def test_every_search_goes_on_beyond_a_task(spark, points, monkeypatch):
    """With tiny bounds each search gives the same rows by its other way."""
    from cartosearch.operators import search_points as sp

    def rows(index):
        pairs = sorted((r["q_id"], r["dataset_id"], round(r["distance"], 9)) for r in sd.similar_pairs(index, 4.0).collect())
        near = sorted((r["q_point_id"], r["rank"], round(r["distance"], 9)) for r in sp.nearest_points(index, "2", "0", 2).collect())
        runs = [[(i, round(v, 9)) for v, i in run.rows] for run in (sd.topk_hausdorff(index, "2", 2), sd.symmetric_topk(index, "2", 2), sd.hausdorff_pair(index, "2", "0"))]
        return pairs, near, runs

    expected = rows(ix.build_index(points, f=3, clean=False))
    monkeypatch.setattr(sd, "MOST_QUERY_POINTS", 8)
    monkeypatch.setattr(ix, "MOST_TASK_POINTS", 8)
    monkeypatch.setattr(sp, "MOST_TASK_POINTS", 8)
    assert rows(ix.build_index(points, f=3, clean=False)) == expected


def test_large_pairs_go_down_their_trees(spark, points, monkeypatch):
    """Part by part, and after a few probes, the distance is that of best-first; the pair is given up beyond the limit only."""
    import numpy as np

    from cartosearch.operators import kernels

    made = np.random.default_rng(5)
    for n, m, d in ((1, 40, 2), (300, 200, 2), (250, 300, 4)):
        a, b = made.normal(size=(n, d)), made.normal(size=(m, d)) * 1.5 + 0.3
        b[: m // 2] = b[0]
        q, t = kernels.build_tree(a, 5), kernels.build_tree(b, 5)
        want = kernels.best_first(q, t).distance
        assert sum(len(p) for _, p in kernels.parts_of(q, 16)) == n
        assert kernels.by_parts(q, t, parts=kernels.parts_of(q, 16))[0] == pytest.approx(want, abs=1e-12)
        assert kernels.by_parts(q, t, want * (1 + 1e-9))[0] is not None and kernels.by_parts(q, t, want * 0.999)[0] is None
        low, high = kernels.by_parts(q, t, slack=0.4)[:2]
        assert low - 1e-9 <= want <= high + 1e-9 and high <= low + 0.4 + 1e-9
        for limit, k in ((float("inf"), 2), (want, 1)):
            far, _, final, _ = sd._probed((q, kernels.outline(q)), [(t, kernels.outline(t))] * 2, limit * (1 + 1e-9), [], k, 0.0, None)
            assert final.all() and far == pytest.approx([want] * 2, abs=1e-12)
    index = ix.build_index(points, f=3, clean=False)
    ids = ["0", "1", "2"]
    rows = lambda: {q: [(i, round(v, 9)) for v, i in run.rows] for q, run in sd.hausdorff_batch(index, ids, 2).items()}
    expected = rows()
    monkeypatch.setattr(sd, "MOST_PLAIN_PAIRS", 0)
    monkeypatch.setattr(sd, "PROBES", 2)
    assert rows() == expected


def test_a_batch_has_no_expression_per_query(spark, monkeypatch):
    """Bounds of many queries are a matter of the tasks; a plan of one expression for each took longer than the search."""
    made = [(str(ds), i, ds % 7 * 2.0 + i % 5 / 3, ds // 7 + i % 3 / 2) for ds in range(40) for i in range(8)]
    index = ix.build_index(spark.createDataFrame(made, "dataset_id string, point_id long, c0 double, c1 double"), f=3, clean=False)
    ids = [str(i) for i in range(40)]
    single = {q: [(i, round(v, 9)) for v, i in sd.topk_hausdorff(index, q, 3).rows] for q in ids[:3]}
    bounds = []
    monkeypatch.setattr(sd, "ball_lower", lambda *a: bounds.append(1))
    got = sd.hausdorff_batch(index, ids, 3)
    assert not bounds and {q: [(i, round(v, 9)) for v, i in got[q].rows] for q in single} == single
