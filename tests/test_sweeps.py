"""What the sweeps of the workloads rest on: the same results from fewer rows and fewer jobs."""

import numpy as np
from pyspark.sql import functions as F

from cartosearch.operators import baselines as base
from cartosearch.operators import index as ix
from cartosearch.operators import search_datasets as sd
from cartosearch.operators.kernels import all_pairs, build_tree, by_parts, parts_of
from cartosearch.operators.upper_index import build_upper, upper_in_task
from cartosearch.plans import workloads as w
from cartosearch.sources.repositories import repository_extent, sized_extent

SF = "/root/testdata/sf0.001"


def test_all_pairs_in_blocks():
    r = np.random.default_rng(3)
    for n, m, d in ((1, 1, 2), (7, 50, 2), (40, 9, 5)):
        q, p = r.normal(size=(n, d)), r.normal(size=(m, d))
        want = np.sqrt(((q[:, None] - p[None]) ** 2).sum(axis=2)).min(axis=1).max()
        assert all(abs(all_pairs(q, p, *x) - want) < 1e-12 for x in ((4096, 16), (4, 3), (1, 1)))


def test_box_bounds_compare_pairs_in_blocks(spark):
    """Pairs of points are no rows, but for datasets beyond `most` points; both ways agree."""
    index = w.built(spark, SF, "ev_home")
    ids = w.queries_of(index, 3)
    got = base.box_bound_batch(index, ids, 4)
    rows = lambda df: sorted((r["query_id"], r["rank"], r["dataset_id"], round(r["score"], 9), r["evaluations"]) for r in df.collect())
    assert "qlo0" not in got._jdf.queryExecution().optimizedPlan().toString()  # the bounds are there already
    assert "q_id" not in got._jdf.queryExecution().optimizedPlan().toString()
    sizes = [r["n"] for r in index.roots.select("n").collect()]
    assert rows(got) == rows(base.box_bound_batch(index, ids, 4, most=0)) == rows(base.box_bound_batch(index, ids, 4, most=sorted(sizes)[len(sizes) // 2]))


def test_upper_tree_in_one_task(spark, monkeypatch):
    """The same nodes and members from one task as from joins."""
    index = w.built(spark, SF, "ev_trip")
    made = upper_in_task(index.roots, 3).collect()
    nodes, members = build_upper(index.roots, 3)
    cut = lambda rows: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows)
    columns = nodes.columns
    assert cut([[r[c] for c in columns] for r in made if r["dataset_id"] is None]) == cut(nodes.collect())
    assert sorted((r["path"], r["dataset_id"]) for r in made if r["dataset_id"] is not None) == sorted(map(tuple, members.collect()))
    # Roots beyond the limit of a task go through joins.
    monkeypatch.setattr(ix, "MOST_NODES", 5)
    again = ix.finish(index.tree, index.spec, 3, None)
    assert cut(again.upper.collect()) == cut(nodes.collect())
    monkeypatch.undo()
    assert cut(ix.finish(index.tree, index.spec, 3, None).upper.select(*columns).collect()) == cut(nodes.collect())


def test_extent_and_sizes_from_one_pass(spark):
    points = w.repository(spark, SF, "ev_home")
    sizes = [r["count"] for r in points.groupBy("dataset_id").count().collect()]
    assert sized_extent(points) == (repository_extent(points), sum(sizes), max(sizes))
    index = ix.build_index(points.filter(F.col("dataset_id").isin(["1", "2"])), clean=False)
    assert index.upper.filter("path = ''").first()["n_datasets"] == index.members.count()


def test_parts_of_a_query_go_down_a_tree_together():
    """The distance of all pairs, or None beyond tau; approximate values within the slack; few passes for many parts."""
    r = np.random.default_rng(5)
    for n, m, d, far in ((3, 4, 2, 0.0), (900, 700, 2, 0.0), (600, 2000, 2, 3.0), (500, 300, 5, 0.5), (2000, 1, 3, 1.0), (40, 900, 2, 40.0)):
        q, p = build_tree(r.normal(size=(n, d)), 10), build_tree(r.normal(size=(m, d)) + far, 10)
        want = all_pairs(q.points, p.points)
        for parts in (None, parts_of(q, 5), parts_of(q, 10_000)):
            value, most, evaluations, _ = by_parts(q, p, np.inf, parts)
            assert abs(value - want) < 1e-12 and most >= value and evaluations > 0
            assert abs(by_parts(q, p, want, parts, want * 0.9)[0] - want) < 1e-12
            assert by_parts(q, p, want * 0.99, parts)[0] is None
            value, most, _, _ = by_parts(q, p, np.inf, parts, 0.0, 0.3)
            assert value - 1e-12 <= want <= most + 1e-12 and want - value <= 0.3 + 1e-9 and most - value <= 0.3 + 1e-9


def test_parts_share_the_passes_over_a_tree(monkeypatch):
    r = np.random.default_rng(6)
    q, p = build_tree(r.normal(size=(3000, 2)), 10), build_tree(r.normal(size=(3000, 2)), 10)
    calls, real = [], type(p).below_all
    monkeypatch.setattr(type(p), "below_all", lambda self, nodes: calls.append(1) or real(self, nodes))
    parts = parts_of(q, 64)
    by_parts(q, p, np.inf, parts)
    assert len(calls) <= len(parts)


def test_many_queries_share_few_waves(spark, monkeypatch):
    """After a first wave that gives limits, many queries take the rest at once; the results are those of single searches."""
    index = w.built(spark, SF, "ev_trip")
    ids, waves, real = w.queries_of(index, 6), [], sd._wave
    assert index.roots.count() > 40
    single = {q: sd.topk_hausdorff(index, q, 3, wave=2).rows for q in ids}
    monkeypatch.setattr(sd, "_wave", lambda *a: waves.append(1) or real(*a))
    state = index.packed.filter(F.col("dataset_id").isin(ids)).collect()
    queries = [sd._task_query(index, r["dataset_id"], True) for r in state]
    got = sd.topk_hausdorff_many(index, queries, 3, wave=2)
    assert len(waves) <= 3
    for q, run in zip(queries, got):
        assert [(round(v, 9), i) for v, i in run.rows] == [(round(v, 9), i) for v, i in single[q.id]]
