"""Measures, and the directions that the experiments should show, on counters rather than on times."""

from pyspark.sql import functions as F

from cartosearch.plans import metrics
from cartosearch.plans import workloads as w

SF = "/root/testdata/sf0.001"


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_measures(spark):
    a = spark.createDataFrame([("q", 1, "x", 1.0), ("q", 2, "y", 2.0), ("r", 1, "x", 1.0)], "query_id string, rank int, dataset_id string, distance double")
    b = spark.createDataFrame([("q", 1, "y", 2.5), ("q", 2, "z", 3.0), ("r", 1, "z", 1.0)], "query_id string, rank int, dataset_id string, distance double")
    assert {r["query_id"]: r["accuracy"] for r in metrics.topk_overlap_accuracy(a, b, 2).collect()} == {"q": 0.5, "r": 0.0}
    assert metrics.overlap_accuracy([(1, "x"), (2, "y")], [(0, "y"), (1, "z")], 2) == 0.5
    e = metrics.approx_error(a.filter("query_id = 'q'"), b.filter("query_id = 'q'"), 0.3).first()
    assert e["error"] == 0.5 and e["within"]
    assert metrics.speedup(10, 2) == 5 and metrics.time_queries(lambda q: None, ["a", "b"]) >= 0
    t = metrics.trend(spark.createDataFrame([(1, 1.0), (2, 1.0), (3, 4.0)], "x int, y double").withColumn("g", F.lit(1)), "x", "y", ["g"]).first()
    assert t["rising"] and not t["falling"] and t["n"] == 3


def test_hausdorff_needs_fewer_evaluations_than_the_rectangle_bound(spark):
    got = rows(w.w_haus_k(spark, SF, repos=("ev_home",), ks=(3, 10), n=4, few=4))
    by = {(r["method"], r["value"]): r for r in got}
    for k in (3.0, 10.0):
        assert by["exact", k]["evaluations"] < by["box_bound", k]["evaluations"]
        assert by["box_bound", k]["accuracy"] == by["box_incremental", k]["accuracy"] == 1.0


def test_smaller_errors_cost_more(spark):
    got = w.w_appro_eps(spark, SF, repos=("li_fort",), thetas=(3, 5, 7), n=3).filter("method = 'approx'").withColumn("g", F.lit(1))
    assert metrics.trend(got, "value", "evaluations", ["g"]).first()["rising"]
    assert got.filter("value = 7").first()["accuracy"] >= got.filter("value = 3").first()["accuracy"]


def test_approximation_beats_shared_cells(spark):
    by = {r["method"]: r["accuracy"] for r in rows(w.w_accuracy(spark, SF, repos=("li_fort",), n=5))}
    assert by["approx"] >= 0.8 and by["approx"] >= by["gbo"]


def test_finer_grids_have_more_postings(spark):
    got = w.w_gbo_theta(spark, SF, repos=("li_fort",), thetas=(3, 5, 7), n=4, few=1).filter("method = 'postings'").withColumn("g", F.lit(1))
    assert metrics.trend(got, "value", "evaluations", ["g"]).first()["rising"]


def test_wider_ranges_lose_nothing(spark):
    for f, m in ((w.w_ranges, "range_datasets"), (w.w_rangep, "range_points")):
        got = f(spark, SF, repos=("ev_home",), n=5).withColumn("g", F.lit(m))
        assert metrics.trend(got, "value", "n_results", ["g"]).first()["rising"]


def test_all_workloads_are_registered():
    assert len(w.WORKLOADS) == 20


def test_grids_have_every_point():
    """The defaults are the whole parameter table."""
    import inspect

    full = {"ks": w.KS, "fs": w.FS, "thetas": w.THETAS, "rs": w.RS, "ds": w.DS, "ms": w.MS}
    for f in w.WORKLOADS.values():
        for name, p in inspect.signature(f).parameters.items():
            assert name not in full or p.default == full[name], (f.__name__, name)


def test_batches_agree_with_single_searches(spark):
    from cartosearch.operators import baselines as base
    from cartosearch.operators import search_datasets as sd
    from cartosearch.operators import search_points as sp

    index = w.built(spark, SF, "ev_home")
    ids = w.queries_of(index, 4)
    many = sd.hausdorff_batch(index, ids, 5)
    boxes = sd.hausdorff_batch(index, ids, 5, box_f=10)
    plain = {q: [] for q in ids}
    for r in base.box_bound_batch(index, ids, 5).orderBy("query_id", "rank").collect():
        plain[r["query_id"]].append((r["score"], r["dataset_id"]))
    cut = lambda x: [(i, round(v, 9)) for v, i in x]
    for q in ids:
        assert cut(many[q].rows) == cut(boxes[q].rows) == cut(plain[q]) == cut(sd.topk_hausdorff(index, q, 5).rows)
        assert cut(base.box_incremental_topk(index, q, 5).rows) == cut(many[q].rows)
    pairs = [(ids[0], ids[1]), (ids[2], ids[3])]
    got = sp.nearest_points_batch(index, pairs)
    for q, d in pairs:
        one = {(r["q_point_id"], r["d_point_id"]) for r in sp.nearest_points(index, q, d, strategy="leaf_join").collect()}
        assert one == {(r["q_point_id"], r["d_point_id"]) for r in got.filter((F.col("query_id") == q) & (F.col("dataset_id") == d)).collect()}
    small, large = base.knn_early_break(index.points, ids[0], ids[1], 3), base.knn_early_break(index.points, ids[0], ids[1], 3, block=20)
    near = lambda df: {(r["q_point_id"], r["rank"], round(r["distance"], 9)) for r in df.collect()}
    assert near(small) == near(large)


def test_rectangles_beyond_a_broadcast(spark):
    from cartosearch.operators import search_datasets as sd

    index = w.built(spark, SF, "ev_trip")
    boxes = w._rectangles(index, w.queries_of(index, 20), 2)
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    assert rows(sd.range_datasets_batch(index, boxes)) == rows(sd.range_datasets_batch(index, boxes, most=3))


def test_shared_cells_of_many_in_blocks(spark):
    """Every dataset as a query, in one block and in many, against sets of cells; ties by dataset_id."""
    from cartosearch.operators import search_datasets as sd

    index = w.built(spark, SF, "ev_home")
    cells = {}
    for r in index.cells.collect():
        cells.setdefault(r["dataset_id"], set()).add(r["cell"])
    want = set()
    for q, own in cells.items():
        scores = sorted((-len(own & c), i) for i, c in cells.items() if i != q and own & c)[:3]
        want |= {(q, rank + 1, i, -s) for rank, (s, i) in enumerate(scores)}
    for got in (sd.gbo_batch(index, list(cells), 3), sd.gbo_batch(index, list(cells), 3, most=40, most_queries=4)):
        assert {(r["query_id"], r["rank"], r["dataset_id"], r["score"]) for r in got.collect()} == want


def test_a_sweep_makes_the_cell_arrays_of_its_scan_once(spark, monkeypatch):
    made, real = [], w.signatures
    monkeypatch.setattr(w, "signatures", lambda *a: made.append(a) or real(*a))
    by = {(r["method"], r["value"]): r["n_results"] for r in rows(w.w_overlap_k(spark, SF, repos=("ev_home",), ks=(2, 4), n=3))}
    assert len(made) == 1 and all(by["scan", k] == by["gbo", k] for k in (2.0, 4.0))
