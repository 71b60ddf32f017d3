from cartosearch.operators import search_datasets as sd
from cartosearch.plans import workloads as w

SF = "/root/testdata/sf0.001"


def test_a_batch_sends_the_driver_one_row_per_query(spark, monkeypatch):
    index = w.built(spark, SF, "ev_home")
    ids = w.queries_of(index, 100)
    plain = {i: sd.topk_hausdorff(index, i, 3).rows for i in ids[:3]}
    hashed = sd.hausdorff_batch(index, ids, 3)
    monkeypatch.setattr(sd, "MANY_QUERIES", 2, raising=False)
    frames = type(index.roots)
    sizes, real = [], frames.collect
    monkeypatch.setattr(frames, "collect", lambda df: (lambda got: sizes.append(len(got)) or got)(real(df)))
    got = sd.hausdorff_batch(index, ids, 3)
    assert max(sizes) <= len(ids)
    assert {i: x.rows for i, x in got.items()} == {i: x.rows for i, x in hashed.items()}
    for i, rows in plain.items():
        assert got[i].rows == rows


def test_all_queries_go_through_the_tree_of_shared_cells(spark):
    """The batch has the results of single searches, whichever nodes the second wave drops."""
    index = w.built(spark, SF, "ev_trip")
    ids = w.queries_of(index, 4)
    for k in (1, 3):
        got = {i: [] for i in ids}
        for r in sd.gbo_tree_batch(index, ids, k).orderBy("query_id", "rank").collect():
            got[r["query_id"]].append((r["score"], r["dataset_id"]))
        assert got == {i: sd.topk_gbo(index, i, k).rows for i in ids}


def test_every_method_of_the_sweeps_has_all_queries(spark, monkeypatch):
    """baselines and the tree form took one or two of the queries."""
    took, real = {}, w.Sheet.add_many
    monkeypatch.setattr(w.Sheet, "add_many", lambda s, *a, **k: took.setdefault((s.workload, a[1]), len(a[4])) and real(s, *a, **k))
    w.w_overlap_f(spark, SF, repos=("ev_home",), fs=(10,), n=4)
    w.w_haus_k(spark, SF, repos=("ev_home",), ks=(3,), n=4)
    assert len(took) == 7 and set(took.values()) == {4}
