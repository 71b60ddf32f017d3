"""Streams against the batch answer, with files out of order."""

import pytest
from pyspark.sql import functions as F

from cartosearch.functions.zorder import signatures
from cartosearch.model import Box
from cartosearch.operators import index as ix
from cartosearch.operators.measures import dataset_boxes
from cartosearch.sources.repositories import combine_queries, read_point_files, repository, repository_extent, sample_datasets, slice_by_time, split_trips
from cartosearch.sources.sinks import register_views, write_result
from cartosearch.streaming import points as st

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The events in three files; the last hours come first."""
    path = str(tmp_path_factory.mktemp("events"))
    spark.read.parquet(f"{SF}/events.parquet").withColumn("_o", -F.col("event_id")).repartitionByRange(3, "_o").drop("_o").write.mode("overwrite").parquet(path)
    return path


@pytest.fixture(scope="module")
def points(spark, folder):
    return st.stream_points(st.stream_events(spark, folder), "ev_user")


@pytest.fixture(scope="module")
def batch(spark):
    return repository(spark, SF, "ev_user").cache()


def test_roots(points, batch):
    got = {r["dataset_id"]: (r["n"], r["lo1"], r["hi1"]) for r in st.to_memory(st.stream_roots(points), "complete").groupBy("dataset_id").agg(F.max_by(F.struct("n", "lo1", "hi1"), "n").alias("x")).select("dataset_id", "x.*").collect()}
    assert got == {r["dataset_id"]: (r["n"], r["lo1"], r["hi1"]) for r in dataset_boxes(batch).collect()}


def test_cells(points, batch):
    spec = ix.GridSpec.from_extent(repository_extent(batch), 5)
    got = {(r["dataset_id"], r["cell"]) for r in st.to_memory(st.stream_cells(points, spec, "400 days"), "append").collect()}
    assert got == {(r["dataset_id"], r["cell"]) for r in signatures(batch, spec).collect()}
    live = st.to_memory(st.stream_gbo(points, spec, signatures(batch, spec).filter("dataset_id = '1'")), "complete")
    assert live.groupBy("dataset_id").agg(F.max("score")).count() > 0


def test_gbo_counts_cells_exactly(spark, tmp_path):
    side = 32
    made = [(str(ds), i, i % side + 0.5, i // side + 0.5) for ds in range(1, 9) for i in range(side * side) if i % ds == 0]
    path = str(tmp_path / "grid")
    spark.createDataFrame(made + made, "dataset_id string, point_id long, c0 double, c1 double").withColumn("ts", F.timestamp_millis("point_id")).repartition(3).write.parquet(path)
    grid = spark.read.parquet(path)
    spec = ix.GridSpec((0.0, 0.0), (float(side), float(side)), 5)
    cells = signatures(grid, spec)
    query = cells.filter("dataset_id = '1'").select("cell")
    live = st.to_memory(st.stream_gbo(st.stream_events(spark, path), spec, query), "complete")
    got = {r["dataset_id"]: r["s"] for r in live.groupBy("dataset_id").agg(F.max("score").alias("s")).collect()}
    assert got == {r["dataset_id"]: r["count"] for r in cells.join(query.distinct(), "cell").groupBy("dataset_id").count().collect()} and got["1"] == side * side


@pytest.mark.parametrize("shape", [("1 day", None, None), ("1 day", "12 hours", None), (None, None, "6 hours")])
def test_slices(points, batch, shape):
    rows = st.to_memory(st.stream_slices(points, *shape, lateness="400 days"), "complete" if not shape[2] else "append").collect()
    assert all(r["lo0"] <= r["hi0"] and r["n"] > 0 for r in rows)
    if shape[:2] == ("1 day", None):
        assert sum(r["n"] for r in rows) == batch.count()


def test_fences_and_pairs(spark, points, batch):
    box = Box((0.0, 20.0), (200.0, 60.0))
    assert st.to_memory(st.stream_range_points(points, box), "append").count() == batch.filter("c0 between 0 and 200 and c1 between 20 and 60").count()
    fences = spark.createDataFrame([("f", 0.0, 20.0, 200.0, 60.0)], "fence string, qlo0 double, qlo1 double, qhi0 double, qhi1 double")
    assert st.to_memory(st.stream_fences(points, fences), "append").count() == batch.filter("c0 between 0 and 200 and c1 between 20 and 60").count()
    pairs = st.to_memory(st.stream_pairs(points, "1 HOUR", 1.0, "400 days"), "append").collect()
    assert all(abs(r["a_c0"] - r["b_c0"]) <= 1 and abs(r["a_c1"] - r["b_c1"]) <= 1 and r["a_ts"] <= r["b_ts"] for r in pairs)


def test_index_append(spark, points, batch, tmp_path):
    holder = [ix.build_index(batch.filter("dataset_id < '4'"), clean=False)]
    known = holder[0].roots.count()
    st.stream_index_append(points.drop("ts").withColumn("ts", F.lit(None).cast("timestamp")), holder, str(tmp_path)).awaitTermination()
    assert holder[0].roots.count() == batch.select("dataset_id").distinct().count() > known


def test_index_append_keeps_points_of_later_batches(spark, points, batch, tmp_path):
    few = ["1", "2", "3", "4"]
    holder = [ix.build_index(batch.filter("dataset_id = '1'").limit(3), clean=False, spec=ix.GridSpec.from_extent(repository_extent(batch), 5))]
    expected = {r["dataset_id"]: r["count"] for r in batch.filter(F.col("dataset_id").isin(few)).groupBy("dataset_id").count().collect()}
    for run in ("a", "b"):  # the second run brings every point again
        st.stream_index_append(points.filter(F.col("dataset_id").isin(few)), holder, str(tmp_path / run)).awaitTermination()
        assert {r["dataset_id"]: r["n"] for r in holder[0].roots.collect()} == expected
        assert {r["dataset_id"]: r["count"] for r in holder[0].points.groupBy("dataset_id").count().collect()} == expected


def test_trips(points, batch):
    closed = st.to_memory(st.trip_state(points, 6 * 3_600_000), "append").collect()
    assert all(r["n"] > 0 and r["first_ms"] <= r["last_ms"] for r in closed) and {r["dataset_id"] for r in closed} <= {r[0] for r in batch.select("dataset_id").distinct().collect()}


def test_files_slices_trips_samples(spark, batch, tmp_path):
    for name, fmt in (("c", "csv"), ("j", "json"), ("o", "orc")):
        target = str(tmp_path / name)
        write_result(batch.filter("dataset_id = '1'").select("c0", "c1").coalesce(1), target, fmt)
        got = read_point_files(spark, target, fmt, ["c0", "c1"], "c0 double, c1 double")
        assert got.count() == batch.filter("dataset_id = '1'").count() and got.select("dataset_id").distinct().count() == 1
    (tmp_path / "t.txt").write_text("1,2\n3,4.5\n")
    assert {(r["c0"], r["c1"]) for r in read_point_files(spark, str(tmp_path / "t.txt"), "text", ["a", "b"]).collect()} == {(1.0, 2.0), (3.0, 4.5)}
    events = spark.read.parquet(f"{SF}/events.parquet")
    assert slice_by_time(events.withColumn("ts", F.col("ts").cast("timestamp")), "ts", "6 hours").select("slice").distinct().count() <= 121
    trips = split_trips(events, "user_id", "ts", "12 HOURS")
    assert trips.groupBy("user_id").agg(F.max("trip").alias("t")).agg(F.max("t")).first()[0] > 0
    assert sample_datasets(batch, 1.0).count() == batch.count() and sample_datasets(batch, 0.0).count() == 0
    assert combine_queries(batch, ["1", "2"], "u").select("dataset_id").distinct().count() == 1
    register_views({"carto_points": batch})
    assert spark.sql("SELECT count(*) FROM carto_points").first()[0] == batch.count()


def test_sql_surface(spark, batch):
    from cartosearch.functions.sql_surface import register, register_search

    register(spark)
    row = spark.sql("SELECT box_overlap_area(0D,0D,2D,2D,1D,1D,3D,3D) AS a, z_interleave_2d(3L, 1L) AS z, ball_lower_2d(0D,0D,3D,4D,1D) AS l, ball_upper_2d(0D,0D,1D,3D,4D,0D) AS u").first()
    assert (row["a"], row["z"], row["l"], row["u"]) == (1.0, 7, 4.0, 6.0)
    index = ix.build_index(batch, clean=False)
    register_search(spark, index)
    first = index.roots.agg(F.min("dataset_id")).first()[0]
    assert spark.sql(f"SELECT * FROM search_datasets('hausdorff', 3, '{first}')").count() == 3
    last = index.roots.agg(F.max("dataset_id")).first()[0]
    assert spark.sql(f"SELECT * FROM search_datasets('hausdorff', 12, '{last}')").count() == 12
    for bad in ("'hausdorff', 3, 'nobody'", f"'nothing', 3, '{first}'"):
        with pytest.raises(Exception, match="no such"):
            spark.sql(f"SELECT * FROM search_datasets({bad})").collect()


def test_replays_keep_no_rows_on_the_driver(spark, points, monkeypatch):
    def refuse(*_):
        raise AssertionError("rows of a stream went to the driver")

    from cartosearch.registry_index import QUERIES

    expected = sorted(map(tuple, st.to_memory(st.stream_range_points(points, Box((10.0, 5.0), (300.0, 40.0))), "append").select("dataset_id", "point_id").collect()))
    monkeypatch.setattr(st, "to_memory", refuse)
    for name in ("stream_cells", "stream_slices", "stream_fences"):
        assert QUERIES[name][0](spark, SF).count() > 0
    assert sorted(map(tuple, QUERIES["stream_range_points"][0](spark, SF).collect())) == expected
    nothing = st.to_files(st.stream_range_points(points, Box((-9.0, -9.0), (-8.0, -8.0))), "append")
    assert nothing.columns == points.columns and nothing.count() == 0
