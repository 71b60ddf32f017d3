"""Streams of points: running boxes and cells of datasets, windows, fences, live overlap and trips."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpoint_dir
from ..functions.geometry import boxes_meet, constants, dims, point_inside, vec
from ..functions.zorder import z_id
from ..model import Box, GridSpec
from ..sources.repositories import REPOSITORIES, in_dialect


def stream_events(spark: SparkSession, folder: str, pattern: str = "*.parquet", per_trigger: int = 1) -> DataFrame:
    """The files of a folder whose names fit the pattern as a stream; ts becomes a TIMESTAMP, as watermarks need one."""
    schema = spark.read.parquet(f"{folder}/{pattern}").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", pattern).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_points(events: DataFrame, handle: str = "ev_user") -> DataFrame:
    """Points of one of the event repositories, with their time."""
    _, dataset, coords, key = REPOSITORIES[handle]
    expr = lambda t: F.expr(in_dialect(t, "spark"))
    return events.select(expr(dataset).alias("dataset_id"), expr(key).alias("point_id"), *(expr(c).cast("double").alias(f"c{i}") for i, c in enumerate(coords)), "ts")


def stream_roots(points: DataFrame) -> DataFrame:
    """Count, box and coordinate sums of every dataset so far (update mode). The exact radius needs all points again, so
    half the box's diagonal around the box centre stands in for it as an upper bound."""
    d = dims(points)
    got = points.groupBy("dataset_id").agg(F.count(F.lit(1)).alias("n"), *(f(f"c{i}").alias(f"{x}{i}") for i in range(d) for f, x in ((F.min, "lo"), (F.max, "hi"), (F.sum, "sum"))))
    diagonal = F.sqrt(sum(((F.col(f"hi{i}") - F.col(f"lo{i}")) * (F.col(f"hi{i}") - F.col(f"lo{i}")) for i in range(d)), F.lit(0.0)))
    return got.withColumn("radius_bound", diagonal)


def stream_cells(points: DataFrame, spec: GridSpec, lateness: str = "1 hour") -> DataFrame:
    """Each (dataset, cell) once within the watermark."""
    return points.withWatermark("ts", lateness).select("dataset_id", z_id(vec("c", spec.d), spec).alias("cell"), "ts").dropDuplicatesWithinWatermark(["dataset_id", "cell"])


def stream_slices(points: DataFrame, width: str, slide: str | None = None, gap: str | None = None, lateness: str = "1 hour") -> DataFrame:
    """Datasets as tumbling, sliding or session windows."""
    d = dims(points)
    w = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    return points.withWatermark("ts", lateness).groupBy(w.alias("w"), "dataset_id").agg(F.count(F.lit(1)).alias("n"), *(f(f"c{i}").alias(f"{x}{i}") for i in range(d) for f, x in ((F.min, "lo"), (F.max, "hi")))).select("dataset_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", *vec("lo", d), *vec("hi", d))


def stream_range_points(points: DataFrame, box: Box) -> DataFrame:
    return points.filter(point_inside(vec("c", box.d), constants(box.lo), constants(box.hi)))


def stream_fences(points: DataFrame, boxes: DataFrame) -> DataFrame:
    """Points with the rectangles (fence, qlo.., qhi..) they lie in; the static side is small and checked by its reader."""
    d = dims(points)
    return points.join(F.broadcast(boxes), boxes_meet(vec("c", d), vec("c", d), vec("qlo", d), vec("qhi", d)))


def stream_gbo(points: DataFrame, spec: GridSpec, query_cells: DataFrame) -> DataFrame:
    """Per dataset the number of the query's cells touched so far (complete or update mode).
    The state of a dataset is the set of them, at most the query's cells."""
    cells = points.select("dataset_id", z_id(vec("c", spec.d), spec).alias("cell"))
    return cells.join(F.broadcast(query_cells.select("cell").distinct()), "cell").groupBy("dataset_id").agg(F.size(F.collect_set("cell")).cast("long").alias("score"))


def trip_state(points: DataFrame, gap_ms: int) -> DataFrame:
    """Closed trips (dataset_id, n, first_ms, last_ms): a pause of more than gap_ms of event time ends one. A
    point that comes later than the trip it would have belonged to is left out."""
    import pandas as pd

    def step(key, frames, state):
        n, first, last = state.get if state.exists else (0, 0, 0)
        out = []
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame([(key[0], n, first, last)], columns=["dataset_id", "n", "first_ms", "last_ms"])
            return
        times = sorted(t for f in frames for t in f["ms"])
        for t in times:
            if n and t < first - gap_ms:
                continue
            if n and t - last > gap_ms:
                out.append((key[0], n, first, last))
                n = 0
            first, last = (min(first, t), max(last, t)) if n else (t, t)
            n += 1
        state.update((n, first, last))
        state.setTimeoutTimestamp(max(last + gap_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["dataset_id", "n", "first_ms", "last_ms"])

    timed = points.withWatermark("ts", "1 hour").withColumn("ms", F.unix_millis("ts")).select("dataset_id", "ts", "ms")
    return timed.groupBy("dataset_id").applyInPandasWithState(step, "dataset_id string, n long, first_ms long, last_ms long", "n long, first long, last long", "append", "EventTimeTimeout")


def stream_pairs(points: DataFrame, within: str, reach: float, lateness: str = "1 hour") -> DataFrame:
    """Pairs of points of different datasets at most `reach` apart in every coordinate, the second within a time after."""
    d = dims(points)
    a = points.withWatermark("ts", lateness).select(*(F.col(c).alias(f"a_{c}") for c in points.columns)).withColumn("cell", F.floor(F.col("a_c0") / reach))
    b = points.withWatermark("ts", lateness).select(*(F.col(c).alias(f"b_{c}") for c in points.columns)).withColumn("cell", F.explode(F.array(*(F.floor(F.col("b_c0") / reach) + k for k in (-1, 0, 1)))))
    near: Column = F.abs(F.col("a_c0") - F.col("b_c0")) <= reach
    for i in range(1, d):
        near = near & (F.abs(F.col(f"a_c{i}") - F.col(f"b_c{i}")) <= reach)
    return a.join(b, (a["cell"] == b["cell"]) & (F.col("a_dataset_id") != F.col("b_dataset_id")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}")) & near).drop("cell")


def stream_index_append(points: DataFrame, index_holder: list, checkpoint: str):
    """A streaming query that adds each batch's new points to the index in index_holder[0], whether their datasets are
    known or new. A batch that is run again after a failure finds its points there and adds nothing."""
    from ..operators.index import grow_datasets

    def add(batch: DataFrame, epoch: int) -> None:
        index_holder[0] = grow_datasets(index_holder[0], batch.drop("ts"))

    return points.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def to_memory(df: DataFrame, mode: str) -> DataFrame:
    """Run a stream over all that is there and return what reached the sink: for tests and replays."""
    name = f"stream_{uuid.uuid4().hex}"
    query = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def to_files(df: DataFrame, mode: str) -> DataFrame:
    """As to_memory, but each batch goes from the tasks to Parquet in the shared checkpoint folder, and no row to the driver.
    A batch that is run again takes its own place."""
    spark = df.sparkSession
    folder = f"{checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={epoch}")

    # The first folder is there even if the stream has no batch.
    spark.createDataFrame([], df.schema).write.parquet(f"{folder}/rows/batch=none")
    query = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows/batch=*")


def replay_roots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The running roots of the events after the last batch; only each dataset's latest row counts."""
    points = stream_points(stream_events(spark, sf_dir, "events.parquet"))
    got = to_files(stream_roots(points), "update")
    latest = Window.partitionBy("dataset_id").orderBy(F.desc("n"))
    return got.withColumn("r", F.row_number().over(latest)).filter("r = 1").select("dataset_id", "n", F.round("lo1", 6).alias("lo1"), F.round("hi1", 6).alias("hi1"))
