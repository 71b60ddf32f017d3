"""SQL functions (inlined by the optimiser) and table functions over small results."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..checkpoints import checkpointed

_BITS = " + ".join(f"shiftleft(shiftright(i, {b}) & 1L, {2 * b}) + shiftleft(shiftright(j, {b}) & 1L, {2 * b + 1})" for b in range(16))
_CELL = "greatest(least(cast(floor(({x} - {lo}) / (({hi} - {lo}) / cast(shiftleft(1L, theta) AS DOUBLE))) AS BIGINT), shiftleft(1L, theta) - 1L), 0L)"

FUNCTIONS = {
    "z_interleave_2d": ("i BIGINT, j BIGINT", "BIGINT", _BITS),
    "z_cell_2d": ("x DOUBLE, y DOUBLE, x0 DOUBLE, y0 DOUBLE, x1 DOUBLE, y1 DOUBLE, theta INT", "BIGINT", f"z_interleave_2d({_CELL.format(x='x', lo='x0', hi='x1')}, {_CELL.format(x='y', lo='y0', hi='y1')})"),
    "box_overlap_area": ("ax0 DOUBLE, ay0 DOUBLE, ax1 DOUBLE, ay1 DOUBLE, bx0 DOUBLE, by0 DOUBLE, bx1 DOUBLE, by1 DOUBLE", "DOUBLE", "greatest(least(ax1, bx1) - greatest(ax0, bx0), 0D) * greatest(least(ay1, by1) - greatest(ay0, by0), 0D)"),
    "distance_2d": ("ax DOUBLE, ay DOUBLE, bx DOUBLE, by DOUBLE", "DOUBLE", "sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))"),
    "ball_lower_2d": ("qx DOUBLE, qy DOUBLE, dx DOUBLE, dy DOUBLE, rd DOUBLE", "DOUBLE", "greatest(sqrt((qx - dx) * (qx - dx) + (qy - dy) * (qy - dy)) - rd, 0D)"),
    "ball_upper_2d": ("qx DOUBLE, qy DOUBLE, rq DOUBLE, dx DOUBLE, dy DOUBLE, rd DOUBLE", "DOUBLE", "sqrt((qx - dx) * (qx - dx) + (qy - dy) * (qy - dy) + rd * rd) + rq"),
    "ball_gap_2d": ("qx DOUBLE, qy DOUBLE, rq DOUBLE, dx DOUBLE, dy DOUBLE, rd DOUBLE", "DOUBLE", "greatest(sqrt((qx - dx) * (qx - dx) + (qy - dy) * (qy - dy)) - rq - rd, 0D)"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions of this session."""
    for name, (arguments, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")


def register_search(spark: SparkSession, index, query_ids: list[str] | None = None, name: str = "search_datasets") -> None:
    """SQL over searches. The view `<name>_results` (measure, query_id, rank, dataset_id, value) has, for the given members or
    for all, every dataset in the order of each measure: shared area, shared cells and Hausdorff distance, found in one plan
    a measure. The function <name>(measure, k, query) is a query over that view, so it answers any of these members and
    any k, and an id or measure that is not there stops the statement instead of giving nothing."""
    from ..operators.search_datasets import exemplar_batch

    ids = query_ids if query_ids is not None else [r[0] for r in index.roots.select("dataset_id").orderBy("dataset_id").collect()]
    every = max(1, index.roots.count())
    found = None
    for measure in ("ia", "gbo", "hausdorff"):
        one = exemplar_batch(index, ids, every, measure).select(F.lit(measure).alias("measure"), "query_id", F.col("rank").cast("int").alias("rank"), "dataset_id", F.col("score").cast("double").alias("value"))
        found = one if found is None else found.unionByName(one)
    checkpointed(found).createOrReplaceTempView(f"{name}_results")
    spark.createDataFrame([(i,) for i in ids], "query_id string").createOrReplaceTempView(f"{name}_members")
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}(m STRING, k INT, q STRING) RETURNS TABLE (rank INT, dataset_id STRING, value DOUBLE)
        RETURN SELECT rank, dataset_id, value FROM {name}_results
        WHERE measure = m AND query_id = q AND rank <= k
          AND assert_true(m IN ('ia', 'gbo', 'hausdorff'), 'no such measure') IS NULL
        UNION ALL
        SELECT CAST(raise_error('no such member or measure') AS INT), NULL, NULL
        FROM (SELECT count(*) AS n FROM {name}_members WHERE query_id = q AND m IN ('ia', 'gbo', 'hausdorff')) t WHERE n = 0""")
