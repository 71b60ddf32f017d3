"""Relational operators around the methods: joins Spark has no one word for, and reports over grouping sets.

Each is a plain DataFrame plan; RELATIONAL pairs a query over the given tables with the same in SQL.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.repositories import load_table


def asof_join(left: DataFrame, right: DataFrame, on: str, ts: str, values: list[str], tie: str) -> DataFrame:
    """left with the values of the latest earlier row of right with the same key; one shuffle by key, no pairs."""
    tagged = left.select(on, ts, tie, F.lit(1).alias("_side"), *(F.lit(None).cast(t).alias(f"_v_{c}") for c, t in right.select(*values).dtypes))
    other = right.select(on, ts, F.lit(None).cast(dict(left.dtypes)[tie]).alias(tie), F.lit(0).alias("_side"), *(F.col(c).alias(f"_v_{c}") for c in values))
    # Rows of the right side sort after left ones of the same time: only strictly earlier ones count.
    along = Window.partitionBy(on).orderBy(F.col(ts), F.col("_side").desc()).rowsBetween(Window.unboundedPreceding, -1)
    seen = tagged.unionByName(other).withColumns({f"prev_{c}": F.last(F.when(F.col("_side") == 0, F.struct(F.col(f"_v_{c}").alias("v"))), True).over(along).getField("v") for c in values})
    return seen.filter("_side = 1").select(on, ts, tie, *(f"prev_{c}" for c in values))


def range_join(points: DataFrame, boxes: DataFrame, width: float, x: str, lo: str, hi: str) -> DataFrame:
    """Rows whose x lies in [lo, hi]: intervals are spread over cells of a fixed width, so the join has an equal key."""
    cells = boxes.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_cell", F.floor(F.col(x) / width)).join(cells, "_cell").filter(F.col(x).between(F.col(lo), F.col(hi))).drop("_cell")


def sessions(df: DataFrame, key: str, ts: str, gap: str) -> DataFrame:
    return df.groupBy(F.session_window(F.col(ts), gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n"))


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return load_table(spark, d, name)


def cube_events(s, d):
    e = _t(s, d, "events").withColumn("day", F.dayofmonth("ts"))
    return e.cube("event_type", F.col("day") % 7).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 2).alias("total")).toDF("event_type", "weekpart", "n", "total")


def rollup_orders(s, d):
    j = _t(s, d, "orders").join(_t(s, d, "customer"), F.expr("o_custkey = c_custkey")).join(F.broadcast(_t(s, d, "nation")), F.expr("c_nationkey = n_nationkey")).join(F.broadcast(_t(s, d, "region")), F.expr("n_regionkey = r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n_orders"), F.countDistinct("o_custkey").alias("n_datasets"))


def asof_events(s, d):
    e = _t(s, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(1).collect()]
    return asof_join(e.filter(F.col("event_type") != kinds[0]), e.filter(F.col("event_type") == kinds[0]), "user_id", "ts", ["value"], "event_id").select("event_id", "prev_value")


def range_join_events(s, d):
    e = _t(s, d, "events").select("event_id", "value")
    boxes = s.createDataFrame([(1, 10.0, 20.0), (2, 15.5, 60.0), (3, 200.0, 250.0)], "box_id int, lo double, hi double")
    return range_join(e, F.broadcast(boxes), 10.0, "value", "lo", "hi").select("box_id", "event_id")


def customers_without_orders(s, d):
    return _t(s, d, "customer").join(_t(s, d, "orders"), F.expr("c_custkey = o_custkey"), "left_anti").select("c_custkey")


def full_outer(s, d):
    a = _t(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("k")).agg(F.count(F.lit(1)).alias("n_lines"))
    b = _t(s, d, "supplier").select(F.col("s_suppkey").alias("k"), F.round("s_acctbal", 2).alias("balance"))
    return a.join(b, "k", "full")


def session_gaps(s, d):
    return sessions(_t(s, d, "events"), "user_id", "ts", "6 hours").groupBy("user_id").agg(F.count(F.lit(1)).alias("n_sessions"), F.max("n").alias("longest"))


def pivot_events(s, d):
    return _t(s, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("value") < 20, 1)).alias("low"), F.count(F.when(F.col("value") >= 20, 1)).alias("high")).unpivot("user_id", ["low", "high"], "band", "n")


def set_operations(s, d):
    a = _t(s, d, "lineitem").filter("l_quantity > 45").select("l_partkey")
    b = _t(s, d, "part").filter("p_size > 25").select(F.col("p_partkey").alias("l_partkey"))
    return a.intersect(b).withColumn("kind", F.lit("both")).unionByName(b.exceptAll(a.distinct()).withColumn("kind", F.lit("parts only")))


def json_field(s, d):
    return _t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


def tile_leaves(s, d):
    w = Window.partitionBy("l_suppkey").orderBy("l_quantity", "l_extendedprice")
    return _t(s, d, "lineitem").withColumn("slab", F.ntile(8).over(w)).groupBy("l_suppkey", "slab").agg(F.count(F.lit(1)).alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"))


def above_own_mean(s, d):
    p = _t(s, d, "part")
    m = p.groupBy(F.col("p_brand").alias("b")).agg(F.avg("p_retailprice").alias("m"))
    return p.join(m, F.expr("p_brand = b AND p_retailprice > m")).select("p_partkey")


def ranks(s, d):
    w = Window.partitionBy("user_id").orderBy(F.col("value").desc(), "event_id")
    return _t(s, d, "events").select("event_id", "user_id", F.row_number().over(w).alias("place"), F.round(F.lag("value").over(w), 6).alias("better"), F.round(F.percent_rank().over(w), 6).alias("share")).filter("place <= 3")


_KIND = "(SELECT min(event_type) FROM events)"
RELATIONAL = {
    "rel_cube": (cube_events, "SELECT event_type, day(ts) % 7 AS weekpart, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY CUBE (event_type, day(ts) % 7)"),
    "rel_rollup": (rollup_orders, "SELECT r_name, n_name, count(*) AS n_orders, count(DISTINCT o_custkey) AS n_datasets FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)"),
    "rel_asof": (asof_events, f"SELECT a.event_id, (SELECT b.value FROM events b WHERE b.event_type = {_KIND} AND b.user_id = a.user_id AND b.ts < a.ts ORDER BY b.ts DESC LIMIT 1) AS prev_value FROM events a WHERE a.event_type <> {_KIND}"),
    "rel_range_join": (range_join_events, "WITH b(box_id, lo, hi) AS (VALUES (1, 10.0, 20.0), (2, 15.5, 60.0), (3, 200.0, 250.0)) SELECT box_id, event_id FROM events JOIN b ON value BETWEEN lo AND hi"),
    "rel_anti": (customers_without_orders, "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    "rel_full_outer": (full_outer, "SELECT coalesce(a.k, b.k) AS k, n_lines, balance FROM (SELECT l_suppkey AS k, count(*) AS n_lines FROM lineitem GROUP BY l_suppkey) a FULL JOIN (SELECT s_suppkey AS k, round(s_acctbal, 2) AS balance FROM supplier) b ON a.k = b.k"),
    "rel_sessions": (session_gaps, "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g), c AS (SELECT user_id, sid, count(*) AS n FROM s GROUP BY user_id, sid) SELECT user_id, count(*) AS n_sessions, max(n) AS longest FROM c GROUP BY user_id"),
    "rel_unpivot": (pivot_events, "SELECT user_id, 'low' AS band, count(*) FILTER (WHERE value < 20) AS n FROM events GROUP BY user_id UNION ALL SELECT user_id, 'high', count(*) FILTER (WHERE value >= 20) FROM events GROUP BY user_id"),
    "rel_sets": (set_operations, "WITH a AS (SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity > 45), b AS (SELECT p_partkey AS l_partkey FROM part WHERE p_size > 25) SELECT l_partkey, 'both' AS kind FROM a WHERE l_partkey IN (SELECT l_partkey FROM b) UNION ALL SELECT l_partkey, 'parts only' FROM b WHERE l_partkey NOT IN (SELECT l_partkey FROM a)"),
    "rel_json": (json_field, "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "rel_tiles": (tile_leaves, "WITH t AS (SELECT *, ntile(8) OVER (PARTITION BY l_suppkey ORDER BY l_quantity, l_extendedprice) AS slab FROM lineitem) SELECT l_suppkey, slab, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi FROM t GROUP BY l_suppkey, slab"),
    "rel_correlated": (above_own_mean, "SELECT p_partkey FROM part a WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part b WHERE b.p_brand = a.p_brand)"),
    "rel_windows": (ranks, "WITH w AS (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS place, round(lag(value) OVER (PARTITION BY user_id ORDER BY value DESC, event_id), 6) AS better, round(percent_rank() OVER (PARTITION BY user_id ORDER BY value DESC, event_id), 6) AS share FROM events) SELECT * FROM w WHERE place <= 3"),
}
