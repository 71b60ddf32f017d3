"""Repositories of point datasets from the given tables, from any frame, and from files.

Every builder gives points: dataset_id, point_id, c0.. and attributes. SQL expressions are kept as text, with
the few that differ between dialects under a name, so that the same repository can be stated to another engine.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.geometry import dims, vec
from ..model import Box, GridSpec

DAY = 86_400_000_000


def _micros(column: str, since: str, epoch: int) -> dict[str, str]:
    """Microseconds since a day, without regard to time zones."""
    return {
        "spark": f"(datediff({column}, DATE'{since}') * {DAY} + hour({column}) * 3600000000 + minute({column}) * 60000000L + CAST(extract(SECOND FROM {column}) * 1000000 AS BIGINT))",
        "duckdb": f"(epoch_us({column}) - {epoch})",
    }


TIMES = {
    "{ts}": _micros("ts", "2024-01-01", 1_704_067_200_000_000),
    "{ship}": _micros("l_shipdate", "1995-01-01", 788_918_400_000_000),
    "{order}": _micros("o_orderdate", "1995-01-01", 788_918_400_000_000),
}
_HOURS, _SHIP, _ORDER = "({ts} / 3.6e9)", "({ship} / 8.64e10)", "({order} / 8.64e10)"
_HOME = [f"(100.0 * (user_id % 13) + {_HOURS} / 2)", "(100.0 * ((7 * user_id) % 11) + value)"]
_WIDE = ["l_quantity", "l_extendedprice / 1000", "(l_discount + 0.0)", "(l_tax + 0.0)", _SHIP, "CAST(l_linenumber AS DOUBLE)", "o_totalprice / 1000", "p_retailprice"]

#: handle: (table or join, dataset id, coordinates, id of a point or None for its place in the order of coordinates)
REPOSITORIES: dict[str, tuple[str, str, list[str], str | None]] = {
    "ev_user": ("events", "CAST(user_id AS STRING)", [_HOURS, "value"], "event_id"),
    "ev_trip": ("events", "concat(CAST(user_id AS STRING), '-', CAST(CAST(floor({ts} / 6.048e11) AS BIGINT) AS STRING))", [_HOURS, "value"], "event_id"),
    "ev_slice": ("events", "CAST(CAST(floor({ts} / 2.16e10) AS BIGINT) AS STRING)", [_HOURS, "value"], "event_id"),
    "ev_home": ("events", "CAST(user_id AS STRING)", _HOME, "event_id"),
    "li_fort": ("lineitem", "CAST(CAST(floor({ship} / 1.296e12) AS BIGINT) AS STRING)", [_SHIP, "l_extendedprice / 1000"], None),
    "li_supp": ("lineitem", "CAST(l_suppkey AS STRING)", ["l_quantity", "l_extendedprice / 1000"], None),
    "li_part": ("lineitem", "CAST(l_partkey AS STRING)", ["l_quantity", "l_extendedprice / 1000"], None),
    "or_cust": ("orders", "CAST(o_custkey AS STRING)", [_ORDER, "o_totalprice / 1000"], None),
    "pa_brand": ("part", "p_brand", ["CAST(p_size AS DOUBLE)", "p_retailprice"], None),
    "li_wide": ("lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey", "CAST(l_suppkey AS STRING)", _WIDE, None),
    "em_label": ("embeddings", "CAST(label AS STRING)", [f"CAST({{embedding[{i}]}} AS DOUBLE)" for i in range(8)], "vec_id"),
    "doc_stats": ("documents", "concat(coalesce(lang, ''), '|', coalesce(source, ''))", ["ln(1 + CAST(n_chars AS DOUBLE))", "CAST({words} AS DOUBLE)"], "doc_id"),
    "cv_turns": ("conversations", "CAST(conv_id AS STRING)", ["CAST(turn AS DOUBLE)", "CAST(length(text) AS DOUBLE)"], None),
    "pg_len": ("pages", "{host}", ["CAST(length(html) AS DOUBLE)", "CAST(length(url) - length(replace(url, '/', '')) AS DOUBLE)"], None),
}
_OTHER = {
    "{words}": {"spark": r"regexp_count(text, '[^\\x20\\x09-\\x0D]+')", "duckdb": r"len(regexp_extract_all(text, '[^\x20\x09-\x0D]+'))"},
    "{host}": {"spark": "regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)", "duckdb": "regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)"},
}
for _i in range(8):
    _OTHER[f"{{embedding[{_i}]}}"] = {"spark": f"embedding[{_i}]", "duckdb": f"embedding[{_i + 1}]"}


def in_dialect(text: str, dialect: str) -> str:
    for name, by in (TIMES | _OTHER).items():
        text = text.replace(name, by[dialect])
    return text


def repository_sql(handle: str, d: int | None = None, dialect: str = "duckdb", where: str = "") -> str:
    """The points of a repository as one SELECT."""
    source, dataset, coords, key = REPOSITORIES[handle]
    coords = coords[: d or default_dims(handle)]
    columns = ", ".join(f"{c} AS c{i}" for i, c in enumerate(coords))
    order = ", ".join(f"c{i}" for i in range(len(coords)))
    inner = f"SELECT {dataset} AS dataset_id, {f'CAST({key} AS BIGINT) AS point_id, ' if key else ''}{columns} FROM {source} {where}"
    outer = inner if key else f"SELECT dataset_id, row_number() OVER (PARTITION BY dataset_id ORDER BY {order}) AS point_id, {order} FROM ({inner}) AS p"
    return in_dialect(outer, dialect)


def default_dims(handle: str) -> int:
    return {"em_label": 4, "li_wide": 4}.get(handle, 2)


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def repository(spark: SparkSession, sf_dir: str, handle: str, d: int | None = None, scale: str = "none") -> DataFrame:
    """Points of one of REPOSITORIES; scale="unit" maps the extent to [0, 1] in each dimension."""
    source, dataset, coords, key = REPOSITORIES[handle]
    coords = coords[: d or default_dims(handle)]
    names = [w for w in source.replace("=", " ").split() if w in ("events", "lineitem", "orders", "part", "embeddings", "documents", "conversations", "pages")]
    df = load_table(spark, sf_dir, names[0])
    if "JOIN" in source:
        df = df.join(load_table(spark, sf_dir, "orders"), F.expr("l_orderkey = o_orderkey")).join(load_table(spark, sf_dir, "part"), F.expr("l_partkey = p_partkey"))
    expr = lambda t: F.expr(in_dialect(t, "spark"))
    points = repository_from(df, expr(dataset), [expr(c) for c in coords], expr(key) if key else None)
    return rescaled(points) if scale == "unit" else points


def repository_from(df: DataFrame, dataset: Column, coords: list[Column], key: Column | None = None, attrs: list[str] = (), on_bad: str = "raise") -> DataFrame:
    """Points from any frame. Without a key, a point's id is its place among its dataset's coordinates. Null or NaN
    coordinates stop the job (on_bad="raise") or go (on_bad="drop")."""
    if len(coords) < 2:
        raise ValueError("points need two dimensions or more")
    columns = [c.cast("double").alias(f"c{i}") for i, c in enumerate(coords)]
    got = df.select(dataset.cast("string").alias("dataset_id"), *([key.cast("long").alias("point_id")] if key is not None else []), *columns, *attrs)
    sound = None
    for i in range(len(coords)):
        ok = F.col(f"c{i}").isNotNull() & ~F.isnan(f"c{i}")
        sound = ok if sound is None else sound & ok
    if on_bad == "drop":
        got = got.filter(sound & F.col("dataset_id").isNotNull())
    else:
        got = got.withColumn("c0", F.when(sound, F.col("c0")).otherwise(F.raise_error(F.lit("null or NaN coordinate")).cast("double")))
    if key is None:
        order = Window.partitionBy("dataset_id").orderBy(*vec("c", len(coords)))
        got = got.withColumn("point_id", F.row_number().over(order).cast("long"))
    return got.select("dataset_id", "point_id", *vec("c", len(coords)), *attrs)


def repository_extent(points: DataFrame) -> Box:
    """The box of all points: one small aggregate to the driver."""
    d = dims(points)
    row = points.agg(*(f(f"c{i}").alias(f"{n}{i}") for i in range(d) for f, n in ((F.min, "lo"), (F.max, "hi")))).first()
    if row["lo0"] is None:
        raise ValueError("a repository without points has no extent")
    return Box(tuple(row[f"lo{i}"] for i in range(d)), tuple(row[f"hi{i}"] for i in range(d)))


def sized_extent(points: DataFrame) -> tuple[Box, int, int]:
    """The box of all points, their number and that of the largest dataset, from one pass."""
    d = dims(points)
    corners = [(f, f"{n}{i}", f"c{i}") for i in range(d) for f, n in ((F.min, "lo"), (F.max, "hi"))]
    each = points.groupBy("dataset_id").agg(F.count(F.lit(1)).alias("n"), *(f(c).alias(x) for f, x, c in corners))
    row = each.agg(F.sum("n").alias("total"), F.max("n").alias("largest"), *(f(x).alias(x) for f, x, _ in corners)).first()
    if row["lo0"] is None:
        raise ValueError("a repository without points has no extent")
    return Box(tuple(row[f"lo{i}"] for i in range(d)), tuple(row[f"hi{i}"] for i in range(d))), row["total"], row["largest"]


def rescaled(points: DataFrame, box: Box | None = None) -> DataFrame:
    box = box or repository_extent(points)
    return points.withColumns({f"c{i}": (F.col(f"c{i}") - a) / F.lit((b - a) or 1.0) for i, (a, b) in enumerate(zip(box.lo, box.hi))})


def read_point_files(spark: SparkSession, path: str, fmt: str, coords: list[str], schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, Parquet or text files; one file is one dataset. Text lines hold numbers between commas."""
    if fmt == "text":
        parts = F.split("value", ",")
        df = spark.read.text(path, **options).withColumns({c: F.try_element_at(parts, F.lit(i + 1)).cast("double") for i, c in enumerate(coords)})
    else:
        reader = spark.read.format(fmt).options(**options)
        df = (reader.schema(schema) if schema else reader).load(path)
    return repository_from(df.withColumn("_file", F.col("_metadata.file_path")), F.col("_file"), [F.col(c) for c in coords])


def slice_by_time(df: DataFrame, ts: str, width: str) -> DataFrame:
    """df with `slice`, the start of the window of that width."""
    return df.withColumn("slice", F.window(ts, width).getField("start"))


def split_trips(df: DataFrame, key: str, ts: str, max_gap: str) -> DataFrame:
    """df with `trip`: it grows by one where the pause since the previous row of the key is longer than max_gap."""
    along = Window.partitionBy(key).orderBy(ts)
    new = (F.col(ts) > F.lag(ts).over(along) + F.expr(f"INTERVAL {max_gap}")).cast("int")
    return df.withColumn("_new", F.coalesce(new, F.lit(0))).withColumn("trip", F.sum("_new").over(along.rowsBetween(Window.unboundedPreceding, 0))).drop("_new")


def sample_datasets(points: DataFrame, fraction: float, seed: int = 42) -> DataFrame:
    """Whole datasets, by a hash of their id, so that repeated draws agree."""
    return points.filter(F.pmod(F.xxhash64("dataset_id", F.lit(seed)), F.lit(1_000_000)) < F.lit(int(fraction * 1_000_000)))


def pick_queries(datasets: DataFrame, n: int, seed: int = 42) -> list[str]:
    """The n datasets of the smallest hashes."""
    ids = datasets.select("dataset_id").distinct()
    return [r[0] for r in ids.orderBy(F.xxhash64("dataset_id", F.lit(seed)), "dataset_id").limit(n).collect()]


def range_around(root, r: float, spec: GridSpec, half: bool = True) -> Box:
    """A rectangle around a root's centre of r cells to each side (half=False: r cells in all)."""
    return Box.around([root[f"o{i}"] for i in range(spec.d)], [w * r * (1 if half else 0.5) for w in spec.widths])


def combine_queries(points: DataFrame, ids: list[str], name: str) -> DataFrame:
    """One query dataset from several members, each point once."""
    return points.filter(F.col("dataset_id").isin(ids)).withColumn("dataset_id", F.lit(name))
