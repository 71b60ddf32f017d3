"""Mixing sources to target weights by systematic sampling.

Each source gets a target of words: the sources, ordered by code point with null last, weigh 5, 2, 1 in turn
and share a budget; no target exceeds twice its source, the excess goes to the others by weight. Inside a
source every document is expected target / size times. Documents stand in one fixed order (by size class, so
that the sample is spread over sizes), expected copies are summed along it from a seeded offset, and a
document is taken once for each whole number that the sum passes at it.

The sum needs no ordered pass over a source: documents are counted by source, size class and a cell of their
doc_id; these counts give each cell its first rank, and ranks inside a cell are its own rows. Cells grow in number
with the table, so that a cell stays small.

Null text: size 0. Null source: a source of its own, last. Null doc_id: first in its cell, which the size decides. Documents of
one doc_id, source and size stand side by side and are taken as separate rows. Empty table: empty result. A source
of size 0 has target 0. Other columns come back as they are, whatever their names.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed

WEIGHTS = (5, 2, 1)
WORD = r"[^\x20\x09-\x0D]+"
#: Cells of a size class at least, and documents of a cell that their number grows for.
CELLS = 64
CELL_ROWS = 65_536
CLASSES = 40
#: doc_ids are dealt to cells by multiplication in a prime field, so that no step between ids fills one cell alone.
PRIME = 2_147_483_647
FACTOR = 1_103_515_245
#: Alike documents that one array lists.
BLOCK = 65_536


def _offset_base(seed: int) -> float:
    return random.Random(seed).random()


def size_class(size: Column) -> Column:
    """How many powers of two are at most the size."""
    return sum((F.when(size >= F.lit(1 << k), 1).otherwise(0) for k in range(CLASSES)), F.lit(0))


def source_targets(sizes: DataFrame, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """source, source_rank, source_size and target from rows of (source, size).

    Sources fill up in order of most * size / weight. Before the k-th one fills up, what is left of the
    budget over the weights left is the level; the first source whose own bound reaches it ends the filling; levels fall from there on.
    """
    sources = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    one = sources.withColumn("source_rank", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))
    weighed = one.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), ((F.col("source_rank") - 1) % len(WEIGHTS) + 1).cast("int")))
    bound = weighed.withColumn("bound", F.lit(most) * F.col("source_size") / F.col("weight"))
    order = Window.orderBy("bound", "source_rank")
    filled = (
        bound.withColumn("level", (F.lit(share) * F.sum("source_size").over(Window.partitionBy()) - F.coalesce(F.lit(most) * F.sum("source_size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))) / F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", F.max(F.when(F.col("level") <= F.col("bound"), F.col("level"))).over(Window.partitionBy()))
    )
    return filled.select("source", "source_rank", "source_size", F.least(F.col("level") * F.col("weight"), F.lit(most) * F.col("source_size")).alias("target"))


def mix(docs: DataFrame, share: float = 1.5, most: float = 2.0, seed: int = 7) -> DataFrame:
    """doc_id, size, source_size, target, copies and taken, one row per document."""
    sized = docs.select("doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))
    placed = place(keep(sized), share, most, seed)
    # Alike documents one by one, in blocks so that no array grows with their number.
    blocks = placed.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("alike") - 1) / BLOCK))))
    single = blocks.withColumn("nth", F.explode(F.sequence(F.col("block") * BLOCK + 1, F.least(F.col("alike"), (F.col("block") + 1) * BLOCK))))
    return single.select("doc_id", "size", "source_size", "target", copies(F.col("nth")).alias("copies")).withColumn("taken", F.col("copies") * F.col("size"))


def keep(df: DataFrame) -> DataFrame:
    """The rows of a narrow frame that several branches read, cut off from how they were made."""
    return checkpointed(df)


def cell_count(rows: int) -> int:
    """Cells of a size class: a power of two, CELLS or more, that leaves about CELL_ROWS rows to a cell at any size of the table."""
    cells = CELLS
    while cells * CELL_ROWS < rows:
        cells *= 2
    return cells


def copies(nth: Column) -> Column:
    """Copies of the nth of alike documents: whole numbers that the sum of expected copies passes there."""
    rank = F.col("before") + nth
    return (F.floor(F.col("offset") + F.col("rate") * rank) - F.floor(F.col("offset") + F.col("rate") * (rank - 1))).cast("long")


def place(sized: DataFrame, share: float, most: float, seed: int) -> DataFrame:
    """doc_id, source, size, alike (documents of all three), source_size, target, rate, offset and before, the number of
    documents in front of them in their source. Documents that are alike are one row from the first exchange on."""
    cell = ["source", "size_class", "cell"]
    number = F.pmod(F.pmod(F.coalesce("doc_id", F.col("size")), F.lit(PRIME)) * F.lit(FACTOR), F.lit(PRIME))
    alike = sized.groupBy("doc_id", "source", "size").agg(F.count(F.lit(1)).alias("alike"))
    rows = alike.withColumn("size_class", size_class(F.col("size"))).withColumn("cell", F.pmod(number, F.lit(cell_count(sized.count()))))
    counts = rows.groupBy(*cell).agg(F.sum("alike").alias("n"), F.sum(F.col("size") * F.col("alike")).alias("size"))
    along = Window.partitionBy("source").orderBy("size_class", "cell").rowsBetween(Window.unboundedPreceding, -1)
    firsts = counts.withColumn("first", F.coalesce(F.sum("n").over(along), F.lit(0))).alias("c").join(source_targets(counts, share, most).alias("s"), F.col("c.source").eqNullSafe(F.col("s.source")))
    firsts = firsts.select(*(F.col(f"c.{x}").alias(f"_{x}") for x in cell), "first", "source_rank", "source_size", "target")
    on = [F.col(x).eqNullSafe(F.col(f"_{x}")) for x in cell]
    inside = Window.partitionBy(*cell).orderBy(F.col("doc_id").asc_nulls_first(), "size").rowsBetween(Window.unboundedPreceding, -1)
    ranked = rows.withColumn("ahead", F.coalesce(F.sum("alike").over(inside), F.lit(0))).join(firsts, on[0] & on[1] & on[2])
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    offset = (F.col("source_rank") * F.lit(0.6180339887498949) + F.lit(_offset_base(seed))) % F.lit(1.0)
    return ranked.select("doc_id", "source", "size", "alike", "source_size", "target", rate.alias("rate"), offset.alias("offset"), (F.col("first") + F.col("ahead")).alias("before"))


def sql(share: float = 1.5, most: float = 2.0, seed: int = 7, documents: str = "documents") -> str:
    """The same in SQL, over a table of documents."""
    weights = f"CASE (source_rank - 1) % 3 WHEN 0 THEN {WEIGHTS[0]} WHEN 1 THEN {WEIGHTS[1]} ELSE {WEIGHTS[2]} END"
    klass = " + ".join(f"CASE WHEN s.size >= {1 << k} THEN 1 ELSE 0 END" for k in range(CLASSES))
    residue = f"(((coalesce(s.doc_id, s.size) % {PRIME}) + {PRIME}) % {PRIME})"
    cell = f"(({residue} * {FACTOR}) % {PRIME}) % (SELECT cells FROM dealt)"
    return rf"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM {documents}),
dealt AS (SELECT CAST(greatest({CELLS}, pow(2, ceil(log2(greatest(count(*), 1) / {CELL_ROWS}.0)))) AS BIGINT) AS cells FROM sized),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
numbered AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) AS source_rank FROM sources),
weighed AS (SELECT *, {weights} AS weight FROM numbered),
bounded AS (SELECT *, CAST({most} AS DOUBLE) * source_size / weight AS bound FROM weighed),
levels AS (
  SELECT *, (CAST({share} AS DOUBLE) * CAST(sum(source_size) OVER () AS DOUBLE)
     - coalesce(CAST({most} AS DOUBLE) * CAST(sum(source_size) OVER (ORDER BY bound, source_rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS DOUBLE), 0.0))
     / CAST(sum(weight) OVER (ORDER BY bound, source_rank ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS level FROM bounded),
targets AS (
  SELECT source, source_rank, source_size, least((SELECT max(level) FROM levels WHERE level <= bound) * weight, CAST({most} AS DOUBLE) * source_size) AS target FROM levels),
placed AS (
  SELECT s.doc_id, s.size, t.source_size, t.target,
    CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate,
    (t.source_rank * CAST(0.6180339887498949 AS DOUBLE) + CAST({_offset_base(seed)!r} AS DOUBLE)) % 1.0 AS start,
    row_number() OVER (PARTITION BY s.source ORDER BY {klass}, {cell}, s.doc_id NULLS FIRST, s.size) AS place
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
  CAST((floor(start + rate * place) - floor(start + rate * (place - 1))) AS BIGINT) AS copies,
  CAST((floor(start + rate * place) - floor(start + rate * (place - 1))) * size AS BIGINT) AS taken FROM placed
"""


def repeated(docs: DataFrame, share: float = 1.5, most: float = 2.0, seed: int = 7) -> DataFrame:
    """The rows of docs, each as often as the mix takes it (not at all, once or twice), columns as given.

    Texts are moved once: rows meet their places on (doc_id, source, size), and where several are alike they are numbered
    in that same partitioning.
    """
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    # The row travels as one column, so that none of its names can meet one of ours.
    whole = docs.select(F.struct("*").alias("row"), F.col("doc_id").alias("doc_id"), F.col("source").alias("source"), size.alias("size"), F.xxhash64("text").alias("hash"))
    placed = place(keep(whole.select("doc_id", "source", "size")), share, most, seed)
    some = placed.filter(F.floor(F.col("offset") + F.col("rate") * (F.col("before") + F.col("alike"))) > F.floor(F.col("offset") + F.col("rate") * F.col("before")))

    def key(side: str) -> list[Column]:
        return [F.coalesce("doc_id", F.lit(0)).alias(f"{side}_id"), F.col("doc_id").isNull().alias(f"{side}_no_id"), F.coalesce("source", F.lit("")).alias(f"{side}_source"), F.col("source").isNull().alias(f"{side}_no_source"), F.col("size").alias(f"{side}_size")]

    names = ("id", "no_id", "source", "no_source", "size")
    rows = whole.select("row", "hash", *key("a"))
    met = rows.join(some.select("alike", "rate", "offset", "before", *key("b")), [F.col(f"a_{n}") == F.col(f"b_{n}") for n in names])
    nth = F.row_number().over(Window.partitionBy(*(f"a_{n}" for n in names)).orderBy("hash"))
    counted = met.withColumn("nth", nth).withColumn("copies", copies(F.col("nth"))).filter("copies > 0")
    return counted.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("row.*")
