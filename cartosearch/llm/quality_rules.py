"""Quality rules as a learned decision list, in DataFrame functions only.

Sequential covering: a conjunction of thresholds is grown on two thirds of the labelled rows until it covers no
good row or has three conditions, and pruned on the rest. Good rows that it covers all the same get rules of their own,
grown within it, which keep them and stand before it. If it is precise then, what it covers is set aside and the next one is
grown. The list becomes ordered Spark conditional expressions over statistics of each text, which are array and
regular-expression functions of the text alone.

Null or empty text: no words, all statistics 0, so the base rule fails it. Ties among conditions go to the
one that fewest rows meet, then the earlier one. Repeated doc_ids in labels count once per matching row. Without labels the list
is empty and keeps what the base rule keeps. Other columns are neither read nor changed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labelled rows that the list is learned from: those of the smallest hashes.
SAMPLE = 4000
SPACE = r"\x20\x09-\x0D"
STATISTICS = ("n_words", "mean_word", "symbols_per_word", "dup_line_share", "repeat_share", "upper_share", "marks_per_word")


def _settled(c: Column) -> Column:
    """The same value behind a test of the task that always holds: the optimiser neither copies such a column into the lambdas
    above it nor pushes a filter through, so each array is made once per row."""
    return F.when(F.spark_partition_id() >= 0, c)


def with_statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the statistics of its text in columns prefixed by `_q_`."""
    t = F.coalesce(F.col(text), F.lit(""))
    # Each step is a projection of its own, so that an array is computed once and not once per element that looks into it.
    split = docs.withColumns({"_q_words": _settled(F.array_remove(F.split(t, f"[{SPACE}]+", -1), "")), "_q_lines": _settled(F.filter(F.split(t, "\n", -1), lambda x: x.rlike(f"[^{SPACE}]")))})
    counted = split.withColumn("_q_n", _settled(F.size("_q_words"))).withColumn("_q_bits", _settled(F.length(F.bin("_q_n")).cast("int")))
    triple = "xxhash64(get(_q_words, i), get(_q_words, i + 1), get(_q_words, i + 2))"
    # One number for each window: its hash above, its place below.
    keys = counted.withColumn("_q_keys", _settled(F.expr(f"CASE WHEN _q_n >= 3 THEN sort_array(transform(sequence(0, _q_n - 3), i -> coalesce(shiftleft({triple}, _q_bits) | cast(i AS BIGINT), 0L))) ELSE cast(array() AS array<bigint>) END")))
    place = "cast({0} & (shiftleft(1L, _q_bits) - 1L) AS INT)"

    place_x, place_y = place.format("x"), place.format("y")

    def alike(other: str) -> str:
        return "(" + " AND ".join(f"get(_q_words, {place_x} + {d}) = get(_q_words, {other} + {d})" for d in range(3)) + ")"

    def beside(k: str) -> str:
        return f"coalesce(shiftright(get(_q_keys, {k}), _q_bits) = shiftright(x, _q_bits), false)"

    # Windows of one hash but other words may stand between two equal ones; only then the whole list is looked through.
    near = f"(({beside('k - 1')} AND {alike(place.format('get(_q_keys, k - 1)'))}) OR ({beside('k + 1')} AND {alike(place.format('get(_q_keys, k + 1)'))}))"
    found = f"({beside('k - 1')} OR {beside('k + 1')}) AND ({near} OR exists(_q_keys, y -> y != x AND {alike(place_y)}))"
    again = keys.withColumn("_q_again", _settled(F.expr(f"transform(filter(_q_keys, (x, k) -> {found}), x -> x & (shiftleft(1L, _q_bits) - 1L))")))
    stats = {
        "_q_n_words": _settled(F.col("_q_n").cast("long")),
        "_q_word_chars": F.length(F.array_join("_q_words", "")).cast("long"),
        "_q_n_symbols": F.regexp_count(t, F.lit(r"[#*$%&|<>]")).cast("long"),
        "_q_n_lines": F.size("_q_lines").cast("long"),
        "_q_n_dup_lines": (F.size("_q_lines") - F.size(F.array_distinct("_q_lines"))).cast("long"),
        "_q_n_repeat_words": F.expr("CASE WHEN size(_q_again) = 0 THEN 0L ELSE cast(size(array_union(array_union(_q_again, transform(_q_again, x -> x + 1L)), transform(_q_again, x -> x + 2L))) AS BIGINT) END"),
        "_q_n_upper": F.regexp_count(t, F.lit(r"[A-Z]")).cast("long"),
        "_q_n_marks": F.regexp_count(t, F.lit(r"[.,!?;:]")).cast("long"),
    }
    return again.withColumns(stats).drop("_q_words", "_q_lines", "_q_n", "_q_bits", "_q_keys", "_q_again")


def measures() -> dict[str, Column]:
    """The statistics that conditions are about, from the columns of with_statistics()."""
    c = lambda x: F.col(f"_q_{x}")
    n = F.greatest(c("n_words"), F.lit(1))
    return {
        "n_words": c("n_words").cast("double"),
        "mean_word": c("word_chars") / n,
        "symbols_per_word": c("n_symbols") / n,
        "dup_line_share": c("n_dup_lines") / F.greatest(c("n_lines"), F.lit(1)),
        "repeat_share": c("n_repeat_words") / n,
        "upper_share": c("n_upper") / F.greatest(c("word_chars"), F.lit(1)),
        "marks_per_word": c("n_marks") / n,
    }


def base_failed() -> Column:
    return (F.col("_q_n_words") < 50) | (100 * F.col("_q_n_repeat_words") > 50 * F.col("_q_n_words"))


@dataclass(frozen=True)
class Condition:
    statistic: str
    above: bool
    threshold: float

    def holds(self, row: dict[str, float]) -> bool:
        return row[self.statistic] > self.threshold if self.above else row[self.statistic] <= self.threshold

    def column(self, by: dict[str, Column]) -> Column:
        return by[self.statistic] > self.threshold if self.above else by[self.statistic] <= self.threshold


@dataclass(frozen=True)
class Rule:
    """What holds for all conditions is kept or rejected."""

    keeps: bool
    conditions: tuple[Condition, ...]

    def holds(self, row: dict[str, float]) -> bool:
        return all(c.holds(row) for c in self.conditions)


def decide(rules: list[Rule], row: dict[str, float]) -> bool:
    """Whether the list keeps a row: the first rule that holds says so, none keeps."""
    return next((r.keeps for r in rules if r.holds(row)), True)


def learn(rows: list[dict[str, float]], bad: list[bool], precision: float = 0.99, support: int = 5, longest: int = 3, thresholds: int = 40) -> list[Rule]:
    """The ordered list. A rejecting rule that also covers good rows is preceded by rules that keep these, grown within it;
    one that stays imprecise is left out and the rows it was grown for are set aside. Sets of rows are bits of an integer,
    so each trial is a few word operations."""
    from math import log2

    def some(values: list[float]) -> list[float]:
        """About `thresholds` of them, evenly spread."""
        return values if len(values) <= thresholds else values[:: len(values) // thresholds]

    conditions: dict[Condition, int] = {}
    for s in STATISTICS:
        values = sorted({r[s] for r in rows})
        # Rejected rows are few: cuts among all values alone would pass over the places where they begin and end.
        marks = {*some(values), *some(sorted({r[s] for r, b in zip(rows, bad) if b}))}
        cuts = sorted({(x + y) / 2 for x, y in zip(values, values[1:]) if x in marks or y in marks})
        for cut in cuts:
            covered = sum(1 << i for i, r in enumerate(rows) if r[s] > cut)
            conditions[Condition(s, True, cut)] = covered
            conditions[Condition(s, False, cut)] = ~covered & ((1 << len(rows)) - 1)
    positive = sum(1 << i for i, b in enumerate(bad) if b)
    left = (1 << len(rows)) - 1
    negative = left & ~positive
    grow = sum(1 << i for i in range(len(rows)) if i % 3)

    def cover(rule: list[Condition], bits: int) -> int:
        for c in rule:
            bits &= conditions[c]
        return bits

    def extended(rule: list[Condition], target: int, other: int, among: int) -> list[Condition]:
        """The conjunction with further conditions, as rows of `among` suggest them."""
        rule = list(rule)
        here = cover(rule, (target | other) & among)
        while len(rule) < longest:
            p0, n0 = (here & target).bit_count(), (here & other).bit_count()
            if not p0 or not n0:
                break
            best, gain, least = None, 0.0, 0
            for c, bits in conditions.items():
                p, n = (here & bits & target).bit_count(), (here & bits & other).bit_count()
                g = p * (log2(p / (p + n)) - log2(p0 / (p0 + n0))) if p else 0.0
                if g > 1e-9 and g > gain - 1e-9:
                    size = bits.bit_count()
                    if g > gain + 1e-9 or size < least:
                        best, gain, least = c, g, size
            if best is None:
                break
            rule.append(best)
            here &= conditions[best]
        return rule

    def grown(target: int, other: int) -> list[list[Condition]]:
        """A conjunction that covers rows of target and few of other: grown on two thirds of them, pruned on the rest; after it
        the forms that pruning went through, up to the whole one, and this one grown on with all rows."""
        rule = extended([], target, other, grow)

        def worth(r: list[Condition]) -> float:
            bits = cover(r, ~grow)
            p, n = (bits & target).bit_count(), (bits & other).bit_count()
            return (p - n) / (p + n) if p + n else -1.0

        size = len(rule)
        while size > 1 and worth(rule[: size - 1]) >= worth(rule[:size]):
            size -= 1
        return [*(rule[:n] for n in range(size, len(rule) + 1)), extended(rule, target, other, -1)] if rule else []

    def precise(bits: int, target: int) -> bool:
        """Enough rows, nearly all of the target, among all rows and among those that the rule was not grown on."""
        p, tried = (bits & target).bit_count(), bits & ~grow
        unseen = (tried & target).bit_count()
        return p >= support and p >= precision * bits.bit_count() and unseen > 0 and unseen >= precision * tried.bit_count()

    def kept_within(rule: list[Condition], bits: int) -> tuple[list[Rule], int]:
        """Rules that keep good rows which `rule` covers, and the rows it is left with."""
        out: list[Rule] = []
        while not precise(bits, positive):
            inner = next((c for c in grown(bits & negative, bits & positive) if precise(cover(c, bits), negative)), None)
            if inner is None:
                break
            out.append(Rule(True, (*rule, *inner)))
            bits &= ~cover(inner, bits)
        return out, bits

    found: list[Rule] = []
    wanted = positive
    while forms := grown(wanted & left, negative & left):
        for rule in forms:
            taken = cover(rule, left)
            before, bits = kept_within(rule, taken)
            if precise(bits, positive):
                found += [*before, Rule(False, tuple(rule))]
                left &= ~taken
                break
        else:
            wanted &= ~taken
    return found


def labelled_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> tuple[list[dict[str, float]], list[bool]]:
    """At most `sample` labelled rows as numbers, in a fixed order."""
    chosen = labels.filter("quality is not null and doc_id is not null").select(F.col("doc_id").alias("_q_id"), F.col("quality").alias("_q_quality")).orderBy(F.xxhash64("_q_id"), "_q_id", "_q_quality").limit(sample)
    joined = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_q_id"))
    values = with_statistics(joined).select("_q_id", "_q_quality", *(c.alias(k) for k, c in measures().items()))
    got = values.orderBy(F.xxhash64("_q_id"), "_q_id", *STATISTICS).limit(sample).collect()
    return [{s: float(r[s]) for s in STATISTICS} for r in got], [r["_q_quality"] == 0 for r in got]


def verdict(rules: list[Rule]) -> Column:
    """The ordered list as one conditional expression: the first rule that holds keeps or rejects, none keeps."""
    by, out = measures(), None
    for rule in rules:
        test = F.lit(True)
        for c in rule.conditions:
            test = test & c.column(by)
        out = F.when(test, F.lit(rule.keeps)) if out is None else out.when(test, F.lit(rule.keeps))
    return F.lit(True) if out is None else out.otherwise(F.lit(True))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, the base statistics, base_failed and kept, one row per document."""
    rules = learn(*labelled_rows(docs, labels))
    base = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    return with_statistics(docs.select("doc_id", "text")).select("doc_id", *(F.col(f"_q_{c}").alias(c) for c in base), base_failed().alias("base_failed"), (~base_failed() & verdict(rules)).alias("kept"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs that are kept, columns as given, whatever their names."""
    rules = learn(*labelled_rows(docs, labels))
    whole = docs.select(F.struct("*").alias("row"), F.col("text").alias("text"))
    return with_statistics(whole).filter(~base_failed() & verdict(rules)).select("row.*")
