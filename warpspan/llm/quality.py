"""Quality rules: a table of thresholds compiled into one Spark projection.

Nothing here runs outside the JVM: lengths, symbols, repeats and ratios are
built-in expressions over the text, its words and its lines, and the verdict
is one conjunction over the table's limits.

Words are runs without blanks (space, tab to carriage return); lines are the
pieces between ``\\n``. A null or empty text has no word and fails the base
rule of fifty words. Extra columns are ignored, repeated rows are judged each
for itself, and an empty table gives an empty result.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from warpspan.llm.common import BLANKS


class Limit(NamedTuple):
    """A document passes if ``low <= metric <= high``; None leaves a side open."""

    name: str
    metric: str
    low: float | None
    high: float | None


# Common function words of the four languages, lower case.
STOP_WORDS = (
    "the of and to in that is was for it with be by on this as are from "
    "der die und das ist nicht ein eine zu den mit von für auf "
    "le la les de des et en un une que est pour dans du qui par sur "
    "el los las y una del se por con para no"
).split()

#: The base rule; it holds whatever else a caller asks for.
BASE = (
    Limit("few_words", "n_words", 50, None),
    Limit("repeated_words", "repeat_word_ratio", None, 0.5),
)

#: Limits of the production run, beyond the base.
STANDARD = (
    Limit("symbols", "symbol_ratio", None, 0.08),
    Limit("word_length", "mean_word_length", 1.5, 25.0),
    Limit("repeated_lines", "dup_line_ratio", None, 0.5),
    Limit("letters", "letter_ratio", 0.4, None),
    Limit("stop_words", "stop_word_ratio", 0.005, None),
    Limit("shouting", "capital_ratio", None, 0.7),
)


def bound_to(value: Column, make) -> Column:
    """``make(v)`` where v stands for ``value``, which is evaluated once however often v occurs."""
    return F.element_at(F.transform(F.array(value), make), 1)


def _words(text: Column) -> Column:
    return F.filter(F.split(text, f"{BLANKS}+"), lambda w: w != "")


def _repeat_words(words: Column) -> Column:
    """Words inside 3-word windows that occur twice or more, the first place included.

    Windows are sorted by hash and then by their own words, so that equal
    windows stand side by side; the covered words follow from the sorted
    starts of the windows that have an equal neighbour.
    """

    def spread(starts: Column) -> Column:
        gaps = F.transform(
            starts, lambda s, i: F.least(F.lit(3), F.coalesce(F.get(starts, i + 1) - s, F.lit(3)))
        )
        return F.aggregate(gaps, F.lit(0).cast("long"), lambda total, gap: total + gap)

    def repeated(ordered: Column) -> Column:
        equal = lambda a, b: (a.h == b.h) & (a.w == b.w)
        return F.transform(
            F.filter(
                ordered,
                lambda x, i: F.coalesce(equal(x, F.get(ordered, i - 1)), F.lit(False))
                | F.coalesce(equal(x, F.get(ordered, i + 1)), F.lit(False)),
            ),
            lambda x: x.i,
        )

    def windows(w: Column) -> Column:
        starts = F.sequence(F.lit(0), F.size(w) - 3)
        return F.transform(starts, lambda i: F.concat_ws(" ", F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))

    def count(found: Column) -> Column:
        ordered = F.sort_array(
            F.transform(found, lambda w, i: F.struct(F.xxhash64(w).alias("h"), w.alias("w"), i.alias("i")))
        )
        slow = bound_to(F.sort_array(bound_to(ordered, repeated)), spread)
        return F.when(F.size(F.array_distinct(found)) == F.size(found), F.lit(0).cast("long")).otherwise(slow)

    long_enough = bound_to(words, lambda w: bound_to(windows(w), count))
    return F.when(F.size(words) < 4, F.lit(0).cast("long")).otherwise(long_enough)


def measure(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """The id and all metrics that limits may name, one row per document."""
    body = F.coalesce(F.col(text), F.lit(""))
    parts = documents.select(
        F.col(id_column),
        body.alias("_body"),
        _words(body).alias("_words"),
        F.filter(F.split(body, "\n"), lambda s: s.rlike("[^ \t-\r]")).alias("_lines"),
    )
    without = lambda signs: F.length(F.regexp_replace("_body", signs, "")).cast("long")
    metrics = {
        "n_words": F.size("_words").cast("long"),
        "word_chars": F.length(F.array_join("_words", "")).cast("long"),
        "n_symbols": F.length("_body").cast("long") - without("[#*$%&|<>]"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "n_repeat_words": _repeat_words(F.col("_words")),
        "n_lines": F.size("_lines").cast("long"),
        "n_stop_words": F.size(F.filter("_words", lambda w: F.lower(w).isin(STOP_WORDS))).cast("long"),
        "n_letters": F.length("_body").cast("long") - without("\\p{L}+"),
        "n_capitals": F.length("_body").cast("long") - without("\\p{Lu}+"),
    }
    # Rows of one struct: a filter on a metric stays above the generator. Below
    # it, it would be pushed into the projections and compute everything again
    # for each mention of a metric.
    row = F.array(F.struct(*(value.alias(name) for name, value in metrics.items())))
    counted = parts.select(F.col(id_column), F.inline(row))
    ratio = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    return counted.select(
        "*",
        ratio("n_repeat_words", "n_words").alias("repeat_word_ratio"),
        ratio("n_symbols", "word_chars").alias("symbol_ratio"),
        ratio("word_chars", "n_words").alias("mean_word_length"),
        ratio("n_dup_lines", "n_lines").alias("dup_line_ratio"),
        ratio("n_letters", "word_chars").alias("letter_ratio"),
        ratio("n_stop_words", "n_words").alias("stop_word_ratio"),
        ratio("n_capitals", "n_letters").alias("capital_ratio"),
    )


def broken(limit: Limit) -> Column:
    """Whether a row of ``measure`` is outside a limit."""
    value, out = F.col(limit.metric), F.lit(False)
    if limit.low is not None:
        out = out | (value < limit.low)
    if limit.high is not None:
        out = out | (value > limit.high)
    return out


def judge(measured: DataFrame, limits: tuple[Limit, ...] = STANDARD) -> DataFrame:
    """Adds ``base_failed``, ``kept`` and ``reasons`` (the broken limits, comma-joined)."""
    any_of = lambda rules: F.exists(F.array(*map(broken, rules)), lambda x: x) if rules else F.lit(False)
    named = [F.when(broken(rule), F.lit(rule.name)) for rule in (*BASE, *limits)]
    return (
        measured.withColumn("base_failed", any_of(BASE))
        .withColumn("kept", ~(F.col("base_failed") | any_of(limits)))
        .withColumn("reasons", F.concat_ws(",", *named))
    )


def keep_good(documents: DataFrame, limits: tuple[Limit, ...] = STANDARD) -> DataFrame:
    """The documents that pass, with their own columns; no join and no shuffle."""
    row = F.struct(*(F.col(f"`{name}`") for name in documents.columns)).alias("_row")
    packed = documents.select(row, F.col("text"))
    return judge(measure(packed, "_row"), limits).where("kept").select("_row.*")
