"""Repeated passages: units of text hashed, grouped over the corpus, kept once.

A unit is a line, or a paragraph that the text itself cuts out. Paragraphs are
needed where a passage stands inside a longer line, is broken into lines in
another way, or has no stops. Of every ``WINDOW`` neighbouring words the one
with the smallest hash is a mark, so marks are ``WINDOW`` words apart at most
and depend on the words near them only: two copies of a passage have the same
marks but for their first and last few words. From every mark the shortest run
of stretches between marks with ``UNIT_WORDS`` words or more is a unit, and so
is a line with as many. Words are normalised (Unicode NFKC, lower case, runs of
letters and digits) before a unit's 128-bit digest is taken.

Of all units with one digest the earliest ranked stays, by document id, then by
a hash of the text, then by place. All others are to be removed. Units overlap; the ones to be
removed in a text are joined to passages, and a passage goes if it has
``PASSAGE_WORDS`` words or more. What is lost of a copy that stands inside other
words is less than a ``WINDOW`` before its first common mark and two behind, so
a copy of over 50 words is found whatever stands around it. Passages come with
their offsets in the original text and the id of what is kept.

A digest that occurs a million times is reduced before it is shuffled (a
minimum per task), and the occurrences meet the kept one in a join whose large
side adaptive execution can split. Units are made twice, once for either step,
rather than stored: their table would be larger than the texts.

Null and empty texts have no units. Rows without an id rank after all others
and are never kept if another has the unit. Repeated rows of one id and text
count as one text; different texts under one id are told apart by a hash. An
empty table gives an empty result.
"""

from __future__ import annotations

import functools
import re
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.llm.common import cut, values

#: Words among which one is a mark, words of a unit at least, and words of a passage that goes.
WINDOW, UNIT_WORDS, PASSAGE_WORDS = 9, 24, 26

_WORD = re.compile(r"[^\W_]+")
_UNITS = "doc_id bigint, mark bigint, start int, after int, first int, last int, again boolean, d0 bigint, d1 bigint"
#: Odd bases of the polynomial hashes: of letters in a word, and of words in a unit.
_LETTERS, _BASES = 0x9E3779B97F4A7C15, (0xD6E8FEB86659FD93, 0xA0761D6478BD642F)
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2 ** 64; what was made is kept."""
    known = _powers.get(base)
    if known is None or len(known) < n:
        known = _powers[base] = np.cumprod(np.append(np.uint64(1), np.full(max(n, 4096) * 2, base, dtype=np.uint64)), dtype=np.uint64)
    return known[:n]


@functools.cache
def _inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


def _mixed(x: np.ndarray) -> np.ndarray:
    """Every bit of the result depends on every bit of the number."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _runs_hashed(numbers: np.ndarray, first: np.ndarray, last: np.ndarray, base: int) -> np.ndarray:
    """A hash of each run ``numbers[first:last]``, from prefix sums of a polynomial."""
    n = len(numbers)
    sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(numbers * _power(base, n), dtype=np.uint64)])
    shift = _power(_inverse(base), n)
    return _mixed((sums[last] - sums[first]) * shift[first] + (last - first).astype(np.uint64))


def _signs(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), dtype="<u4")


@functools.cache
def _letter_table() -> np.ndarray:
    """Whether a code point of the first plane is a letter or digit."""
    return np.array([chr(c).isalnum() for c in range(1 << 16)])


def words_hashed(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where each word starts and ends in the text in code points, and its hash after normalisation."""
    lowered = text.lower()
    if len(lowered) == len(text) and (text.isascii() or unicodedata.is_normalized("NFKC", lowered)):
        signs = _signs(lowered)
        inside = np.zeros(len(signs) + 2, dtype=np.int8)
        low = signs < 1 << 16
        inside[1:-1] = _letter_table()[np.where(low, signs, 0)]
        for at in np.flatnonzero(~low):
            inside[at + 1] = lowered[at].isalnum()
        turns = np.flatnonzero(np.diff(inside))
        starts, ends = turns[::2], turns[1::2]
        return starts, ends, _runs_hashed(signs.astype(np.uint64), starts, ends, _LETTERS)
    spans = [m.span() for m in _WORD.finditer(text)]
    words = [unicodedata.normalize("NFKC", text[a:b].lower()) for a, b in spans]
    after = np.cumsum([len(w) for w in words], dtype=np.int64)
    before = after - np.array([len(w) for w in words], dtype=np.int64)
    places = np.array(spans, dtype=np.int64).reshape(-1, 2)
    return places[:, 0], places[:, 1], _runs_hashed(_signs("".join(words)).astype(np.uint64), before, after, _LETTERS)


def marks_in(hashes: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Places of the smallest hash of every ``window`` neighbours, of equal ones the last."""
    n = len(hashes) - window + 1
    if n < 1:
        return np.array([], dtype=np.int64)
    back = np.lib.stride_tricks.sliding_window_view(hashes, window)[:, ::-1]
    places = np.arange(n) + window - 1 - back.argmin(axis=1)
    return places[np.diff(places, prepend=-1) > 0]


def units_of(text: str | None) -> np.ndarray:
    """A row ``start, after, first word, word after, again, d0, d1`` for each unit of a text, by place; offsets in code points.

    ``again`` is 1 for a unit that stands earlier in the text already.
    """
    none = np.zeros((0, 7), dtype=np.int64)
    starts, ends, words = words_hashed(text) if text else (none, none, none)
    if len(words) < UNIT_WORDS:
        return none
    marks = marks_in(words)
    at = np.searchsorted(marks, marks + UNIT_WORDS)
    first, last = marks[at < len(marks)], marks[at[at < len(marks)]]
    breaks = np.array([m.start() for m in re.finditer("\n", text)] + [len(text)])
    line_last = np.searchsorted(starts, breaks)
    line_first = np.concatenate([[0], line_last[:-1]])
    long = line_last - line_first >= UNIT_WORDS
    firsts, lasts = np.concatenate([first, line_first[long]]), np.concatenate([last, line_last[long]])
    spans = np.unique((firsts << 32) | lasts)
    first, last = spans >> 32, spans & ((1 << 32) - 1)
    digests = [_runs_hashed(_mixed(words + np.uint64(k)), first, last, base).view(np.int64) for k, base in enumerate(_BASES)]
    out = np.stack([starts[first], ends[last - 1], first, last, np.zeros_like(first), *digests], axis=1)
    if len(np.unique(digests[0])) < len(out):
        # A unit is no copy of itself where a text repeats at once.
        reached: dict[tuple[int, int], int] = {}
        keep = np.ones(len(out), dtype=bool)
        for row, (begin, end, _, a, b) in enumerate(out[:, 2:].tolist()):
            if begin >= reached.get((a, b), 0):
                out[row, 4] = (a, b) in reached
                reached[a, b] = end
            else:
                keep[row] = False
        out = out[keep]
    return out


def units(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, mark, start, after, first, last, again, d0, d1``: a row for each unit; ``mark`` tells texts of one id apart."""
    names = ["start", "after", "first", "last", "again", "d0", "d1"]
    kinds = (*(pa.int32(),) * 4, pa.bool_(), *(pa.int64(),) * 2)

    def make(source):
        for batch in source:
            for piece in (batch.slice(k, 512) for k in range(0, batch.num_rows, 512)):
                found = [units_of(value) for value in piece.column(2).to_pylist()]
                rows = np.concatenate(found)
                owner = pa.array(np.repeat(np.arange(len(found)), [len(f) for f in found]))
                columns = [pa.array(rows[:, k]).cast(kind) for k, kind in enumerate(kinds)]
                yield pa.record_batch([piece.column(0).take(owner), piece.column(1).take(owner), *columns], names=["doc_id", "mark", *names])

    body = F.col(text).cast("string")
    return documents.select(F.col(id_column).cast("bigint"), F.xxhash64(body), body).mapInArrow(make, _UNITS)


#: What a missing id ranks as.
_LAST_ID = (1 << 63) - 1


def repeated(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """Passages to remove: ``doc_id, mark, start, after, words, kept_id, digest``; the last two are of a passage's first unit."""
    rank = F.struct(F.coalesce("doc_id", F.lit(_LAST_ID)).alias("id"), "mark")
    kept = cut(
        units(documents, id_column, text)
        .select("d0", "d1", rank.alias("rank"))
        .groupBy("d0", "d1")
        .agg(F.count("*").alias("n"), F.min("rank").alias("kept"))
        .where("n > 1")
        .select("d0", "d1", "kept")
    )
    # The kept text's own first occurrence stays, and so do repeated rows of that text.
    again = units(documents, id_column, text).join(kept, ["d0", "d1"]).where((rank != F.col("kept")) | F.col("again")).drop("again").distinct()
    # Units that overlap or touch are one passage.
    text_of = Window.partitionBy("doc_id", "mark").orderBy("first", "last")
    reach = F.max("last").over(text_of.rowsBetween(Window.unboundedPreceding, -1))
    begun = again.withColumn("_new", F.coalesce(F.col("first") > reach, F.lit(True)).cast("int"))
    numbered = begun.withColumn("_passage", F.sum("_new").over(text_of.rowsBetween(Window.unboundedPreceding, 0)))
    head = F.min(F.struct("first", "last", "kept", "d0", "d1")).alias("_head")
    passages = numbered.groupBy("doc_id", "mark", "_passage").agg(
        F.min("start").alias("start"), F.max("after").alias("after"), (F.max("last") - F.min("first")).alias("words"), head
    )
    return passages.where(F.col("words") >= PASSAGE_WORDS).select(
        "doc_id", "mark", "start", "after", "words", F.nullif(F.col("_head.kept.id"), F.lit(_LAST_ID)).alias("kept_id"),
        F.lower(F.concat(*(F.lpad(F.hex(f"_head.{d}"), 16, "0") for d in ("d0", "d1")))).alias("digest"),
    )


def removal_spans(removed: DataFrame) -> DataFrame:
    """``doc_id, mark, spans``: each text's removed passages in order."""
    return removed.groupBy("doc_id", "mark").agg(F.array_sort(F.collect_list(F.struct("start", "after"))).alias("spans"))


def without_repeats(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with later copies of passages cut out of ``text``."""
    spans = removal_spans(repeated(documents, id_column, text)).toDF("_removed_id", "_removed_mark", "_spans")
    row = F.struct(*(F.col(f"`{n}`") for n in documents.columns)).alias("_row")
    body = F.col(text).cast("string")
    packed = documents.select(row, F.col(id_column).cast("bigint").alias("_id"), F.xxhash64(body).alias("_mark"), F.col(text).alias("_text"))
    mine = F.col("_id").eqNullSafe(F.col("_removed_id")) & (F.col("_mark") == F.col("_removed_mark"))
    joined = packed.join(spans, mine, "left")

    @F.arrow_udf("string")
    def clean(texts: pa.Array, cuts: pa.Array) -> pa.Array:
        out = []
        for value, spans in zip(values(texts), values(cuts), strict=True):
            for span in reversed(spans or []):
                value = value[: span["start"]] + value[span["after"] :]
            out.append(value)
        return pa.array(out, pa.string())

    cut_text = clean(F.col("_text"), F.col("_spans")).alias(text)
    return joined.select(*(F.col(f"_row.`{n}`").alias(n) if n != text else cut_text for n in documents.columns))
