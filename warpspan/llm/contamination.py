"""Benchmark decontamination: one automaton over the benchmark's word windows.

Texts and items are lower-cased (A-Z) and cut into words. A window is
``width`` consecutive words of an item, or the whole of a shorter item. All
windows go into one Aho-Corasick automaton over word numbers, so a text is
read once however many items there are, and a hit's place is known in words
and, where asked for, in bytes and code points of the original text.

The benchmark is the side that every task holds. Up to ``most_words`` words
make one automaton. A larger benchmark is cut into runs of items of that size.
Each run is a scan of its own, which writes the hits of the texts that have
any, so no task ever holds more than one automaton; the hits of all runs are
then joined by a digest of the text. Nothing is dropped either way.

Null texts have no words, and items without words have no window. An item
without an id counts for hits and verdicts but is in no list of items.
Repeated rows are judged each for itself. Empty tables give empty results.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from warpspan.llm.common import cut, utf8, values, words_of

WIDTH = 13
#: Words of one automaton; about 100 bytes a word in each Python worker.
MOST_WORDS = 2_000_000

HITS = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("hit", T.ArrayType(T.StructType([T.StructField("first", T.IntegerType()), T.StructField("after", T.IntegerType())]))),
        T.StructField("items", T.ArrayType(T.StringType())),
        T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))),
    ]
)
_ARROW_HITS = pa.struct(
    [
        ("n_words", pa.int64()),
        ("hit", pa.list_(pa.struct([("first", pa.int32()), ("after", pa.int32())]))),
        ("items", pa.list_(pa.string())),
        ("spans", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))),
    ]
)
#: The words in the original text.
_PLACES = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


class WindowScanner:
    """Finds the benchmark windows that occur in a list of words."""

    def __init__(self, items: list[tuple[str | None, list[bytes]]], width: int = WIDTH):
        self.numbers: dict[bytes, int] = {}
        windows: dict[tuple[int, ...], set[str | None]] = {}
        for item, words in items:
            coded = [self.numbers.setdefault(w, len(self.numbers) + 1) for w in words]
            for start in range(max(1, len(coded) - width + 1) if coded else 0):
                windows.setdefault(tuple(coded[start : start + width]), set()).add(item)
        self.automaton = None
        if windows:
            self.automaton = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
            for window, owners in windows.items():
                self.automaton.add_word(window, (len(window), tuple(sorted(owners - {None}))))
            self.automaton.make_automaton()

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Maximal runs ``(first, after)`` of hit words, and the items with a window here."""
        if self.automaton is None or not words:
            return [], set()
        found: set[str] = set()
        spans = []
        number = self.numbers.get
        for end, (length, owners) in self.automaton.iter(tuple([number(w, 0) for w in words])):
            spans.append((end - length + 1, end + 1))
            found.update(owners)
        return merged(spans), found


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The union of half-open intervals as disjoint intervals in order."""
    out: list[tuple[int, int]] = []
    for first, after in sorted(spans):
        if out and first <= out[-1][1]:
            out[-1] = (out[-1][0], max(after, out[-1][1]))
        else:
            out.append((first, after))
    return out


def word_places(text: str) -> list[tuple[int, int]]:
    """Start and end of each word in code points of the original text."""
    return [m.span() for m in _PLACES.finditer(text)]


def original_spans(text: str, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Runs of words as code points of the text."""
    places = word_places(text) if runs else []
    return [(places[first][0], places[after - 1][1]) for first, after in runs]


def benchmark_runs(benchmark: DataFrame, most_words: int = MOST_WORDS) -> Iterator[list[tuple[str | None, list[bytes]]]]:
    """The items with their words, in runs of at most ``most_words`` words (one item at least).

    Items stream to the driver one partition at a time; a run is let go before
    the next is read.
    """
    run: list[tuple[str | None, list[bytes]]] = []
    size = 0
    rows = benchmark.select(F.col("item_id").cast("string"), utf8("text"))
    for item, text in rows.where(F.length("text") > 0).toLocalIterator():
        words = words_of(bytes(text))
        if not words:
            continue
        if run and size + len(words) > most_words:
            yield run
            run, size = [], 0
        run.append((item, words))
        size += len(words)
    yield run


def _found(value: bytes | None, scanner: WindowScanner) -> dict:
    words = words_of(value)
    runs, items = scanner.scan(words)
    spans = original_spans(value.decode(), runs) if runs else []
    return {
        "n_words": len(words),
        "hit": [{"first": a, "after": b} for a, b in runs],
        "items": sorted(items),
        "spans": [{"start": a, "end": b} for a, b in spans],
    }


def _scan_column(spark, run: list, width: int, text: Column) -> Column:
    shared = spark.sparkContext.broadcast(run)
    ready: list[WindowScanner] = []

    @F.arrow_udf(HITS)
    def scan(texts: pa.Array) -> pa.Array:
        if not ready:
            ready.append(WindowScanner(shared.value, width))
        return pa.array([_found(value, ready[0]) for value in values(texts)], _ARROW_HITS)

    return scan(utf8(text))


def _digest(text: Column) -> Column:
    return F.struct(F.xxhash64(text).alias("a"), F.xxhash64(F.lit(1), text).alias("b"))


def with_hits(documents: DataFrame, benchmark: DataFrame, text: str = "text", into: str = "_found", width: int = WIDTH, most_words: int = MOST_WORDS) -> DataFrame:
    """Adds a struct of ``n_words``, ``hit`` (word intervals), ``items`` and ``spans`` (code points of the original text)."""
    spark, body = documents.sparkSession, F.col(f"`{text}`")
    runs = benchmark_runs(benchmark, most_words)
    first = next(runs)
    second = next(runs, None)
    if second is None:
        return documents.withColumn(into, _scan_column(spark, first, width, body))
    parts = []
    for run in itertools.chain((first, second), runs):
        seen = documents.select(_digest(body).alias("_of"), _scan_column(spark, run, width, body).alias("_hit")).where(F.size("_hit.hit") > 0)
        parts.append(cut(seen.dropDuplicates(["_of"])))
    every = functools.reduce(DataFrame.unionByName, parts).groupBy("_of").agg(F.collect_list("_hit").alias("_hits"))
    counted = documents.withColumn(into, _scan_column(spark, [], width, body)).withColumn("_text_of", _digest(body))
    joined = counted.join(every, F.col("_text_of") == F.col("_of"), "left")

    @F.arrow_udf(HITS)
    def put_together(texts: pa.Array, plain: pa.Array, pieces: pa.Array) -> pa.Array:
        rows = []
        for value, row, found in zip(values(texts), values(plain), values(pieces), strict=True):
            if found:
                hit = merged([(h["first"], h["after"]) for piece in found for h in piece["hit"]])
                row["hit"] = [{"first": a, "after": b} for a, b in hit]
                row["items"] = sorted({item for piece in found for item in piece["items"]})
                row["spans"] = [{"start": a, "end": b} for a, b in original_spans(value.decode(), hit)]
            rows.append(row)
        return pa.array(rows, _ARROW_HITS)

    return joined.withColumn(into, put_together(utf8(body), F.col(into), F.col("_hits"))).drop("_text_of", "_of", "_hits")


def judged(hits: Column) -> tuple[Column, Column]:
    """Hit words, and whether they make the document contaminated: a twentieth of its words or more."""
    n_hit = F.aggregate(
        F.transform(hits.hit, lambda h: (h.after - h["first"]).cast("long")), F.lit(0).cast("long"), lambda a, b: a + b
    )
    return n_hit, (n_hit > 0) & (20 * n_hit >= hits.n_words)


def _packed(documents: DataFrame, text: str) -> DataFrame:
    """The rows as one struct beside their text, so that no name of theirs meets one of ours."""
    return documents.select(F.struct(*(F.col(f"`{name}`") for name in documents.columns)).alias("_row"), F.col(f"`{text}`").alias("_text"))


def scan_documents(documents: DataFrame, benchmark: DataFrame, id_column: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row per document: words, hit words, items found, the verdict, and the hit stretches of the original text."""
    found = with_hits(_packed(documents, text), benchmark, "_text", **options)
    n_hit, contaminated = judged(F.col("_found"))
    items = F.col("_found.items")
    return found.select(
        F.col(f"_row.`{id_column}`").alias(id_column),
        F.col("_found.n_words").alias("n_words"),
        n_hit.alias("n_hit"),
        F.size(items).cast("long").alias("n_items"),
        F.sha2(F.array_join(items, ","), 256).alias("items_sha256"),
        contaminated.alias("contaminated"),
        items.alias("items"),
        F.col("_found.spans").alias("spans"),
    )


def drop_contaminated(documents: DataFrame, benchmark: DataFrame, text: str = "text", **options) -> DataFrame:
    """The documents that aren't contaminated, with their own columns."""
    found = with_hits(_packed(documents, text), benchmark, "_text", **options)
    _, contaminated = judged(F.col("_found"))
    return found.where(~contaminated).select("_row.*")


def hit_spans(text: str, scanner: WindowScanner) -> list[tuple[int, int]]:
    """Hit runs of one text in code points of the original."""
    runs, _ = scanner.scan(words_of(text.encode()))
    return original_spans(text, runs)


def items_digest(items: set[str]) -> str:
    """SHA-256 of the sorted, comma-joined item ids."""
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
