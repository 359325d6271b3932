import random

import pytest

TYPES = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="session")
def make_docs(spark):
    """Documents from texts; ids from 1 unless pairs are given."""

    def make(texts, parts=3):
        rows = [t if isinstance(t, tuple) else (i, t) for i, t in enumerate(texts, 1)]
        rows = [(i, t, "en" if (i or 0) % 2 else None, f"s{(i or 0) % 3}" if (i or 0) % 5 else None, None if t is None else len(t)) for i, t in rows]
        return spark.createDataFrame(rows, TYPES).repartition(parts)

    return make


@pytest.fixture(scope="session")
def odd_texts():
    """Null, empty, blanks, long, non-ASCII, ties and copies."""
    rng = random.Random(5)
    words = ["".join(rng.choice("abcdeéñ") for _ in range(rng.randint(1, 6))) for _ in range(300)]
    prose = lambda n: " ".join(rng.choice(words) for _ in range(n))
    long = prose(30_000)
    copy = prose(80)
    return [None, "", "   \n\t ", "x", "\x00\x1c\x85 b  　", copy, copy, copy + " end", long, "A" * 50_000, "1" * 50_000, "@" * 2_000, "ÀÉ Straße 東京\n東京 \U0001f600", prose(200), prose(60) + "\n" + prose(60)]


@pytest.fixture
def clashing(make_docs, odd_texts):
    """Odd texts in a table whose further columns have names that operators use inside."""
    from pyspark.sql import functions as F

    frame = make_docs(odd_texts)
    for name in ("spans", "kept", "words", "_row", "fp", "key", "found", "_cell", "size", "_removed_id", "component_id", "n_words"):
        frame = frame.withColumn(name, F.lit("mine"))
    return frame
