"""Token counts without token ids.

A text is cut into pre-tokens: a run of white space that a word does not
follow directly, or an optional blank with the run of other characters after
it. The tokenizer's own pre-tokenisation never joins characters across these
cuts, so a text has as many tokens as its pre-tokens together.

1. Documents are tallied in batches. A batch gives its *ledger* (for each
   document the numbers of its distinct pre-tokens and how often each occurs)
   and, for each bucket of a hash, the list of its distinct pre-tokens there.
2. The lists are dealt out by bucket. All lists of a bucket meet in one task,
   which counts the pieces of each distinct pre-token once. There are as many
   buckets as the size of the input asks for, so a task holds the distinct
   pre-tokens of one bucket and no more, and never forgets one of them.
3. Piece counts go back by batch and meet the ledger there: each document's
   tokens are the sum of frequency times pieces.

Texts are read once and never shuffled; lists and ledgers are compressed. A
pre-token is listed once per batch however common it is, and a batch is
bounded by its characters, so no task gets more than its share.

Null and empty texts have no tokens. Repeated rows and ids are kept apart by
their place in the ledger. An empty table gives an empty result.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from warpspan.llm.common import values

# White space as Unicode has it; Python's own class also holds \x1c to \x1f.
_SPACE = "\t-\r \x85\xa0  -     　"
PRE_TOKEN = re.compile(f" ?[^{_SPACE}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]+")

#: A batch is closed at so many characters; its distinct pre-tokens fit a worker's memory.
BATCH_CHARS = 8_000_000

#: Stored bytes of input for one bucket, and how few and many buckets there may be (their numbers take two bytes).
BUCKET_BYTES, LEAST_BUCKETS, MOST_BUCKETS = 4_000_000, 16, 60_000
#: From here on an estimate stands for "unknown".
UNKNOWN_BYTES = 1 << 60

_ROWS = pa.schema([("bucket", pa.int32()), ("batch", pa.int64()), ("listed", pa.int32()), ("body", pa.binary())])
_ROW_TYPES = "bucket int, batch bigint, listed int, body binary"
_COUNTS = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64())])


def _row(*cells) -> pa.RecordBatch:
    return pa.record_batch([pa.array([x], f.type) for x, f in zip(cells, _ROWS, strict=True)], schema=_ROWS)


def special_strings(definition: str) -> list[str]:
    """The added tokens that the library recognises inside texts, longest first; ``definition`` is the tokenizer's JSON."""
    import json

    added = json.loads(definition).get("added_tokens", [])
    return sorted((x["content"] for x in added), key=len, reverse=True)


def pre_tokens(text: str, special: re.Pattern | None = None) -> list[str]:
    """All pre-tokens in order; special strings stand by themselves."""
    if special is None or special.search(text) is None:
        return PRE_TOKEN.findall(text)
    out = []
    for part in special.split(text):
        out += [part] if special.fullmatch(part) else PRE_TOKEN.findall(part)
    return out


def _special(strings: list[str]) -> re.Pattern | None:
    return re.compile("(" + "|".join(map(re.escape, strings)) + ")") if strings else None


class _Numbers(dict):
    """Gives each new key the next number."""

    def __missing__(self, key):
        self[key] = number = len(self)
        return number


class _Tally:
    """The pre-tokens of a batch of documents, in the making."""

    def __init__(self) -> None:
        self.numbers = _Numbers()
        self.ids: list[int | None] = []
        self.lengths: list[int] = []
        self.sizes: list[int] = []
        self.codes: list[int] = []
        self.times: list[int] = []
        self.chars = 0

    def add(self, doc_id: int | None, text: str | None, special: re.Pattern | None) -> None:
        counted = Counter(pre_tokens(text, special)) if text else {}
        self.codes += [self.numbers[x] for x in counted]
        self.times += counted.values()
        self.sizes.append(len(counted))
        self.ids.append(doc_id)
        self.lengths.append(len(text.encode()) if text else 0)
        self.chars += len(text or "")

    def ledger(self, bucket_of: np.ndarray) -> bytes:
        """All but the pre-tokens themselves, compressed; numbers are sorted in a document and stored as steps."""
        sizes = np.array(self.sizes, dtype="<i4")
        owner = np.repeat(np.arange(len(sizes), dtype=np.int64), sizes)
        codes, times = np.array(self.codes, dtype=np.int64), np.array(self.times, dtype="<i4")
        order = np.argsort((owner << 32) | codes, kind="stable")
        steps = np.diff(codes[order], prepend=0).astype("<i4")
        plane = lambda x: np.ascontiguousarray(x.view(np.uint8).reshape(-1, 4).T).tobytes()
        ids = np.array([0 if x is None else x for x in self.ids], dtype="<i8")
        known = np.array([x is not None for x in self.ids], dtype=np.uint8)
        head = np.array([len(sizes), len(codes), len(bucket_of)], dtype="<i8")
        parts = [head, ids, np.array(self.lengths, dtype="<i8"), known, sizes, bucket_of.astype("<u2")]
        return zstandard.compress(b"".join([x.tobytes() for x in parts] + [plane(steps), plane(times[order])]), 6)

    def rows(self, batch: int, buckets: int):
        """The ledger's row, then one for each bucket with the batch's pre-tokens in the order of their numbers."""
        words = list(self.numbers)
        bucket_of = np.fromiter((zlib.crc32(w.encode()) % buckets for w in words), dtype=np.int64, count=len(words))
        yield _row(batch % buckets, batch, -1, self.ledger(bucket_of))
        order = np.argsort(bucket_of, kind="stable")
        cuts = np.searchsorted(bucket_of[order], np.arange(buckets + 1))
        for bucket in range(buckets):
            chosen = order[cuts[bucket] : cuts[bucket + 1]]
            if len(chosen):
                text = [words[k] for k in chosen]
                sizes = np.array([len(w) for w in text], dtype="<u4").tobytes()
                yield _row(bucket, batch, len(chosen), zstandard.compress(sizes + "".join(text).encode(), 6))


def _listed(body: bytes, n: int) -> list[str]:
    raw = zstandard.decompress(body)
    ends = np.cumsum(np.frombuffer(raw, "<u4", n)).tolist()
    text = raw[4 * n :].decode()
    return [text[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def _read_ledger(body: bytes):
    raw = zstandard.decompress(body)
    n, entries, distinct = np.frombuffer(raw, "<i8", 3)
    at = 24

    def take(kind: str, count: int) -> np.ndarray:
        nonlocal at
        out = np.frombuffer(raw, kind, count, at)
        at += out.nbytes
        return out

    ids, lengths, known, sizes, bucket_of = take("<i8", n), take("<i8", n), take("u1", n), take("<i4", n), take("<u2", distinct)
    planes = [np.ascontiguousarray(take("u1", 4 * entries).reshape(4, -1).T).view("<i4").ravel() for _ in range(2)]
    return ids, known, lengths, sizes, np.cumsum(planes[0].astype(np.int64)), planes[1], bucket_of


def tallies(documents: DataFrame, special: list[str], buckets: int, batch_chars: int = BATCH_CHARS) -> DataFrame:
    """Rows of ledgers and of lists of pre-tokens, batch by batch."""
    pattern = _special(special)

    def make(source):
        from pyspark import TaskContext

        place, tally = TaskContext.get().partitionId() << 24, _Tally()
        for batch in source:
            for doc_id, text in zip(values(batch.column(0), 64), values(batch.column(1), 64), strict=True):
                tally.add(doc_id, text, pattern)
                if tally.chars >= batch_chars or len(tally.ids) >= 1_000_000:
                    yield from tally.rows(place, buckets)
                    place, tally = place + 1, _Tally()
        if tally.ids:
            yield from tally.rows(place, buckets)

    return documents.mapInArrow(make, _ROW_TYPES)


def _tokenizer(definition: str):
    """The tokenizer of a definition, kept in the worker process for later tasks; one thread, as the task has one core."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    import tokenizers

    kept = tokenizers.__dict__.setdefault("_kept_by_definition", {})
    key = zlib.crc32(definition.encode()), len(definition)
    if key not in kept:
        kept[key] = tokenizers.Tokenizer.from_str(definition)
    return kept[key]


def count_pieces(rows: DataFrame, definition: str) -> DataFrame:
    """Puts the numbers of pieces in place of listed pre-tokens; ledgers pass through. Rows come bucket by bucket."""
    shared = rows.sparkSession.sparkContext.broadcast(definition)

    def make(source):
        tokenizer = _tokenizer(shared.value)
        memo: dict[str, int] = {}
        bucket = None
        for batch in source:
            for row in batch.to_pylist():
                if row["listed"] >= 0:
                    if row["bucket"] != bucket:
                        # A pre-token belongs to one bucket, so it is never asked for again.
                        bucket, memo = row["bucket"], {}
                    words = _listed(row["body"], row["listed"])
                    new = [w for w in words if w not in memo]
                    for start in range(0, len(new), 1024):
                        part = new[start : start + 1024]
                        memo.update(zip(part, (len(x.ids) for x in tokenizer.encode_batch(part, add_special_tokens=False)), strict=True))
                    row["body"] = zstandard.compress(np.array([memo[w] for w in words], dtype="<i4").tobytes())
                yield _row(*row.values())

    return rows.mapInArrow(make, _ROW_TYPES)


def _settle(rows: pa.Table) -> pa.Table:
    by_bucket = {}
    ledger = None
    for row in rows.to_pylist():
        if row["listed"] < 0:
            ledger = row["body"]
        else:
            by_bucket[row["bucket"]] = np.frombuffer(zstandard.decompress(row["body"]), "<i4")
    ids, known, lengths, sizes, codes, times, bucket_of = _read_ledger(ledger)
    pieces = np.zeros(max(1, len(bucket_of)), dtype=np.int64)
    for bucket, counts in by_bucket.items():
        pieces[: len(bucket_of)][bucket_of == bucket] = counts
    sums = np.concatenate([[0], np.cumsum(pieces[codes] * times)])
    ends = np.cumsum(sizes)
    return pa.table([pa.array(ids, mask=known == 0), lengths, sums[ends] - sums[ends - sizes]], schema=_COUNTS)


def buckets_for(documents: DataFrame) -> int:
    """One bucket for so many stored bytes of the input, by the plan's own estimate of its size.

    A plan that can't tell (rows that come from no table) has as many as the session has shuffle partitions.
    """
    size = int(str(documents._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    wanted = -(-size // BUCKET_BYTES) if size < UNKNOWN_BYTES else int(documents.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return min(MOST_BUCKETS, max(LEAST_BUCKETS, wanted))


def count_tokens(
    documents: DataFrame, tokenizer_file: str, id_column: str = "doc_id", text: str = "text", batch_chars: int = BATCH_CHARS, buckets: int | None = None
) -> DataFrame:
    """``doc_id, n_bytes, n_tokens`` for every document; the tokenizer's file is read here and sent to the tasks."""
    with open(tokenizer_file, encoding="utf-8") as file:
        definition = file.read()
    source = documents.select(F.col(id_column).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    n = buckets or buckets_for(documents)
    dealt = tallies(source, special_strings(definition), n, batch_chars).repartition(n, "bucket").sortWithinPartitions("bucket")
    return count_pieces(dealt, definition).groupBy("batch").applyInArrow(_settle, "doc_id bigint, n_bytes bigint, n_tokens bigint")
