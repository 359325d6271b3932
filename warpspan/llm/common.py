"""Helpers that the text operators share."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterable
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII letters go to lower case and every other ASCII byte outside 0-9 and
#: a-z to a blank; bytes of multi-byte characters stay. Splitting the result
#: at blanks gives the words of ``[^\x00-\x2F\x3A-\x60\x7B-\x7F]+``.
WORD_TABLE = bytes(
    b if b >= 0x80 or 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A else b + 32 if 0x41 <= b <= 0x5A else 0x20
    for b in range(256)
)

#: The blanks of ``[\x20\x09-\x0D]``, as a Java or DuckDB character class.
BLANKS = r"[ \t-\r]"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words_of(text: bytes | None) -> list[bytes]:
    """Lower-cased words of a text in UTF-8; none for null."""
    return text.translate(WORD_TABLE).split() if text else []


def utf8(text: str | Column) -> Column:
    """The text's UTF-8 bytes, so that Python gets them without decoding."""
    return (F.col(text) if isinstance(text, str) else text).cast("binary")


def values(column: pa.Array | pa.ChunkedArray, piece: int = 512) -> Iterable:
    """Python values of an Arrow column, made a few at a time."""
    for start in range(0, len(column), piece):
        yield from column.slice(start, piece).to_pylist()


def checkpoint_dir(spark: SparkSession) -> str:
    """The folder for checkpoints that the session names; one of our own if it names none.

    A cluster sets ``spark.checkpoint.dir`` to a folder that all executors
    share. In a session without it, one on a single machine gets a temporary
    folder and any other a folder of the warehouse, which is shared as well.
    """
    context = spark.sparkContext
    found = context.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        base = tempfile.gettempdir() if context.master.startswith("local") else spark.conf.get("spark.sql.warehouse.dir")
        found = os.path.join(base, "warpspan-checkpoints")
    if not context.getCheckpointDir():
        context.setCheckpointDir(found)
    return found


#: Places of the tables that ``cut`` wrote and nothing deleted, in order.
_written: list[str] = []


def cut(frame: DataFrame) -> DataFrame:
    """The same rows with their lineage cut: written once to the shared checkpoint folder and read again.

    A written table is computed once, is there for every executor, and tells
    later joins its size.
    """
    spark = frame.sparkSession
    place = f"{checkpoint_dir(spark).rstrip('/')}/cut-{uuid.uuid4().hex}"
    with freeing(spark):
        frame.write.parquet(place)
    out = spark.read.schema(frame.schema).parquet(place)
    out._cut_at = place
    _written.append(place)
    return out


#: Spark's switch for deleting a plan's shuffle files when it has run; what was written or counted needs them no more.
FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def freeing(spark: SparkSession):
    """Plans that run inside let go of their shuffle files at their end; else these stay until the driver collects its garbage."""
    before = spark.conf.get(FREED, None)
    spark.conf.set(FREED, "true")
    try:
        yield
    finally:
        spark.conf.unset(FREED) if before is None else spark.conf.set(FREED, before)


def discard(frame: DataFrame) -> None:
    """Deletes what ``cut`` wrote for a frame that nothing needs any more."""
    place = getattr(frame, "_cut_at", None)
    if place in _written:
        _delete(frame.sparkSession, place)


def written_so_far() -> int:
    return len(_written)


def discard_since(mark: int, but: DataFrame) -> None:
    """Deletes all tables that ``cut`` wrote since ``written_so_far`` gave ``mark``, but for that of one frame."""
    for place in _written[mark:]:
        if place != getattr(but, "_cut_at", None):
            _delete(but.sparkSession, place)


def _delete(spark: SparkSession, place: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    _written.remove(place)
