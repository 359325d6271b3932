"""Sharding along a Hilbert curve over metadata.

Language, source and the logarithm of the length are quantised to four bits
each; a document's cell on the three-dimensional Hilbert curve over them is
its first sort key, so a shard is a run of the curve and holds few distinct
values of every dimension. Files cut from such runs have narrow min/max
ranges in all dimensions, which lets readers skip them.

Equal texts are one group: it stands in the cell of its member with the
smallest id, side by side, so that a group falls on both sides of a cut only
where the cut runs through it.

The curve has 4,096 cells, so the table of cell counts has a fixed bound. A
cell with many documents (a hot source) is split by a hash of the text into
parts of about ``part_rows(N)`` rows, and a group larger than that by a hash of
the id; ranks then come from prefix sums over the table of parts, of at most
140,000 rows at any size, and a row number inside each part.

Law ``rows``: with N documents, the shards get N // n or one more each. Law
``bytes``: a document goes to the shard in whose share of all bytes it starts,
so shard sizes differ from the mean by less than the largest document.

Null languages and sources are values of their own, a null text has size 1
and CRC-32 zero and is equal to an empty one. Repeated rows get slots of their
own; ties are broken by all columns that the rank uses, and rows equal in these
are interchangeable. An empty table gives an empty result.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.llm.common import cut

BITS = 4
DIMENSIONS = ("lang", "source", "size")
SHARDS = 16
#: Rows of a part where documents are few, and parts (besides cells) where they are many.
LEAST_ROWS, MOST_PARTS = 4_096, 65_536
#: Groups of equal texts that are sent to every task; more are joined by a shuffle.
MOST_SENT = 2_000_000


def part_rows(n: Column) -> Column:
    """Rows that one sorted part should have if there are n in all."""
    return F.greatest(F.lit(float(LEAST_ROWS)), n / F.lit(MOST_PARTS))


def hilbert_place(point: list[int], bits: int = BITS) -> int:
    """The place on the Hilbert curve of a point with ``bits`` bits in each axis.

    From the highest bit down, an axis with its bit set inverts the lower bits
    of the first axis, and one without exchanges its lower bits with the first
    axis; a Gray code over the axes follows, and the bits are interleaved.
    """
    x, n = list(point), len(point)
    for level in range(bits - 1, 0, -1):
        low = (1 << level) - 1
        for k in range(n):
            if x[k] >> level & 1:
                x[0] ^= low
            else:
                differ = (x[0] ^ x[k]) & low
                x[0] ^= differ
                x[k] ^= differ
    for k in range(1, n):
        x[k] ^= x[k - 1]
    turn = 0
    for level in range(bits - 1, 0, -1):
        if x[-1] >> level & 1:
            turn ^= (1 << level) - 1
    index = 0
    for level in range(bits - 1, -1, -1):
        for axis in x:
            index = index << 1 | ((axis ^ turn) >> level & 1)
    return index


def _axes(lang: Column, source: Column, chars: Column) -> list[Column]:
    top = (1 << BITS) - 1
    code = lambda value: F.pmod(F.crc32(F.coalesce(value.cast("string"), F.lit("")).cast("binary")), F.lit(top + 1))
    return [code(lang), code(source), F.least(F.lit(top), F.floor(F.log2(F.coalesce(chars, F.lit(0)) + 1)))]


def curve_table(bits: int = BITS, axes: int = 3) -> list[int]:
    """The curve index of every cell, cells numbered with the first axis as the highest digit."""
    out = []
    for cell in range(1 << (bits * axes)):
        point = [(cell >> (bits * (axes - 1 - k))) & ((1 << bits) - 1) for k in range(axes)]
        out.append(hilbert_place(point, bits))
    return out


def with_cell(documents: DataFrame, into: str = "_cell") -> DataFrame:
    """Adds the Hilbert cell; the curve's table is looked up, so the plan stays small."""
    lang, source, chars = _axes(F.col("lang"), F.col("source"), F.length("text"))
    number = (lang * (1 << 2 * BITS) + source * (1 << BITS) + chars).cast("int")
    table = F.array(*map(F.lit, curve_table()))
    return documents.withColumn(into, F.get(table, number))


_PART_KEYS = ["_cell", "_part", "_hot", "_piece"]


class Layout(NamedTuple):
    """Small tables that say where rows go: groups of equal texts, cells, and parts with what stands before them."""

    groups: DataFrame
    cells: DataFrame
    parts: DataFrame


def _in_parts(rows: DataFrame, groups: DataFrame, cells: DataFrame) -> DataFrame:
    """Adds the part's keys. Rows have ``_id, _cell, _group, size`` and ``_crc``."""
    rows = rows.join(groups, "_group", "left").withColumn("_cell", F.coalesce("_home", "_cell"))
    placed = rows.join(F.broadcast(cells), "_cell").withColumn("_part", F.pmod(F.xxhash64("_group"), "_parts").cast("int"))
    # A group beyond a part's size is parts of its own.
    pieces, hot = F.ceil(F.col("_large") / F.col("_most")).cast("int"), F.coalesce(F.col("_large") > F.col("_most"), F.lit(False))
    return (
        placed.withColumn("_hot", F.when(hot, F.col("_group")).otherwise(F.lit(0)).cast("bigint"))
        .withColumn("_piece", F.when(hot, F.pmod(F.xxhash64("_id", "_crc", "size"), pieces)).otherwise(0).cast("int"))
        .drop("_parts", "_most", "_large", "_home")
    )


def layout(light: DataFrame) -> Layout:
    """The tables for rows with ``_id, _cell, _group, size, _crc``; ``light`` should hold no more than these.

    A group takes the cell of its member with the smallest id. Only groups of
    two or more are listed; they are sent to all tasks if they are few.
    """
    first = F.min(F.struct(F.col("_id").isNull().alias("no_id"), "_id", "_cell"))
    groups = cut(
        light.groupBy("_group").agg(F.count("*").alias("_large"), first.alias("_first")).where("_large > 1").select("_group", "_large", F.col("_first._cell").alias("_home"))
    )
    if groups.count() <= MOST_SENT:
        groups = F.broadcast(groups)
    whole = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    homes = light.join(groups, "_group", "left").groupBy(F.coalesce("_home", "_cell").alias("_cell")).agg(F.count("*").alias("_n"))
    most = part_rows(F.sum("_n").over(whole))
    cells = cut(homes.select("_cell", F.ceil(F.col("_n") / most).cast("int").alias("_parts"), most.alias("_most")))
    parts = _in_parts(light, groups, cells).groupBy(*_PART_KEYS).agg(F.count("*").alias("_n"), F.sum("size").alias("_size"))
    in_order = Window.orderBy(*_PART_KEYS).rowsBetween(Window.unboundedPreceding, -1)
    before = parts.select(
        *_PART_KEYS,
        F.coalesce(F.sum("_n").over(in_order), F.lit(0)).alias("_rows_before"),
        F.coalesce(F.sum("_size").over(in_order), F.lit(0)).alias("_size_before"),
        F.sum("_n").over(whole).alias("_rows"),
        F.sum("_size").over(whole).alias("_bytes"),
    )
    return Layout(groups, cells, cut(before))


def ranked(rows: DataFrame, plan: Layout, shards: int = SHARDS, law: str = "rows") -> DataFrame:
    """Adds ``shard`` and ``slot`` to rows with ``_id, _cell, _group, size, _crc``, in one shuffle."""
    if law not in ("rows", "bytes"):
        raise ValueError("law is 'rows' or 'bytes'")
    placed = _in_parts(rows, plan.groups, plan.cells)
    inside = Window.partitionBy(*_PART_KEYS).orderBy("_group", "_id", "_crc", "size")
    ahead = inside.rowsBetween(Window.unboundedPreceding, -1)
    numbered = placed.withColumn("_row", F.row_number().over(inside) - 1)
    if law == "bytes":
        numbered = numbered.withColumn("_ahead", F.coalesce(F.sum("size").over(ahead), F.lit(0)))
    else:
        numbered = numbered.withColumn("_ahead", F.col("_row").cast("long"))
    placed = numbered.join(F.broadcast(plan.parts), _PART_KEYS)
    if law == "rows":
        rank, total = F.col("_rows_before") + F.col("_row"), F.col("_rows")
        base, more = F.expr(f"_rows div {shards}"), total % shards
        head = more * (base + 1)
        shard = F.when(rank < head, F.floor(rank / (base + 1))).otherwise(more + F.floor((rank - head) / F.greatest(base, F.lit(1))))
        start = F.col("shard") * base + F.least(F.col("shard").cast("long"), more)
        out = placed.withColumn("_rank", rank).withColumn("shard", shard.cast("int")).withColumn("slot", F.col("_rank") - start)
    else:
        start = F.col("_size_before") + F.col("_ahead")
        out = placed.withColumn("_rank", F.col("_rows_before") + F.col("_row")).withColumn(
            "shard", F.least(F.lit(shards - 1), F.floor(start * F.lit(shards).cast("decimal(20,0)") / F.col("_bytes"))).cast("int")
        )
        firsts = F.broadcast(out.groupBy("shard").agg(F.min("_rank").alias("_first")))
        out = out.join(firsts, "shard").withColumn("slot", F.col("_rank") - F.col("_first"))
    inner = ("_row", "_ahead", "_rows_before", "_size_before", "_rows", "_bytes", "_rank", "_first")
    return out.drop("_id", "_group", "_crc", *_PART_KEYS, *inner)


def _text_group(text: Column) -> Column:
    """A hash of the text, in which null is as empty."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def _keyed(documents: DataFrame, id_column: str = "doc_id") -> DataFrame:
    """The documents as one struct ``_whole`` beside what the layout asks for."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return with_cell(documents).select(
        F.struct(*(F.col(f"`{name}`") for name in documents.columns)).alias("_whole"),
        F.col(id_column).alias("_id"),
        "_cell",
        _text_group(F.col("text")).alias("_group"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text.cast("binary")).alias("_crc"),
    )


def assign(documents: DataFrame, shards: int = SHARDS, law: str = "rows", id_column: str = "doc_id") -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot`` of every document; texts are read once and never moved."""
    light = cut(_keyed(documents, id_column).drop("_whole"))
    out = ranked(light.withColumn("doc_id", F.col("_id")).withColumn("text_crc32", F.col("_crc")), layout(light), shards, law)
    return out.select(
        "doc_id", "size", "text_crc32", F.lit(law).alias("law"), "shard", F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def attach(documents: DataFrame, shards: int = SHARDS, law: str = "rows") -> DataFrame:
    """The documents with ``shard`` and ``slot``; columns of these names that are there already come out as ``old_shard`` and ``old_slot``."""
    keyed = _keyed(documents)
    out = ranked(keyed, layout(cut(keyed.drop("_whole"))), shards, law)
    names = [F.col(f"_whole.`{name}`").alias(f"old_{name}" if name in ("shard", "slot") else name) for name in documents.columns]
    return out.select(*names, "shard", F.col("slot").cast("long").alias("slot"))


def write_shards(documents: DataFrame, path: str, shards: int = SHARDS, **options) -> None:
    """Writes the documents as one folder per shard, rows in curve order inside it."""
    laid = attach(documents, shards, **options)
    laid.repartitionByRange(shards, "shard").sortWithinPartitions("shard", "slot").write.mode("errorifexists").partitionBy(
        "shard"
    ).parquet(path)
