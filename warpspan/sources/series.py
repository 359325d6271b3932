"""Series builders: tables to packed or long series, and back.

Packed series are rows ``(series_id BIGINT, v ARRAY<DOUBLE>, label STRING)``;
long ones have a row ``(series_id, pos, val)`` for each sample, ``pos`` from 1.
Every series built from a table holds whole numbers (cents, scaled
components, ``n*v - sum(v)`` for centring), so that sums are exact in any
order and engines agree to the last bit.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from warpspan.functions import kernels
from warpspan.sources.tables import table

PACKED = T.StructType(
    [T.StructField("series_id", T.LongType()), T.StructField("v", T.ArrayType(T.DoubleType())), T.StructField("label", T.StringType())]
)
SERIES = pa.list_(pa.float64())


def matrix(column: pa.Array) -> np.ndarray:
    """An Arrow list column as a matrix; all lists must be equally long."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1).astype(float, copy=False)


def arrays(rows: np.ndarray) -> pa.Array:
    """A matrix as an Arrow list column."""
    offsets = np.arange(0, rows.size + 1, rows.shape[1], dtype=np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.ascontiguousarray(rows, dtype=float).ravel()))


def pack(long: DataFrame, label: Column | None = None) -> DataFrame:
    """Long to packed; samples are put in order of ``pos``."""
    gathered = F.array_sort(F.collect_list(F.struct("pos", F.col("val").cast("double").alias("val"))))
    out = long.groupBy("series_id").agg(F.transform(gathered, lambda s: s.val).alias("v"))
    return out.withColumn("label", (F.lit(None) if label is None else label).cast("string"))


def unpack(packed: DataFrame) -> DataFrame:
    """Packed to long."""
    return packed.select("series_id", F.posexplode("v").alias("p", "val")).select(
        "series_id", (F.col("p") + 1).alias("pos"), F.col("val").cast("bigint").alias("val")
    )


def clean(packed: DataFrame, n: int) -> DataFrame:
    """Series of length n without null or NaN samples; others are left out, as NaN breaks every bound."""
    good = F.coalesce(~F.exists("v", lambda s: s.isNull() | F.isnan(s)), F.lit(False))
    return packed.where((F.size("v") == n) & good)


def check(packed: DataFrame, n: int) -> None:
    """Fails if any series has another length or a sample that is null or NaN."""
    if bad := packed.join(clean(packed, n), "series_id", "left_anti").limit(1).count():
        raise ValueError(f"{bad} or more series don't have {n} proper samples")


def walk(packed: DataFrame) -> DataFrame:
    """Centred and cumulated, in whole numbers; one vectorised pass."""

    @F.arrow_udf(T.ArrayType(T.DoubleType()))
    def cumulated(v: pa.Array) -> pa.Array:
        return arrays(kernels.walk(matrix(v))) if len(v) else v

    return packed.withColumn("v", cumulated("v"))


def normalised(packed: DataFrame) -> DataFrame:
    """Opt-in: mean 0 and deviation 1 (constant series become 0)."""
    n = F.size("v").cast("double")
    mean = F.aggregate("v", F.lit(0.0), lambda a, x: a + x) / n
    spread = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + (x - F.col("_m")) * (x - F.col("_m"))) / n)
    out = packed.withColumn("_m", mean).withColumn("_s", spread)
    unit = F.transform("v", lambda x: F.when(F.col("_s") > 0, (x - F.col("_m")) / F.col("_s")).otherwise(0.0))
    return out.withColumn("v", unit).drop("_m", "_s")


def gap_filled(sums: DataFrame, keys: DataFrame, steps: int) -> DataFrame:
    """Sparse ``(series_id, pos, val)`` onto the whole grid of keys and positions 1..steps, gaps 0."""
    grid = keys.select("series_id", F.explode(F.sequence(F.lit(1), F.lit(steps))).alias("pos"))
    return grid.join(sums, ["series_id", "pos"], "left").select("series_id", "pos", F.coalesce("val", F.lit(0)).alias("val"))


def on_grid(sums: DataFrame, steps: int) -> DataFrame:
    """The same packed, without a join: a map of the sparse sums is read at every position."""
    entries = F.map_from_entries(F.collect_list(F.struct("pos", F.col("val").cast("double"))))
    filled = F.transform(F.sequence(F.lit(1), F.lit(steps)), lambda i: F.coalesce(F.element_at(F.col("_m"), i), F.lit(0.0)))
    return sums.groupBy("series_id").agg(entries.alias("_m")).select("series_id", filled.alias("v"), F.lit(None).cast("string").alias("label"))


def _day(column: str) -> Column:
    return F.date_diff(F.to_date(column), F.lit("1995-01-02").cast("date"))


def _supplier_sums(spark: SparkSession, sf_dir: str, pos: Column, steps: int) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("series_id"), pos.alias("pos"), "l_quantity")
    return lines.where(F.col("pos").between(1, steps)).groupBy("series_id", "pos").agg(F.sum("l_quantity").alias("val"))


MONTHS, WEEKS, DAYS = 83, 256, 1000


def supplier_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity by supplier and month from January 1995, 83 months."""
    month = (F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate")
    return on_grid(_supplier_sums(spark, sf_dir, month, MONTHS), MONTHS)


def supplier_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity by supplier and week from 2 January 1995, 256 weeks."""
    week = F.floor(_day("l_shipdate") / 7).cast("int") + 1
    return on_grid(_supplier_sums(spark, sf_dir, week, WEEKS), WEEKS)


def supplier_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity by supplier and day, 1000 days."""
    return on_grid(_supplier_sums(spark, sf_dir, _day("l_shipdate") + 1, DAYS), DAYS)


def _first_n(rows: DataFrame, key: str, order: list[str], value: Column, n: int) -> DataFrame:
    """The first n values of each key, of keys that have as many."""
    numbered = rows.select(F.col(key).alias("series_id"), value.cast("double").alias("val"), *order)
    ranked = numbered.withColumn("pos", F.row_number().over(Window.partitionBy("series_id").orderBy(*order)))
    return pack(ranked.where(F.col("pos") <= n)).where(F.size("v") == n)


def part_qty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first 24 quantities of a part by ship date, order and line."""
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_quantity")
    return _first_n(lines, "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber"], F.col("l_quantity"), 24)


def user_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first 48 event values of a user in cents, by time."""
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "value")
    return _first_n(events, "user_id", ["ts", "event_id"], F.floor(F.col("value") * 100 + 0.5), 48)


def embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 64 components of a vector, in millionths."""
    scaled = F.transform("embedding", lambda e: F.floor(e.cast("double") * 1e6 + 0.5).cast("double"))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("series_id"), scaled.alias("v"), F.col("label").cast("string").alias("label"))


def word_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths of the first 251 pieces of a text between blanks; the language is the label."""
    pieces = F.transform(F.slice(F.split("text", " "), 1, 251), lambda s: F.length(s).cast("double"))
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("series_id"), pieces.alias("v"), F.col("lang").alias("label")).where(F.size("v") == 251)


def char_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Code points of the first 1024 characters of a text."""
    signs = F.split(F.substring("text", 1, 1024), "")
    code = F.transform(F.filter(signs, lambda s: s != ""), lambda s: F.ascii(s).cast("double"))
    return table(spark, sf_dir, "documents").where(F.length("text") >= 1024).select(F.col("doc_id").alias("series_id"), code.alias("v"), F.col("lang").alias("label"))


def nation_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order value in cents by nation and month, 80 months; the region is the label."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_totalprice")
    nations = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    month = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate")
    sums = (
        orders.join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
        .select(F.col("c_nationkey").cast("bigint").alias("series_id"), month.alias("pos"), F.floor(F.col("o_totalprice") * 100 + 0.5).alias("cents"))
        .where(F.col("pos").between(1, 80))
        .groupBy("series_id", "pos")
        .agg(F.sum("cents").alias("val"))
    )
    named = nations.select(F.col("n_nationkey").cast("bigint").alias("series_id"), F.col("r_name").alias("label"))
    return on_grid(sums, 80).drop("label").join(F.broadcast(named), "series_id")


def turn_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text lengths by turn of a conversation: short series of unequal length."""
    turns = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("series_id"), F.col("turn").alias("pos"), F.length("text").alias("val"))
    return pack(turns)


def tag_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths of the first 64 pieces of a page between opening brackets."""
    pieces = F.transform(F.slice(F.split("html", "<"), 1, 64), lambda s: F.length(s).cast("double"))
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("series_id"), pieces.alias("v"), F.lit(None).cast("string").alias("label")).where(F.size("v") == 64)


def sparse_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders a customer placed by month as a map from month to count, as long rows."""
    month = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate")
    counts = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("series_id"), month.alias("pos")).count()
    maps = counts.groupBy("series_id").agg(F.map_from_entries(F.collect_list(F.struct("pos", "count"))).alias("m"))
    return maps.select("series_id", F.explode("m").alias("pos", "val"))


def _walked(build: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: walk(build(spark, sf_dir))


#: Name of a fixture to its builder and its length.
FIXTURES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], int]] = {
    "supplier_month_raw": (supplier_month, MONTHS),
    "supplier_month_walk": (_walked(supplier_month), MONTHS),
    "supplier_week_raw": (supplier_week, WEEKS),
    "supplier_week_walk": (_walked(supplier_week), WEEKS),
    "supplier_day_walk": (_walked(supplier_day), DAYS),
    "part_qty_raw": (part_qty, 24),
    "part_qty_walk": (_walked(part_qty), 24),
    "user_raw": (user_events, 48),
    "user_walk": (_walked(user_events), 48),
    "embedding_walk": (_walked(embedding), 64),
    "word_length_raw": (word_lengths, 251),
    "word_walk": (_walked(word_lengths), 251),
    "char_walk": (_walked(char_codes), 1024),
    "nation_month": (nation_month, 80),
    "tag_walk": (_walked(tag_lengths), 64),
}


def fixture(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return FIXTURES[name][0](spark, sf_dir)


def hash_order(ids: str | Column = "series_id", salt: int = 1) -> Column:
    """A fixed pseudo-random order of ids in whole numbers that any engine reproduces."""
    z = (F.col(ids) if isinstance(ids, str) else ids) * 7919 + salt * 1299709
    z = F.pmod(z, F.lit(1000003))
    return F.pmod(z * z + salt, F.lit(1000003))


def split_queries(packed: DataFrame, n_queries: int) -> tuple[DataFrame, DataFrame]:
    """Held-out protocol: the first series in hash order are the queries and leave the database.

    There are ``n_queries`` of them, but at most half of the series.
    """
    first = packed.orderBy(hash_order(), "series_id").limit(2 * n_queries)
    in_order, whole = Window.orderBy(hash_order(), "series_id"), Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    placed = first.withColumn("_place", F.row_number().over(in_order)).withColumn("_n", F.count("*").over(whole))
    chosen = placed.where(F.col("_place") * 2 <= F.col("_n")).drop("_place", "_n")
    queries = chosen.select(F.col("series_id").alias("query_id"), F.col("v").alias("y"), "label")
    ids = F.broadcast(queries.select(F.col("query_id").alias("series_id")))
    return queries, packed.join(ids, "series_id", "left_anti")


def fraction_rank(packed: DataFrame) -> DataFrame:
    """Adds ``place`` (1 to N in hash order) and ``places`` (N): the first ceil(f * N) places are the fraction f, and fractions nest.

    Hashes have a million values, so the counts before each are a bounded
    table; rows of one hash are numbered by id.
    """
    rows = packed.withColumn("_h", hash_order())
    counts = rows.groupBy("_h").agg(F.count("*").alias("_c"))
    earlier = Window.orderBy("_h").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = counts.select("_h", F.coalesce(F.sum("_c").over(earlier), F.lit(0)).alias("_b"), F.sum("_c").over(whole).alias("places"))
    inside = F.row_number().over(Window.partitionBy("_h").orderBy("series_id"))
    return rows.join(F.broadcast(before), "_h").withColumn("place", F.col("_b") + inside).drop("_h", "_b")
