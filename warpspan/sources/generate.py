"""Generated series: random walks and two families of shape classes.

Each generator draws in the engine, by seeded column expressions, so that any
number of series is made in parallel: one for each of a number of ids, or one
for each row of a table with a column ``id``. ``whole`` variants use whole
numbers and an integer hash, for comparison with other engines.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from warpspan.sources.series import arrays, matrix, walk


def hash_noise(series_id: Column, pos: Column, salt: int) -> Column:
    """Whole numbers from -1000 to 1000 from id, position and salt."""
    z = F.pmod(series_id * 7919 + pos * 104729 + F.lit(salt * 1299709), F.lit(1000003))
    z = F.pmod(z * z + salt, F.lit(1000003))
    return F.pmod(z * 7 + F.floor(z / 1009), F.lit(2001)) - 1000


def _bell(series_id: Column, pos: Column, salt: int) -> Column:
    return hash_noise(series_id, pos, salt) + hash_noise(series_id, pos, salt + 1) + hash_noise(series_id, pos, salt + 2)


def _ids(spark: SparkSession, series: int | DataFrame) -> DataFrame:
    """The ids that series are drawn for: those of the rows, dealt to all cores as a series is much work for an id, or so many from 0."""
    if isinstance(series, DataFrame):
        return series.select(F.col("id").cast("bigint").alias("id")).repartition(spark.sparkContext.defaultParallelism)
    return spark.range(series)


def _uniform(series_id: Column, pos: Column, salt: int) -> Column:
    """Numbers inside (0, 1) that follow from id, position and salt."""
    return (F.shiftrightunsigned(F.xxhash64(series_id, pos, F.lit(salt)), 11).cast("double") + 0.5) / float(1 << 53)


def _gauss(series_id: Column, pos: Column, seed: int) -> Column:
    """Gaussian noise that follows from id, position and seed, however rows are dealt."""
    return F.sqrt(-2 * F.log(_uniform(series_id, pos, 2 * seed))) * F.cos(2 * math.pi * _uniform(series_id, pos, 2 * seed + 1))


def random_walk(spark: SparkSession, series: int | DataFrame, n: int, seed: int = 0) -> DataFrame:
    """Walks that start at 0 with independent Gaussian steps."""
    steps = F.concat(F.array(F.lit(0.0)), F.filter(F.transform(F.sequence(F.lit(1), F.lit(max(n - 1, 1))), lambda i: _gauss(F.col("id"), i, seed)), lambda _, k: k < n - 1))

    @F.arrow_udf(T.ArrayType(T.DoubleType()))
    def cumulated(v: pa.Array) -> pa.Array:
        return arrays(matrix(v).cumsum(axis=1)) if len(v) else v

    rows = _ids(spark, series).select(F.col("id").alias("series_id"), steps.alias("v"), F.lit(None).cast("string").alias("label"))
    return rows.withColumn("v", cumulated("v"))


def whole_walk(spark: SparkSession, series: int | DataFrame, n: int, salt: int = 11) -> DataFrame:
    """Centred walks of whole bell-shaped steps."""
    steps = F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i: _bell(F.col("id"), i.cast("long"), salt).cast("double"))
    rows = _ids(spark, series).select(F.col("id").alias("series_id"), steps.alias("v"), F.lit(None).cast("string").alias("label"))
    return walk(rows)


def shape_classes(spark: SparkSession, kind: str, series: int | DataFrame, n: int | None = None, seed: int = 0) -> DataFrame:
    """Labelled shapes in noise, classes in turn.

    ``cbf``: a plateau, a rising or a falling ramp of random place and height
    over noise. ``control``: a level with noise, a cycle, a trend up or down, a
    shift up or down.
    """
    if kind == "cbf":
        return _plateaus(spark, series, n or 128, seed)
    if kind == "control":
        return _charts(spark, series, n or 60, seed)
    raise ValueError(f"no kind {kind}")


def _drawn(spark: SparkSession, series: int | DataFrame, n: int, seed: int, classes: list[str], draws: dict[str, Column]) -> DataFrame:
    noise = F.array(*(F.randn(seed + 101 + k) for k in range(n)))
    label = F.element_at(F.array(*map(F.lit, classes)), (F.col("id") % len(classes) + 1).cast("int"))
    return _ids(spark, series).select(F.col("id").alias("series_id"), label.alias("label"), noise.alias("z"), *(c.alias(k) for k, c in draws.items()))


def _plateaus(spark: SparkSession, series: int | DataFrame, n: int, seed: int) -> DataFrame:
    draws = {"a": F.floor(n / 8 + F.rand(seed + 1) * n / 8), "d": F.floor(n / 4 + F.rand(seed + 2) * n / 2), "h": 6 + F.randn(seed + 3)}
    rows = _drawn(spark, series, n, seed, ["flat", "up", "down"], draws)

    def value(z: Column, i: Column) -> Column:
        inside = (i >= F.col("a")) & (i < F.col("a") + F.col("d"))
        ramp = (i - F.col("a")) / F.col("d")
        form = F.when(F.col("label") == "flat", 1.0).when(F.col("label") == "up", ramp).otherwise(1 - ramp)
        return z + F.when(inside, F.col("h") * form).otherwise(0.0)

    return rows.select("series_id", F.transform("z", value).alias("v"), "label")


def _charts(spark: SparkSession, series: int | DataFrame, n: int, seed: int) -> DataFrame:
    draws = {
        "size": 10 + 5 * F.rand(seed + 1), "period": 10 + 5 * F.rand(seed + 2), "slope": 0.2 + 0.3 * F.rand(seed + 3),
        "at": F.floor(n / 3 + F.rand(seed + 4) * n / 3), "jump": 7.5 + 12.5 * F.rand(seed + 5),
    }
    rows = _drawn(spark, series, n, seed, ["normal", "cycle", "rise", "fall", "step_up", "step_down"], draws)

    def value(z: Column, i: Column) -> Column:
        label, late = F.col("label"), (i >= F.col("at")).cast("double")
        extra = (
            F.when(label == "cycle", F.col("size") * F.sin(i * (2 * math.pi) / F.col("period")))
            .when(label == "rise", F.col("slope") * i)
            .when(label == "fall", -F.col("slope") * i)
            .when(label == "step_up", F.col("jump") * late)
            .when(label == "step_down", -F.col("jump") * late)
            .otherwise(0.0)
        )
        return 30 + 2 * z + extra

    return rows.select("series_id", F.transform("z", value).alias("v"), "label")


def whole_shapes(spark: SparkSession, kind: str, series: int | DataFrame, n: int | None = None, salt: int = 21) -> DataFrame:
    """The shape classes in whole thousandths, drawn by the integer hash."""
    n = n or {"cbf": 128, "control": 60}[kind]
    draw = lambda k, low, high: F.lit(low) + F.floor((hash_noise(F.col("id"), F.lit(0), salt + k) + 1000) * (high - low) / 2001)
    noise = lambda i: F.floor(_bell(F.col("id"), i.cast("long"), salt + 10) * F.lit(1 if kind == "cbf" else 2))
    kinds = 3 if kind == "cbf" else 6
    form = F.col("id") % kinds

    def cbf(i: Column) -> Column:
        start, length = draw(1, n // 8, n // 4), draw(2, n // 4, 3 * n // 4)
        height, inside = draw(3, 5000, 7000), (i >= start) & (i < start + length)
        ramp = F.floor(height * (i - start) / length)
        shape = F.when(form == 0, height).when(form == 1, ramp).otherwise(height - ramp)
        return noise(i) + F.when(inside, shape).otherwise(F.lit(0))

    def control(i: Column) -> Column:
        late = (i >= draw(4, n // 3, 2 * n // 3)).cast("long")
        period = draw(5, 10, 15)
        saw = F.abs(F.pmod(i, period) * 4 - period * 2) * 10000 - period * 10000  # a cycle without a sine
        extra = (
            F.when(form == 1, F.floor(saw / period)).when(form == 2, draw(6, 200, 500) * i).when(form == 3, -draw(6, 200, 500) * i)
            .when(form == 4, draw(7, 7500, 20000) * late).when(form == 5, -draw(7, 7500, 20000) * late).otherwise(F.lit(0))
        )
        return 30000 + noise(i) + extra

    make = cbf if kind == "cbf" else control
    v = F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i: make(i).cast("double"))
    return _ids(spark, series).select(F.col("id").alias("series_id"), v.alias("v"), form.cast("string").alias("label"))
