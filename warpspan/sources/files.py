"""Series to and from files: Parquet, ORC, CSV, JSON lines and delimited text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from warpspan.sources.series import PACKED


def write_series(packed: DataFrame, path: str, kind: str = "parquet", separator: str = " ") -> None:
    """One row or line a series. Text and CSV lines hold the id, the label and the samples."""
    if kind in ("parquet", "orc", "json"):
        packed.select("series_id", "v", "label").write.mode("errorifexists").format(kind).save(path)
    elif kind in ("text", "csv"):
        line = F.concat_ws("," if kind == "csv" else separator, F.col("series_id").cast("string"), F.coalesce("label", F.lit("-")), F.transform("v", lambda x: x.cast("string")))
        packed.select(line.alias("value")).write.mode("errorifexists").text(path)
    else:
        raise ValueError(f"no kind {kind}")


def read_series(spark: SparkSession, path: str, kind: str = "parquet", separator: str = " ") -> DataFrame:
    """What ``write_series`` wrote, with an explicit schema."""
    if kind in ("parquet", "orc", "json"):
        return spark.read.schema(PACKED).format(kind).load(path)
    if kind not in ("text", "csv"):
        raise ValueError(f"no kind {kind}")
    return parse_lines(spark.read.text(path), "," if kind == "csv" else separator)


def parse_lines(lines: DataFrame, separator: str = " ") -> DataFrame:
    """Packed series from lines of id, label and samples; '-' is no label."""
    parts = F.split("value", f"[{separator}]+" if separator == " " else separator)
    rows = lines.select(parts.alias("f"))
    v = F.transform(F.slice("f", 3, F.size("f")), lambda x: x.cast("double"))
    return rows.select(F.get("f", F.lit(0)).cast("bigint").alias("series_id"), v.alias("v"), F.nullif(F.get("f", F.lit(1)), F.lit("-")).alias("label"))


def save_table(packed: DataFrame, name: str) -> None:
    packed.write.mode("overwrite").saveAsTable(name)
