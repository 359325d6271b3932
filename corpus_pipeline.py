"""From raw documents to sharded training text, in five stages.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is
written as Parquet and read again as the next one's ``docs``. All but the last
return the columns of ``documents``.

1. quality rules: documents that break a limit go;
2. near-dedup: of documents alike to 0.8 in their five-word runs one stays;
3. benchmark decontamination: contaminated documents go;
4. mixing: documents of sources under their target weight repeat, in blocks of the mixture;
5. sharding: every row gets a shard and a slot along the Hilbert curve.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from warpspan.llm import contamination, mixing, nearcopies, quality, sharding
from warpspan.llm.common import cut, discard_since, read_table, written_so_far


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return nearcopies.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return contamination.drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.remix(docs)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sharding.attach(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_dedup", near_dedup),
    ("decontaminate", decontaminate),
    ("mix_sources", mix_sources),
    ("shard", shard),
]

#: Components of near copies have no form in SQL; tests compare with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written to the shared checkpoint folder, and what it used there is deleted."""
    docs, mark = read_table(spark, sf_dir, "documents"), written_so_far()
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
        discard_since(mark, but=docs)
    return STAGES[-1][1](spark, docs, sf_dir)
