"""Mixing sources to target weights.

Token shares p of the sources become weights w proportional to p ** a. The
exponent a lies between 0 (all sources alike) and 1 (as they come). It is
found by repeated narrowing: the largest a whose weights reach the wished
entropy, raised if need be until no source is repeated more than
``most_repeats`` times as often as the least repeated one.

Weights are made real without random sampling. A source's documents are dealt
by a seeded hash into parts, rows in hash order. An epoch of the source is a
permutation of these parts, another one each time, and its sequence is epoch
after epoch, cut where its share of the token budget ends. The place of a
document's first token in that sequence, as a part of the source's budget,
says into which block of the mixture it goes, so every block holds each source
in its weight.

The places come from prefix sums over the permuted parts and, in a part, over
its rows, so a source with a third of all rows is as many parts as other rows
would be. The sources' table is small beside the documents; it is sent to all
tasks if it has at most ``MOST_SOURCES`` rows and joined by a shuffle otherwise.

A null source is a source of its own. A document has its words as tokens, and
one at least, so empty and null texts take part. Repeated rows of one id and
text share their places' order and are interchangeable. An empty table gives
an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.llm.common import BLANKS, cut
from warpspan.llm.sharding import part_rows

MOST_SOURCES = 100_000
#: Documents whose uses are sent to every task.
MOST_SENT = 2_000_000
MOST_REPEATS = 4.0
ENTROPY_SHARE = 0.97
BLOCK_TOKENS = 1_000_000
_GRID = 24


def tokens_in(text: Column) -> Column:
    """Words of a text, one at least."""
    words = F.filter(F.split(F.coalesce(text, F.lit("")), f"{BLANKS}+"), lambda w: w != "")
    return F.greatest(F.size(words), F.lit(1)).cast("long")


def source_key(source: Column) -> Column:
    return F.coalesce(F.concat(F.lit("="), source.cast("string")), F.lit("null"))


def source_sizes(items: DataFrame) -> DataFrame:
    """``key, rows, tokens, share`` of each source; items have ``key`` and ``tokens``."""
    sizes = items.groupBy("key").agg(F.count("*").alias("rows"), F.sum("tokens").alias("tokens"))
    total = sizes.agg(F.sum("tokens").alias("all_tokens"), F.sum("rows").alias("all_rows"))
    return sizes.crossJoin(F.broadcast(total)).withColumn("share", F.col("tokens") / F.col("all_tokens"))


def measures_at(sizes: DataFrame, exponents: list[float]) -> list[tuple[float, float]]:
    """For each exponent: the weights' entropy, and the largest over the smallest repetition."""
    p = F.col("share")
    wanted = []
    for k, a in enumerate(exponents):
        raw = F.pow(p, F.lit(a))
        wanted += [
            F.sum(raw).alias(f"s{k}"),
            F.sum(raw * F.log(p) * F.lit(a)).alias(f"t{k}"),
            F.max(F.pow(p, F.lit(a - 1))).alias(f"x{k}"),
            F.min(F.pow(p, F.lit(a - 1))).alias(f"n{k}"),
        ]
    row = sizes.agg(*wanted).first()
    return [(math.log(row[f"s{k}"]) - row[f"t{k}"] / row[f"s{k}"], row[f"x{k}"] / row[f"n{k}"]) for k in range(len(exponents))]


def find_exponent(sizes: DataFrame, entropy_share: float | None = ENTROPY_SHARE, most_repeats: float | None = MOST_REPEATS, rounds: int = 4) -> float:
    """The exponent in [0, 1]; each round narrows the interval ``_GRID`` times in one small job.

    ``entropy_share`` is a part of the largest possible entropy, the logarithm
    of the number of sources. Entropy falls and repetition falls as a rises.
    With only a limit of repetition the sources are as even as it allows.
    """
    sources = sizes.count()
    if sources < 2:
        return 1.0

    def largest(fits, low: float = 0.0, high: float = 1.0) -> float:
        """The end of the run of fitting exponents that starts at ``low``; fits are monotone."""
        for _ in range(rounds):
            grid = [low + (high - low) * k / _GRID for k in range(_GRID + 1)]
            good = [fits(*m) for m in measures_at(sizes, grid)]
            if all(good):
                return high
            at = good.index(False)
            if at == 0:
                return low
            low, high = grid[at - 1], grid[at]
        return low

    exponent = 1.0 if most_repeats is None else 0.0
    if entropy_share is not None:
        goal = entropy_share * math.log(sources)
        exponent = largest(lambda h, _: h >= goal - 1e-12)
    if most_repeats is not None:
        def breaks(_, ratio):
            return ratio > most_repeats * (1 + 1e-12)

        low = largest(breaks)
        step = _GRID ** -rounds if low > 0 or breaks(*measures_at(sizes, [0.0])[0]) else 0.0
        exponent = max(exponent, min(1.0, low + step))
    return exponent


def target_weights(sizes: DataFrame, exponent: float, budget: int | None = None) -> DataFrame:
    """Adds ``weight``, ``target`` (tokens of the budget) and ``repeats`` to the sources.

    Without a budget it is the least that uses every document once at least.
    """
    raw = F.pow("share", F.lit(exponent))
    sums = sizes.agg(F.sum(raw).alias("_sum"), F.max(F.pow("share", F.lit(1 - exponent))).alias("_cover"))
    out = sizes.crossJoin(F.broadcast(sums)).withColumn("weight", raw / F.col("_sum"))
    whole = F.lit(float(budget)) if budget is not None else F.col("all_tokens") * F.col("_sum") * F.col("_cover")
    # Rounding must not cut the last document of a source that is used just once.
    target = F.round(F.col("weight") * whole, 3)
    return out.withColumn("target", target).withColumn("repeats", target / F.col("tokens")).drop("_sum", "_cover")


def _sent(sizes: DataFrame, n: int) -> DataFrame:
    return F.broadcast(sizes) if n <= MOST_SOURCES else sizes


def _unit(h: Column) -> Column:
    """A hash as a number in [0, 1)."""
    return F.pmod(h, F.lit(1 << 40)).cast("double") / F.lit(float(1 << 40))


def _placed(
    items: DataFrame, entropy_share: float | None, most_repeats: float | None, budget: int | None, block_tokens: int, seed: int
) -> DataFrame:
    """A row for each use of each item, with ``copy, block`` and ``place`` (its order in the block).

    Items have ``key, tokens, h`` and ``tie`` besides columns that are only carried.
    """
    light = items.select("key", "tokens", "h")
    sizes = cut(source_sizes(light))
    n_sources = sizes.count()
    weights = target_weights(sizes, find_exponent(sizes, entropy_share, most_repeats), budget)
    plan = cut(
        weights.select(
            "key",
            F.col("target").alias("_target"),
            F.col("tokens").alias("_epoch"),
            F.ceil("repeats").cast("int").alias("_copies"),
            F.ceil(F.col("rows") / part_rows(F.col("all_rows"))).cast("int").alias("_parts"),
            F.sum("target").over(Window.partitionBy()).alias("_budget"),
        )
    )
    plan = _sent(plan, n_sources)
    part = F.floor(_unit(F.col("h")) * F.col("_parts")).cast("int").alias("_part")
    sums = light.join(plan, "key").select("key", "tokens", "_copies", "_epoch", part).groupBy("key", "_part")
    sums = sums.agg(F.sum("tokens").alias("_here"), F.first("_copies").alias("_copies"), F.first("_epoch").alias("_epoch"))
    epochs = sums.withColumn("copy", F.explode(F.sequence(F.lit(0), F.col("_copies") - 1)))
    turned = Window.partitionBy("key", "copy").orderBy(F.xxhash64(F.lit(seed), "copy", "_part"), "_part").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("_here").over(turned), F.lit(0)) + F.col("copy") * F.col("_epoch")
    starts = epochs.select("key", "_part", F.struct("copy", before.alias("before")).alias("_use"))
    starts = F.broadcast(starts.groupBy("key", "_part").agg(F.sort_array(F.collect_list("_use")).alias("_uses")))
    inside = Window.partitionBy("key", "_part").orderBy("h", "tie").rowsBetween(Window.unboundedPreceding, -1)
    dealt = items.join(plan, "key").withColumn("_part", part)
    ahead = F.coalesce(F.sum("tokens").over(inside), F.lit(0))
    uses = dealt.withColumn("_ahead", ahead).join(starts, ["key", "_part"]).withColumn("_use", F.explode("_uses"))
    start = F.col("_use.before") + F.col("_ahead")
    n_blocks = F.greatest(F.lit(1), F.ceil(F.col("_budget") / F.lit(block_tokens)))
    block = F.least(n_blocks - 1, F.floor(start / F.col("_target") * n_blocks)).cast("int")
    return (
        uses.where(start < F.col("_target"))
        .withColumn("copy", F.col("_use.copy"))
        .withColumn("block", block)
        .withColumn("place", F.xxhash64("h", "copy"))
        .drop("_target", "_epoch", "_copies", "_parts", "_budget", "_part", "_ahead", "_uses", "_use")
    )


def _hash(id_column: str, text: str, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col(id_column), F.crc32(F.coalesce(F.col(text), F.lit("")).cast("binary")))


def schedule(
    documents: DataFrame,
    entropy_share: float | None = ENTROPY_SHARE,
    most_repeats: float | None = MOST_REPEATS,
    budget: int | None = None,
    block_tokens: int = BLOCK_TOKENS,
    seed: int = 0,
    id_column: str = "doc_id",
    source: str = "source",
    text: str = "text",
) -> DataFrame:
    """``doc_id, source, n_tokens, copy, block, slot``: a row for each use of each document."""
    items = cut(
        documents.select(
            F.col(id_column).alias("doc_id"),
            F.col(source).alias("source"),
            source_key(F.col(source)).alias("key"),
            tokens_in(F.col(text)).alias("tokens"),
            _hash(id_column, text, seed).alias("h"),
            F.col(id_column).alias("tie"),
        )
    )
    uses = _placed(items, entropy_share, most_repeats, budget, block_tokens, seed)
    in_block = Window.partitionBy("block").orderBy("place", "doc_id", "copy")
    return uses.select(
        "doc_id", "source", F.col("tokens").alias("n_tokens"), "copy", "block",
        (F.row_number().over(in_block) - 1).cast("long").alias("slot"),
    )


def remix(
    documents: DataFrame,
    entropy_share: float | None = ENTROPY_SHARE,
    most_repeats: float | None = MOST_REPEATS,
    budget: int | None = None,
    block_tokens: int = BLOCK_TOKENS,
    seed: int = 0,
    id_column: str = "doc_id",
    source: str = "source",
    text: str = "text",
) -> DataFrame:
    """The documents as the mixture uses them, once a use, block by block: what ``schedule`` lists, with all columns.

    A block is whole in one task and its rows are in the order of their slots,
    so files written from here hold blocks one after another. The schedule is
    made from small rows; texts move once, to their blocks, and once more to
    meet their uses only where more than ``MOST_SENT`` documents have some.
    Rows alike in id and text share their uses out among them.
    """
    h, mark = _hash(id_column, text, seed), F.xxhash64(F.col(text))
    items = cut(documents.select(source_key(F.col(source)).alias("key"), tokens_in(F.col(text)).alias("tokens"), h.alias("h"), F.col(id_column).alias("tie"), mark.alias("mark")))
    uses = _placed(items, entropy_share, most_repeats, budget, block_tokens, seed)
    listed = uses.groupBy("h", "mark").agg(F.sort_array(F.collect_list(F.struct("block", "place", "copy"))).alias("_uses"))
    alike = items.groupBy("h", "mark").agg(F.count("*").cast("int").alias("_alike"))
    listed = cut(listed.join(alike, ["h", "mark"]).withColumnsRenamed({"h": "_use_h", "mark": "_use_mark"}))
    if listed.count() <= MOST_SENT:
        listed = F.broadcast(listed)
    row = F.struct(*(F.col(f"`{name}`") for name in documents.columns)).alias("_row")
    rows = documents.select(row, h.alias("_h"), mark.alias("_mark"))
    met = rows.join(listed, (F.col("_h") == F.col("_use_h")) & (F.col("_mark") == F.col("_use_mark")))
    twins = Window.partitionBy("_h", "_mark").orderBy(F.to_json("_row"))
    several = met.where("_alike > 1").withColumn("_mine", (F.row_number().over(twins) - 1).cast("int"))
    own = F.filter("_uses", lambda use, k: k % F.col("_alike") == F.col("_mine"))
    shares = met.where("_alike = 1").select("_row", "_uses").unionByName(several.select("_row", own.alias("_uses")))
    out = shares.select("_row", F.explode("_uses").alias("_use")).select("_row", "_use.*")
    return out.repartition("block").sortWithinPartitions("block", "place", "copy").select("_row.*")
