"""The box index: piecewise sums of every series as points, in pages with bounding boxes.

A series is reduced to d sums over a disjoint cover of its positions. The sums
of a query's envelope form a box; a point's distance to that box is a lower
bound of the warping distance, and a page's box bounds all its points.

Points live in scalar columns ``s1 .. sd`` apart from the arrays, so that a
scan for candidates reads d numbers a series and Parquet's min/max statistics
apply. Pages are tiles: quantile strips of s1, each cut at quantiles of s2.
Quantiles are exact: mergeable sketches say near which values each lies, and
only the points there are sorted, so the build has no global sort; the edges
that reach the driver number as many as the pages.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.functions import expressions as X
from warpspan.functions import kernels

D = 8
#: Points of a page: 4096 bytes hold 56 of eight sums and an id. A cluster takes far larger pages.
SMALL_PAGE, LARGE_PAGE = 56, 65_536
#: Pages of one folder of a stored index; a search leaves out the folders that it doesn't reach.
GROUP_PAGES = 256

Cover = list[tuple[int, int]]


def floor_cover(n: int, d: int = D) -> Cover:
    """d - 1 intervals of n // d positions; the last takes the rest."""
    if not 0 < d <= n:
        raise ValueError(f"cannot cover {n} positions by {d} intervals")
    step = n // d
    return [(k * step, (k + 1) * step if k < d - 1 else n) for k in range(d)]


def equal_cover(n: int, d: int) -> Cover:
    """Intervals of one length only, as an earlier form of the reduction demands."""
    if d < 1 or n % d:
        raise ValueError(f"{d} does not divide {n}")
    return floor_cover(n, d)


def check_cover(cover: Cover, n: int) -> Cover:
    """Fails unless the intervals are disjoint and cover 0 .. n - 1."""
    if sorted(k for a, b in cover for k in range(a, b)) != list(range(n)):
        raise ValueError(f"the cover doesn't fit series of {n} samples")
    return cover


def points_of(series: DataFrame, cover: Cover) -> DataFrame:
    """``series_id, s1 .. sd``: one projection, no Python."""
    return series.select("series_id", *X.piecewise_sums("v", cover))


def query_boxes(queries: DataFrame, w: int, cover: Cover) -> DataFrame:
    """``query_id, lo1 .. lod, hi1 .. hid``: sums of the queries' envelopes."""
    env = queries.select("query_id", X.envelope("y", w).alias("e"))
    lows = [c.alias(f"lo{k}") for k, c in enumerate(X.piecewise_sums(F.col("e.lo"), cover), 1)]
    highs = [c.alias(f"hi{k}") for k, c in enumerate(X.piecewise_sums(F.col("e.hi"), cover), 1)]
    return env.select("query_id", *lows, *highs)


def _names(prefix: str, d: int, suffix: str = "") -> list[Column]:
    return [F.col(f"{prefix}{k}{suffix}") for k in range(1, d + 1)]


def point_bound_pow(cover: Cover, p: float = 1) -> Column:
    """The box bound on rows that hold a point and a query box."""
    d = len(cover)
    return X.box_bound_pow(_names("s", d), _names("lo", d), _names("hi", d), cover, p)


def page_bound_pow(cover: Cover, p: float = 1) -> Column:
    """The least box bound that any point of a page can have."""
    d, parts = len(cover), []
    for low, high, lo, hi in zip(_names("s", d, "_min"), _names("s", d, "_max"), _names("lo", d), _names("hi", d), strict=True):
        # How far apart the two intervals are; 0 where they meet.
        parts.append(F.greatest(lo - high, low - hi, F.lit(0.0)))
    zero = [F.lit(0.0)] * d
    return X.box_bound_pow(parts, zero, zero, cover, p)


class BoxIndex(NamedTuple):
    """``points`` has ``series_id, s1 .. sd, page_id``, ``pages`` a row a page, ``paged`` the arrays with their page."""

    paged: DataFrame
    points: DataFrame
    pages: DataFrame
    cover: Cover
    n_pages: int


#: Share of the points on either side of a quantile that are sorted for it; twice the sketches' error.
SLACK = 2e-4


def _edges(values: DataFrame, column: str, tiles: int, group: Column | None = None) -> dict[int, np.ndarray]:
    """The values at ranks ``ceil(k / tiles * count)``, k from 1, of each group (or of group 0), exactly.

    Sketches give a stretch of values for each rank. The points below it are
    counted and those in it are numbered; where a stretch misses its rank, it is
    all values instead.
    """
    if tiles < 2:
        return {}
    shares = [k / tiles for k in range(1, tiles)]
    sides = [[max(0.0, s - SLACK) for s in shares], [min(1.0, s + SLACK) for s in shares]]
    rows = values.select((F.lit(0) if group is None else group).alias("g"), F.col(column).cast("double").alias("x"))
    sketch = [F.percentile_approx("x", side, 10_000).alias(name) for name, side in zip(("lo", "hi"), sides, strict=True)]
    stretches, ranks = {}, {}
    for r in rows.groupBy("g").agg(F.count("x").alias("c"), *sketch).collect():
        stretches[r.g] = (np.array(r.lo), np.array(r.hi))
        ranks[r.g] = [max(1, math.ceil(s * r.c)) for s in shares]
    found = _ranked(rows, stretches, ranks)
    missed = {g for g, wanted in ranks.items() if len(found.get(g, {})) < len(wanted)}
    if missed:
        everything = {g: (np.full(len(shares), -np.inf), np.full(len(shares), np.inf)) for g in missed}
        found |= _ranked(rows, everything, {g: ranks[g] for g in missed})
    return {g: np.array([e for _, e in sorted(edges.items())]) for g, edges in found.items()}


def _ranked(rows: DataFrame, stretches: dict, ranks: dict[int, list[int]]) -> dict[int, dict[int, float]]:
    """Of rows ``g, x``: the values at the ranks that lie in their stretches of values, by group and place in ``ranks``."""

    def split(source):
        for batch in source:
            group, x = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            for g in np.unique(group):
                if g not in stretches:
                    continue
                lo, hi = stretches[g]
                mine = x[group == g]
                # Stretches are in order, so a value lies in those from ``first`` to before ``after``.
                first, after = np.searchsorted(hi, mine, "left"), np.searchsorted(lo, mine, "right")
                below, counts = np.unique(after, return_counts=True)
                inside = np.maximum(after - first, 0)
                at = np.repeat(first, inside) + np.arange(inside.sum()) - np.repeat(np.cumsum(inside) - inside, inside)
                size = len(below) + len(at)
                yield pa.record_batch(
                    [
                        pa.array(np.full(size, g), pa.int32()), pa.array(np.concatenate([below, at]), pa.int32()),
                        pa.array(np.concatenate([np.zeros(len(below)), np.repeat(mine, inside)]), mask=np.arange(size) < len(below)),
                        pa.array(np.concatenate([counts, np.ones(len(at), int)]), pa.int64()),
                    ],
                    names=["g", "k", "x", "n"],
                )

    listed = rows.mapInArrow(split, "g int, k int, x double, n bigint")
    below: dict[int, np.ndarray] = {g: np.zeros(len(r) + 1, dtype=np.int64) for g, r in ranks.items()}
    for r in listed.where("x is null").groupBy("g", "k").agg(F.sum("n").alias("n")).collect():
        below[r.g][r.k] = r.n
    # A point that reaches k stretches' starts is below all later ones.
    wanted = [(g, k, int(rank - before)) for g, r in ranks.items() for k, (rank, before) in enumerate(zip(r, np.cumsum(below[g]), strict=False))]
    places = F.broadcast(rows.sparkSession.createDataFrame(wanted, "g int, k int, place bigint"))
    before = Window.partitionBy("g", "k").orderBy("x").rowsBetween(Window.unboundedPreceding, 0)
    counted = listed.where("x is not null").groupBy("g", "k", "x").agg(F.sum("n").alias("n")).withColumn("upto", F.sum("n").over(before))
    hits = counted.join(places, ["g", "k"]).where("place <= upto and place > upto - n").collect()
    found: dict[int, dict[int, float]] = {}
    for r in hits:
        found.setdefault(r.g, {})[r.k] = r.x
    return found


class Tiling(NamedTuple):
    """Strips by edges of s1, tiles in each strip by edges of s2."""

    first: np.ndarray
    second: dict[int, np.ndarray]
    per_strip: int

    @property
    def n_pages(self) -> int:
        return (len(self.first) + 1) * self.per_strip

    def page_of(self, s1: Column, s2: Column) -> Column:
        first, second, per_strip = self.first, self.second, self.per_strip

        @F.arrow_udf("int")
        def page(a: pa.Array, b: pa.Array) -> pa.Array:
            x, y = a.to_numpy(zero_copy_only=False), b.to_numpy(zero_copy_only=False)
            strips_of = np.searchsorted(first, x)
            out = strips_of * per_strip
            for s in np.unique(strips_of):
                if s in second:
                    mine = strips_of == s
                    out[mine] += np.searchsorted(second[s], y[mine])
            return pa.array(out.astype(np.int32))

        return page(s1, s2)


def tiling(points: DataFrame, page_rows: int = LARGE_PAGE, n_points: int | None = None) -> Tiling:
    """Edges of pages of about ``page_rows`` points; as many numbers as pages come to the driver."""
    n_pages = max(1, math.ceil((points.count() if n_points is None else n_points) / page_rows))
    if n_pages == 1:
        return Tiling(np.array([]), {}, 1)
    strips = max(1, math.ceil(math.sqrt(n_pages)))
    per_strip = math.ceil(n_pages / strips)
    first = _edges(points, "s1", strips).get(0, np.array([]))
    second: dict[int, np.ndarray] = {}
    if per_strip > 1 and "s2" in points.columns:
        second = _edges(points, "s2", per_strip, _bin_of(first)("s1"))
    return Tiling(first, second, per_strip)


def with_pages(points: DataFrame, tiles: Tiling) -> DataFrame:
    """Adds ``page_id``, which follows from a row's sums alone."""
    if tiles.n_pages == 1:
        return points.withColumn("page_id", F.lit(0))
    return points.withColumn("page_id", tiles.page_of(F.col("s1"), F.col("s2" if "s2" in points.columns else "s1")))


def _bin_of(edges: np.ndarray):
    @F.arrow_udf("int")
    def find(a: pa.Array) -> pa.Array:
        return pa.array(np.searchsorted(edges, a.to_numpy(zero_copy_only=False)).astype(np.int32))

    return find


def page_table(points: DataFrame, d: int) -> DataFrame:
    """``page_id, rows`` and each sum's least and largest value: a small table, one row a page."""
    sides = [f(f"s{k}").alias(f"s{k}_{name}") for k in range(1, d + 1) for name, f in (("min", F.min), ("max", F.max))]
    return points.groupBy("page_id").agg(F.count("*").alias("rows"), *sides)


def _paged(series: DataFrame, cover: Cover, tiles: Tiling) -> DataFrame:
    """The series with their pages. A page follows from a series' own sums, so no join is needed."""
    sums = X.piecewise_sums("v", cover)[:2]
    others = [name for name in ("label",) if name in series.columns]
    return with_pages(series.select("series_id", "v", *others, *sums), tiles).drop("s1", "s2")


def build(series: DataFrame, n: int, d: int = D, page_rows: int = LARGE_PAGE, cover: Cover | None = None) -> BoxIndex:
    """The index over packed series of n samples; ``write`` stores it.

    Several steps read the points, so these (d numbers a series) and the page
    table are kept in memory and on disk until ``release``.
    """
    cover = check_cover(cover or floor_cover(n, d), n)
    points = points_of(series, cover).persist(StorageLevel.MEMORY_AND_DISK)
    tiles = tiling(points, page_rows)
    placed = with_pages(points, tiles)
    pages = page_table(placed, len(cover)).persist(StorageLevel.MEMORY_AND_DISK)
    return BoxIndex(_paged(series, cover, tiles), placed, pages, cover, tiles.n_pages)


def release(index: BoxIndex, series: DataFrame) -> None:
    """Lets go of what ``build`` kept of ``series``."""
    points_of(series, index.cover).unpersist()
    index.pages.unpersist()


def page_group() -> Column:
    return F.floor(F.col("page_id") / GROUP_PAGES).cast("int")


def write(index: BoxIndex, path: str) -> None:
    """Points and series in the order of pages, the page table and the cover, as Parquet.

    ``page_group`` names the folder of the arrays. A join with the pages in
    reach prunes by it while it runs, so that the rest is never read.
    """
    spark = index.paged.sparkSession
    in_order = lambda rows: rows.repartitionByRange("page_id", "series_id").sortWithinPartitions("page_id", "series_id")
    in_order(index.points).write.mode("overwrite").parquet(f"{path}/points")
    in_order(index.paged).withColumn("page_group", page_group()).write.mode("overwrite").partitionBy("page_group").parquet(f"{path}/series")
    page_table(spark.read.parquet(f"{path}/points"), len(index.cover)).write.mode("overwrite").parquet(f"{path}/pages")
    spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(index.cover)], "k int, start int, after int").coalesce(1).write.mode(
        "overwrite"
    ).parquet(f"{path}/cover")


def read(spark: SparkSession, path: str) -> BoxIndex:
    cover = [(r.start, r.after) for r in spark.read.parquet(f"{path}/cover").orderBy("k").collect()]
    load = lambda name: spark.read.parquet(f"{path}/{name}")
    return BoxIndex(load("series"), load("points"), load("pages"), cover, load("pages").count())


def append(index: BoxIndex, more: DataFrame, page_rows: int = LARGE_PAGE) -> BoxIndex:
    """The index with further series in pages of their own, numbered after the present ones."""
    last = index.pages.agg(F.coalesce(F.max("page_id"), F.lit(-1)).alias("m")).first().m
    points = points_of(more, index.cover)
    tiles = tiling(points, page_rows)
    after = lambda rows: rows.withColumn("page_id", F.col("page_id") + last + 1)
    placed = after(with_pages(points, tiles))
    both = lambda old, new: old.unionByName(new.select(*old.columns))
    return BoxIndex(
        both(index.paged, after(_paged(more, index.cover, tiles)).withColumn("page_group", page_group())), both(index.points, placed),
        both(index.pages, page_table(placed, len(index.cover))), index.cover, index.n_pages + tiles.n_pages,
    )


def box_pow(sums: np.ndarray, lo: np.ndarray, hi: np.ndarray, cover: Cover, p: float = 1) -> np.ndarray:
    """The box bound of rows of piecewise sums against one query's envelope."""
    low, high = (kernels.piecewise_sums(side[None, :], cover) for side in (lo, hi))
    gap = np.maximum(np.maximum(low - sums, sums - high), 0.0)
    sizes = np.array([b - a for a, b in cover], dtype=float)
    if p == kernels.INF:
        return (gap / sizes).max(axis=1)
    return (gap**p / sizes ** (p - 1)).sum(axis=1)
