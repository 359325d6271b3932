"""Similarity joins under time warping."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from warpspan.functions import expressions as X
from warpspan.functions import kernels
from warpspan.operators import boxindex
from warpspan.sources.series import matrix
from warpspan.sources.store import stored


#: Samples of one side that meet the other's in one piece; cells with more on a side are cut by a hash of the id.
PIECE_VALUES = 1 << 20
#: Cells that a box reaches along an axis, at most; a wider one is listed in a coarser grid.
MOST_CELLS = 3
#: Rows of the right side that a piece's points are held against at once, and pairs that are verified at once.
ROWS_AT_ONCE, PAIRS_AT_ONCE = 64, 2048
_PAIR = "left_id bigint, right_id bigint, dist double"


def _cells(low, high, width: float, level):
    """First and last cell of a stretch in the grid of a level, whose cells are twice as wide as the level's before."""
    size = F.lit(width) * F.pow(F.lit(2.0), level)
    return F.floor(low / size), F.floor(high / size)


def _boxed(series: DataFrame, w: int, cover: boxindex.Cover) -> DataFrame:
    """``series_id, v`` with the sums of the cover and those of the envelope, written once."""
    rows = series.select("series_id", "v", *X.piecewise_sums("v", cover), X.envelope("v", w).alias("_e"))
    sides = {"lo": X.piecewise_sums(F.col("_e.lo"), cover), "hi": X.piecewise_sums(F.col("_e.hi"), cover)}
    for name, sums in sides.items():
        rows = rows.withColumns({f"{name}{k}": c for k, c in enumerate(sums, 1)})
    return stored(rows.drop("_e").where("s1 is not null"))


def _dealt(points: DataFrame, boxes: DataFrame, reaches: list[float], piece_rows: int) -> tuple[DataFrame, DataFrame, list[str]] | None:
    """Both sides listed in the pieces of grid cells over the first sums, and the piece's columns; a point meets a box in one piece at most.

    A box is listed in the few cells that it reaches at a level of its own
    size, a point once in each level that some box uses. A cell with many rows
    has pieces of its points, each of which meets each piece of its boxes.
    """
    axes = range(1, len(reaches) + 1)
    spread = boxes.agg(*(F.avg(F.col(f"hi{k}") - F.col(f"lo{k}")).alias(f"m{k}") for k in axes)).first()
    widths = [max(2 * r + (spread[f"m{k}"] or 0.0), 1e-9) / 2 for k, r in zip(axes, reaches, strict=True)]
    wide = F.greatest(F.lit(1.0), *((F.col(f"hi{k}") - F.col(f"lo{k}") + 2 * r) / (w * (MOST_CELLS - 1)) for k, r, w in zip(axes, reaches, widths, strict=True)))
    leveled = boxes.withColumn("_level", F.ceil(F.log2(wide)).cast("int"))
    levels = [r._level for r in leveled.select("_level").distinct().collect()]
    if not levels:
        return None
    names = [f"_c{k}" for k in axes]
    spots = points.withColumn("_level", F.explode(F.array(*map(F.lit, sorted(levels)))))
    for name, k, width in zip(names, axes, widths, strict=True):
        spots = spots.withColumn(name, _cells(F.col(f"s{k}"), F.col(f"s{k}"), width, F.col("_level"))[0])
    listed = leveled
    for name, k, r, width in zip(names, axes, reaches, widths, strict=True):
        first, last = _cells(F.col(f"lo{k}") - r, F.col(f"hi{k}") + r, width, F.col("_level"))
        listed = listed.withColumn(name, F.explode(F.sequence(first, last)))
    keys = ["_level", *names]
    sides = {"_own": spots, "_other": listed}
    # One row for a piece's rows, at most.
    hot = {s: F.broadcast(rows.groupBy(*keys).agg(F.ceil(F.count("*") / piece_rows).cast("int").alias(f"{s}s")).where(f"{s}s > 1")) for s, rows in sides.items()}
    out = []
    for side, across, named in (("_own", "_other", ("left_id", "x")), ("_other", "_own", ("right_id", "y"))):
        rows = sides[side].join(hot["_own"], keys, "left").join(hot["_other"], keys, "left")
        rows = rows.withColumn(side, F.pmod(F.xxhash64("series_id"), F.coalesce(f"{side}s", F.lit(1))).cast("int"))
        rows = rows.withColumn(across, F.explode(F.sequence(F.lit(0), F.coalesce(f"{across}s", F.lit(1)) - 1)))
        out.append(rows.select(*keys, "_own", "_other", F.col("series_id").alias(named[0]), F.col("v").alias(named[1])))
    return out[0], out[1], [*keys, "_own", "_other"]


def _in_boxes(s: np.ndarray, lows: np.ndarray, highs: np.ndarray, cover: boxindex.Cover, p: float) -> np.ndarray:
    """The box bound of points against boxes; shapes are broadcast, sums come first."""
    out = None
    for k, (a, b) in enumerate(cover):
        gap = np.maximum(np.maximum(lows[k] - s[k], s[k] - highs[k]), 0.0)
        part = gap if p == 1 else gap / (b - a) if p == kernels.INF else gap**p / float(b - a) ** (p - 1)
        out = part if out is None else kernels.add(out, part, p)
    return out


def near_in_piece(left: np.ndarray, x: np.ndarray, right: np.ndarray, y: np.ndarray, cover: boxindex.Cover, w: int, p: float, eps: float, self_join: bool = False):
    """``left_id, right_id, dist`` of the pairs of a piece within ``eps``: the box bound both ways, both passes, the distance."""
    limit = kernels.power(eps, p)
    by_left, by_right = np.argsort(left), np.argsort(right)
    left, x, right, y = left[by_left], x[by_left], right[by_right], y[by_right]
    envelopes = [kernels.envelope(side, w) for side in (x, y)]
    sums = [np.ascontiguousarray(kernels.piecewise_sums(side, cover).T) for side in (x, y)]
    (x_low, x_high), (y_low, y_high) = ([np.ascontiguousarray(kernels.piecewise_sums(edge, cover).T) for edge in e] for e in envelopes)
    lo, hi = envelopes[1]
    found = []

    def verify(i: np.ndarray, j: np.ndarray) -> None:
        for start in range(0, len(i), PAIRS_AT_ONCE):
            a, b = i[start : start + PAIRS_AT_ONCE], j[start : start + PAIRS_AT_ONCE]
            alive = kernels.pass1_pow(x[a], lo[b], hi[b], p) <= limit
            a, b = a[alive], b[alive]
            alive = kernels.pass2_pow(x[a], y[b], lo[b], hi[b], w, p) <= limit
            a, b = a[alive], b[alive]
            if len(a):
                power = kernels.dtw_pow(x[a], y[b], w, p)
                near = power <= limit
                found.append((left[a[near]], right[b[near]], kernels.root(power[near], p)))

    for start in range(0, len(right), ROWS_AT_ONCE):
        stop = min(start + ROWS_AT_ONCE, len(right))
        # Ids are in order: of a self join only the points before a row count.
        most = np.searchsorted(left, right[stop - 1], "left") if self_join else len(left)
        bound = _in_boxes(sums[0][:, None, :most], y_low[:, start:stop, None], y_high[:, start:stop, None], cover, p)
        j, i = np.nonzero(bound <= limit)
        j += start
        if self_join:
            before = left[i] < right[j]
            i, j = i[before], j[before]
        back = _in_boxes(sums[1][:, j], x_low[:, i], x_high[:, i], cover, p) <= limit
        verify(i[back], j[back])
    empty = (left[:0], right[:0], np.zeros(0))
    return tuple(np.concatenate(part) for part in zip(empty, *found, strict=True))


def warp_join(left: DataFrame, right: DataFrame, n: int, eps: float, w: int | None = None, p: float = 1, d: int = boxindex.D, self_join: bool = False) -> DataFrame:
    """Pairs with a distance of ``eps`` or less: ``left_id, right_id, dist``.

    A range join on the first two sums, in grids whose cells suit the boxes.
    Each series goes to its cells once, with its array; the pairs of a cell
    are formed and verified where both sides lie, so that only pairs of the
    result are rows. A self join gives each pair once, the smaller id on the left.
    """
    kernels.check_norm(p)
    w = kernels.check_band(w, n)
    cover = boxindex.floor_cover(n, min(d, n))
    kept = _boxed(left, w, cover[:2])
    other = kept if self_join else _boxed(right, w, cover[:2])
    reaches = [eps * ((b - a) ** (1 - 1 / p) if p != kernels.INF else b - a) for a, b in cover[:2]]
    dealt = _dealt(kept, other, reaches, max(256, PIECE_VALUES // n))
    if dealt is None:
        return kept.select(F.col("series_id").alias("left_id"), F.col("series_id").alias("right_id"), F.lit(0.0).alias("dist")).where("false")

    def run(points: pa.Table, boxes: pa.Table) -> pa.Table:
        sides = []
        for side, ids, values in ((points, "left_id", "x"), (boxes, "right_id", "y")):
            sides += [side.column(ids).to_numpy(), matrix(side.column(values).combine_chunks()) if len(side) else np.zeros((0, n))]
        made = near_in_piece(*sides, cover, w, p, eps, self_join) if len(points) and len(boxes) else (np.zeros(0, np.int64),) * 2 + (np.zeros(0),)
        return pa.table(dict(zip(("left_id", "right_id", "dist"), made, strict=True)))

    spots, listed, piece = dealt
    return spots.groupBy(*piece).cogroup(listed.groupBy(*piece)).applyInArrow(run, _PAIR)


def lp_pairs(queries: DataFrame, series: DataFrame, p: float) -> DataFrame:
    """Unwarped distances of all query-candidate pairs; queries are broadcast."""
    pairs = series.select("series_id", "v").crossJoin(F.broadcast(queries.select("query_id", "y")))
    return pairs.select("query_id", "series_id", X.lp_distance_pow("v", "y", p).alias("power"))
