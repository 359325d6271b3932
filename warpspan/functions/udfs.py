"""Arrow functions over pairs of arrays, and their registration for SQL."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from warpspan.functions import kernels
from warpspan.sources.series import arrays, matrix

ARRAY = T.ArrayType(T.DoubleType())
ENVELOPE = T.StructType([T.StructField("lo", ARRAY), T.StructField("hi", ARRAY)])


def _equal_length(x: pa.Array, y: pa.Array):
    """Groups of rows whose two arrays have the same lengths, as matrices."""
    x, y = (c.cast(pa.list_(pa.float64())) if pa.types.is_null(c.type) else c for c in (x, y))
    lengths = np.stack([np.asarray(c.value_lengths().fill_null(-1)) for c in (x, y)], axis=1)
    for pair in np.unique(lengths, axis=0):
        rows = np.flatnonzero((lengths == pair).all(axis=1))
        if (pair > 0).all():
            yield rows, matrix(x.take(pa.array(rows))), matrix(y.take(pa.array(rows)))


def _by_length(x: pa.Array, y: pa.Array, kernel) -> pa.Array:
    """A number for each pair; null where an array is null or empty."""
    out = np.full(len(x), np.nan)
    for rows, a, b in _equal_length(x, y):
        out[rows] = kernel(a, b)
    return pa.array(out, mask=np.isnan(out))


def pair_function(kernel):
    """An Arrow function of two array columns from a kernel over matrices."""

    @F.arrow_udf("double")
    def apply(x: pa.Array, y: pa.Array) -> pa.Array:
        return _by_length(x, y, kernel)

    return apply


def dtw(x: str | Column, y: str | Column, w: int | None = None, p: float = 1, rooted: bool = True) -> Column:
    """The banded warping distance; lengths may differ within the band."""
    kernels.check_norm(p, bound=False)
    finish = kernels.root if rooted else lambda v, _: v
    return pair_function(lambda a, b: finish(kernels.dtw_pow(a, b, w, p), p))(x, y)


def pass1(x: str | Column, y: str | Column, w: int, p: float = 1) -> Column:
    kernels.check_norm(p)
    return pair_function(lambda a, b: kernels.root(kernels.pass1_pow(a, *kernels.envelope(b, w), p), p))(x, y)


def pass2(x: str | Column, y: str | Column, w: int, p: float = 1) -> Column:
    kernels.check_norm(p)

    def both(a, b):
        return kernels.root(kernels.pass2_pow(a, b, *kernels.envelope(b, w), kernels.check_band(w, b.shape[1]), p), p)

    return pair_function(both)(x, y)


def ndtw(x: str | Column, y: str | Column, w: int | None = None, p: float = 1) -> Column:
    """The non-monotonic distance, by an assignment; for short series."""
    kernels.check_norm(p, bound=False)
    return pair_function(lambda a, b: kernels.root(kernels.ndtw_pows(a, b, w, p), p))(x, y)


def ndtw_sorted(x: str | Column, y: str | Column, p: float = 1) -> Column:
    """The non-monotonic distance without a band, on sorted values."""
    return pair_function(lambda a, b: kernels.root(kernels.dtw_pow(np.sort(a, axis=1), np.sort(b, axis=1), None, p), p))(x, y)


def envelope(y: str | Column, w: int) -> Column:
    """A struct of ``lo`` and ``hi``; null for null and empty arrays."""

    @F.arrow_udf(ENVELOPE)
    def run(column: pa.Array) -> pa.Array:
        lengths = np.asarray(column.value_lengths().fill_null(-1))
        lo: list = [None] * len(column)
        hi: list = [None] * len(column)
        for n in np.unique(lengths[lengths > 0]):
            rows = np.flatnonzero(lengths == n)
            for at, low, high in zip(rows, *kernels.envelope(matrix(column.take(pa.array(rows))), w), strict=True):
                lo[at], hi[at] = low, high
        kind = pa.list_(pa.float64())
        return pa.StructArray.from_arrays([pa.array(lo, kind), pa.array(hi, kind)], ["lo", "hi"])

    return run(y)


def envelope_by_queues(y: str | Column, w: int) -> Column:
    """The envelope in a single pass by queues, with the comparisons it took."""

    @F.arrow_udf("struct<lo array<double>, hi array<double>, comparisons bigint>")
    def run(column: pa.Array) -> pa.Array:
        rows = [kernels.envelope_by_queues(v, w) if v else (None, None, None) for v in column.to_pylist()]
        kinds = (pa.list_(pa.float64()), pa.list_(pa.float64()), pa.int64())
        return pa.StructArray.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)] if rows else [pa.array([], k) for k in kinds], ["lo", "hi", "comparisons"])

    return run(y)


def path_rows(x: list[float], y: list[float], w: int, p: float):
    """Rows of a cheapest minimal path: step, positions from 1, and the two values."""
    path, _ = kernels.warping_path(x, y, w if w >= 0 else None, p)
    for step, (i, j) in enumerate(path, 1):
        yield step, i + 1, j + 1, float(x[i]), float(y[j])


@F.udtf(returnType="step int, i int, j int, xi double, yj double")
class WarpPath:
    """SQL: ``LATERAL warp_path(x, y, w)``; a negative band means none."""

    def eval(self, x: list, y: list, w: int):
        yield from path_rows(x, y, w, 1)


def explain_rows(x: list[float], y: list[float], w: int):
    """What the bounds are made of, position by position."""
    a, b = np.array([x], dtype=float), np.array([y], dtype=float)
    lo, hi = kernels.envelope(b, w)
    h = kernels.clamp(a, lo, hi)
    lo2, hi2 = kernels.envelope(h, w)
    first = np.abs(a - h)
    second = np.maximum(np.maximum(lo2 - b, b - hi2), 0.0)
    for at, row in enumerate(zip(*(m[0].tolist() for m in (a, b, lo, hi, h, lo2, hi2, first, second)), strict=True), 1):
        yield (at, *row)


@F.udtf(returnType="pos int, xi double, yi double, lo double, hi double, clamped double, lo2 double, hi2 double, first double, second double")
class ExplainBounds:
    """SQL: ``LATERAL explain_bounds(x, y, w)``."""

    def eval(self, x: list, y: list, w: int):
        yield from explain_rows(x, y, w)


def _varying(kernel):
    """A function of two arrays, a band and a norm that may differ by row; a negative band means none, norm 0 means the maximum."""

    @F.arrow_udf("double")
    def apply(x: pa.Array, y: pa.Array, w: pa.Array, p: pa.Array) -> pa.Array:
        out = np.full(len(x), np.nan)
        keys = list(zip(w.to_pylist(), p.to_pylist(), strict=True))
        for key in set(keys):
            rows = np.array([k for k, own in enumerate(keys) if own == key])
            if None in key:
                continue
            band, norm = None if key[0] < 0 else int(key[0]), math.inf if key[1] == 0 else float(key[1])
            for at, a, b in _equal_length(x.take(pa.array(rows)), y.take(pa.array(rows))):
                out[rows[at]] = kernel(a, b, band, norm)
        return pa.array(out, mask=np.isnan(out))

    return apply


def _pass1_kernel(a, b, w, p):
    return kernels.root(kernels.pass1_pow(a, *kernels.envelope(b, w), p), p)


def _pass2_kernel(a, b, w, p):
    return kernels.root(kernels.pass2_pow(a, b, *kernels.envelope(b, w), kernels.check_band(w, b.shape[1]), p), p)


def _dtw_kernel(a, b, w, p):
    return kernels.root(kernels.dtw_pow(a, b, w, p), p)


def _ndtw_kernel(a, b, w, p):
    return [kernels.root(kernels.ndtw_pow(u, v, w, p), p) for u, v in zip(a, b, strict=True)]


def _sums(x: pa.Array, d: pa.Array) -> pa.Array:
    """Sums over d stretches of equal floor length, the last with the rest; null where x is null or shorter than d."""
    out = []
    for v, k in zip(x.to_pylist(), d.to_pylist(), strict=True):
        if v is None or k is None or not 0 < k <= len(v):
            out.append(None)
        else:
            step = len(v) // k
            out.append([float(sum(v[i * step : (i + 1) * step if i < k - 1 else len(v)])) for i in range(k)])
    return pa.array(out, pa.list_(pa.float64()))


def _sides(x: pa.Array, y: pa.Array, w: pa.Array):
    """Row by row: x, y and y's envelope, or nothing where an array is null, empty or of another length."""
    for a, b, band in zip(x.to_pylist(), y.to_pylist(), w.to_pylist(), strict=True):
        if not a or not b or band is None or len(a) != len(b):
            yield None
        else:
            yield np.array([a], dtype=float), np.array([b], dtype=float), *kernels.envelope(np.array([b], dtype=float), None if band < 0 else band)


def _sql_scalars() -> dict:
    @F.arrow_udf(ENVELOPE)
    def warp_envelope(y: pa.Array, w: pa.Array) -> pa.Array:
        found = [None if s is None else (s[2][0], s[3][0]) for s in _sides(y, y, w)]
        kind = pa.list_(pa.float64())
        return pa.StructArray.from_arrays([pa.array([None if f is None else f[k] for f in found], kind) for k in (0, 1)], ["lo", "hi"])

    @F.arrow_udf(ARRAY)
    def warp_clamp(x: pa.Array, y: pa.Array, w: pa.Array) -> pa.Array:
        return pa.array([None if s is None else kernels.clamp(s[0], s[2], s[3])[0] for s in _sides(x, y, w)], pa.list_(pa.float64()))

    @F.arrow_udf(ARRAY)
    def warp_psum(x: pa.Array, d: pa.Array) -> pa.Array:
        return _sums(x, d)

    return {"warp_envelope": warp_envelope, "warp_clamp": warp_clamp, "warp_psum": warp_psum}


@F.udtf(returnType="rank int, at int, dist double")
class NearestIn:
    """SQL: ``LATERAL nearest_in(y, candidates, w, k)``, the k nearest of an array of series, ``at`` counting from 1."""

    def eval(self, y: list, candidates: list, w: int, k: int):
        pool = [(at, x) for at, x in enumerate(candidates or [], 1) if x and y and len(x) == len(y)]
        if pool:
            powers = kernels.dtw_pow(np.array([x for _, x in pool], dtype=float), np.array([y], dtype=float), None if w < 0 else w)
            for rank, (dist, at) in enumerate(sorted(zip(powers.tolist(), [at for at, _ in pool], strict=True))[:k], 1):
                yield rank, at, float(dist)


def pack_series(pos: str | Column, value: str | Column) -> Column:
    """Aggregate: the values in order of their positions."""
    pair = F.struct((F.col(pos) if isinstance(pos, str) else pos).alias("pos"), (F.col(value) if isinstance(value, str) else value).cast("double").alias("val"))
    return F.transform(F.array_sort(F.collect_list(pair)), lambda s: s.val)


def best_match(dist: str | Column, series_id: str | Column) -> Column:
    """Aggregate: a struct of the least distance and its series, of equal ones the smallest id."""
    return F.min(F.struct((F.col(dist) if isinstance(dist, str) else dist).alias("dist"), (F.col(series_id) if isinstance(series_id, str) else series_id).alias("series_id")))


def medoid(series_id: str, v: str, w: int | None = None, most: int = 2_000) -> Column:
    """Aggregate for small groups: the id whose summed distance to the rest of its group is least, of equal ones the smallest.

    It compares all pairs of a group, so groups of more than ``most`` are refused.
    """

    @F.pandas_udf("long")
    def find(ids: pd.Series, rows: pd.Series) -> int:
        if len(ids) > most:
            raise ValueError(f"a group of {len(ids)} is too large for a medoid of at most {most}")
        x, order = np.stack(rows.tolist()), np.argsort(ids.to_numpy(), kind="stable")
        sums = [kernels.dtw_pow(x, x[k : k + 1], w).sum() for k in order]
        return int(ids.to_numpy()[order[int(np.argmin(sums))]])

    return find(series_id, v)


def register(spark: SparkSession) -> None:
    """SQL names: warp_dtw, warp_ndtw, warp_pass1, warp_pass2 (x, y, w, p), warp_envelope, warp_clamp, warp_psum, warp_path, explain_bounds, nearest_in."""
    for name, kernel in (("warp_dtw", _dtw_kernel), ("warp_ndtw", _ndtw_kernel), ("warp_pass1", _pass1_kernel), ("warp_pass2", _pass2_kernel)):
        spark.udf.register(name, _varying(kernel))
    for name, function in _sql_scalars().items():
        spark.udf.register(name, function)
    for name, table in (("warp_path", WarpPath), ("explain_bounds", ExplainBounds), ("nearest_in", NearestIn)):
        spark.udtf.register(name, table)
