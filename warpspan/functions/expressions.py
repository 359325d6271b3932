"""Distances and bounds as built-in column expressions: no Python runs in any of them.

Array arguments are columns of ``ARRAY<DOUBLE>``. Names that end in ``_pow``
give powers; the others take the root.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from warpspan.functions.kernels import INF, check_norm


def _col(value: str | Column) -> Column:
    return F.col(value) if isinstance(value, str) else value


def let(value: Column, make) -> Column:
    """``make(v)`` with v bound to ``value``, which is then evaluated once."""
    return F.element_at(F.transform(F.array(value), make), 1)


def cost(difference: Column, p: float) -> Column:
    size = F.abs(difference)
    return size if p in (1, INF) else size * size if p == 2 else F.pow(size, F.lit(float(p)))


def total(costs: Column, p: float) -> Column:
    """Costs of an array put together."""
    if p == INF:
        return F.coalesce(F.array_max(costs), F.lit(0.0))
    return F.aggregate(costs, F.lit(0.0), lambda a, c: a + c)


def root(value: Column, p: float) -> Column:
    return value if p in (1, INF) else F.sqrt(value) if p == 2 else F.pow(value, F.lit(1.0 / p))


def add(a: Column, b: Column, p: float) -> Column:
    return F.greatest(a, b) if p == INF else a + b


def lp_norm(x: str | Column, p: float = 1) -> Column:
    check_norm(p, bound=False)
    return root(total(F.transform(_col(x), lambda v: cost(v, p)), p), p)


def lp_distance_pow(x: str | Column, y: str | Column, p: float = 1) -> Column:
    check_norm(p, bound=False)
    return total(F.zip_with(_col(x), _col(y), lambda a, b: cost(a - b, p)), p)


def lp_distance(x: str | Column, y: str | Column, p: float = 1) -> Column:
    return root(lp_distance_pow(x, y, p), p)


def interval_distance(v: str | Column, lo: str | Column, hi: str | Column) -> Column:
    """How far a value is outside [lo, hi]."""
    return F.greatest(_col(lo) - _col(v), _col(v) - _col(hi), F.lit(0.0))


def envelope(y: str | Column, w: int) -> Column:
    """A struct of ``lo`` and ``hi``, by slices of the array."""
    y = _col(y)
    at = F.sequence(F.lit(1), F.size(y))
    window = lambda i: F.slice(y, F.greatest(i - w, F.lit(1)), F.least(i + w, F.size(y)) - F.greatest(i - w, F.lit(1)) + 1)
    return F.struct(
        F.transform(at, lambda i: F.array_min(window(i))).alias("lo"), F.transform(at, lambda i: F.array_max(window(i))).alias("hi")
    )


def clamp(x: str | Column, lo: str | Column, hi: str | Column) -> Column:
    above = F.zip_with(_col(x), _col(lo), lambda a, b: F.greatest(a, b))
    return F.zip_with(above, _col(hi), lambda a, b: F.least(a, b))


def pass1_pow(x: str | Column, lo: str | Column, hi: str | Column, p: float = 1) -> Column:
    """The envelope bound in one sweep over three zipped arrays."""
    check_norm(p)
    x = _col(x)
    below = F.zip_with(_col(lo), x, lambda a, b: F.greatest(a - b, F.lit(0.0)))
    above = F.zip_with(x, _col(hi), lambda a, b: F.greatest(a - b, F.lit(0.0)))
    return total(F.zip_with(below, above, lambda a, b: cost(F.greatest(a, b), p)), p)


def pass1(x: str | Column, lo: str | Column, hi: str | Column, p: float = 1) -> Column:
    return root(pass1_pow(x, lo, hi, p), p)


def gap2_pow(x: str | Column, y: str | Column, lo: str | Column, hi: str | Column, w: int, p: float = 1) -> Column:
    """The envelope bound of y against the clamped x."""
    return let(
        clamp(x, lo, hi), lambda h: let(envelope(h, w), lambda e: pass1_pow(_col(y), e.getField("lo"), e.getField("hi"), p))
    )


def pass2_pow(x: str | Column, y: str | Column, lo: str | Column, hi: str | Column, w: int, p: float = 1) -> Column:
    return add(pass1_pow(x, lo, hi, p), gap2_pow(x, y, lo, hi, w, p), p)


def pass1_error_limit(y: str | Column, lo: str | Column, hi: str | Column, p: float = 1) -> Column:
    """The most by which any distance to y can exceed the envelope bound; the query alone decides it."""
    reach = F.zip_with(
        F.zip_with(_col(hi), _col(y), lambda a, b: a - b), F.zip_with(_col(y), _col(lo), lambda a, b: a - b), lambda a, b: cost(F.greatest(a, b), p)
    )
    return root(total(reach, p), p)


def anchor_bound(x: str | Column, h: str | Column, p: float = 1) -> Column:
    """The generic bound of any admissible h."""
    check_norm(p)
    return lp_distance(x, h, p)


def anchor_error_limit(h: str | Column, y: str | Column, p: float = 1) -> Column:
    """The most by which the distance can exceed the generic bound."""
    return lp_distance(h, y, p)


def is_admissible(x: str | Column, h: str | Column, lo: str | Column, hi: str | Column) -> Column:
    """Whether h is x, or between x and the near side of the envelope, everywhere."""
    inside = lambda a, b: F.zip_with(a, b, lambda u, v: u <= v)
    x, h, lo, hi = map(_col, (x, h, lo, hi))
    same = F.zip_with(x, h, lambda u, v: u == v)
    down = F.zip_with(inside(h, x), inside(hi, h), lambda u, v: u & v)
    up = F.zip_with(inside(x, h), inside(h, lo), lambda u, v: u & v)
    return F.forall(F.zip_with(same, F.zip_with(down, up, lambda u, v: u | v), lambda u, v: u | v), lambda ok: ok)


def separated_shortcut(x: str | Column, y: str | Column) -> Column:
    """The distance for p = 1 where one series lies wholly above the other; null elsewhere."""
    x, y = _col(x), _col(y)
    apart = (F.array_min(x) >= F.array_max(y)) | (F.array_min(y) >= F.array_max(x))
    return F.when(apart, lp_distance_pow(x, y, 1))


def piecewise_sums(x: str | Column, cover: list[tuple[int, int]]) -> list[Column]:
    """One column ``s1 .. sd`` for each interval of the cover."""
    x = _col(x)
    return [
        F.aggregate(F.slice(x, a + 1, b - a), F.lit(0.0), lambda t, v: t + v).alias(f"s{k}") for k, (a, b) in enumerate(cover, 1)
    ]


def box_bound_pow(points: list[Column], lows: list[Column], highs: list[Column], cover: list[tuple[int, int]], p: float = 1) -> Column:
    """Distance of a point of piecewise sums to a box, interval by interval.

    For p > 1 each interval's share is divided by its length to the p - 1
    (power means), for p = inf by its length.
    """
    parts = []
    for point, lo, hi, (a, b) in zip(points, lows, highs, cover, strict=True):
        gap = interval_distance(point, lo, hi)
        parts.append(gap if p == 1 else gap / (b - a) if p == INF else F.pow(gap, F.lit(float(p))) / float(b - a) ** (p - 1))
    if p == INF:
        return F.greatest(*parts) if len(parts) > 1 else parts[0]
    out = parts[0]
    for part in parts[1:]:
        out = out + part
    return out


def ndtw_inf(x: str | Column, y: str | Column, w: int) -> Column:
    """Largest gap of any point to its nearest partner in the band."""

    def nearest(a: Column, b: Column) -> Column:
        window = lambda i: F.slice(b, F.greatest(i + 1 - w, F.lit(1)), F.least(i + 1 + w, F.size(b)) - F.greatest(i + 1 - w, F.lit(1)) + 1)
        return F.array_max(F.transform(a, lambda v, i: F.array_min(F.transform(window(i), lambda u: F.abs(u - v)))))

    return F.greatest(nearest(_col(x), _col(y)), nearest(_col(y), _col(x)))


def dtw_pow(x: str | Column, y: str | Column, n: int, w: int, p: float = 1) -> Column:
    """The banded distance for series of length n as a fold over anti-diagonals; for where no Python may run.

    The state is the last two diagonals; slot i + 2 holds cell (i, k - i).
    """
    x, y = _col(x), _col(y)
    far = F.lit(1e300)
    blank = F.array_repeat(far, n + 1)

    def step(state: Column, k: Column) -> Column:
        old, older = state.getField("old"), state.getField("older")

        def cell(i: Column) -> Column:
            c = cost(F.get(x, i) - F.get(y, k - i), p)
            best = F.least(F.get(old, i), F.get(old, i + 1), F.get(older, i))
            value = F.when(k == 0, c).otherwise(F.greatest(c, best) if p == INF else c + best)
            live = (k - i >= 0) & (k - i < n) & (F.abs(2 * i - k) <= w)
            return F.when(live, value).otherwise(far)

        new = F.concat(F.array(far), F.transform(F.sequence(F.lit(0), F.lit(n - 1)), cell))
        return F.struct(new.alias("old"), old.alias("older"))

    start = F.struct(blank.alias("old"), blank.alias("older"))
    end = F.aggregate(F.sequence(F.lit(0), F.lit(2 * n - 2)), start, step)
    return F.element_at(end.getField("old"), n + 1)
