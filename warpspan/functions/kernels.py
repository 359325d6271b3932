"""Numpy kernels over batches: row b of every matrix is one series or one pair.

Costs are carried as powers (sums of |.|**p, or maxima for p = inf); the p-th
root is only taken for output. A band of ``w`` allows cell (i, j) if
|i - j| <= w; ``None`` or anything from n - 1 up means no band.
"""

from __future__ import annotations

import math
from collections import deque

import numpy as np

INF = math.inf


def check_norm(p: float, bound: bool = True) -> float:
    """Norms from 1 to infinity for bounds, any positive one for distances."""
    if not p > 0 or bound and p < 1:
        raise ValueError(f"p must be {'at least 1' if bound else 'positive'}, not {p}")
    return float(p)


def check_band(w: int | None, n: int) -> int:
    """The band as a number from 0 to n - 1."""
    if w is None:
        return max(0, n - 1)
    if w < 0:
        raise ValueError(f"the band must not be negative, it is {w}")
    return min(int(w), max(0, n - 1))


def cost(difference: np.ndarray, p: float) -> np.ndarray:
    """|d|**p, or |d| for p = inf."""
    size = np.abs(difference)
    return size if p == 1 or p == INF else size * size if p == 2 else size**p


def total(costs: np.ndarray, p: float) -> np.ndarray:
    """Costs put together along the last axis."""
    if p == INF:
        return costs.max(axis=-1, initial=0.0)
    return costs.sum(axis=-1)


def add(a: np.ndarray, b: np.ndarray, p: float) -> np.ndarray:
    return np.maximum(a, b) if p == INF else a + b


def root(power: np.ndarray | float, p: float):
    return power if p in (1, INF) else np.power(power, 1.0 / p)


def power(value: float, p: float) -> float:
    return float(value) if p in (1, INF) else float(value) ** p


def lp_pow(x: np.ndarray, y: np.ndarray, p: float = 1) -> np.ndarray:
    return total(cost(x - y, p), p)


def _running_max(y: np.ndarray, w: int) -> np.ndarray:
    """Maximum over positions i - w .. i + w, by windows that double in length."""
    n = y.shape[-1]
    padded = np.full((*y.shape[:-1], n + 2 * w), -INF)
    padded[..., w : w + n] = y
    width, size = 1, 2 * w + 1
    while 2 * width <= size:
        padded = np.maximum(padded[..., : padded.shape[-1] - width], padded[..., width:])
        width *= 2
    rest = size - width
    return np.maximum(padded[..., :n], padded[..., rest : rest + n])


def envelope(y: np.ndarray, w: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Running minimum and maximum ``(lo, hi)`` over the band, for every row."""
    y = np.asarray(y, dtype=float)
    w = check_band(w, y.shape[-1])
    if w == 0:
        return y.copy(), y.copy()
    return -_running_max(-y, w), _running_max(y, w)


def envelope_by_queues(y, w: int | None) -> tuple[list[float], list[float], int]:
    """``lo, hi`` of one series in a single pass, and the comparisons of samples it took.

    One queue holds positions with falling values, one with rising values. A
    sample is compared with its predecessor first; that alone says which of
    the queues it may shorten, so there are three comparisons a sample at most.
    """
    n = len(y)
    w = check_band(w, n)
    falling, rising = deque([0]), deque([0])
    lo, hi, comparisons = [0.0] * n, [0.0] * n, 0

    def emit(at: int) -> None:
        for queue, out in ((falling, hi), (rising, lo)):
            while queue[0] < at - w:
                queue.popleft()
            out[at] = y[queue[0]]

    if w == 0:
        emit(0)
    for i in range(1, n):
        comparisons += 1
        queue, sign = (falling, 1) if y[i] > y[i - 1] else (rising, -1)
        queue.pop()
        while queue:
            comparisons += 1
            if sign * y[i] <= sign * y[queue[-1]]:
                break
            queue.pop()
        falling.append(i)
        rising.append(i)
        if i >= w:
            emit(i - w)
    for at in range(max(0, n - w), n):
        emit(at)
    return lo, hi, comparisons


def clamp(x: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The series between the envelope's sides that is nearest to x."""
    return np.minimum(np.maximum(x, lo), hi)


def pass1_pow(x: np.ndarray, lo: np.ndarray, hi: np.ndarray, p: float = 1) -> np.ndarray:
    """The envelope bound: how far x is outside the other series' envelope."""
    return total(cost(np.maximum(np.maximum(lo - x, x - hi), 0.0), p), p)


def gap2_pow(x: np.ndarray, y: np.ndarray, lo: np.ndarray, hi: np.ndarray, w: int, p: float = 1) -> np.ndarray:
    """The envelope bound of y against the clamped x."""
    return pass1_pow(y, *envelope(clamp(x, lo, hi), w), p)


def pass2_pow(x: np.ndarray, y: np.ndarray, lo: np.ndarray, hi: np.ndarray, w: int, p: float = 1) -> np.ndarray:
    """Both passes together; at least as much as the first and at most the distance."""
    return add(pass1_pow(x, lo, hi, p), gap2_pow(x, y, lo, hi, w, p), p)


def abandoning_pass1(x: np.ndarray, lo: np.ndarray, hi: np.ndarray, limit: np.ndarray, p: float = 1, chunk: int = 32) -> tuple[np.ndarray, int]:
    """The envelope bound, given up for a row once its partial value reaches ``limit``.

    Rows that were given up hold the partial value, which is a bound too. Also
    says how many samples were read.
    """
    rows, n = x.shape
    lo, hi = np.broadcast_to(lo, x.shape), np.broadcast_to(hi, x.shape)
    out = np.zeros(rows)
    live, read = np.arange(rows), 0
    for start in range(0, n, chunk):
        part = slice(start, min(n, start + chunk))
        out[live] = add(out[live], pass1_pow(x[live, part], lo[live, part], hi[live, part], p), p)
        read += len(live) * (part.stop - start)
        live = live[out[live] < np.broadcast_to(limit, (rows,))[live]]
        if not len(live):
            break
    return out, read


def abandoning_pass2(
    x: np.ndarray, y: np.ndarray, lo: np.ndarray, hi: np.ndarray, w: int, first: np.ndarray, limit: np.ndarray, p: float = 1, chunk: int = 64
) -> tuple[np.ndarray, int]:
    """Both passes from the first one's values on, given up for a row once its partial value reaches ``limit``.

    Only the stretch of the second envelope that the next samples need is
    made. Rows that were given up hold the partial value. Also says how many
    samples of y were compared.
    """
    rows, n = x.shape
    y, lo, hi = (np.broadcast_to(side, x.shape) for side in (y, lo, hi))
    out = np.array(first, dtype=float)
    live, read = np.arange(rows), 0
    for start in range(0, n, chunk):
        live = live[out[live] < np.broadcast_to(limit, (rows,))[live]]
        if not len(live):
            break
        end = min(n, start + chunk)
        near = slice(max(0, start - w), min(n, end + w))
        low, high = envelope(clamp(x[live, near], lo[live, near], hi[live, near]), w)
        part = slice(start - near.start, end - near.start)
        out[live] = add(out[live], pass1_pow(y[live, start:end], low[:, part], high[:, part], p), p)
        read += len(live) * (end - start)
    return out, read


def dtw_pow(x: np.ndarray, y: np.ndarray, w: int | None = None, p: float = 1) -> np.ndarray:
    """Powered banded warping distance of the pairs (x[b], y[b]).

    The anti-diagonals i + j = k of the table are solved one after another,
    each for all pairs at once; only the last two are kept. Slot i + 1 of a
    diagonal holds cell (i, k - i). A diagonal's cells have infinite slots on
    both sides, which is all that the next two read beyond them.
    """
    x, y = np.atleast_2d(np.asarray(x, dtype=float)), np.atleast_2d(np.asarray(y, dtype=float))
    pairs = max(x.shape[0], y.shape[0])
    n, m = x.shape[1], y.shape[1]
    w = check_band(w, max(n, m))
    if abs(n - m) > w:
        return np.full(pairs, INF)
    # Time first, so that a diagonal's slice is a block of rows.
    a, b = np.ascontiguousarray(x.T), np.ascontiguousarray(y[:, ::-1].T)
    older, old, new = (np.full((n + 2, pairs), INF) for _ in range(3))
    widest = min(n, m, w + 1)
    gaps, least = np.empty((widest, pairs)), np.empty((widest, pairs))
    for k in range(n + m - 1):
        first = max(0, k - m + 1, -((w - k) // 2))
        last = min(n - 1, k, (k + w) // 2)
        new[first] = new[last + 2] = INF
        if first <= last:
            c, best = gaps[: last - first + 1], least[: last - first + 1]
            # b is reversed: y[k - i] is b[m - 1 - k + i].
            np.subtract(a[first : last + 1], b[m - 1 - k + first : m - k + last], out=c)
            if p in (1, INF):
                np.abs(c, out=c)
            else:
                c[...] = cost(c, p)
            if k == 0:
                new[1] = c[0]
            else:
                np.minimum(old[first : last + 1], old[first + 1 : last + 2], out=best)
                np.minimum(best, older[first : last + 1], out=best)
                (np.maximum if p == INF else np.add)(c, best, out=new[first + 1 : last + 2])
        older, old, new = old, new, older
    return old[n].copy()


def band_cells(n: int, w: int | None) -> int:
    """Cells of the table that the band leaves."""
    w = check_band(w, n)
    return n * (2 * w + 1) - w * (w + 1)


def warping_path(x, y, w: int | None = None, p: float = 1) -> tuple[list[tuple[int, int]], float]:
    """A cheapest minimal monotonic path of one pair, 0-based, and its powered cost."""
    x, y = np.asarray(x, dtype=float), np.asarray(y, dtype=float)
    n, m = len(x), len(y)
    w = check_band(w, max(n, m))
    table = np.full((n + 1, m + 1), INF)
    table[0, 0] = 0.0
    c = cost(x[:, None] - y[None, :], p)
    for i in range(n):
        for j in range(max(0, i - w), min(m, i + w + 1)):
            best = min(table[i, j], table[i, j + 1], table[i + 1, j])
            table[i + 1, j + 1] = max(c[i, j], best) if p == INF else c[i, j] + best
    i, j, path = n, m, []
    while i and j:
        path.append((i - 1, j - 1))
        # A diagonal step first: it leaves no match that could be spared.
        i, j = min(((i - 1, j - 1), (i - 1, j), (i, j - 1)), key=lambda at: table[at])
    return minimal_path(path[::-1]), float(table[n, m])


def minimal_path(path: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Leaves out matches whose two points are both matched elsewhere, as long as there are any."""
    rows: dict[int, int] = {}
    columns: dict[int, int] = {}
    for i, j in path:
        rows[i] = rows.get(i, 0) + 1
        columns[j] = columns.get(j, 0) + 1
    kept = []
    for i, j in path:
        if rows[i] > 1 and columns[j] > 1:
            rows[i] -= 1
            columns[j] -= 1
        else:
            kept.append((i, j))
    return kept


def aligned(x, y, path: list[tuple[int, int]]) -> tuple[list[float], list[float]]:
    """The two series with values repeated as the path says."""
    return [x[i] for i, _ in path], [y[j] for _, j in path]


def ndtw_inf(x, y, w: int | None = None) -> float:
    """Largest gap of any point to its nearest partner in the band: each point may choose alone."""
    x, y = np.asarray(x, dtype=float), np.asarray(y, dtype=float)
    gaps = np.abs(x[:, None] - y[None, :])
    gaps[np.abs(np.subtract.outer(np.arange(len(x)), np.arange(len(y)))) > check_band(w, max(len(x), len(y)))] = INF
    return float(max(gaps.min(axis=1).max(), gaps.min(axis=0).max()))


def _best_matching(gain: np.ndarray) -> float:
    """Largest total gain of a matching; cells of gain 0 count as no match."""
    n = len(gain)
    # Shortest augmenting paths with row and column prices.
    row_price, column_price = np.zeros(n + 1), np.zeros(n + 1)
    owner = np.zeros(n + 1, dtype=int)
    loss = -gain
    for row in range(1, n + 1):
        owner[0], column = row, 0
        slack, came, seen = np.full(n + 1, INF), np.zeros(n + 1, dtype=int), np.zeros(n + 1, dtype=bool)
        while owner[column]:
            seen[column] = True
            at = owner[column]
            free = ~seen
            free[0] = False
            reduced = loss[at - 1] - row_price[at] - column_price[1:]
            shorter = free[1:] & (reduced < slack[1:])
            slack[1:][shorter] = reduced[shorter]
            came[1:][shorter] = column
            step = slack[free].min()
            following = int(np.flatnonzero(free & (slack == step))[0])
            row_price[owner[seen]] += step
            column_price[seen] -= step
            slack[free] -= step
            column = following
        while column:
            owner[column] = owner[came[column]]
            column = came[column]
    return float(sum(gain[owner[j] - 1, j - 1] for j in range(1, n + 1)))


def ndtw_pow(x, y, w: int | None = None, p: float = 1) -> float:
    """Powered non-monotonic distance: the cheapest cover of all points by matches in the band.

    Every point pays for its cheapest match; a match that is cheapest for
    neither end, or for both, saves what a matching can save. Cubic in n.
    """
    if p == INF:
        return ndtw_inf(x, y, w)
    x, y = np.asarray(x, dtype=float), np.asarray(y, dtype=float)
    n, m = len(x), len(y)
    c = cost(x[:, None] - y[None, :], p)
    c[np.abs(np.subtract.outer(np.arange(n), np.arange(m))) > check_band(w, max(n, m))] = INF
    cheapest_x, cheapest_y = c.min(axis=1), c.min(axis=0)
    size = max(n, m)
    gain = np.zeros((size, size))
    gain[:n, :m] = np.maximum(cheapest_x[:, None] + cheapest_y[None, :] - c, 0.0)
    return float(cheapest_x.sum() + cheapest_y.sum() - _best_matching(gain))


#: Cells of the banded tables that are solved at once.
NDTW_CELLS = 2_000_000


def ndtw_pows(x: np.ndarray, y: np.ndarray, w: int | None = None, p: float = 1) -> np.ndarray:
    """``ndtw_pow`` of the pairs (x[b], y[b]) of equal length, all pairs together."""
    x, y = (np.atleast_2d(np.asarray(side, dtype=float)) for side in (x, y))
    pairs, n = x.shape
    w = check_band(w, n)
    if p == INF or y.shape != x.shape:
        return np.array([ndtw_pow(a, b, w, p) for a, b in zip(x, y, strict=True)])
    solve = _cover_of_one if w == 1 else _cover_by_matching
    block = max(1, NDTW_CELLS // (n * (2 * w + 1)))
    parts = [solve(x[k : k + block], y[k : k + block], w, p) for k in range(0, pairs, block)]
    return np.concatenate(parts) if parts else np.zeros(0)


def _cover_of_one(x: np.ndarray, y: np.ndarray, w: int, p: float) -> np.ndarray:
    """The cheapest cover with a band of one: only whether the last x and the last y have a partner matters for what follows."""
    here = cost(x - y, p)
    back, ahead = cost(x[:, 1:] - y[:, :-1], p), cost(x[:, :-1] - y[:, 1:], p)
    # By whether x and y at this place have partners.
    least = {(False, False): np.zeros(len(x)), (True, True): here[:, 0]}
    for k in range(1, x.shape[1]):
        following: dict = {}
        for (has_x, has_y), so_far in least.items():
            for one in (False, True):  # this x to the y before
                for two in (False, True):  # this y to the x before
                    if not ((has_y or one) and (has_x or two)):
                        continue
                    crossed = so_far + one * back[:, k - 1] + two * ahead[:, k - 1]
                    for state, value in (((one, two), crossed), ((True, True), crossed + here[:, k])):
                        following[state] = np.minimum(following[state], value) if state in following else value
        least = following
    return least[True, True]


def _cover_by_matching(x: np.ndarray, y: np.ndarray, w: int, p: float) -> np.ndarray:
    """Every point's cheapest partner, less the most that a matching saves; column c of a row is place i - w + c of y."""
    pairs, n = x.shape
    width = 2 * w + 1
    place = np.arange(n)[:, None] + np.arange(-w, w + 1)[None, :]
    inside = (place >= 0) & (place < n)
    place = np.clip(place, 0, n - 1)
    c = np.where(inside, cost(x[:, :, None] - y[:, place], p), INF)
    cheapest_x, cheapest_y = c.min(axis=2), np.full((pairs, n), INF)
    for k in range(width):
        first, after = max(0, w - k), min(n, n + w - k)
        part = slice(first - w + k, after - w + k)
        cheapest_y[:, part] = np.minimum(cheapest_y[:, part], c[:, first:after, k])
    gain = np.maximum(cheapest_x[:, :, None] + cheapest_y[:, place] - c, 0.0)
    return cheapest_x.sum(axis=1) + cheapest_y.sum(axis=1) - _best_matchings(gain, place)


def _best_matchings(gain: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Largest total gain of a matching for each of many banded tables; points may stay alone.

    Rows enter one after another, in all tables at once. From a new row a
    shortest path of reduced losses leads to a free column, or to a row that is
    better left alone; tables drop out of a step as their path ends.
    """
    tables, n, width = gain.shape
    row_price, column_price = np.zeros((tables, n)), np.zeros((tables, n))
    owner, partner = np.full((tables, n), -1), np.full((tables, n), -1)
    for new in range(n):
        best = (gain[:, new] - column_price[:, place[new]]).max(axis=1)
        active = np.flatnonzero(best > 0)
        if not len(active):
            continue
        row_price[active, new] = best[active]
        size = len(active)
        far, came = np.full((size, n), INF), np.full((size, n), -1)
        seen, reach = np.zeros((size, n), bool), np.full((size, n), INF)  # columns done, and rows in the tree with their distances
        row, at = np.full(size, new), np.zeros(size)
        end, end_row, end_column = np.full(size, INF), np.full(size, -1), np.full(size, -1)
        live = np.arange(size)
        while len(live):
            t, r, d = active[live], row[live], at[live]
            reach[live, r] = d
            leave = d + row_price[t, r]
            shorter = leave < end[live]
            end[live[shorter]], end_row[live[shorter]] = leave[shorter], r[shorter]
            columns, own = place[r], gain[t, r]
            there = (d + row_price[t, r])[:, None] + column_price[t[:, None], columns] - own
            # A gain of 0 is no match; it also stands outside the table.
            better = (own > 0) & (there < far[live[:, None], columns]) & ~seen[live[:, None], columns]
            at_row, at_column = np.nonzero(better)
            far[live[at_row], columns[at_row, at_column]] = there[at_row, at_column]
            came[live[at_row], columns[at_row, at_column]] = r[at_row]
            open_far = np.where(seen[live], INF, far[live])
            following = open_far.argmin(axis=1)
            step = open_far[np.arange(len(live)), following]
            going = step < end[live]
            live, following, step = live[going], following[going], step[going]
            free = owner[active[live], following] < 0
            done = live[free]
            end[done], end_row[done], end_column[done] = step[free], -1, following[free]
            live, following, step = live[~free], following[~free], step[~free]
            seen[live, following] = True
            row[live], at[live] = owner[active[live], following], step
        inside = reach < end[:, None]
        row_price[active] -= np.where(inside, end[:, None] - np.where(inside, reach, 0.0), 0.0)
        passed = seen & (far < end[:, None])
        column_price[active] += np.where(passed, end[:, None] - np.where(passed, far, 0.0), 0.0)
        # Partners change along the path, from its end back to the new row.
        alone = np.flatnonzero(end_column < 0)
        column = end_column.copy()
        column[alone] = partner[active[alone], end_row[alone]]
        partner[active[alone], end_row[alone]] = -1
        moving = np.flatnonzero(column >= 0)
        while len(moving):
            t, j = active[moving], column[moving]
            r = came[moving, j]
            before = partner[t, r]
            owner[t, j], partner[t, r] = r, j
            column[moving] = before
            moving = moving[before >= 0]
    cell = np.clip(partner - np.arange(n) + width // 2, 0, width - 1)
    kept = np.take_along_axis(gain, cell[:, :, None], axis=2)[:, :, 0]
    return np.where(partner >= 0, kept, 0.0).sum(axis=1)


def ndtw_sorted_pow(x, y, p: float = 1) -> float:
    """The same without a band: sorted values need no crossing, so the monotonic distance of the sorted series is it."""
    return float(dtw_pow(np.sort(x), np.sort(y), None, p)[0])


def piecewise_sums(x: np.ndarray, cover: list[tuple[int, int]]) -> np.ndarray:
    """Sums over each interval ``[start, after)`` of a cover."""
    return np.stack([x[..., a:b].sum(axis=-1) for a, b in cover], axis=-1)


def walk(v: np.ndarray) -> np.ndarray:
    """Centred by n*v - sum(v), which keeps integers whole, and summed up."""
    v = np.atleast_2d(v)
    return np.cumsum(v.shape[1] * v - v.sum(axis=1, keepdims=True), axis=1)
