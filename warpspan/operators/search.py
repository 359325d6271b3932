"""Nearest neighbours under time warping: filter by bounds, refine by the distance.

Every method gives the same exact answers; they differ in how many distances
they compute. The cheap bounds come first:

* ``brute``: the distance to every candidate;
* ``scan_pass1``, ``scan_pass2``: a scan with the envelope bound, or with both
  passes;
* ``box_only``, ``box_pass1``, ``box_pass2``: candidates from the box index,
  then no, one or both passes;
* ``lp``: the unwarped distance, for contrast.

Queries are a small set. Their count is checked: up to ``QUERY_VALUES`` samples
travel to every task; larger sets are cut into tiles with a scan each. A task
keeps the k best of each query and its own limit, which only falls and is
always the distance of some candidate, so tasks need nothing of each other. A
candidate is dropped only if a bound is above the limit; ties at the limit are
computed and the smaller id wins.

The box methods always go by pages: a query's nearest pages give it a first
limit, then the arrays of the pages within that limit are read where they lie
and each page's rows meet only the queries that reach it. Nothing is shuffled
but the page table's few rows.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.functions import expressions as X
from warpspan.functions import kernels
from warpspan.operators import boxindex
from warpspan.sources.series import matrix

METHODS = {
    "brute": (), "scan_pass1": ("pass1",), "scan_pass2": ("pass1", "pass2"),
    "box_only": ("box",), "box_pass1": ("box", "pass1"), "box_pass2": ("box", "pass1", "pass2"),
}
#: Samples of queries that one task holds: 64 MB with their envelopes.
QUERY_VALUES = 2_500_000
#: Candidates of a query that are refined at once at first; the number doubles from turn to turn.
CHUNK = 32
#: Pairs of all queries together that the distance kernel takes at once.
MOST_PAIRS = 2_048
#: Pairs of a page and a query that reaches it which are sent to every task; more are joined by a shuffle.
MOST_HITS = 5_000_000

_FOUND = pa.schema([("query_id", pa.int64()), ("series_id", pa.int64()), ("power", pa.float64()), ("counts", pa.list_(pa.int64()))])
_FOUND_TYPES = "query_id bigint, series_id bigint, power double, counts array<bigint>"
COUNTERS = ("candidates", "after_box", "after_pass1", "after_pass2", "dtw_done", "samples_read", "bound_ns", "dtw_ns")


class Query(NamedTuple):
    y: np.ndarray
    lo: np.ndarray
    hi: np.ndarray


class Plan(NamedTuple):
    """What a kernel needs to know besides the queries."""

    w: int
    p: float
    k: int
    passes: tuple[str, ...]
    early_abandon: bool = False
    exclude_self: bool = False
    eps: float | None = None
    #: Intervals of the index that is searched.
    cover: tuple[tuple[int, int], ...] | None = None


def query_tiles(queries: DataFrame, w: int | None, most_values: int = QUERY_VALUES) -> Iterator[tuple[dict[int, Query], int]]:
    """Queries with their envelopes, computed once, in tiles that fit a task; and the band."""
    tile: dict[int, Query] = {}
    size, band = 0, 0
    for row in queries.select("query_id", "y").toLocalIterator():
        y = np.array(row.y, dtype=float)
        if not len(y) or np.isnan(y).any():
            raise ValueError(f"query {row.query_id} has no samples, or some that are no numbers")
        if tile and size + len(y) > most_values:
            yield tile, band
            tile, size = {}, 0
        band = kernels.check_band(w, len(y))
        lo, hi = kernels.envelope(y[None, :], band)
        tile[row.query_id] = Query(y, lo[0], hi[0])
        size += len(y)
    if tile:
        yield tile, band


class Best:
    """The k best candidates of a query so far, and the limit beyond which none can enter.

    With a range (``eps``) the limit is fixed and matches wait only until the
    task has written them, so a task holds no more than a batch of them.
    """

    def __init__(self, plan: Plan, limit: float, query_id: int):
        self.plan, self.seed, self.query_id, self.rows = plan, limit, query_id, []
        self.counts = np.zeros(len(COUNTERS), dtype=np.int64)

    @property
    def limit(self) -> float:
        if self.plan.eps is not None or len(self.rows) < self.plan.k:
            return self.seed
        return min(self.seed, self.rows[self.plan.k - 1][0])

    def offer(self, powers: np.ndarray, ids: np.ndarray) -> None:
        near = powers <= self.limit
        new = list(zip(powers[near].tolist(), ids[near].tolist(), strict=True))
        if self.plan.eps is not None:
            self.rows += new
        elif new:
            self.rows = heapq.nsmallest(self.plan.k, self.rows + new)

    def filtered(self, query: Query, rows: np.ndarray, ids: np.ndarray, x: np.ndarray, sums: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Rows of a block that the box bound and the first pass leave, with their bounds, the least first."""
        plan, started = self.plan, time.perf_counter_ns()
        if plan.exclude_self:
            rows = rows[ids[rows] != self.query_id]
        self.counts[0] += len(rows)
        bound = np.zeros(len(rows))
        if sums is not None:
            bound = boxindex.box_pow(sums[rows], query.lo, query.hi, plan.cover, plan.p)
            alive = bound <= self.limit
            rows, bound = rows[alive], bound[alive]
        self.counts[1] += len(rows)
        if "pass1" in plan.passes:
            block = x[rows]
            if plan.early_abandon:
                bound, read = kernels.abandoning_pass1(block, query.lo, query.hi, self.beyond, plan.p)
            else:
                bound, read = kernels.pass1_pow(block, query.lo, query.hi, plan.p), block.size
            self.counts[5] += read
            alive = bound <= self.limit
            rows, bound = rows[alive], bound[alive]
        self.counts[2] += len(rows)
        order = np.argsort(bound, kind="stable")
        self.counts[6] += time.perf_counter_ns() - started
        return rows[order], bound[order]

    @property
    def beyond(self) -> float:
        """The least value above the limit: what reaches it can't enter, and ties stay."""
        return np.nextafter(self.limit, np.inf)

    def drained(self) -> list[tuple]:
        """The rows so far, which are then forgotten."""
        rows, self.rows = self.rows, []
        return [(self.query_id, series_id, power, None) for power, series_id in rows]

    def output(self) -> list[tuple]:
        return [*self.drained(), (self.query_id, None, None, self.counts.tolist())]


def refine(bests: dict[int, Best], queries: dict[int, Query], plan: Plan, ids: np.ndarray, x: np.ndarray, rows_of: dict[int, np.ndarray], sums: np.ndarray | None = None) -> None:
    """The cascade over a block of candidates; ``rows_of`` names the rows that each query meets.

    Each query's candidates are filtered by the cheap bounds and put in order.
    Then, turn by turn, the next few of all queries go through the second pass
    and the distance together, as one call costs little more for many pairs.
    """
    names = list(rows_of)
    for start in range(0, len(names), MOST_PAIRS // CHUNK):
        open_ = {q: bests[q].filtered(queries[q], rows_of[q], ids, x, sums) for q in names[start : start + MOST_PAIRS // CHUNK]}
        take = CHUNK
        while open_:
            parts = {}
            for q, (rows, bound) in open_.items():
                good = int(np.searchsorted(bound[:take], bests[q].limit, side="right"))
                if good:
                    parts[q] = rows[:good], bound[:good]
            # A query is done when its next candidate is beyond its limit.
            open_ = {q: (rows[take:], bound[take:]) for q, (rows, bound) in open_.items() if q in parts and len(parts[q][0]) == take and len(rows) > take}
            if parts:
                _refine_together(parts, bests, queries, plan, ids, x)
            take = min(2 * take, MOST_PAIRS // max(1, len(open_)))


def _refine_together(parts: dict, bests: dict[int, Best], queries: dict[int, Query], plan: Plan, ids: np.ndarray, x: np.ndarray) -> None:
    started = time.perf_counter_ns()
    own = list(parts)
    sizes = [len(parts[q][0]) for q in own]
    owner = np.repeat(np.arange(len(own)), sizes)
    rows, bound = (np.concatenate([parts[q][k] for q in own]) for k in (0, 1))
    y, lo, hi = (np.stack([getattr(queries[q], side) for q in own]) for side in ("y", "lo", "hi"))
    block = x[rows]
    limits = np.array([bests[q].limit for q in own])[owner]
    if "pass2" in plan.passes:
        read = [size * x.shape[1] for size in sizes]
        if plan.early_abandon:
            beyond = np.array([bests[q].beyond for q in own])[owner]
            both, samples = kernels.abandoning_pass2(block, y[owner], lo[owner], hi[owner], plan.w, bound, beyond, plan.p)
            read = [samples * size // len(rows) for size in sizes]
        else:
            both = kernels.add(bound, kernels.gap2_pow(block, y[owner], lo[owner], hi[owner], plan.w, plan.p), plan.p)
        alive = both <= limits
        block, owner, rows = block[alive], owner[alive], rows[alive]
        for q, samples in zip(own, read, strict=True):
            bests[q].counts[5] += samples
    begun = time.perf_counter_ns()
    powers = kernels.dtw_pow(block, y[owner], plan.w, plan.p) if len(rows) else np.zeros(0)
    ended = time.perf_counter_ns()
    for k, q in enumerate(own):
        mine = owner == k
        done = int(mine.sum())
        bests[q].counts[3:5] += done
        bests[q].counts[6:8] += ((begun - started) // len(own), (ended - begun) * done // max(1, len(rows)))
        if done:
            bests[q].offer(powers[mine], ids[rows[mine]])


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
    return pa.record_batch([pa.array(c, f.type) for c, f in zip(columns, _FOUND, strict=True)], schema=_FOUND)


def _lengths_agree(x: np.ndarray, query: Query) -> None:
    if x.shape[1] != len(query.y):
        raise ValueError(f"a series has {x.shape[1]} samples, a query {len(query.y)}")


def _share(frame: DataFrame, tile: dict[int, Query], limits: dict[int, float] | None):
    """A broadcast of plain values, which workers read without this package."""
    return frame.sparkSession.sparkContext.broadcast(({q: tuple(x) for q, x in tile.items()}, limits or {}))


def _shared(shared) -> tuple[dict[int, Query], dict[int, float]]:
    queries, limits = shared.value
    return {q: Query(*x) for q, x in queries.items()}, limits


def _start(plan: Plan) -> float:
    return float("inf") if plan.eps is None else kernels.power(plan.eps, plan.p)


def scan(series: DataFrame, tile: dict[int, Query], plan: Plan, limits: dict[int, float] | None = None) -> DataFrame:
    """Each task's best candidates of each query, from a scan of all series."""
    shared = _share(series, tile, limits)

    def run(source):
        queries, seeds = _shared(shared)
        best = {q: Best(plan, seeds.get(q, _start(plan)), q) for q in queries}
        for batch in source:
            if not batch.num_rows:
                continue
            ids, x = batch.column(0).to_numpy(), matrix(batch.column(1))
            every = np.arange(len(ids))
            for query in queries.values():
                _lengths_agree(x, query)
            refine(best, queries, plan, ids, x, {q: every for q in queries})
            if plan.eps is not None:
                yield _batch([row for b in best.values() for row in b.drained()])
        yield _batch([row for b in best.values() for row in b.output()])

    return series.select("series_id", "v").mapInArrow(run, _FOUND_TYPES)


def refine_pages(paged: DataFrame, tile: dict[int, Query], plan: Plan, limits: dict[int, float] | None = None) -> DataFrame:
    """The same for rows ``owners, series_id, v``, where ``owners`` lists the queries that reach the row's page."""
    shared = _share(paged, tile, limits)

    def run(source):
        queries, seeds = _shared(shared)
        best: dict[int, Best] = {}
        for batch in source:
            if not batch.num_rows:
                continue
            owners, ids, x = batch.column(0), batch.column(1).to_numpy(), matrix(batch.column(2))
            sums = kernels.piecewise_sums(x, plan.cover)
            row = np.repeat(np.arange(len(ids)), np.asarray(owners.value_lengths()))
            owner = owners.flatten().to_numpy()
            rows_of = {q: row[owner == q] for q in np.unique(owner).tolist()}
            for q in rows_of:
                _lengths_agree(x, queries[q])
                best.setdefault(q, Best(plan, seeds.get(q, _start(plan)), q))
            refine(best, queries, plan, ids, x, rows_of, sums)
            if plan.eps is not None:
                yield _batch([row for b in best.values() for row in b.drained()])
        yield _batch([row for b in best.values() for row in b.output()])

    return paged.select("owners", "series_id", "v").mapInArrow(run, _FOUND_TYPES)


def merged(found: DataFrame, k: int, p: float) -> DataFrame:
    """``query_id, rank, series_id, dist`` from the tasks' lists of at most k rows each."""
    order = Window.partitionBy("query_id").orderBy("power", "series_id")
    top = found.where("series_id is not null").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return top.select("query_id", "rank", "series_id", X.root(F.col("power"), p).alias("dist"))


def counters(found: DataFrame) -> DataFrame:
    """Live counters of each query, summed over tasks; they depend on how the data are cut."""
    sums = [F.sum(F.get("counts", F.lit(i))).alias(name) for i, name in enumerate(COUNTERS)]
    return found.where("series_id is null").groupBy("query_id").agg(*sums)


def _box_frame(spark: SparkSession, tile: dict[int, Query], cover: boxindex.Cover) -> DataFrame:
    """``query_id, lo1 .. lod, hi1 .. hid`` of a tile, from the envelopes that the driver has."""
    names = [f"{side}{k}" for side in ("lo", "hi") for k in range(1, len(cover) + 1)]
    rows = [(q, *kernels.piecewise_sums(x.lo, cover).tolist(), *kernels.piecewise_sums(x.hi, cover).tolist()) for q, x in tile.items()]
    return spark.createDataFrame(rows, ", ".join(["query_id bigint", *(f"{name} double" for name in names)]))


def page_distances(index: boxindex.BoxIndex, boxes: DataFrame, p: float) -> DataFrame:
    """``query_id, page_id, page_bound`` and the query's box for all pages; boxes are broadcast."""
    return index.pages.crossJoin(F.broadcast(boxes)).withColumn("page_bound", boxindex.page_bound_pow(index.cover, p))


def reached(index: boxindex.BoxIndex, hits: DataFrame, n_queries: int) -> DataFrame:
    """``owners, series_id, v``: the arrays of the pages in ``hits`` (``query_id, page_id``), each with its queries.

    The page table's part of this is sent to all tasks where pages and queries
    are few enough; the arrays are never shuffled then.
    """
    # The filter holds for every row; it marks this side as one to prune folders by.
    owners = hits.groupBy("page_id").agg(F.collect_list("query_id").alias("owners")).where(F.size("owners") > 0)
    keys = ["page_id"]
    if "page_group" in index.paged.columns:
        owners, keys = owners.withColumn("page_group", boxindex.page_group()), ["page_group", "page_id"]
    if index.n_pages * n_queries <= MOST_HITS:
        owners = F.broadcast(owners)
    return index.paged.join(owners, keys).select("owners", "series_id", "v")


def _kth_limits(found: DataFrame, plan: Plan) -> dict[int, float]:
    """The k-th best power of each query that has k: one row a query comes to the driver."""
    top = merged(found, plan.k, 1).where(F.col("rank") == plan.k)
    return {r.query_id: r.dist for r in top.select("query_id", "dist").collect()}


def nearest_pages(pages: DataFrame, k: int) -> DataFrame:
    """Of ``page_distances``, each query's nearest pages that together hold more than k points."""
    ranked = Window.partitionBy("query_id").orderBy("page_bound", "page_id")
    earlier = F.coalesce(F.sum("rows").over(ranked.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return pages.withColumn("_ahead", earlier).where(F.col("_ahead") <= k)


def _limit_table(spark: SparkSession, tile: dict[int, Query], limits: dict[int, float], plan: Plan) -> DataFrame:
    return F.broadcast(spark.createDataFrame([(q, limits.get(q, _start(plan))) for q in tile], "query_id bigint, `limit` double"))


def seeded(index: boxindex.BoxIndex, tile: dict[int, Query], plan: Plan) -> tuple[DataFrame, dict[int, float]]:
    """The page hits ``query_id, page_id, rows, page_bound`` within each query's first limit, and these limits.

    A first limit is the k-th least distance in the query's nearest pages; of
    a range search it is the range.
    """
    spark = index.paged.sparkSession
    pages = page_distances(index, _box_frame(spark, tile, index.cover), plan.p)
    limits: dict[int, float] = {}
    if plan.eps is None:
        limits = _kth_limits(refine_pages(reached(index, nearest_pages(pages, plan.k), len(tile)), tile, plan), plan)
    table = _limit_table(spark, tile, limits, plan)
    return pages.join(table, "query_id").where("page_bound <= `limit`").select("query_id", "page_id", "rows", "page_bound"), limits


def _index_search(index: boxindex.BoxIndex, tile: dict[int, Query], plan: Plan) -> DataFrame:
    """Seed from each query's nearest pages, then all pages and points within the seed's distance."""
    plan = plan._replace(cover=tuple(index.cover))
    hits, limits = seeded(index, tile, plan)
    return refine_pages(reached(index, hits, len(tile)), tile, plan, limits)


def search_rounds(index: boxindex.BoxIndex, queries: DataFrame, w: int | None = None, p: float = 1, k: int = 1, growth: int = 4, method: str = "box_pass2") -> DataFrame:
    """Best-first over pages in rounds of growing size, until no page is within reach.

    Between rounds only the k best of each query visit the driver. A round
    takes ``growth`` times as many pages of each query as the one before.
    """
    kernels.check_norm(p)
    spark, outs = index.paged.sparkSession, []
    for tile, band in query_tiles(queries, w):
        plan = Plan(band, p, k, METHODS[method], cover=tuple(index.cover))
        ranked = Window.partitionBy("query_id").orderBy("page_bound", "page_id")
        pages = page_distances(index, _box_frame(spark, tile, index.cover), p).withColumn("_r", F.row_number().over(ranked)).persist()
        best: dict[int, list[tuple[float, int]]] = {q: [] for q in tile}
        done, take = 0, 1
        while True:
            limit = {q: rows[k - 1][0] for q, rows in best.items() if len(rows) >= k}
            table = _limit_table(spark, tile, limit, plan)
            reach = pages.where(F.col("_r") > done).join(table, "query_id").where("page_bound <= `limit`")
            if not reach.limit(1).count():
                break
            found = refine_pages(reached(index, reach.where(F.col("_r") <= done + take), len(tile)), tile, plan, limit)
            for r in merged(found, k, 1).collect():
                best[r.query_id] = sorted({*best[r.query_id], (r.dist, r.series_id)})[:k]
            done, take = done + take, take * growth
        pages.unpersist()
        rows = [(q, rank, s, float(kernels.root(d, p))) for q, found in best.items() for rank, (d, s) in enumerate(found, 1)]
        outs.append(spark.createDataFrame(rows, "query_id bigint, rank int, series_id bigint, dist double"))
    return _union(outs)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for frame in frames[1:]:
        out = out.unionByName(frame)
    return out


def _searched(queries: DataFrame, series: DataFrame | boxindex.BoxIndex, w: int | None, plan: Plan, method: str) -> DataFrame:
    found = []
    for tile, band in query_tiles(queries, w):
        own = plan._replace(w=band)
        if "box" in plan.passes:
            if not isinstance(series, boxindex.BoxIndex):
                n = len(next(iter(tile.values())).y)
                series = boxindex.build(series, n, min(boxindex.D, n))
            found.append(_index_search(series, tile, own))
        else:
            rows = series.paged if isinstance(series, boxindex.BoxIndex) else series
            found.append(scan(rows, tile, own))
    if not found:
        spark = queries.sparkSession
        return spark.createDataFrame([], _FOUND_TYPES)
    return _union(found)


def nearest(
    queries: DataFrame,
    series: DataFrame | boxindex.BoxIndex,
    w: int | None = None,
    p: float = 1,
    k: int = 1,
    method: str = "box_pass2",
    early_abandon: bool = False,
    exclude_self: bool = False,
    cascade: tuple[str, ...] | None = None,
) -> DataFrame:
    """The k nearest series of each query: ``query_id, rank, series_id, dist``.

    ``queries`` has ``query_id, y``; ``series`` has ``series_id, v`` or is an
    index. ``cascade`` names the bounds to use, cheapest first, instead of a
    method's own.
    """
    if method == "lp":
        return nearest_lp(queries, series, p, k)
    kernels.check_norm(p)
    if k < 1:
        raise ValueError("k must be 1 or more")
    passes = METHODS[method] if cascade is None else tuple(cascade)
    if unknown := set(passes) - {"box", "pass1", "pass2"}:
        raise ValueError(f"unknown bounds {unknown}")
    if "pass2" in passes and "pass1" not in passes:
        raise ValueError("the second pass builds on the first")
    plan = Plan(0, p, k, passes, early_abandon, exclude_self)
    return merged(_searched(queries, series, w, plan, method), k, p)


def within(queries: DataFrame, series: DataFrame | boxindex.BoxIndex, eps: float, w: int | None = None, p: float = 1, method: str = "scan_pass2") -> DataFrame:
    """All series at a distance of ``eps`` or less: ``query_id, series_id, dist``."""
    kernels.check_norm(p)
    plan = Plan(0, p, 1, METHODS[method], eps=eps)
    found = _searched(queries, series, w, plan, method).where("series_id is not null")
    return found.select("query_id", "series_id", X.root(F.col("power"), p).alias("dist"))


def reach_counts(queries: DataFrame, index: boxindex.BoxIndex, w: int | None = None, p: float = 1, k: int = 1) -> DataFrame:
    """``query_id, pages, points, pages_reached, points_reached``: what the index leaves of the collection for each query.

    Reached is what stands within the first limit, the k-th distance in the
    nearest pages; how a search is cut into tasks doesn't change it.
    """
    outs = []
    for tile, band in query_tiles(queries, w):
        plan = Plan(band, p, k, METHODS["box_only"], cover=tuple(index.cover))
        hits, _ = seeded(index, tile, plan)
        every = index.pages.agg(F.count("*").alias("pages"), F.coalesce(F.sum("rows"), F.lit(0)).alias("points"))
        near = hits.groupBy("query_id").agg(F.count("*").alias("pages_reached"), F.sum("rows").alias("points_reached"))
        outs.append(near.crossJoin(F.broadcast(every)))
    return _union(outs).select("query_id", "pages", "points", "pages_reached", "points_reached")


def live_counters(queries: DataFrame, series: DataFrame | boxindex.BoxIndex, w: int | None = None, p: float = 1, method: str = "scan_pass2", early_abandon: bool = False) -> DataFrame:
    """What a search really computed, by query."""
    return counters(_searched(queries, series, w, Plan(0, p, 1, METHODS[method], early_abandon), method))


def nearest_lp(queries: DataFrame, series: DataFrame, p: float = 1, k: int = 1) -> DataFrame:
    """Neighbours under the unwarped distance, in built-in expressions only."""
    pairs = series.select("series_id", "v").crossJoin(F.broadcast(queries.select("query_id", "y")))
    found = pairs.select("query_id", "series_id", X.lp_distance_pow("v", "y", p).alias("power"))
    return merged(found, k, p)


def native_scan(queries: DataFrame, series: DataFrame, w: int, limits: DataFrame, p: float = 1) -> DataFrame:
    """Scan and first pass as a plan of built-in expressions; the distance runs on what the filter leaves.

    ``limits`` has ``query_id, limit`` (any distance that some candidate has,
    as a power). The filter is an expression of the JVM, so it stays below the
    Python evaluation of the distance.
    """
    from warpspan.functions import udfs

    ready = queries.join(limits, "query_id").select("query_id", "y", "limit", X.envelope("y", w).alias("e"))
    pairs = series.select("series_id", "v").crossJoin(F.broadcast(ready))
    left = pairs.where(X.pass1_pow("v", F.col("e.lo"), F.col("e.hi"), p) <= F.col("limit"))
    found = left.select("query_id", "series_id", udfs.dtw("v", "y", w, p, rooted=False).alias("power"))
    return merged(found, 1, p)
