"""Cost and accuracy measures: pruning power, comparisons, tightness, error limits.

Counters of the sequential algorithms are exact without running them one
candidate after another. A candidate that a bound prunes has a distance no
smaller than the limit, so leaving it out never changes the limit; the limit
before a candidate is therefore the least true distance of all earlier ones,
which is a prefix minimum over the table of all bounds and distances. That
table is what a measurement costs; searches don't need it.

For counts alone most of the table can be left out, exactly (``counting_table``):
the first candidates of each order get their distances, and the least of these
is above every later limit. A later candidate whose first bound reaches it is
pruned whatever comes, and one whose second bound reaches it has no distance
that could lower a limit.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.functions import expressions as X
from warpspan.functions import kernels
from warpspan.operators import boxindex, search
from warpspan.sources import store
from warpspan.sources.series import matrix

BOUNDS = ("box", "pass1", "pass2", "dtw", "lp")


def bound_table(queries: DataFrame, series: DataFrame, w: int | None = None, p: float = 1, d: int = boxindex.D, cover: boxindex.Cover | None = None) -> DataFrame:
    """``query_id, series_id`` and the powers ``box, pass1, pass2, dtw, lp`` of all pairs."""
    kernels.check_norm(p)
    outs = []
    for tile, band in search.query_tiles(queries, w):
        outs.append(_bounds_of(series, tile, band, p, d, cover))
    return search._union(outs)


def _bounds_of(series: DataFrame, tile, w: int, p: float, d: int, cover) -> DataFrame:
    shared = search._share(series, tile, None)

    def run(source):
        queries, _ = search._shared(shared)
        for batch in source:
            if not batch.num_rows:
                continue
            ids, x = batch.column(0).to_numpy(), matrix(batch.column(1))
            n = x.shape[1]
            parts = cover or boxindex.floor_cover(n, min(d, n))
            sums = kernels.piecewise_sums(x, parts)
            for q, query in queries.items():
                box = boxindex.box_pow(sums, query.lo, query.hi, parts, p)
                first = kernels.pass1_pow(x, query.lo, query.hi, p)
                second = kernels.add(first, kernels.gap2_pow(x, query.y, query.lo, query.hi, w, p), p)
                columns = (box, first, second, kernels.dtw_pow(x, query.y, w, p), kernels.lp_pow(x, query.y, p))
                yield pa.record_batch([pa.array(np.full(len(ids), q)), pa.array(ids), *map(pa.array, columns)], names=["query_id", "series_id", *BOUNDS])

    types = ", ".join(f"{b} double" for b in BOUNDS)
    return series.select("series_id", "v").mapInArrow(run, f"query_id bigint, series_id bigint, {types}")


#: First candidates of each order that get their distances before all others.
SEEDS = 32


class Counting(NamedTuple):
    """``rows`` has ``query_id, series_id, first, box0 .., pass1, pass2, dtw``, ``sizes`` the candidates of each part."""

    rows: DataFrame
    sizes: list[int]


def counting_table(queries: DataFrame, series: DataFrame, w: int | None = None, dims: tuple[int, ...] = (boxindex.D,), parts: int = 1, p: float = 1) -> Counting:
    """The rows that sequential counts of any order need, for several sums a series and nested parts of the series.

    ``series`` may say in ``first`` the first of the ``parts`` that it belongs
    to; it belongs to all later ones too. A distance that no count needs is
    infinite. The series are stored, as they are read three times.
    """
    kernels.check_norm(p)
    kept = series if "first" in series.columns else series.withColumn("first", F.lit(0))
    kept = store.stored(kept.select("series_id", "v", F.col("first").cast("int").alias("first")))
    sizes = {r.first: r.n for r in kept.groupBy("first").agg(F.count("*").alias("n")).collect()}
    outs = [_counting_rows(kept, tile, band, dims, parts, p) for tile, band in search.query_tiles(queries, w)]
    return Counting(store.stored(search._union(outs)), [sum(n for f, n in sizes.items() if f <= k) for k in range(parts)])


def _box_of(x: np.ndarray, query, dims: tuple[int, ...], p: float, sums: dict) -> list[np.ndarray]:
    boxes = []
    for d in dims:
        cover = boxindex.floor_cover(x.shape[1], min(d, x.shape[1]))
        if d not in sums:
            sums[d] = kernels.piecewise_sums(x, cover)
        boxes.append(boxindex.box_pow(sums[d], query.lo, query.hi, cover, p))
    return boxes


def _counting_rows(series: DataFrame, tile, w: int, dims: tuple[int, ...], parts: int, p: float) -> DataFrame:
    seeds = _seeds(series, tile, dims, parts, p)
    limits = _seed_limits(series, tile, w, seeds, p)
    shared = search._share(series, tile, limits)

    def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        pieces = [kernels.dtw_pow(x[k : k + 256], y[None, :], w, p) for k in range(0, len(x), 256)]
        return np.concatenate(pieces) if pieces else np.zeros(0)

    def run(source):
        tiled, limits = search._shared(shared)
        for batch in source:
            if not batch.num_rows:
                continue
            ids, x, first = batch.column(0).to_numpy(), matrix(batch.column(1)), batch.column(2).to_numpy()
            sums: dict = {}
            for q, query in tiled.items():
                boxes, one = _box_of(x, query, dims, p, sums), kernels.pass1_pow(x, query.lo, query.hi, p)
                keep, early, least = np.zeros(len(ids), bool), np.zeros(len(ids), bool), np.full(len(ids), -np.inf)
                for (order, part), (value, last, last_id) in limits[q].items():
                    bound = ids if order < 0 else boxes[order]
                    mine = first <= part
                    seed = mine & ((bound < last) | ((bound == last) & (ids <= last_id)))
                    test = one if order < 0 else boxes[order]
                    wanted = seed | (mine & (test < value))
                    keep, early = keep | wanted, early | seed
                    # The highest limit under which the row is wanted decides about its distance.
                    least[wanted] = np.maximum(least[wanted], value)
                at = np.flatnonzero(keep)
                if not len(at):
                    continue
                two = kernels.add(one[at], kernels.gap2_pow(x[at], query.y, query.lo, query.hi, w, p), p)
                done = np.full(len(at), np.inf)
                need = early[at] | (two < least[at])
                done[need] = distances(x[at[need]], query.y)
                columns = [np.full(len(at), q), ids[at], *(b[at] for b in boxes), one[at], two, done]
                yield pa.record_batch([*map(pa.array, columns), pa.array(first[at], pa.int32())], names=["query_id", "series_id", *names, "pass1", "pass2", "dtw", "first"])

    names = [f"box{k}" for k in range(len(dims))]
    types = ", ".join(f"{b} double" for b in (*names, "pass1", "pass2", "dtw"))
    return series.mapInArrow(run, f"query_id bigint, series_id bigint, {types}, first int")


def _seeds(series: DataFrame, tile, dims: tuple[int, ...], parts: int, p: float) -> DataFrame:
    """``query_id, kind, part, bound, series_id, place``: each order's first candidates; kind -1 is the order of ids, for all queries."""
    shared = search._share(series, tile, None)

    def run(source):
        tiled, _ = search._shared(shared)
        for batch in source:
            if not batch.num_rows:
                continue
            ids, x, first = batch.column(0).to_numpy(), matrix(batch.column(1)), batch.column(2).to_numpy()
            members = [np.flatnonzero(first <= part) for part in range(parts)]
            sums: dict = {}
            for q, query in tiled.items():
                for kind, bound in enumerate([np.zeros(len(ids)), *_box_of(x, query, dims, p, sums)], -1):
                    found, of = [], []
                    for part, mine in enumerate(members):
                        top = mine[np.lexsort((ids[mine], bound[mine]))[:SEEDS]]
                        found.append(top)
                        of.append(np.full(len(top), part))
                    top, size = np.concatenate(found), sum(map(len, found))
                    columns = [pa.array(np.full(size, q)), pa.array(np.full(size, kind), pa.int32()), pa.array(np.concatenate(of), pa.int32()), pa.array(bound[top]), pa.array(ids[top])]
                    yield pa.record_batch(columns, names=["query_id", "kind", "part", "bound", "series_id"])

    rows = series.mapInArrow(run, "query_id bigint, kind int, part int, bound double, series_id bigint")
    place = F.row_number().over(Window.partitionBy("query_id", "kind", "part").orderBy("bound", "series_id"))
    return store.stored(rows.withColumn("place", place).where(F.col("place") <= SEEDS))


def _seed_limits(series: DataFrame, tile, w: int, seeds: DataFrame, p: float) -> dict:
    """By query, then by order and part: the seeds' least distance, and the last seed's place in the order."""
    wanted = series.join(F.broadcast(seeds.groupBy("series_id").agg(F.collect_set("query_id").alias("queries"))), "series_id")
    shared = search._share(series, tile, None)

    def run(source):
        tiled, _ = search._shared(shared)
        for batch in source:
            for i, v, own in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                y = np.stack([tiled[q].y for q in own])
                done = kernels.dtw_pow(np.repeat([v], len(own), axis=0), y, w, p)
                yield pa.record_batch([pa.array(own, pa.int64()), pa.array([i] * len(own), pa.int64()), pa.array(done)], names=["query_id", "series_id", "dtw"])

    known = wanted.select("series_id", "v", "queries").mapInArrow(run, "query_id bigint, series_id bigint, dtw double")
    rows = seeds.join(known, ["query_id", "series_id"]).groupBy("query_id", "kind", "part").agg(F.min("dtw").alias("least"), F.max(F.struct("bound", "series_id")).alias("last"))
    limits: dict = {q: {} for q in tile}
    for r in rows.collect():
        # In the order of ids the id itself is the place.
        last = float(r.last.series_id) if r.kind < 0 else r.last.bound
        limits[r.query_id][r.kind, r.part] = (r.least, last, r.last.series_id)
    return limits


def with_limit(bounds: DataFrame, order: list[str], name: str = "limit") -> DataFrame:
    """Adds the least distance among each query's earlier candidates, infinite for the first.

    Rows are cut into ranges of (query, order), so that a query's sequence may
    be as long as the collection: the least distance of the ranges before comes
    from a table of one row a range, and that inside a range from a window.
    The ranges are stored, as they hang on a sample.
    """
    ranged = store.stored(bounds.repartitionByRange("query_id", *order).withColumn("_block", F.spark_partition_id()))
    least = ranged.groupBy("query_id", "_block").agg(F.min("dtw").alias("_least"))
    earlier = Window.partitionBy("query_id").orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    before = F.broadcast(least.select("query_id", "_block", F.min("_least").over(earlier).alias("_before")))
    inside = Window.partitionBy("query_id", "_block").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    limit = F.coalesce(F.least(F.min("dtw").over(inside), F.col("_before")), F.lit(float("inf")))
    return ranged.join(before, ["query_id", "_block"]).withColumn(name, limit).drop("_block", "_before")


#: Method to the bounds it tests, with the visiting order of its candidates.
SEQUENTIAL = {
    "scan_pass1": (("pass1",), ["series_id"]), "scan_pass2": (("pass1", "pass2"), ["series_id"]),
    "box_only": (("box",), ["box", "series_id"]), "box_pass1": (("box", "pass1"), ["box", "series_id"]),
    "box_pass2": (("box", "pass1", "pass2"), ["box", "series_id"]),
}


def sequential_counts(bounds: DataFrame, methods: list[str], by: list[str] = ["query_id"], candidates: Column | None = None) -> DataFrame:  # noqa: B006
    """For each method: candidates, and how many are left after each bound and get a distance.

    Bounds prune strictly, as in the sequential algorithms: a tie with the
    limit is pruned. Rows of a ``counting_table`` are not all candidates, so
    their number is given with them.
    """
    total = F.count("*") if candidates is None else F.max(candidates)
    orders = {tuple(SEQUENTIAL[m][1]): f"limit{k}" for k, m in enumerate(methods)}
    ranked = bounds
    for order, limit in orders.items():
        ranked = with_limit(ranked, list(order), limit)
    sums, rows = [total.cast("bigint").alias("candidates")], []
    for k, method in enumerate(methods):
        tests, order = SEQUENTIAL[method]
        passed, cells = None, []
        for name in ("box", "pass1", "pass2"):
            if name in tests:
                test = F.col(name) < F.col(orders[tuple(order)])
                passed = test if passed is None else passed & test
            sums.append((total if passed is None else F.sum(passed.cast("long"))).cast("bigint").alias(f"m{k}_{name}"))
            cells.append(F.col(f"m{k}_{name}").alias(f"after_{name}"))
        rows.append(F.struct(F.lit(method).alias("method"), "candidates", *cells, F.col(f"m{k}_pass2").alias("dtw_done")))
    # All methods from one pass over the table.
    return ranked.groupBy(*by).agg(*sums).select(*by, F.inline(F.array(*rows)))


def survivors(bounds: DataFrame, methods: list[str]) -> DataFrame:
    """``method, query_id, series_id`` of the candidates that get a distance."""
    outs = []
    for method in methods:
        tests, order = SEQUENTIAL[method]
        left = with_limit(bounds, order)
        for name in tests:
            left = left.where(F.col(name) < F.col("limit"))
        outs.append(left.select(F.lit(method).alias("method"), "query_id", "series_id"))
    return search._union(outs)


def distinct_survivors(bounds: DataFrame, methods: list[str], error: float = 0.05) -> DataFrame:
    """Series that any query computes a distance to, exactly, and whether a sketch of fixed size agrees to three times its error."""
    left = survivors(bounds, methods).groupBy("method")
    both = left.agg(F.count_distinct("series_id").alias("survivors"), F.approx_count_distinct("series_id", error).alias("sketch"))
    close = F.abs(F.col("sketch") - F.col("survivors")) <= F.greatest(F.lit(1.0), 3 * error * F.col("survivors"))
    return both.select("method", "survivors", close.alias("sketch_agrees"))


def stage_histogram(bounds: DataFrame, order: list[str] = ["box", "series_id"]) -> DataFrame:  # noqa: B006
    """Candidates of each query by the last stage they reach: box, pass1, pass2 or dtw."""
    limit = F.col("limit")
    stage = (
        F.when(F.col("box") >= limit, "box").when(F.col("pass1") >= limit, "pass1").when(F.col("pass2") >= limit, "pass2").otherwise("dtw")
    )
    ranked = with_limit(bounds, order)
    return ranked.groupBy("query_id", stage.alias("stage")).agg(F.count("*").alias("candidates"))


def pruning_power(counts: DataFrame, by: list[str]) -> DataFrame:
    """Share of candidates that are spared the distance, in whole millionths (rounded down)."""
    spared = F.floor((F.sum("candidates") - F.sum("dtw_done")) * 1000000 / F.sum("candidates"))
    return counts.groupBy(*by).agg(spared.alias("pruned_ppm"), F.sum("dtw_done").alias("dtw_done"))


def pruning_ratios(counts: DataFrame, first: str, second: str) -> DataFrame:
    """Pruned shares and survivors of one method against another."""
    total = counts.groupBy("method").agg(F.sum("candidates").alias("c"), F.sum("dtw_done").alias("d"))
    a, b = total.where(F.col("method") == first), total.where(F.col("method") == second)
    pair = a.select(F.col("c").alias("c1"), F.col("d").alias("d1")).crossJoin(b.select(F.col("c").alias("c2"), F.col("d").alias("d2")))
    share = ((F.col("c2") - F.col("d2")) / F.col("c2")) / F.nullif((F.col("c1") - F.col("d1")) / F.col("c1"), F.lit(0.0))
    return pair.select(share.alias("pruned_ratio"), ((F.col("d1") / F.col("c1")) / F.nullif(F.col("d2") / F.col("c2"), F.lit(0.0))).alias("survivor_ratio"))


def scan_comparisons(queries: DataFrame, series: DataFrame, w: int) -> DataFrame:
    """Comparisons of samples with the envelope in one first pass over all series, by query.

    A sample above the upper side takes one comparison, any other two. Beside
    them stands the limit 2Nn; an envelope by queues takes 3n more at most.
    """
    env = queries.select("query_id", X.envelope("y", w).alias("e"))
    pairs = series.select("v").crossJoin(F.broadcast(env))
    each = F.zip_with("v", F.col("e.hi"), lambda x, hi: F.when(x > hi, F.lit(1)).otherwise(F.lit(2)))
    made = F.aggregate(each, F.lit(0).cast("long"), lambda a, c: a + c.cast("long"))
    return pairs.groupBy("query_id").agg(F.sum(made).alias("comparisons"), F.sum(F.size("v").cast("long") * 2).alias("most"))


def second_pass_comparisons(bounds: DataFrame, queries: DataFrame, series: DataFrame, w: int) -> DataFrame:
    """Comparisons of samples in the second pass, for the candidates that the first leaves in a sequential scan, by query.

    A second envelope by queues is counted as it runs; the query is then held
    against it, with one or two comparisons a sample. ``most`` is 5 a sample.
    """
    left = with_limit(bounds, ["series_id"]).where("pass1 < `limit`").select("query_id", "series_id")
    env = queries.select("query_id", "y", X.envelope("y", w).alias("e"))
    pairs = left.join(series.select("series_id", "v"), "series_id").join(F.broadcast(env), "query_id")

    def count(source):
        for batch in source:
            x, y, lo, hi = (matrix(batch.column(k)) for k in range(1, 5)) if batch.num_rows else [np.zeros((0, 1))] * 4
            made = []
            for h, own in zip(kernels.clamp(x, lo, hi), y, strict=True):
                _, top, seen = kernels.envelope_by_queues(h.tolist(), w)
                made.append(seen + 2 * len(own) - int((own > np.array(top)).sum()))
            yield pa.record_batch([batch.column(0), pa.array(made, pa.int64()), pa.array([5 * x.shape[1]] * len(made), pa.int64())], names=["query_id", "comparisons", "most"])

    rows = pairs.select("query_id", "v", "y", "e.lo", "e.hi").mapInArrow(count, "query_id bigint, comparisons bigint, most bigint")
    return rows.groupBy("query_id").agg(F.sum("comparisons").alias("comparisons"), F.sum("most").alias("most"))


def comparison_limits(counts: DataFrame, n: int) -> DataFrame:
    """The stated limits (2N + 3)n of the scan with one pass, and 5 comparisons a sample more for each candidate that the first leaves."""
    c = counts.where("method = 'scan_pass2'")
    one = (2 * F.col("candidates") + 3) * n
    return c.select("query_id", one.alias("limit_pass1"), (one + 5 * F.col("after_pass1") * n).alias("limit_pass2"))


def cells_done(counts: DataFrame, n: int, w: int) -> DataFrame:
    """Cells of the distance's table that were filled."""
    return counts.select("query_id", "method", (F.col("dtw_done") * kernels.band_cells(n, w)).alias("cells"))


def tightness(bounds: DataFrame) -> DataFrame:
    """Means and medians of bound over distance, in whole thousandths, over pairs that are apart."""
    apart = bounds.where("dtw > 0")
    out = []
    for name in ("box", "pass1", "pass2"):
        ratio = F.floor(F.col(name) * 1000 / F.col("dtw"))
        out += [F.floor(F.sum(ratio) / F.count("*")).alias(f"{name}_mean"), F.expr(f"percentile_disc(0.5) within group (order by floor({name} * 1000 / dtw))").alias(f"{name}_median")]
    return apart.agg(*out, F.count("*").alias("pairs"))


def chain_violations(bounds: DataFrame, slack: float = 1e-9) -> DataFrame:
    """Pairs that break box <= pass1 <= pass2 <= distance <= unwarped distance; none are expected."""
    names = ("box", "pass1", "pass2", "dtw", "lp")
    broken = F.lit(False)
    for a, b in zip(names, names[1:], strict=False):
        broken = broken | (F.col(a) > F.col(b) + F.lit(slack) * F.greatest(F.col(b), F.lit(1.0)))
    return bounds.where(broken)


def pages_touched(index: boxindex.BoxIndex, queries: DataFrame, w: int, limits: DataFrame, p: float = 1) -> DataFrame:
    """Pages within each query's limit, and all pages."""
    boxes = boxindex.query_boxes(queries, w, index.cover)
    pages = search.page_distances(index, boxes, p).join(F.broadcast(limits), "query_id")
    return pages.groupBy("query_id").agg(F.sum((F.col("page_bound") <= F.col("limit")).cast("long")).alias("touched"), F.count("*").alias("pages"))
