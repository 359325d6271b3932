"""What small tables can't show: exact edges, many pairs at once, pruned counts, copies."""

import math

import numpy as np
import pyarrow as pa
import pytest

from warpspan.functions import kernels as K
from warpspan.operators import boxindex


def test_page_edges_are_the_values_at_their_ranks(spark):
    """Of 20,000 points, more than a sketch holds; every third value is a copy."""
    n, page_rows = 20_000, 400
    rng = np.random.default_rng(3)
    x, y = np.round(rng.normal(0, 1e6, n)), np.round(rng.normal(0, 50, n))
    x[::3] = x[0]
    points = spark.createDataFrame(pa.table({"series_id": np.arange(n), "s1": x, "s2": y})).repartition(7)
    tiles = boxindex.tiling(points, page_rows)
    strips = math.ceil(math.sqrt(n / page_rows))
    per_strip = math.ceil(n / page_rows / strips)
    at = lambda values, parts: np.sort(values)[[math.ceil(k / parts * len(values)) - 1 for k in range(1, parts)]]
    assert tiles.per_strip == per_strip and np.array_equal(tiles.first, at(x, strips))
    strip = np.searchsorted(tiles.first, x)
    for s in np.unique(strip):
        assert np.array_equal(tiles.second[s], at(y[strip == s], per_strip))


@pytest.mark.parametrize("w", [0, 1, 3, 8, None])
@pytest.mark.parametrize("p", [1, 2, math.inf])
def test_non_monotonic_distances_of_many_pairs_at_once(w, p):
    rng = np.random.default_rng(1)
    for n in (1, 2, 7, 19):
        x, y = (rng.integers(-6, 7, (30, n)).cumsum(axis=1).astype(float) for _ in range(2))
        y[:3] += 1000
        assert K.ndtw_pows(x, y, w, p).tolist() == [K.ndtw_pow(a, b, w, p) for a, b in zip(x, y, strict=True)]


def test_non_monotonic_distance_of_two_thousand_pairs_is_quick():
    """They took half a minute to two minutes one by one."""
    import time

    rng = np.random.default_rng(2)
    x, y = (rng.integers(-600, 700, (2000, 83)).cumsum(axis=1).astype(float) for _ in range(2))
    start = time.process_time()
    for w in (1, 8):
        K.ndtw_pows(x, y, w)
    assert time.process_time() - start < 20


def test_counts_from_few_rows_are_those_of_all_rows(spark, monkeypatch):
    """Ties, nested parts and several numbers of sums; the table leaves most pairs and distances out."""
    from pyspark.sql import functions as F

    from warpspan.operators import measures
    from warpspan.sources import series as S

    monkeypatch.setattr(measures, "SEEDS", 4)
    rng = np.random.default_rng(7)
    rows = rng.integers(-3, 4, (400, 32)).cumsum(axis=1).astype(float)
    rows[200:230] = rows[10:40]
    every = spark.createDataFrame([(i, r.tolist(), None) for i, r in enumerate(rows)], S.PACKED).repartition(4)
    queries, db = S.split_queries(every, 5)
    db = db.withColumn("first", (F.col("series_id") % 3).cast("int"))
    made = measures.counting_table(queries, db, 3, (4, 8), 3)
    methods = list(measures.SEQUENTIAL)
    assert made.rows.where("dtw < double('inf')").count() < 0.6 * 5 * db.count()
    for part in range(3):
        own = db.where(F.col("first") <= part)
        assert made.sizes[part] == own.count()
        for k, d in enumerate((4, 8)):
            few = made.rows.where(F.col("first") <= part).withColumnRenamed(f"box{k}", "box")
            found = measures.sequential_counts(few, methods, candidates=F.lit(made.sizes[part]))
            wanted = measures.sequential_counts(measures.bound_table(queries, own, 3, d=d), methods)
            assert found.schema == wanted.schema or found.columns == wanted.columns
            assert sorted(map(tuple, found.collect())) == sorted(map(tuple, wanted.collect()))


@pytest.mark.parametrize("p", [1, 2, math.inf])
def test_join_moves_series_and_never_pairs(spark, monkeypatch, p):
    """Cells in many pieces; candidate pairs once carried both arrays through two joins."""
    from warpspan.operators import join
    from warpspan.sources import series as S

    monkeypatch.setattr(join, "PIECE_VALUES", 1)
    monkeypatch.setattr(join, "PAIRS_AT_ONCE", 100)
    rng = np.random.default_rng(11)
    rows = rng.integers(-5, 6, (700, 24)).cumsum(axis=1).astype(float)
    rows[600:620] = rows[20:40]
    eps = {1: 60.0, 2: 16.0, math.inf: 5.0}[p]
    every = spark.createDataFrame([(i, r.tolist(), None) for i, r in enumerate(rows)] + [(700, None, None)], S.PACKED).repartition(4)
    some = every.where("series_id < 90")
    at = [(i, j) for i in range(700) for j in range(i + 1, 700)]
    power = K.dtw_pow(rows[[i for i, _ in at]], rows[[j for _, j in at]], 3, p)
    wanted = {pair for pair, near in zip(at, power <= K.power(eps, p), strict=True) if near}
    assert len(wanted) > 30
    found = join.warp_join(every, every, 24, eps, 3, p, self_join=True)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "left_id" in plan and "Join Inner" not in plan
    assert sorted((r.left_id, r.right_id) for r in found.collect()) == sorted(wanted)
    across = join.warp_join(every, some, 24, eps, 3, p).collect()
    assert sorted((r.left_id, r.right_id) for r in across) == sorted({(a, b) for x, y in wanted for a, b in ((x, y), (y, x)) if b < 90} | {(i, i) for i in range(90)})
